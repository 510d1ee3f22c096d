"""Quantizers, indexes, search, de-duplication and measures."""
