"""Incremental de-duplication on streams."""
