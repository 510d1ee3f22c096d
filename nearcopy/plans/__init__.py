"""Planner rules and experiment workloads."""
