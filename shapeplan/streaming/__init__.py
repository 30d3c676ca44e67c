"""Validation of event streams."""
