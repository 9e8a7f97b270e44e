"""Changing edge costs as streams."""
