"""Bounds, searches and the loop that runs them as supersteps or in a kernel per task."""
