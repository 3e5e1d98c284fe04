"""Sliding-window analytics on Spark that samples and reuses at the same time."""

__version__ = "0.1.0"
