"""Aligned string templates and position rules on Spark."""

__version__ = "0.1.0"
