"""Summarise-then-cluster engine for long streams of high-dimensional points."""

__version__ = "0.1.0"
