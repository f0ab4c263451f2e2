"""Structured Streaming forms: summary log, keyed state, windows, late data."""
