"""Structured Streaming forms of the passes, and windowed edge counts."""
