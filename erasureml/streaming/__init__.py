"""Structured Streaming forms of the waiting rules."""
