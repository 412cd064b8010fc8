"""Structured Streaming forms of encoding and of the feedback loop."""
