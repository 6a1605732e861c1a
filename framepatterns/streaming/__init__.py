"""Structured Streaming: the patterns that also run on streams."""
