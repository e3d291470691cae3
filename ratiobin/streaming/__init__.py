"""Structured Streaming forms of the codec."""
