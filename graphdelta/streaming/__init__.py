"""Continuous matching over Structured Streaming."""
