"""Continuous matching with Structured Streaming."""
