"""Structured Streaming forms of the sketch."""
