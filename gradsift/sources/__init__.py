"""Typed table scans, streams, and stores for sketches, models and metrics."""
