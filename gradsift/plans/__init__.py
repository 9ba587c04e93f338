"""Durable intermediates, topology of merges, cost and bound calculators."""
