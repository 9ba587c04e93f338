"""Fixtures, registered queries with their SQL twins, and experiments."""
