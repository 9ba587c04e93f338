"""All registered queries of the library."""

from gradsift.workloads import cost_queries, experiments, relational_queries, sketch_queries, stream_queries, training_queries  # noqa: F401
from gradsift.workloads.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
