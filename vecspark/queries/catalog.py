"""All registered queries of the engine."""

from vecspark.queries import baselines, bounded, core, families, relational, workloads  # noqa: F401
from vecspark.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
