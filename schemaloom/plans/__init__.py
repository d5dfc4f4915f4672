"""Registered queries over the given tables and the SQL they are held against."""

from schemaloom.plans import affinities, hierarchies, inference, methods, streams, surrounding, workloads  # noqa: F401
from schemaloom.plans.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
