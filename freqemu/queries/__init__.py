"""All queries of the engine, by name, with SQL that gives the same rows where SQL can."""

from ..plans.registry import ORACLES, QUERIES
from . import advice, flagship, methods, relational, streams, workloads  # noqa: F401  they register themselves

__all__ = ["ORACLES", "QUERIES"]
