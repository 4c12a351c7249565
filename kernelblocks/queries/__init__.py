"""The registered queries and their SQL."""

from kernelblocks.queries import checks, methods, relational, runs  # noqa: F401
from kernelblocks.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
