"""All registered queries, each beside its DuckDB oracle where SQL can express it."""

from .registry import ORACLES, QUERIES
from . import baseline, block1, block2, block3, experts, relational, workloads  # noqa: F401  fill the registry

__all__ = ["ORACLES", "QUERIES"]
