"""All queries of the graph engine with their SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import experiment_queries, gnn_queries, relational, stream_queries  # noqa: F401  (they add to the same tables)
from .gnn_queries import flagship  # noqa: F401


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(gnn_queries.QUERIES)


def oracles() -> dict[str, str]:
    return dict(gnn_queries.ORACLES)
