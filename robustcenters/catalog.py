"""Every query of the engine by name, with the DuckDB SQL that it is held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .plans import clustering_queries, relational_queries, workloads
from .plans.pipeline import RobustSpec, fit, report
from .sources import points
from .streaming import stream_queries


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The complete algorithm on event values: centers with their points, weight, cost and outliers."""
    p = points.events_scalar(spark, sf_dir)
    return report(p, fit(p, RobustSpec(5, 100, 0.5, "refined", "abs", parts=4, outlier_factor=2.0, options={"eps": 0.5})))


def _sets():
    return clustering_queries, relational_queries, workloads, stream_queries


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for s in _sets() for k, f in s.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for s in _sets() for k, q in s.ORACLES.items()}
