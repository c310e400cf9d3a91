"""SQL surface: distance functions, grouped aggregates and table functions under their names in a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from .table_functions import BallCover, KMeansOut


def _medoid(pid: pd.Series, x: pd.Series) -> int:
    """The member with the least total distance to its group; ties by least id. For scalars, by sorted prefix sums."""
    order = pd.DataFrame({"p": pid, "x": x}).sort_values("x", kind="stable")
    v = order["x"].to_numpy("float64")
    n, prefix = len(v), v.cumsum()
    at = pd.Series(range(n)).to_numpy()
    total = v * (2 * at + 2 - n) + prefix[-1] - 2 * prefix
    return int(min(zip(total.round(6), order["p"]))[1])


def _trimmed_sum(dist: pd.Series, z: pd.Series) -> float:
    """Sum of squares after the z largest are forgotten."""
    return float((dist.sort_values(ascending=False).iloc[int(z.iloc[0]) :] ** 2).sum())


def medoid(pid, x):
    """Column: the medoid of a group. Made on call, since a grouped function needs a session."""
    return pandas_udf(_medoid, "long")(pid, x)


def trimmed_sum(dist, z):
    """Column: the trimmed cost of a group."""
    return pandas_udf(_trimmed_sum, "double")(dist, z)


SQL_FUNCTIONS = {
    "l2": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, t) -> s + t))",
    "l1": "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, t) -> s + t)",
    "linf": "array_max(zip_with(a, b, (x, y) -> abs(x - y)))",
}


def register(spark: SparkSession) -> None:
    """Make everything callable from SQL text in this session."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION jaccard_dist(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN 1 - size(array_intersect(a, b)) / size(array_union(a, b))")
    spark.udtf.register("ball_cover", udtf(BallCover, returnType="pid bigint, w bigint"))
    spark.udtf.register("kmeans_out", udtf(KMeansOut, returnType="pid bigint, cost double"))
    spark.udf.register("medoid", pandas_udf(_medoid, "long"))
    spark.udf.register("trimmed_sum", pandas_udf(_trimmed_sum, "double"))


