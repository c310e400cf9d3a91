"""Queries against their DuckDB SQL on the smallest tables."""

import duckdb
import pytest

from robustcenters import catalog

NAMES = [
    "assign_nearest_l2", "assign_block_kernel", "cost_trimmed", "cost_weighted_trimmed", "trim_weights_rows", "range_cut_threshold", "round_one_values",
    "coreset_direct_values", "coreset_refined_values", "ball_cover_weighted", "seed_farthest", "fit_direct_exact", "collapse_duplicates", "stream_dedup",
    "rel_join_asof", "rel_join_interval", "rel_cube", "rel_udaf_medoid", "planted_outlier_pr",
]


def rows_of(rows):
    return sorted(repr([round(float(v), 4) + 0.0 if isinstance(v, float) else v for v in r]) for r in rows)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, small, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    df = catalog.queries()[name](spark, small)
    sql = con.sql(catalog.oracle_sql()[name])
    columns = sorted(df.columns)
    assert sorted(sql.columns) == columns
    at = [sql.columns.index(c) for c in columns]
    assert rows_of([tuple(r[c] for c in columns) for r in df.collect()]) == rows_of([tuple(r[i] for i in at) for r in sql.fetchall()])


def test_flagship(spark, small):
    rows = catalog.flagship(spark, small).collect()
    assert 0 < len(rows) <= 5 and sum(r["n_outliers"] for r in rows) == 100


def test_validation(spark):
    from robustcenters.sources import points

    bad = spark.createDataFrame([(1, [1.0]), (2, [float("nan")]), (2, [1.0])], "pid long, pt array<double>")
    with pytest.raises(ValueError):
        points.validate(bad)
    assert points.validate(bad, "drop").count() == 2


def test_no_rows_are_capped_unsaid(spark, tmp_path, monkeypatch):
    from robustcenters.operators import cost
    from robustcenters.sources import points

    d = str(tmp_path)
    spark.range(300).selectExpr("id % 7 AS user_id", "concat('t', id % 100) AS event_type").write.parquet(f"{d}/events.parquet")
    spark.range(2500).selectExpr("CAST(id AS INT) AS n_nationkey", "1 AS n_regionkey").write.parquet(f"{d}/nation.parquet")
    spark.range(2500).selectExpr("id AS c_custkey", "CAST(id AS INT) AS c_nationkey", "1.0D AS c_acctbal").write.parquet(f"{d}/customer.parquet")
    want = {(r["user_id"], r["event_type"]): r["count"] for r in spark.read.parquet(f"{d}/events.parquet").groupBy("user_id", "event_type").count().collect()}
    assert {(r["user_id"], r["event_type"]): r["n"] for r in catalog.queries()["rel_pivot"](spark, d).collect()} == want
    assert {(r["pid"], r["event_type"]): r["n"] for r in catalog.queries()["feat_pivot"](spark, d).collect()} == want
    assert points.customer_nation(spark, d).count() == 2500
    monkeypatch.setattr(points, "MOST_TYPES", 99)
    monkeypatch.setattr(cost, "MOST_CENTERS", 2499)
    with pytest.raises(ValueError):
        points.user_types(spark, d)
    with pytest.raises(ValueError):
        cost.center_rows(points.customer_nation(spark, d))
