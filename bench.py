"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.path.dirname(os.path.abspath(__file__)) + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402

from robustcenters.catalog import queries  # noqa: E402
from robustcenters.operators import coreset, cost  # noqa: E402
from robustcenters.sources import points  # noqa: E402


def assign_lineitem(spark, sf_dir):
    """All of lineitem in three dimensions to 100 centers."""
    p = points.lineitem_3d(spark, sf_dir)
    return cost.cost(p, p.orderBy("pid").limit(100), "l2")


def coreset_lineitem(spark, sf_dir):
    p = points.lineitem_3d(spark, sf_dir)
    return coreset.build(p, 6, 200, 0.9, "refined", "l2", parts=64).rows


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    known = queries()
    names = ["cost_plain", "cost_trimmed", "collapse_duplicates", "rel_agg_hash", "rel_join_merge", "report_flagship"]
    runs = {n: known[n] for n in names} | {"assign_lineitem": assign_lineitem, "coreset_lineitem": coreset_lineitem}
    try:
        from robustcenters.llm.queries import QUERIES as more

        runs |= {n: f for n, f in more.items() if n.startswith("op")}
    except ImportError:
        pass
    took = {}
    for name, f in runs.items():
        start = time.time()
        f(spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - start, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
