"""Point tables (pid, pt[, w][, part_id]) from the given tables, their checks, scaling and partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shared import checkpoint

#: Event types that become columns; more are an error.
MOST_TYPES = 10_000
LINE_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_columns(df: DataFrame, pid: str, columns: list[Column | str], scale: list[float] | None = None) -> DataFrame:
    cols = [F.col(c) if isinstance(c, str) else c for c in columns]
    scaled = [(c.cast("double") * F.lit(s)) if s != 1 else c.cast("double") for c, s in zip(cols, scale or [1.0] * len(cols))]
    return df.select(F.col(pid).cast("bigint").alias("pid"), F.array(*scaled).alias("pt"))


def from_scalar(df: DataFrame, pid: str, column: Column | str) -> DataFrame:
    return df.select(F.col(pid).cast("bigint").alias("pid"), (F.col(column) if isinstance(column, str) else column).cast("double").alias("pt"))


def from_words(df: DataFrame, pid: str, text: str) -> DataFrame:
    """Distinct lower-case words of letters a-z."""
    words = F.array_distinct(F.filter(F.split(F.lower(text), "[^a-z]+"), lambda w: w != ""))
    return df.select(F.col(pid).cast("bigint").alias("pid"), words.alias("pt"))


def collapse(points: DataFrame) -> DataFrame:
    """Equal payloads become one weighted point with the least id; partial aggregation runs before the shuffle."""
    weight = F.sum("w") if "w" in points.columns else F.count("*")
    return points.groupBy("pt").agg(F.min("pid").alias("pid"), weight.cast("bigint").alias("w")).select("pid", "pt", "w")


def validate(points: DataFrame, policy: str = "error") -> DataFrame:
    """Refuse, drop or report null payloads, NaN or infinite coordinates, ragged vectors and repeated ids."""
    kind = dict(points.dtypes)["pt"]
    bad = F.col("pt").isNull() | F.col("pid").isNull()
    finite = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    if kind == "double":
        bad = bad | finite(F.col("pt"))
    elif kind == "array<double>":
        first = points.where("pt is not null").agg(F.min(F.size("pt")).alias("lo"), F.max(F.size("pt")).alias("hi")).first()
        bad = bad | F.exists("pt", finite) | (F.lit(first["lo"] != first["hi"]) & (F.size("pt") != F.lit(first["hi"] or 0)))
    bad = F.coalesce(bad, F.lit(True))
    if policy == "drop":
        return points.where(~bad)
    counts = points.agg(F.count_if(bad).alias("bad")).crossJoin(points.groupBy("pid").count().agg(F.count_if(F.col("count") > 1).alias("repeated_ids")))
    if policy == "report":
        return counts
    row = counts.first()
    if row["bad"] or row["repeated_ids"]:
        raise ValueError(f"{row['bad']} bad payloads, {row['repeated_ids']} repeated ids")
    return points


def scale(points: DataFrame, how: str = "minmax") -> DataFrame:
    """Coordinates to [0, 1] or to zero mean and unit deviation, from one aggregate row per coordinate."""
    stats = points.select(F.posexplode("pt").alias("axis", "x")).groupBy("axis").agg(F.min("x").alias("lo"), F.max("x").alias("hi"), F.avg("x").alias("mean"), F.stddev_pop("x").alias("sd")).orderBy("axis").collect()
    offset = [r["lo"] if how == "minmax" else r["mean"] for r in stats]
    factor = [(r["hi"] - r["lo"] if how == "minmax" else r["sd"]) or 1.0 for r in stats]
    return points.withColumn("pt", F.array(*[(F.col("pt")[i] - offset[i]) / factor[i] for i in range(len(stats))]))


def ranked(points: DataFrame) -> DataFrame:
    """points with rank, from 0 in the order of pid: sorted ranges, each offset by the rows before it."""
    tasks = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = checkpoint(points.repartitionByRange(tasks, "pid").sortWithinPartitions("pid").withColumn("_mark", F.monotonically_increasing_id()))
    at = F.shiftright("_mark", 33).cast("int")
    bases, total = [], 0
    for r in rows.groupBy(at.alias("at")).count().orderBy("at").collect():  # a row for each task
        bases.append((r["at"], total))
        total += r["count"]
    table = F.broadcast(points.sparkSession.createDataFrame(bases, "_at int, _base long"))
    placed = rows.withColumn("_at", at).join(table, "_at")
    return placed.withColumn("rank", F.col("_base") + F.col("_mark").bitwiseAND(F.lit((1 << 33) - 1))).select(*points.columns, "rank")


def partition(points: DataFrame, parts: int, scheme: str = "hash", seed: int = 42) -> DataFrame:
    """Column part_id, a function of the row (and, for even, of its checkpointed rank), so that both rounds and every retry agree."""
    if scheme == "hash":
        part = F.pmod(F.xxhash64("pid"), F.lit(parts))
    elif scheme == "modulo":
        part = F.pmod("pid", F.lit(parts))
    elif scheme == "range":
        bounds = points.agg(F.min("pid").alias("lo"), F.max("pid").alias("hi")).first()
        width = ((bounds["hi"] or 0) - (bounds["lo"] or 0)) // parts + 1
        part = F.floor((F.col("pid") - (bounds["lo"] or 0)) / width)
    elif scheme == "random":
        part = F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(parts))
    elif scheme == "even":
        # sizes at most one apart
        return ranked(points).withColumn("part_id", F.pmod("rank", F.lit(parts)).cast("int")).drop("rank")
    elif scheme == "given":
        return points
    else:
        raise ValueError(scheme)
    return points.withColumn("part_id", part.cast("int"))


# point sets of the given tables


def supplier_scalar(spark, sf_dir):
    return from_scalar(table(spark, sf_dir, "supplier"), "s_suppkey", "s_acctbal")


def events_scalar(spark, sf_dir):
    return from_scalar(table(spark, sf_dir, "events"), "event_id", "value")


def nation_balances(spark, sf_dir):
    """A point for each nation, all customers' mean balance: few points at any size, for what needs brute force."""
    joined = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy(F.col("n_nationkey").cast("bigint").alias("pid")).agg(F.round(F.avg("c_acctbal"), 2).alias("pt"), F.count("*").alias("w")).select("pid", "pt", "w")


def events_2d(spark, sf_dir):
    return from_columns(table(spark, sf_dir, "events"), "event_id", ["value", F.hour("ts") + F.minute("ts") / 60])


def lineitem_lattice(spark, sf_dir):
    q, d = F.col("l_quantity"), F.round(100 * F.col("l_discount"))
    return table(spark, sf_dir, "lineitem").groupBy(q.alias("q"), d.alias("d")).agg(F.count("*").alias("w")).select((100 * F.col("q") + F.col("d")).cast("bigint").alias("pid"), F.array("q", "d").alias("pt"), "w")


def _line_ids(df: DataFrame) -> DataFrame:
    return df.withColumn("pid", F.xxhash64(*LINE_KEY))


def lineitem_3d(spark, sf_dir):
    return from_columns(_line_ids(table(spark, sf_dir, "lineitem")), "pid", ["l_quantity", "l_discount", "l_tax"], [0.02, 10.0, 12.5])


def lineitem_4d(spark, sf_dir):
    return from_columns(_line_ids(table(spark, sf_dir, "lineitem")), "pid", ["l_quantity", "l_discount", "l_tax", "l_extendedprice"], [0.02, 10.0, 12.5, 1e-5])


def orders_2d(spark, sf_dir):
    years = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")) / 365.25
    return from_columns(table(spark, sf_dir, "orders"), "o_orderkey", [F.col("o_totalprice") / 1e5, years])


def customer_nation(spark, sf_dir):
    joined = table(spark, sf_dir, "customer").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return from_columns(joined, "c_custkey", [F.col("c_acctbal") / 11000, "n_nationkey", "n_regionkey"])


def part_names(spark, sf_dir):
    return table(spark, sf_dir, "part").groupBy(F.col("p_name").alias("pt")).agg(F.min("p_partkey").cast("bigint").alias("pid"), F.count("*").alias("w")).select("pid", "pt", "w")


def doc_words(spark, sf_dir):
    return from_words(table(spark, sf_dir, "documents"), "doc_id", "text")


def embeddings(spark, sf_dir, first: int | None = None):
    v = F.col("embedding").cast("array<double>")
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("pid"), (v if first is None else F.slice(v, 1, first)).alias("pt"))


def event_types(events: DataFrame) -> list[str]:
    """All event types in order; refuses nulls and more than MOST_TYPES, so that none is left out unsaid."""
    kinds = [r[0] for r in events.select("event_type").distinct().limit(MOST_TYPES + 1).collect()]
    if len(kinds) > MOST_TYPES:
        raise ValueError(f"more than {MOST_TYPES} event types")
    if None in kinds:
        raise ValueError("an event has no type")
    return sorted(kinds)


def user_types(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    kinds = event_types(events)
    counts = events.groupBy("user_id").pivot("event_type", kinds).count().na.fill(0)
    return from_columns(counts, "user_id", [f"`{k}`" for k in kinds])


def events_planted(spark, sf_dir):
    v = F.when(F.col("event_id") % 500 == 7, F.col("value") * 50).otherwise(F.col("value"))
    return from_scalar(table(spark, sf_dir, "events"), "event_id", v)


def conversations(spark, sf_dir):
    turns = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.count("*").alias("n"), F.avg(F.length("text")).alias("len"), F.avg((F.col("role") == "user").cast("double")).alias("share"))
    return from_columns(turns, "conv_id", [F.col("n"), F.col("len") / 100, "share"])


def pages(spark, sf_dir):
    html = F.col("html")
    tags = F.length(html) - F.length(F.replace(html, F.lit("<"), F.lit("")))
    depth = F.length("url") - F.length(F.replace(F.col("url"), F.lit("/"), F.lit("")))
    return from_columns(table(spark, sf_dir, "pages"), "page_id", [F.length(html) / 1000, tags / 10, depth])


def page_urls(spark, sf_dir):
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("bigint").alias("pid"), F.col("url").alias("pt"))


def doc_stats(spark, sf_dir):
    words = F.filter(F.split(F.lower("text"), "[^a-z]+"), lambda w: w != "")
    d = table(spark, sf_dir, "documents").select("doc_id", F.length("text").alias("n"), F.size(words).alias("w"), F.size(F.array_distinct(words)).alias("u"))
    return from_columns(d, "doc_id", [F.col("n") / 1000, F.col("w") / 100, F.col("u") / F.greatest(F.col("w"), F.lit(1))])
