"""The relational surface around the methods: scans, joins, aggregates, windows, sets and functions.

Where both engines speak the same SQL one text serves both; {name} is a table. The rest pairs a DataFrame plan with
its DuckDB text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import cost
from ..shared import shared_folder
from ..sources import points as src

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _both(text: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        used = {t: src.table(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in text}
        return spark.sql(text, **used)

    return run


SHARED = {
    "rel_scan_pruned": "SELECT event_id, value FROM {events} WHERE value > 200 AND event_type <> 'x'",
    "rel_range_literal": "SELECT l_orderkey, i, s FROM (VALUES (1, 'a'), (2, 'b'), (3, 'c')) AS t(i, s) JOIN {lineitem} ON l_linenumber = i WHERE i >= 2",
    "rel_filter_mix": "SELECT p_partkey, p_name FROM {part} WHERE p_size BETWEEN 5 AND 20 AND p_name LIKE '%a%' AND p_brand IN (SELECT min(p_brand) FROM {part} UNION ALL SELECT max(p_brand) FROM {part})",
    "rel_having": "SELECT o_orderpriority, count(*) AS n FROM {orders} GROUP BY o_orderpriority HAVING count(*) > 10",
    "rel_join_broadcast": "SELECT c_custkey, n_name, r_name FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey",
    "rel_join_theta": "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM {supplier} a JOIN {supplier} b ON a.s_acctbal < b.s_acctbal AND a.s_nationkey = b.s_nationkey",
    "rel_join_outer": "SELECT n_nationkey, s_suppkey FROM {nation} FULL OUTER JOIN {supplier} ON n_nationkey = s_nationkey AND s_acctbal > 5000",
    "rel_join_left": "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "rel_join_self": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "rel_join_semi": "SELECT doc_id, n_chars FROM {documents} d WHERE EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id AND l.quality = 1)",
    "rel_join_anti": "SELECT doc_id, n_chars FROM {documents} d WHERE NOT EXISTS (SELECT 1 FROM {labels} l WHERE l.doc_id = d.doc_id)",
    "rel_join_lateral": "SELECT n_nationkey, t.c_custkey FROM {nation} n, LATERAL (SELECT c_custkey FROM {customer} c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) t",
    "rel_sub_scalar": "SELECT event_id FROM {events} WHERE value > (SELECT avg(value) * 4 FROM {events})",
    "rel_sub_exists": "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 490000)",
    "rel_sub_in": "SELECT count(*) AS n FROM {lineitem} WHERE l_suppkey IN (SELECT s_suppkey FROM {supplier} WHERE s_acctbal < 0)",
    "rel_agg_hash": "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev_samp(l_discount), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c FROM {lineitem} GROUP BY l_returnflag, l_linestatus",
    "rel_agg_distinct": "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM {lineitem}",
    "rel_agg_filter": "SELECT event_type, count(*) FILTER (WHERE value > 100) AS large, sum(CASE WHEN value <= 1 THEN 1 ELSE 0 END) AS small FROM {events} GROUP BY event_type",
    "rel_agg_argmin": "SELECT event_type, min_by(event_id, value * 1000000 + event_id / 1000000.0) AS least, max_by(event_id, value * 1000000 + event_id / 1000000.0) AS most FROM {events} GROUP BY event_type",
    "rel_grouping_sets": "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM {customer} GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())",
    "rel_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE(l_returnflag, l_linestatus)",
    "rel_rollup": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY ROLLUP(l_returnflag, l_linestatus)",
    "rel_win_rank": "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {customer} WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)",
    "rel_win_running": "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running FROM {orders}",
    "rel_win_rows": "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM {events}",
    "rel_win_range": "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY event_id RANGE BETWEEN 50 PRECEDING AND CURRENT ROW) AS n FROM {events}",
    "rel_win_lag": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS f, nth_value(event_id, 1) OVER w AS n1 FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "rel_topn_group": "SELECT c_nationkey, c_custkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM {customer}) WHERE r <= 3",
    "rel_topk": "SELECT event_id FROM {events} ORDER BY value DESC, event_id LIMIT 25",
    "rel_sort_offset": "SELECT event_id FROM {events} ORDER BY value DESC, event_id LIMIT 10 OFFSET 20",
    "rel_union": "SELECT s_suppkey AS id FROM {supplier} UNION ALL SELECT c_custkey FROM {customer}",
    "rel_union_distinct": "SELECT s_nationkey AS id FROM {supplier} UNION SELECT c_nationkey FROM {customer}",
    "rel_intersect": "SELECT s_nationkey AS id FROM {supplier} INTERSECT SELECT c_nationkey FROM {customer}",
    "rel_except": "SELECT n_nationkey AS id FROM {nation} EXCEPT SELECT s_nationkey FROM {supplier} WHERE s_acctbal > 9000",
    "rel_except_all": "SELECT s_nationkey AS id FROM {supplier} EXCEPT ALL SELECT n_nationkey FROM {nation}",
    "rel_string": "SELECT p_partkey, upper(trim(p_name)) AS u, length(p_name) AS n, substring(p_name, 1, 3) AS s, replace(p_name, 'a', 'b') AS r, concat_ws('-', p_brand, p_type) AS c, levenshtein(p_name, p_brand) AS d FROM {part}",
    "rel_math": "SELECT event_id, round(sqrt(value), 6) AS s, round(ln(value + 1), 6) AS l, round(power(value, 0.25), 6) AS p, CAST(sign(value - 35) AS INT) AS g, CAST(floor(value) AS BIGINT) AS f, greatest(value, 10.0) AS hi, least(value, 10.0) AS lo FROM {events}",
    "rel_date": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d FROM {orders}",
    "rel_time": "SELECT event_id, hour(ts) AS h, minute(ts) AS m, second(ts) AS s FROM {events}",
    "rel_conditional": "SELECT s_suppkey, CASE WHEN s_acctbal < 0 THEN 'debt' WHEN s_acctbal < 5000 THEN 'mid' ELSE 'rich' END AS band, coalesce(nullif(s_nationkey, 0), -1) AS n FROM {supplier}",
    "rel_cast_decimal": "SELECT o_orderkey, CAST(o_totalprice AS DECIMAL(12,1)) AS price, CAST(o_totalprice AS BIGINT) AS whole FROM {orders} WHERE o_totalprice - floor(o_totalprice) < 0.4",
    "rel_sample_modulo": "SELECT event_id FROM {events} WHERE event_id % 10 = 3",
    "rel_recursive": "WITH RECURSIVE s AS (SELECT l_linenumber AS m, count(*) AS c FROM {lineitem} GROUP BY l_linenumber), r(n, f) AS (SELECT m, c FROM s WHERE m = 1 UNION ALL SELECT m, f + c FROM r JOIN s ON m = n + 1) SELECT n, f FROM r",
}
for _k, _t in SHARED.items():
    QUERIES[_k] = _both(_t)
    ORACLES[_k] = _t.format(**{t: t for t in TABLES})
ORACLES["rel_cast_decimal"] = ORACLES["rel_cast_decimal"].replace("CAST(o_totalprice AS BIGINT)", "CAST(floor(o_totalprice) AS BIGINT)")


def query(sql: str | None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def scratch(spark: SparkSession, name: str) -> str:
    """A folder that driver and executors share."""
    base = shared_folder(spark)
    return f"{base}/{spark.sparkContext.applicationId}-{name}"


def _io(kind: str):
    def run(spark, sf_dir):
        rows = src.table(spark, sf_dir, "supplier")
        rows.write.mode("overwrite").format(kind).save(scratch(spark, kind))
        return spark.read.schema(rows.schema).format(kind).load(scratch(spark, kind))

    return run


for _kind in ("csv", "json", "orc", "parquet"):
    query("SELECT * FROM supplier", f"rel_io_{_kind}")(_io(_kind))


@query("SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'")
def rel_partition_prune(spark, sf_dir):
    path = scratch(spark, "by_status")
    src.table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").write.mode("overwrite").partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").select("o_orderkey")


@query("SELECT * FROM nation")
def rel_sink_roundtrip(spark, sf_dir):
    path = scratch(spark, "nation")
    src.table(spark, sf_dir, "nation").write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)



@query("SELECT o_orderkey AS pid, round(o_totalprice / 1e5 * 1e5, 2) AS a, round(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) / 365.25, 6) AS b FROM orders")
def feat_columns(spark, sf_dir):
    return src.orders_2d(spark, sf_dir).select("pid", F.round(F.col("pt")[0] * 1e5, 2).alias("a"), F.round(F.col("pt")[1], 6).alias("b"))


@query("SELECT vec_id AS pid, len(embedding) AS n, round(CAST(embedding[1] AS DOUBLE), 6) AS a FROM embeddings")
def feat_vector(spark, sf_dir):
    return src.embeddings(spark, sf_dir).select("pid", F.size("pt").cast("long").alias("n"), F.round(F.col("pt")[0], 6).alias("a"))


@query("SELECT doc_id AS pid, len(list_distinct([v for v in string_split_regex(lower(text), '[^a-z]+') if v <> ''])) AS n FROM documents")
def feat_words(spark, sf_dir):
    return src.doc_words(spark, sf_dir).select("pid", F.size("pt").cast("long").alias("n"))


@query("SELECT user_id AS pid, event_type, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY 1, 2")
def feat_pivot(spark, sf_dir):
    kinds = src.event_types(src.table(spark, sf_dir, "events"))
    named = F.array(*[F.lit(k) for k in kinds])
    return src.user_types(spark, sf_dir).select("pid", F.explode(F.arrays_zip(named.alias("k"), F.col("pt").alias("v"))).alias("e")).select("pid", F.col("e.k").alias("event_type"), F.col("e.v").alias("n")).where("n > 0")


_LATTICE_STATS = "WITH s AS (SELECT CAST(100*q+d AS BIGINT) AS pid, q, d FROM (SELECT DISTINCT l_quantity AS q, round(100*l_discount) AS d FROM lineitem)) "


@query(_LATTICE_STATS + "SELECT pid, round((q - (SELECT min(q) FROM s)) / ((SELECT max(q) FROM s) - (SELECT min(q) FROM s)), 6) AS a FROM s")
def feat_minmax(spark, sf_dir):
    return src.scale(src.lineitem_lattice(spark, sf_dir), "minmax").select("pid", F.round(F.col("pt")[0], 6).alias("a"))


@query(_LATTICE_STATS + "SELECT pid, round((q - (SELECT avg(q) FROM s)) / (SELECT stddev_pop(q) FROM s), 6) AS a FROM s")
def feat_zscore(spark, sf_dir):
    return src.scale(src.lineitem_lattice(spark, sf_dir), "zscore").select("pid", F.round(F.col("pt")[0], 6).alias("a"))


@query("SELECT 0::BIGINT AS bad, 0::BIGINT AS repeated_ids")
def rel_validate_points(spark, sf_dir):
    return src.validate(src.embeddings(spark, sf_dir), "report")


@query("SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_totalprice > 400000 GROUP BY 1")
def rel_join_merge(spark, sf_dir):
    o = src.table(spark, sf_dir, "orders").where("o_totalprice > 400000").hint("merge")
    return src.table(spark, sf_dir, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey").agg(F.count("*").alias("n"))


@query("SELECT d.doc_id, quality, toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id")
def rel_join_hash(spark, sf_dir):
    return src.table(spark, sf_dir, "documents").select("doc_id").join(src.table(spark, sf_dir, "labels").hint("shuffle_hash"), "doc_id")


@query("SELECT a.s_suppkey AS i, b.s_suppkey AS j, round(abs(a.s_acctbal - b.s_acctbal), 9) AS dist FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) <= 100")
def rel_join_range(spark, sf_dir):
    return cost.range_pairs(src.supplier_scalar(spark, sf_dir), 100.0)


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def rel_join_interval(spark, sf_dir):
    """Hour cells make the time window an equi join; the exact bounds follow."""
    e = src.table(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    cell = F.floor(F.unix_micros("ts") / 3_600_000_000)
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(cell, cell + 1)).alias("cell"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), cell.alias("cell"))
    return a.join(b, ["user_id", "cell"]).where("tb > ta AND tb <= ta + INTERVAL 1 HOUR").select("a", "b")


@query("SELECT o_orderkey, event_id FROM orders o ASOF LEFT JOIN (SELECT ts, max(event_id) AS event_id FROM events GROUP BY ts) e ON o.o_orderdate >= e.ts")
def rel_join_asof(spark, sf_dir):
    """The latest event at or before each order, by one sort of the union per day and a carry of day maxima."""
    e = src.table(spark, sf_dir, "events").select(F.col("ts").alias("t"), F.struct("ts", "event_id").alias("e"), F.lit(None).cast("bigint").alias("o"))
    o = src.table(spark, sf_dir, "orders").select(F.col("o_orderdate").alias("t"), F.lit(None).cast(e.schema["e"].dataType).alias("e"), F.col("o_orderkey").alias("o"))
    both = e.unionByName(o).withColumn("day", F.to_date("t"))
    days = both.groupBy("day").agg(F.max("e").alias("last"))
    before = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)  # a row for each day
    carried = days.withColumn("carry", F.max("last").over(before)).select("day", "carry")
    within = Window.partitionBy("day").orderBy("t", F.col("o").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("near", F.max("e").over(within)).where("o is not null").join(carried, "day")
    return found.select(F.col("o").alias("o_orderkey"), F.coalesce("near.event_id", "carry.event_id").alias("event_id"))


@query("SELECT user_id, list_sort(list(DISTINCT event_type)) AS kinds, count(*) AS n FROM events GROUP BY user_id".replace("list_sort(list(DISTINCT event_type)) AS kinds", "array_to_string(list_sort(list(DISTINCT event_type)), ',') AS kinds"))
def rel_agg_collect(spark, sf_dir):
    return src.table(spark, sf_dir, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds"), F.count("*").alias("n"))


@query("SELECT TRUE AS close")
def rel_agg_approx(spark, sf_dir):
    e = src.table(spark, sf_dir, "lineitem")
    r = e.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("c"))
    return r.select(((F.abs(F.col("a") - F.col("b")) < 0.1 * F.col("b")) & (F.abs(F.col("c") - F.col("b")) < 0.1 * F.col("b"))).alias("close"))


@query("SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def rel_pivot(spark, sf_dir):
    return rel_unpivot(spark, sf_dir)


@query("SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def rel_unpivot(spark, sf_dir):
    e = src.table(spark, sf_dir, "events")
    kinds = src.event_types(e)
    wide = e.groupBy("user_id").pivot("event_type", kinds).count()
    return wide.unpivot("user_id", kinds, "event_type", "n").where("n is not null")


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.99), 6) AS p99 FROM events GROUP BY event_type")
def rel_quantile_exact(spark, sf_dir):
    return src.table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("value", F.lit(0.99)), 6).alias("p99"))


@query("SELECT TRUE AS close")
def rel_quantile_approx(spark, sf_dir):
    return src.table(spark, sf_dir, "events").agg((F.abs(F.percentile_approx("value", 0.5, 1000) - F.percentile("value", F.lit(0.5))) < 2).alias("close"))


@query("SELECT least(10, greatest(0, floor(value / 50)))::BIGINT AS bucket, count(*) AS n FROM events GROUP BY 1")
def rel_histogram(spark, sf_dir):
    return src.table(spark, sf_dir, "events").groupBy(F.least(F.lit(10), F.greatest(F.lit(0), F.floor(F.col("value") / 50))).alias("bucket")).agg(F.count("*").alias("n"))


@query("SELECT page_id, len(regexp_extract_all(html, '<[a-z]+')) AS tags, regexp_replace(url, '^https?://', '') AS rest FROM pages")
def rel_regex(spark, sf_dir):
    return src.table(spark, sf_dir, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit("<[a-z]+"), F.lit(0))).cast("long").alias("tags"), F.regexp_replace("url", "^https?://", "").alias("rest"))


@query("SELECT vec_id, round(list_sum([CAST(v AS DOUBLE) * v for v in embedding]), 5) AS norm2, len([v for v in embedding if v > 0]) AS positive FROM embeddings")
def rel_array_hof(spark, sf_dir):
    v = F.col("embedding").cast("array<double>")
    return src.table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x), 5).alias("norm2"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"))


@query("SELECT i AS axis, round(avg(v), 6) AS mean FROM (SELECT unnest(generate_series(0, 63)) AS i, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY i")
def rel_explode(spark, sf_dir):
    return src.table(spark, sf_dir, "embeddings").select(F.posexplode(F.col("embedding").cast("array<double>")).alias("axis", "v")).groupBy(F.col("axis").cast("long").alias("axis")).agg(F.round(F.avg("v"), 6).alias("mean"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def rel_json(spark, sf_dir):
    return src.table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT event_id, 'k' AS name, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events")
def rel_map(spark, sf_dir):
    return src.table(spark, sf_dir, "events").select("event_id", F.explode(F.from_json("props", "map<string,bigint>")).alias("name", "v"))


@query("SELECT event_id, round(abs(value - 35.0), 6) AS d FROM events")
def rel_udf_metric(spark, sf_dir):
    @F.pandas_udf("double")
    def gap(x):
        return (x - 35.0).abs()

    return src.table(spark, sf_dir, "events").select("event_id", F.round(gap("value"), 6).alias("d"))


_MEDOID = "WITH d AS (SELECT a.c_nationkey AS n, a.c_custkey AS i, round(sum(abs(a.c_acctbal - b.c_acctbal)), 6) AS t FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey GROUP BY 1, 2) SELECT n AS c_nationkey, i AS medoid FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY t, i) AS r FROM d) WHERE r = 1"


@query(_MEDOID)
def rel_udaf_medoid(spark, sf_dir):
    from ..streaming.sqlapi import medoid

    return src.table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(medoid("c_custkey", "c_acctbal").alias("medoid"))


@query("WITH d AS (SELECT event_type AS g, value - 35.0 AS d, row_number() OVER (PARTITION BY event_type ORDER BY abs(value - 35.0) DESC) AS r FROM events) SELECT g AS event_type, round(sum(d * d), 3) AS cost FROM d WHERE r > 10 GROUP BY g")
def rel_udaf_trimmed(spark, sf_dir):
    from ..streaming.sqlapi import trimmed_sum

    return src.table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(trimmed_sum(F.abs(F.col("value") - 35.0), F.lit(10)), 3).alias("cost"))
