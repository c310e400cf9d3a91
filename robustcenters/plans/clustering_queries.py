"""Queries for the methods, measures and baselines, each with SQL that gives the same rows, or constant invariant rows."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bounds, metrics
from ..operators import coreset as cs
from ..operators import cost, solvers
from ..shared import shared_folder
from ..sources import points as src
from . import audit, baselines
from . import oracles as o
from .pipeline import Model, RobustSpec, build, fit, fit_by, model_of, report, sweep

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def ok_rows(spark: SparkSession, found: dict[str, bool]) -> DataFrame:
    return spark.createDataFrame([(k, bool(v)) for k, v in found.items()], "check_name string, ok boolean")


def first(points: DataFrame, k: int) -> list:
    return cost.center_rows(points.orderBy("pid").limit(k))


def rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, 6) for n in names})


A_EVENTS = "WITH " + o.assigned(o.EVENTS, o.first_centers(o.EVENTS, 5), "abs")
A_LATTICE = "WITH " + o.assigned(o.LATTICE, o.first_centers(o.LATTICE, 4), "l2")
T_EVENTS = "WITH " + o.trimmed(o.EVENTS, o.first_centers(o.EVENTS, 5), "abs", 100)
T_LATTICE = "WITH " + o.trimmed(o.LATTICE, o.first_centers(o.LATTICE, 4), "l2", 700)

# assignment and costs


def _assign(metric):
    def run(spark, sf_dir):
        p = src.embeddings(spark, sf_dir)
        return rounded(cost.assign(p, first(p, 10), metric).select("pid", "cid", "dist"), "dist")

    return run


for _m in ("l2", "angular"):
    query("WITH " + o.assigned(o.EMBEDDINGS, o.first_centers(o.EMBEDDINGS, 10), _m) + " SELECT pid, cid, round(dist, 6) AS dist FROM a", f"assign_nearest_{_m}")(_assign(_m))

_WORDS = "SELECT {id} AS pid, list_distinct([v for v in string_split_regex(lower(text), '[^a-z]+') if v <> '']) AS x, 1 AS w FROM {t}"


@query("WITH " + o.assigned(_WORDS.format(id="doc_id", t="documents"), "SELECT pid AS cid, x AS cx FROM (" + _WORDS.format(id="item_id", t="benchmark") + ")", "jaccard") + " SELECT pid, cid, round(dist, 6) AS dist FROM a WHERE dist < 1")
def assign_foreign_centers(spark, sf_dir):
    """Benchmark passages as centers of all documents."""
    docs = src.doc_words(spark, sf_dir)
    centers = src.from_words(src.table(spark, sf_dir, "benchmark"), "item_id", "text")
    return rounded(cost.assign(docs, centers, "jaccard").where("dist < 1").select("pid", "cid", "dist"), "dist")


@query(A_EVENTS + " SELECT pid, cid, round(dist, 6) AS dist FROM a")
def assign_block_kernel(spark, sf_dir):
    """The same rows from the block kernel that serves large center sets."""
    p = src.events_scalar(spark, sf_dir)
    return rounded(cost._assign_blocks(p, first(p, 5), metrics.ABS).select("pid", "cid", "dist"), "dist")


@query(A_EVENTS + " SELECT round(sum(dist * dist), 4) AS cost FROM a")
def cost_plain(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return cost.cost(p, first(p, 5), "abs").select(F.round("cost", 4).alias("cost"))


@query(A_LATTICE + " SELECT round(sum(w * dist * dist), 4) AS cost FROM a")
def cost_weighted(spark, sf_dir):
    p = src.lineitem_lattice(spark, sf_dir)
    return cost.cost(p, first(p, 4), "l2").select(F.round("cost", 4).alias("cost"))


@query(A_EVENTS + " SELECT round(sum(dist), 4) AS cost FROM a")
def cost_kmedian(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return cost.cost(p, first(p, 5), "abs", 1).select(F.round("cost", 4).alias("cost"))


@query(A_EVENTS + " SELECT pid, round(dist, 6) AS dist FROM a ORDER BY a.dist DESC, pid LIMIT 100")
def farthest_z(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return rounded(cost.farthest(p, first(p, 5), 100, "abs"), "dist")


@query(T_EVENTS + " SELECT round(sum(w_hat * dist * dist), 4) AS cost FROM t")
def cost_trimmed(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return cost.trimmed_cost(p, first(p, 5), 100, "abs").select(F.round("cost", 4).alias("cost"))


@query(T_EVENTS + " SELECT round(sum(w_hat * dist), 4) AS cost FROM t")
def cost_trimmed_kmedian(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return cost.trimmed_cost(p, first(p, 5), 100, "abs", 1).select(F.round("cost", 4).alias("cost"))


@query(T_LATTICE + " SELECT round(sum(w_hat * dist * dist), 4) AS cost FROM t")
def cost_weighted_trimmed(spark, sf_dir):
    p = src.lineitem_lattice(spark, sf_dir)
    return cost.trimmed_cost(p, first(p, 4), 700, "l2").select(F.round("cost", 4).alias("cost"))


@query(T_LATTICE + " SELECT pid, w, CAST(w_hat AS BIGINT) AS w_hat FROM t")
def trim_weights_rows(spark, sf_dir):
    p = src.lineitem_lattice(spark, sf_dir)
    return cost.trim_weights(p, first(p, 4), 700, "l2")


@query(A_EVENTS + " SELECT round(sum(dist * dist), 4) AS cost FROM a WHERE pid % 50 <> 3")
def cost_without_given(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    return cost.cost_without(p, p.where("pid % 50 = 3"), first(p, 5), "abs").select(F.round("cost", 4).alias("cost"))


@query(A_EVENTS + ", cut AS (SELECT dist FROM a ORDER BY dist DESC, pid LIMIT 1 OFFSET 99) SELECT round(cut.dist, 6) AS threshold, (SELECT count(*) FROM a WHERE a.dist > cut.dist) AS above, (SELECT count(*) FROM a WHERE a.dist = cut.dist) AS at_threshold FROM cut")
def range_cut_threshold(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    t, above, at = cost.range_cut(cost.assign(p, first(p, 5), "abs"), 100, buckets=64, sort_rows=50)
    return spark.createDataFrame([(round(t, 6), int(above), int(at))], "threshold double, above long, at_threshold long")


# exact optima and inequalities

_S = o.SUPPLIER


def _suppliers(spark, sf_dir):
    return src.supplier_scalar(spark, sf_dir)


def _nations(spark, sf_dir):
    """All nations by their customers' mean balance, of mass one: 25 points at any size, for what is cubic or worse."""
    return src.nation_balances(spark, sf_dir).select("pid", "pt")


@query(o.optimum(_S, "abs", 2, 0))
def opt_k_bruteforce(spark, sf_dir):
    return cost.optimum(_suppliers(spark, sf_dir), 2, 0, "abs")


@query(o.optimum(_S, "abs", 2, 3))
def opt_kz_bruteforce(spark, sf_dir):
    return cost.optimum(_suppliers(spark, sf_dir), 2, 3, "abs")


@query(o.optimum(o.PARTS, "edit", 2, 40))
def opt_kz_weighted(spark, sf_dir):
    return cost.optimum(src.part_names(spark, sf_dir), 2, 40, "edit")


@query(o.optimum(_S, "abs", 2, 3, 1))
def opt_kmedian_bruteforce(spark, sf_dir):
    return cost.optimum(_suppliers(spark, sf_dir), 2, 3, "abs", 1)


@query(o.checks("more centers are no worse"))
def extra_centers_inequality(spark, sf_dir):
    p = _nations(spark, sf_dir)
    a, b = cost.optimum(p, 3, 0, "abs").first()["cost"], cost.optimum(p, 2, 1, "abs").first()["cost"]
    return ok_rows(spark, {"more centers are no worse": a <= b + 1e-9})


@query(f"SELECT 0::BIGINT AS violations, count(*) AS triples FROM ({o.NATIONS}) a, ({o.NATIONS}) b, ({o.NATIONS}) c")
def relaxed_triangle_violations(spark, sf_dir):
    """d(p,r)^2 <= (1+c) d(p,q)^2 + (1+1/c) d(q,r)^2 on all triples of nations, for several c."""
    p = _nations(spark, sf_dir)
    a, b, c = (p.select(F.col("pid").alias(f"i{n}"), F.col("pt").alias(f"x{n}")) for n in "abc")
    sq = lambda x, y: F.pow(F.col(x) - F.col(y), F.lit(2))
    bad = F.lit(False)
    for t in (0.1, 0.5, 1.0, 2.0, 10.0):
        bad = bad | (sq("xa", "xc") > (1 + t) * sq("xa", "xb") + (1 + 1 / t) * sq("xb", "xc") + 1e-6)
    return a.crossJoin(b).crossJoin(c).agg(F.count_if(bad).alias("violations"), F.count("*").alias("triples"))


def _axioms(metric, make, along):
    def run(spark, sf_dir):
        return (metrics.axiom_violations_along if along else metrics.axiom_violations)(make(spark, sf_dir), metric() if callable(metric) else metric)

    return run


def _lattice(spark, sf_dir):
    return src.lineitem_lattice(spark, sf_dir).select("pid", "pt")


def _places(spark, sf_dir):
    """Invented coordinates of nations: latitude and longitude by key."""
    k = F.col("n_nationkey")
    return src.from_columns(src.table(spark, sf_dir, "nation"), "n_nationkey", [k * 7 % 180 - 90, k * 29 % 360 - 180])


def _region_hops():
    """Regions on a ring, the distance being the steps between two."""
    return metrics.lookup("region_ring", [[min(abs(i - j), 5 - abs(i - j)) for j in range(5)] for i in range(5)])


#: Metric, points and whether every point meets the next two ids (whole large tables) or all triples are taken (small tables).
_AXIOMS = {
    "l1": ("l1", _lattice, True),
    "l2": ("l2", _lattice, True),
    "linf": ("linf", _lattice, True),
    "l3": (lambda: metrics.lp(3), _lattice, True),
    "hamming": ("hamming", _lattice, True),
    "edit": ("edit", lambda s, d: src.part_names(s, d).select("pid", "pt"), False),
    "discrete": ("discrete", lambda s, d: src.part_names(s, d).select("pid", "pt"), False),
    "jaccard": ("jaccard", src.doc_words, True),
    "ultra": ("ultra", lambda s, d: src.from_columns(src.table(s, d, "nation"), "n_nationkey", ["n_nationkey", "n_regionkey"]), False),
    "haversine": ("haversine", _places, False),
    "lookup": (_region_hops, lambda s, d: src.from_scalar(src.table(s, d, "region"), "r_regionkey", "r_regionkey"), False),
    "angular": ("angular", src.embeddings, True),
}
_NEXT_TWO = "SELECT 0::BIGINT AS identity, 0::BIGINT AS symmetry, 0::BIGINT AS triangle, count(*) AS triples FROM ({p}) a JOIN ({p}) b ON b.pid = a.pid + 1 JOIN ({p}) c ON c.pid = a.pid + 2"
_ALONG = {"jaccard": "SELECT doc_id AS pid FROM documents", "angular": o.EMBEDDINGS}
for _name, (_metric, _make, _along) in _AXIOMS.items():
    query(_NEXT_TWO.format(p=_ALONG.get(_name, o.LATTICE)) if _along else "SELECT 0::BIGINT AS identity, 0::BIGINT AS symmetry, 0::BIGINT AS triangle", f"metric_axioms_{_name}")(_axioms(_metric, _make, _along))


@query("WITH " + o.assigned("SELECT s_suppkey AS pid, s_nationkey % 5 AS x, 1 AS w FROM supplier", "SELECT r_regionkey AS cid, r_regionkey AS cx FROM region WHERE r_regionkey IN (0, 2)", "abs").replace("abs(x - cx)", "least(abs(x - cx), 5 - abs(x - cx))") + " SELECT pid, cid, CAST(dist AS DOUBLE) AS dist FROM a")
def assign_lookup(spark, sf_dir):
    """Nearest of two regions on a ring that is given by its matrix."""
    p = src.from_scalar(src.table(spark, sf_dir, "supplier"), "s_suppkey", F.col("s_nationkey") % 5)
    return cost.assign(p, [(0, 0.0), (2, 2.0)], _region_hops()).select("pid", "cid", "dist")


@query("SELECT CAST(event_id AS BIGINT) AS pid FROM events")
def partition_random(spark, sf_dir):
    """Every point is in one of the parts, which differ by seed."""
    p = src.events_scalar(spark, sf_dir)
    a, b = (src.partition(p, 5, "random", seed) for seed in (1, 2))
    moved = a.join(b.select("pid", F.col("part_id").alias("other")), "pid")
    if not moved.agg(F.max("part_id") < 5).first()[0] or moved.where("part_id <> other").isEmpty():
        raise ValueError("parts do not depend on the seed")
    return moved.select("pid")


@query(o.checks("squared distance breaks the triangle", "one minus cosine is flagged"))
def non_metrics_flagged(spark, sf_dir):
    v = metrics.axiom_violations_along(_lattice(spark, sf_dir), "squared_l2").first()
    return ok_rows(spark, {"squared distance breaks the triangle": v["triangle"] > 0 and not metrics.SQUARED.is_metric, "one minus cosine is flagged": not metrics.COSINE.is_metric})


# partitioning and seeding


@query("SELECT CAST(event_id % 7 AS INT) AS part_id, count(*) AS n FROM events GROUP BY 1")
def partition_modulo(spark, sf_dir):
    return src.partition(src.events_scalar(spark, sf_dir), 7, "modulo").groupBy("part_id").agg(F.count("*").alias("n"))


@query("SELECT CAST((row_number() OVER (ORDER BY event_id) - 1) % 7 AS INT) AS part_id, event_id AS pid FROM events")
def partition_even(spark, sf_dir):
    return src.partition(src.events_scalar(spark, sf_dir), 7, "even").select("part_id", "pid")


@query(o.checks("sizes within a fifth", "every row once"))
def partition_hash_sizes(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    n = [r["count"] for r in src.partition(p, 4).groupBy("part_id").count().collect()]
    return ok_rows(spark, {"sizes within a fifth": max(n) < 1.2 * sum(n) / len(n), "every row once": sum(n) == p.count()})


@query("SELECT pid, CAST(pid % 4 AS INT) AS part_id FROM (SELECT *, row_number() OVER (PARTITION BY pid % 4 ORDER BY pid) AS r FROM (" + o.EVENTS + ")) WHERE r <= 5")
def seed_first_ids(spark, sf_dir):
    return cs.seed(src.partition(src.events_scalar(spark, sf_dir), 4, "modulo"), 5, "first_ids", "abs").select("pid", "part_id")


@query("WITH RECURSIVE base AS (" + o.EVENTS + "), " + o.farthest_seeds("f", "base", "abs", 8) + " SELECT cid AS pid FROM f")
def seed_farthest(spark, sf_dir):
    return cs.seed(src.events_scalar(spark, sf_dir).withColumn("part_id", F.lit(0)), 8, "farthest", "abs").select("pid")


def _seed_checks(method):
    def run(spark, sf_dir):
        p = src.partition(src.events_scalar(spark, sf_dir), 4)
        a, b = (sorted(r["pid"] for r in cs.seed(p, 6, method, "abs").collect()) for _ in range(2))
        base, got = cost.cost(p, first(p, 24), "abs").first()[0], cost.cost(p, p.where(F.col("pid").isin(a)), "abs").first()[0]
        return ok_rows(spark, {"repeats": a == b, "members": p.where(F.col("pid").isin(a)).count() == len(a), "no more than k": len(a) <= 24, "better than the first ids": got < base})

    return run


for _m in ("dsq", "swap"):
    query(o.checks("repeats", "members", "no more than k", "better than the first ids"), f"seed_{_m}_checks")(_seed_checks(_m))


@query(o.checks("members", "more seeds cost less", "reduced to k"))
def seed_rounds_checks(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    s = cs.seed_rounds(p, 10, "abs", rounds=3)
    ten = cs.seed_rounds(p, 10, "abs", rounds=3, reduce=True)
    ids = [i for i, _ in s]
    at = [cost.cost(p, x, "abs").first()[0] for x in (s, ten, first(p, 10), s[:2])]
    return ok_rows(spark, {"members": p.where(F.col("pid").isin(ids)).count() == len(ids), "more seeds cost less": at[0] < at[3], "reduced to k": len(ten) == 10 and at[0] <= at[1] < at[2]})


# covers and coresets against recursive SQL; seeds are the least ids, parts are pid % 4

K, PARTS_N = 4, 4
DELTA = 0.25
ONE = "WITH RECURSIVE " + o.round_one(o.EVENTS, "abs", K, DELTA, PARTS_N)
DIRECT = ONE + ", " + o.radius() + ", " + o.round_two("one_y", "abs", DELTA)
REFINED = ONE + ", " + o.radius() + ", " + o.compact("abs", K, DELTA) + ", " + o.round_two("mini_y", "abs", DELTA)
GAMMA = DELTA * math.sqrt(2)


def _events(spark, sf_dir):
    return src.events_scalar(spark, sf_dir)


def _build(spark, sf_dir, variant, **more):
    return cs.build(_events(spark, sf_dir), K, 0, GAMMA, variant, "abs", parts=PARTS_N, seeding="first_ids", scheme="modulo", **more)


def _values(rows):
    return rows.select("pid", "w", "part_id")


@query(ONE + " SELECT CAST(part AS INT) AS part_id, n, round(cost, 6) AS cost, round(radius, 6) AS radius FROM sums")
def partition_radius(spark, sf_dir):
    return rounded(_build(spark, sf_dir, "one_round").stats["summaries"].select("part_id", "n", "cost", "radius"), "cost", "radius")


@query(ONE + ", " + o.radius() + " SELECT round(r, 6) AS radius FROM rad")
def global_radius(spark, sf_dir):
    return spark.createDataFrame([(round(_build(spark, sf_dir, "one_round").radius, 6),)], "radius double")


@query(ONE + " SELECT pid, w, CAST(part AS INT) AS part_id FROM one_y")
def round_one_values(spark, sf_dir):
    return _values(_build(spark, sf_dir, "one_round").rows)


QUERIES["coreset_one_round"], ORACLES["coreset_one_round"] = round_one_values, ORACLES["round_one_values"]


@query(DIRECT + " SELECT pid, w, CAST(part AS INT) AS part_id FROM two_y")
def coreset_direct_values(spark, sf_dir):
    return _values(_build(spark, sf_dir, "direct").rows)


@query(ONE + ", " + o.radius() + ", " + o.compact("abs", K, DELTA) + " SELECT pid, w FROM mini_y")
def compact_reference_values(spark, sf_dir):
    c = _build(spark, sf_dir, "one_round")
    return cs.compact(c.rows, K, c.delta, c.radius, "first_ids", "abs").select("pid", "w")


@query(REFINED + " SELECT pid, w, CAST(part AS INT) AS part_id FROM two_y")
def coreset_refined_values(spark, sf_dir):
    return _values(_build(spark, sf_dir, "refined").rows)


_one_power1 = "WITH RECURSIVE " + o.round_one(o.EVENTS, "abs", K, DELTA, PARTS_N, 1)


@query(_one_power1 + ", " + o.radius(1) + ", " + o.round_two("one_y", "abs", DELTA) + " SELECT pid, w, CAST(part AS INT) AS part_id FROM two_y")
def coreset_kmedian(spark, sf_dir):
    return _values(cs.build(_events(spark, sf_dir), K, 0, 2 * DELTA, "direct", "abs", 1, parts=PARTS_N, seeding="first_ids", scheme="modulo").rows)


@query("WITH RECURSIVE " + o.round_one(o.EVENTS, "abs", 7, DELTA, PARTS_N) + ", " + o.radius() + ", " + o.round_two("one_y", "abs", DELTA) + " SELECT pid, w, CAST(part AS INT) AS part_id FROM two_y")
def coreset_with_outliers(spark, sf_dir):
    """k = 4, z = 3: seeds are k + z a part."""
    return _values(cs.build(_events(spark, sf_dir), 4, 3, GAMMA, "direct", "abs", parts=PARTS_N, seeding="first_ids", scheme="modulo").rows)


QUERIES["coreset_no_outliers"], ORACLES["coreset_no_outliers"] = coreset_direct_values, ORACLES["coreset_direct_values"]


def _cover_oracle(points, metric, refs, delta, radius, tail):
    base = f"pts AS (SELECT 0 AS part, * FROM ({points})), refs AS (SELECT pid, x FROM pts ORDER BY pid LIMIT {refs}), base AS (SELECT p.part, p.pid, any_value(p.x) AS x, any_value(p.w) AS w, round({delta} * greatest({radius}, min({o.dist(metric, 'p.x', 'r.x')})), 9) AS thr FROM pts p, refs r GROUP BY p.part, p.pid)"
    return f"WITH RECURSIVE {base}, " + o.cover("c", "base", metric) + tail


def _cover(points, metric, refs, delta, radius, proxies=False):
    p = points.withColumn("part_id", F.lit(0))
    return cs.ball_cover(p, first(points, refs), delta, radius, metric, proxies=proxies)


_Y = " SELECT pid, w FROM c_y"


@query(_cover_oracle(o.EVENTS, "abs", 5, 0.25, 10.0, _Y))
def ball_cover_values(spark, sf_dir):
    return _cover(_events(spark, sf_dir), "abs", 5, 0.25, 10.0).select("pid", "w")


@query(_cover_oracle(o.LATTICE, "l2", 4, 0.25, 4.0, _Y))
def ball_cover_weighted(spark, sf_dir):
    return _cover(src.lineitem_lattice(spark, sf_dir), "l2", 4, 0.25, 4.0).select("pid", "w")


@query(_cover_oracle(o.EVENTS, "abs", 5, 0.25, 10.0, " SELECT pid, proxy AS proxy_id, round(pd, 6) AS proxy_dist FROM c"))
def ball_cover_proxies(spark, sf_dir):
    return rounded(_cover(_events(spark, sf_dir), "abs", 5, 0.25, 10.0, True).select("pid", "proxy_id", "proxy_dist"), "proxy_dist")


@query(_cover_oracle(o.EVENTS, "abs", 5, 0.25, 10.0, " SELECT proxy AS proxy_id, count(*) AS w FROM c GROUP BY proxy"))
def proxy_weights(spark, sf_dir):
    """Weights from the map alone."""
    return _cover(_events(spark, sf_dir), "abs", 5, 0.25, 10.0, True).groupBy("proxy_id").agg(F.count("*").alias("w"))


@query(_cover_oracle(o.PARTS, "edit", 3, 0.5, 12.0, _Y))
def ball_cover_edit(spark, sf_dir):
    return _cover(src.part_names(spark, sf_dir), "edit", 3, 0.5, 12.0).select("pid", "w")


@query(f"SELECT min(pid) AS pid, count(*) AS w FROM ({o.EVENTS}) GROUP BY x")
def ball_cover_zero_radius(spark, sf_dir):
    """Radius 0 with every point a reference merges exact copies only; the same as collapsing."""
    p = _events(spark, sf_dir)
    return cs.ball_cover(p.withColumn("part_id", F.lit(0)), p, 0.25, 0.0, "abs").select("pid", "w")


@query(f"SELECT min(pid) AS pid, count(*) AS w FROM ({o.EVENTS}) GROUP BY x")
def collapse_duplicates(spark, sf_dir):
    return src.collapse(src.events_scalar(spark, sf_dir)).select("pid", "w")


def _pick_checks(pick):
    def run(spark, sf_dir):
        p = src.partition(src.events_scalar(spark, sf_dir), 2)
        refs = first(p, 5)
        rows, prox = (cs.ball_cover(p, refs, 0.3, 20.0, "abs", pick, x) for x in (False, True))
        return ok_rows(spark, {"mass": audit.mass(rows) == p.count(), "no violation": audit.cover_violations(prox).first()[0] == 0, "picked is own proxy": prox.join(rows.select("pid"), "pid", "left_semi").where("pid <> proxy_id").count() == 0})

    return run


for _m in ("farthest", "random", "densest"):
    query(o.checks("mass", "no violation", "picked is own proxy"), f"ball_cover_{_m}_checks")(_pick_checks(_m))


@query("SELECT CAST(count(*) AS BIGINT) AS w FROM events")
def coreset_merge_mass(spark, sf_dir):
    """Coresets of two halves, united and covered again."""
    p = src.events_scalar(spark, sf_dir)
    halves = [cs.build(p.where(F.col("pid") % 2 == i), 5, 20, 0.5, "refined", "abs", parts=2).rows for i in (0, 1)]
    return cs.recover(cs.merge(*halves), 25, 0.5, metric="abs").agg(F.sum("w").alias("w"))


@query(o.checks("mass", "smaller reference", "certificate"))
def coreset_tree_checks(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    c = cs.build(p, 5, 20, 0.5, "direct", "abs", parts=8, levels=1, fan_in=2)
    e = audit.proxy_distortion(cs.proxies(p, c, "abs")).first()[0]
    s = first(p, 5)
    full, small = cost.cost(p, s, "abs").first()[0], cost.cost(c.rows, s, "abs").first()[0]
    return ok_rows(spark, {"mass": audit.mass(c.rows) == p.count(), "smaller reference": c.reference.num_rows <= c.stats["first"].count(), "certificate": abs(full - small) <= audit.certificate(e, full) + 1e-6})


# complete algorithm, solvers, models


def _exact_fit(variant):
    def run(spark, sf_dir):
        p = _suppliers(spark, sf_dir)
        m = fit(p, RobustSpec(2, 3, GAMMA, variant, "abs", parts=2, seeding="first_ids", scheme="modulo", solver="exhaustive"))
        return spark.createDataFrame([(",".join(str(i) for i, _ in m.centers), round(m.cost, 6))], "centers string, cost double")

    return run


for _v in ("direct", "refined"):
    _s1 = "WITH RECURSIVE " + o.round_one(_S, "abs", 5, DELTA, 2) + ", " + o.radius() + (", " + o.compact("abs", 5, DELTA) if _v == "refined" else "") + ", " + o.round_two("mini_y" if _v == "refined" else "one_y", "abs", DELTA)
    query(_s1 + ", " + o.optimum("SELECT pid, x, w FROM two_y", "abs", 2, 3).removeprefix("WITH "), f"fit_{_v}_exact")(_exact_fit(_v))


def _solver_checks(solver, checks, **options):
    def run(spark, sf_dir):
        p = src.part_names(spark, sf_dir)
        rows = {r["kind"]: r["value"] for r in solvers.solve(p, 3, 40, solver, "edit", **options).collect() if r["pid"] is None}
        all_rows = solvers.solve(p, 3, 40, solver, "edit", **options).collect()
        n = sum(r["kind"] == "center" for r in all_rows)
        mass = sum(r["value"] for r in all_rows if r["kind"] == "outlier")
        inl = sum(r["value"] for r in all_rows if r["kind"] == "center")
        best = {r["kind"]: r["value"] for r in solvers.solve(p, 3, 40, "exhaustive", "edit").collect() if r["pid"] is None}["cost"]
        total = audit.mass(p)
        return ok_rows(spark, {k: f(rows, n, mass, best, inl, total) for k, f in checks.items()})

    return run


_mass_kept = lambda r, n, m, b, i, t: abs(m + i - t) < 1e-9
query(o.checks("mass kept", "three centers", "within 274", "never rises"), "fit_trimmed_swap_checks")(
    _solver_checks("trimmed_swap", {"mass kept": _mass_kept, "three centers": lambda r, n, m, b, i, t: n == 3, "within 274": lambda r, n, m, b, i, t: r["cost"] <= 274 * b + 1e-9, "never rises": lambda r, n, m, b, i, t: r["cost"] <= r["stat:start_cost"] + 1e-9})
)
query(o.checks("mass kept", "exactly z", "at most (1+eps)k", "never rises"), "fit_multi_swap_checks")(
    _solver_checks("multi_swap", {"mass kept": _mass_kept, "exactly z": lambda r, n, m, b, i, t: m == 40, "at most (1+eps)k": lambda r, n, m, b, i, t: n <= 4, "never rises": lambda r, n, m, b, i, t: r["cost"] <= r["stat:start_cost"] + 1e-9}, eps=0.5, swap_size=2)
)
query(o.checks("exactly z", "extra centers used"), "fit_multi_swap_add_drop")(
    _solver_checks("multi_swap", {"exactly z": lambda r, n, m, b, i, t: m == 40, "extra centers used": lambda r, n, m, b, i, t: 3 <= n <= 4}, eps=0.34, swap_size=1, allow=("add", "drop", "swap"))
)
for _m in ("plain_then_trim", "alternate"):
    query(o.checks("exactly z", "not under the optimum"), "fit_plain_trim" if _m == "plain_then_trim" else "fit_alternate")(
        _solver_checks(_m, {"exactly z": lambda r, n, m, b, i, t: m == 40, "not under the optimum": lambda r, n, m, b, i, t: r["cost"] >= b - 1e-9})
    )
query(o.checks("equals the exact trim"), "solver_kmedian")(_solver_checks("exhaustive", {"equals the exact trim": lambda r, n, m, b, i, t: m == 40}, power=1))


@query(o.checks("same cost"))
def solver_identity_replicated(spark, sf_dir):
    """Nations with the number of their suppliers as weight, and as many equal points, cost the same with the same mass forgotten."""
    suppliers = src.table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").cast("bigint").alias("pid")).agg(F.count("*").alias("w"))
    p = _nations(spark, sf_dir).join(suppliers, "pid").select("pid", "pt", "w")
    found = []
    for x in (p, baselines.replicated(p)):
        rows = solvers.solve(x, 3, 4, "trimmed_swap", "abs", init="farthest").collect()
        found.append((next(r["value"] for r in rows if r["kind"] == "cost"), sum(r["value"] for r in rows if r["kind"] == "outlier")))
    (a, m), (b, n) = found
    return ok_rows(spark, {"same cost": abs(a - b) <= 1e-9 * max(a, b, 1.0) and m == n})


_SPEC = RobustSpec(5, 100, 0.5, "refined", "abs", parts=4, outlier_factor=2.0, options={"eps": 0.5})


@query(o.checks("exactly z outliers", "every point once", "reload equals"))
def model_transform_outliers(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    m = fit(p, _SPEC)
    t = m.transform(p)
    found = {"exactly z outliers": t.where("is_outlier").count() == 100, "every point once": t.count() == p.count()}
    path = f"{shared_folder(spark)}/model-{spark.sparkContext.applicationId}"
    m.save(path)
    found["reload equals"] = Model.load(spark, path).centers == m.centers
    return ok_rows(spark, found)


@query("SELECT n_nationkey AS key, least(2, count(*)) AS centers, count(*) - least(3, count(*) - 1) AS weight FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def fit_per_nation(spark, sf_dir):
    c = src.table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("bigint").alias("pid"), F.col("c_acctbal").alias("pt"), "c_nationkey")
    return fit_by(c, "c_nationkey", RobustSpec(2, 3, metric="abs", solver="plain_then_trim")).groupBy("key").agg(F.count("*").alias("centers"), F.sum("weight").alias("weight"))


@query(o.checks("more centers cost less", "more outliers cost less"))
def sweep_k_cost(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    rows = {(k, z): c for k, z, c in sweep(p, RobustSpec(8, 100, 0.5, "refined", "abs", parts=4, solver="plain_then_trim"), [(2, 50), (4, 50), (8, 50), (4, 100)])}
    return ok_rows(spark, {"more centers cost less": rows[2, 50] > rows[4, 50] > rows[8, 50], "more outliers cost less": rows[4, 100] < rows[4, 50]})


# audits


@query(o.checks("coreset error", "certificate", "violations", "mass", "distortion"))
def coreset_error_given(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    c = cs.build(p, 5, 20, 0.5, "direct", "abs", parts=4)
    prox = cs.checkpoint(cs.proxies(p, c, "abs"))
    s = first(p, 5)
    z = cost.farthest(p, s, 20, "abs")
    r = audit.coreset_error(p, c.rows, prox, s, z, "abs").first()
    e = audit.proxy_distortion(prox).first()[0]
    seeds = c.stats["summaries"].agg(F.sum("cost")).first()[0]
    return ok_rows(spark, {
        "coreset error": r["error"] <= bounds.coreset_quality(0.5, "direct"), "certificate": abs(r["full"] - r["small"]) <= audit.certificate(e, r["full"]) + 1e-6,
        "violations": audit.cover_violations(prox).first()[0] == 0, "mass": audit.mass(c.rows) == p.count(), "distortion": e <= 4 * 0.25 * seeds,
    })


def _recursive_measure(tail):
    return "WITH RECURSIVE " + o.round_one(o.EVENTS, "abs", K, DELTA, PARTS_N) + ", " + o.radius() + ", " + o.round_two("one_y", "abs", DELTA) + tail


@query(_recursive_measure(" SELECT round(sum(pd * pd), 4) AS distortion FROM two"))
def proxy_distortion(spark, sf_dir):
    c = _build(spark, sf_dir, "direct")
    return audit.proxy_distortion(cs.proxies(_events(spark, sf_dir), c, "abs")).select(F.round("distortion", 4).alias("distortion"))


@query(_recursive_measure(" SELECT count(*) FILTER (WHERE pd > thr) AS violations FROM two"))
def cover_violations(spark, sf_dir):
    c = _build(spark, sf_dir, "direct")
    return audit.cover_violations(cs.proxies(_events(spark, sf_dir), c, "abs"))


@query(_recursive_measure(" SELECT (SELECT count(*) FROM one_y) AS first, (SELECT count(*) FROM two_y) AS coreset, (SELECT CAST(sum(w) AS BIGINT) FROM two_y) AS mass"))
def coreset_sizes(spark, sf_dir):
    c = _build(spark, sf_dir, "direct")
    s = audit.sizes(c)
    return spark.createDataFrame([(s["first"], s["coreset"], audit.mass(c.rows))], "first long, coreset long, mass long")


@query(_recursive_measure(" SELECT (SELECT max(n) FROM (SELECT count(*) AS n FROM pts GROUP BY part)) AS round_1, (SELECT max(n) FROM (SELECT count(*) AS n FROM pts GROUP BY part)) + (SELECT count(*) FROM one_y) AS round_2, (SELECT count(*) FROM two_y) AS round_3"))
def local_memory(spark, sf_dir):
    c = _build(spark, sf_dir, "direct")
    m = audit.local_memory(c.stats["routed"], c)
    return spark.createDataFrame([(m["round_1"], m["round_2"], m["round_3"])], "round_1 long, round_2 long, round_3 long")


@query("SELECT 'direct' AS variant, 2 AS coreset, 3 AS complete UNION ALL SELECT 'refined', 2, 3 UNION ALL SELECT 'one_round', 1, 2")
def rounds_table(spark, sf_dir):
    """Rounds as shuffles of points in the physical plans of the steps; what a refined reference gathers is no round of points."""
    p = _events(spark, sf_dir)
    found = []
    for variant in ("direct", "refined", "one_round"):
        c = _build(spark, sf_dir, variant)
        one = audit.exchanges(cs.round_one(cs.narrow(src.partition(p, PARTS_N, "modulo")), K, c.delta, "first_ids", "abs"))
        two = 0 if variant == "one_round" else audit.exchanges(cs.ball_cover(c.stats["routed"], c.reference, c.delta, c.radius, "abs"))
        three = audit.exchanges(solvers.solve(c.rows, K, 0, "alternate", "abs"))
        found.append((variant, one + two, one + two + three))
    return spark.createDataFrame(found, "variant string, coreset int, complete int")


_GAMMAS = "SELECT DISTINCT round(l_discount + l_tax, 2) AS g FROM lineitem WHERE l_discount + l_tax > 0 AND l_discount + l_tax < 1"


@query(f"SELECT g, round(4*g + 4*g*g, 9) AS direct_quality, round(11*g*g + 2*sqrt(11)*g, 9) AS refined_quality, round(27*g, 9) AS direct_slack, round(47*g, 9) AS refined_slack, g <= sqrt(0.375) - 0.5 AS direct_ok, g <= (sqrt(3) - sqrt(2)) / 6 AS refined_ok FROM ({_GAMMAS})")
def bounds_table(spark, sf_dir):
    """The closed forms at every precision that discount and tax of a line make together."""
    each = F.col("l_discount") + F.col("l_tax")
    gammas = src.table(spark, sf_dir, "lineitem").where((each > 0) & (each < 1)).select(F.round(each, 2).alias("g")).distinct()

    def run(batches):
        for batch in batches:
            g = batch.column(0).to_pylist()
            found = [g, *([round(f(x, v), 9) for x in g] for f in (bounds.coreset_quality, bounds.centroid_slack) for v in ("direct", "refined")), *([bounds.check_gamma(x, v, False) for x in g] for v in ("direct", "refined"))]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.float64()) for x in found[:5]] + [pa.array(x, pa.bool_()) for x in found[5:]], names=["g", "direct_quality", "refined_quality", "direct_slack", "refined_slack", "direct_ok", "refined_ok"])

    return gammas.mapInArrow(run, "g double, direct_quality double, refined_quality double, direct_slack double, refined_slack double, direct_ok boolean, refined_ok boolean")


@query(o.checks(*[n for n, _ in bounds.constants_hold()]))
def constants_table(spark, sf_dir):
    """The facts on a grid that all distinct event values make, from 0 to the direct cap."""
    values = src.table(spark, sf_dir, "events").where("value > 0").select("value").distinct()
    top = values.agg(F.max("value")).first()[0]

    def run(batches):
        for batch in batches:
            found = bounds.constants_hold([bounds.DIRECT_CAP * x / top for x in batch.column(0).to_pylist()])
            yield pa.RecordBatch.from_pydict({"check_name": [n for n, _ in found], "ok": [bool(ok) for _, ok in found]})

    return values.mapInArrow(run, "check_name string, ok boolean").groupBy("check_name").agg(F.bool_and("ok").alias("ok"))


_GUARANTEES = ("error", "centroid", "witness", "end to end", "distortion", "compact reference")


def _guarantees(variant, g):
    def run(spark, sf_dir):
        """Guarantees against the true optimum on all nations, with exhaustive seeding so that beta is 1."""
        from itertools import combinations

        p = cs.checkpoint(_nations(spark, sf_dir))
        opt, wide = (cost.optimum(p, k, z, "abs").first() for k, z in ((2, 1), (3, 0)))
        c = cs.build(p, 2, 1, g, variant, "abs", parts=2, seeding="exact", scheme="modulo", strict=True)
        inside = [r["pid"] for r in c.rows.select("pid").collect()]
        pts = {r["pid"]: r["pt"] for r in p.collect()}
        prox = {r["pid"]: r["proxy_id"] for r in cs.proxies(p, c, "abs").collect()}
        ids = sorted(pts)
        x, y = (np.array([pts[f(i)] for i in ids]) for f in (lambda i: i, prox.get))
        best, errors = np.inf, []
        for a in combinations(ids, 2):
            at = np.array([pts[i] for i in a])
            full, small = (np.abs(v[:, None] - at).min(axis=1) ** 2 for v in (x, y))
            if set(a) <= set(inside):
                best = min(best, float(np.sort(full)[:-1].sum()))
            # every set of one outlier
            whole, own = full.sum() - full, small.sum() - small
            errors += (np.abs(whole - own)[whole > 0] / whole[whole > 0]).tolist()
        witness = [min(inside, key=lambda i: (round(abs(pts[i] - pts[int(q)]), 9), i)) for q in opt["centers"].split(",")]
        m = model_of(c.rows, RobustSpec(2, 1, metric="abs", solver="exhaustive"))
        found, slack = cost_of(pts, [q for _, q in m.centers], 1), 1 + bounds.centroid_slack(g, variant)
        ref = np.array([pts[i] for i in c.reference["pid"].to_pylist()])
        compact = float((np.abs(x[:, None] - ref).min(axis=1) ** 2).sum())
        return ok_rows(spark, {
            "error": max(errors) <= bounds.coreset_quality(g, variant), "centroid": best <= slack * opt["cost"] + 1e-6,
            "witness": cost_of(pts, [pts[i] for i in witness], 1) <= slack * opt["cost"] + 1e-6, "end to end": c.certified and found <= bounds.end_to_end(g, variant) * opt["cost"] + 1e-6,
            "distortion": float(((x - y) ** 2).sum()) <= bounds.distortion_factor(g, variant) * wide["cost"] + 1e-6,
            "compact reference": compact <= bounds.distortion_factor(g, "compact" if variant == "refined" else "first") * wide["cost"] + 1e-6,
        })

    return run


for _v, _g in (("direct", 0.1), ("refined", 0.05)):
    query(o.checks(*_GUARANTEES), f"centroid_ratio_{_v}" if _v == "refined" else "centroid_ratio")(_guarantees(_v, _g))


@query("SELECT 'exact' AS seeding, TRUE AS certified UNION ALL SELECT 'dsq', FALSE UNION ALL SELECT 'first_ids', FALSE UNION ALL SELECT 'swap', FALSE")
def certified_seedings(spark, sf_dir):
    """Only a seeding of a proven ratio certifies a run, whatever beta is assumed."""
    found = [(s, cs.build(_nations(spark, sf_dir), 2, 1, 0.1, "direct", "abs", parts=2, seeding=s).certified) for s in ("exact", "dsq", "first_ids", "swap")]
    return spark.createDataFrame(found, "seeding string, certified boolean")


def cost_of(pts: dict, centers: list[float], z: int) -> float:
    d = sorted((min(abs(x - c) for c in centers) for x in pts.values()), reverse=True)[z:]
    return float(np.sum(np.array(d) ** 2))


@query(o.checks("certificate holds for random centers and three kinds of outliers"))
def certificate_holds(spark, sf_dir):
    p = src.events_2d(spark, sf_dir)
    c = cs.build(p, 5, 20, 0.9, "refined", "l2", parts=4)
    prox = cs.checkpoint(cs.proxies(p, c, "l2"))
    e, good = audit.proxy_distortion(prox).first()[0], True
    for seed in (1, 2):
        s = cost.center_rows(p.orderBy(F.xxhash64("pid", F.lit(seed))).limit(5))
        heavy = c.rows.orderBy(F.desc("w"), "pid").first()["pid"]
        for z in (cost.farthest(p, s, 20, "l2"), p.orderBy(F.xxhash64("pid", F.lit(seed + 9))).limit(20), prox.where(F.col("proxy_id") == heavy).orderBy("pid").limit(20)):
            r = audit.coreset_error(p, c.rows, prox, s, z, "l2").first()
            good &= abs(r["full"] - r["small"]) <= audit.certificate(e, r["full"]) + 1e-6
    return ok_rows(spark, {"certificate holds for random centers and three kinds of outliers": good})


def _copies(points, times):
    """Copies of a table, each shifted so that no two are equal."""
    n = F.explode(F.sequence(F.lit(0), F.lit(times - 1)))
    return points.withColumn("n", n).select((F.col("pid") * times + F.col("n")).alias("pid"), (F.col("pt") + F.col("n") * 1e-6).alias("pt"))


@query(o.checks("direct grows by two thirds", "refined grows by one half", "direct grows faster"))
def memory_slope(spark, sf_dir):
    """The largest first-round group of log N against log N, over the table once, four and sixteen times."""
    p, slopes = src.events_scalar(spark, sf_dir), {}
    for variant in ("direct", "refined"):
        rows = []
        for times in (1, 4, 16):
            grown = _copies(p, times)
            n = grown.count()
            parts = bounds.partitions(n, bounds.kprime(3, 5), variant)
            rows.append((n, src.partition(grown, parts).groupBy("part_id").count().agg(F.max("count")).first()[0]))
        slopes[variant] = audit.memory_slope(rows)
    return ok_rows(spark, {"direct grows by two thirds": abs(slopes["direct"] - 2 / 3) < 0.06, "refined grows by one half": abs(slopes["refined"] - 1 / 2) < 0.06, "direct grows faster": slopes["direct"] > slopes["refined"]})


@query(o.checks("size settles while the table grows", "mass", "certificate"))
def w30(spark, sf_dir):
    """The table ten and a hundred times: the coreset follows the data's shape and not its rows."""
    p, found = src.events_scalar(spark, sf_dir), []
    start = first(p, 3)
    for times in (1, 10, 100):
        grown = _copies(p, times)
        c = cs.build(grown, 3, 5, 0.9, "refined", "abs", parts=8)
        e = audit.proxy_distortion(cs.proxies(grown, c, "abs")).first()[0]
        full, small = (cost.cost(x, start, "abs").first()[0] for x in (grown, c.rows))
        found.append((grown.count(), c.rows.count(), audit.mass(c.rows), abs(full - small) <= audit.certificate(e, full) * (1 + 1e-9) + 1e-6))
    return ok_rows(spark, {"size settles while the table grows": found[2][1] < 10 * found[0][1], "mass": all(m == n for n, _, m, _ in found), "certificate": all(x for *_, x in found)})


@query(o.checks("rounds shuffle every point once", "bytes are counted"))
def engine_cost_checks(spark, sf_dir):
    """Rows and bytes that the first round's shuffle wrote, from the executed plan."""
    p = src.partition(src.events_scalar(spark, sf_dir), 4)
    found = audit.engine_cost(cs.round_one(cs.narrow(p), 5, 0.3, "dsq", "abs"))
    return ok_rows(spark, {"rounds shuffle every point once": found["rows_shuffled"] == p.count(), "bytes are counted": found["bytes_shuffled"] > 0 and found["exchanges"] == 1})


@query(o.checks("embeddings are high", "a line is low"))
def doubling_estimate_checks(spark, sf_dir):
    return ok_rows(spark, {"embeddings are high": audit.doubling_dimension(src.embeddings(spark, sf_dir), "l2") > 4, "a line is low": audit.doubling_dimension(src.events_scalar(spark, sf_dir), "abs") < 3})


@query("WITH p AS (" + o.EMBEDDINGS + "), c AS (SELECT x AS cx FROM p WHERE pid = 0) SELECT pid, round(" + o.dist("l2", "x", "cx") + ", 6) AS dist FROM p, c WHERE " + o.dist("l2", "x", "cx") + " <= 1.3")
def ball_members(spark, sf_dir):
    p = src.embeddings(spark, sf_dir)
    return rounded(audit.ball(p, p.where("pid = 0").first()["pt"], 1.3, "l2"), "dist")


@query("SELECT round(max(d) / min(d), 4) AS spread FROM (SELECT abs(a.s_acctbal - b.s_acctbal) AS d FROM supplier a, supplier b WHERE a.s_suppkey < b.s_suppkey) WHERE d > 0")
def spread_supplier(spark, sf_dir):
    return audit.spread(src.supplier_scalar(spark, sf_dir), "abs").select(F.round("spread", 4).alias("spread"))


# baselines


def _baseline(f, z=100):
    def run(spark, sf_dir):
        p = src.events_scalar(spark, sf_dir)
        m = f(p, RobustSpec(5, z, 0.5, "refined", "abs", parts=4, solver="plain_then_trim"))
        got = cost.trimmed_cost(p, m.centers, z, "abs").first()[0]
        return ok_rows(spark, {"k centers": len(m.centers) == 5, "better than the first ids": got < cost.trimmed_cost(p, first(p, 5), z, "abs").first()[0]})

    return run


for _n, _f in (("per_part_solver", baselines.per_part_outlier_solver), ("outlier_blind", baselines.outlier_blind_coreset), ("ignoring_outliers", baselines.ignoring_outliers)):
    query(o.checks("k centers", "better than the first ids"), _n)(_baseline(_f))


@query("SELECT CAST(count(*) AS BIGINT) AS w, least(200, count(*)) AS n FROM events")
def uniform_sample_mass(spark, sf_dir):
    return baselines.uniform(src.events_scalar(spark, sf_dir), 200).agg(F.sum("w").alias("w"), F.count("*").alias("n"))


@query(o.checks("means cost no more than members"))
def lloyd_compare(spark, sf_dir):
    p = src.events_2d(spark, sf_dir)
    c = list(enumerate(baselines.lloyd(p, 4, 40)))
    a = cost.assign(p, c, "l2")
    near = [r["pt"] for r in a.groupBy("cid").agg(F.min_by("pt", F.struct("dist", "pid")).alias("pt")).orderBy("cid").collect()]
    means, members, start = (cost.cost(p, x, "l2").first()[0] for x in (c, list(enumerate(near)), first(p, 4)))
    return ok_rows(spark, {"means cost no more than members": means <= 1.001 * members <= 4 * means and means < start})


@query(o.checks("solver on everything is within the certificate"))
def sequential_compare(spark, sf_dir):
    p = _nations(spark, sf_dir)
    spec = RobustSpec(2, 3, 0.1, "direct", "abs", parts=2, solver="exhaustive", seeding="exact")
    a, b = baselines.sequential(p, spec), fit(p, spec)
    at = [cost.trimmed_cost(p, m.centers, 3, "abs").first()[0] for m in (a, b)]
    return ok_rows(spark, {"solver on everything is within the certificate": at[0] <= at[1] + 1e-6 <= bounds.end_to_end(0.1, "direct") * at[0] + 1e-5})


@query(o.checks("refined reference is smaller", "masses equal", "all solve"))
def compare_variants(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    rows = {v: (r, t, c, m) for v, r, t, c, m in baselines.compare_variants(p, RobustSpec(5, 20, 0.3, "direct", "abs", parts=8, solver="alternate"))}
    return ok_rows(spark, {"refined reference is smaller": rows["refined"][0] < rows["direct"][0], "masses equal": all(m == p.count() for *_, m in rows.values()), "all solve": all(c > 0 for _, _, c, _ in rows.values())})


@query(o.checks("one part keeps all mass"))
def single_machine_coreset(spark, sf_dir):
    p = _events(spark, sf_dir)
    return ok_rows(spark, {"one part keeps all mass": audit.mass(baselines.single_machine(p, RobustSpec(4, 5, 0.5, "direct", "abs")).rows) == p.count()})


# measures on planted and labelled outliers


@query("WITH v AS (SELECT event_id AS pid, CASE WHEN event_id % 500 = 7 THEN value * 50 ELSE value END AS x, 1 AS w FROM events), " + o.assigned("SELECT * FROM v", "SELECT pid AS cid, x AS cx FROM v ORDER BY pid LIMIT 5", "abs") + ", f AS (SELECT pid FROM a ORDER BY dist DESC, pid LIMIT 20), g AS (SELECT pid FROM v WHERE pid % 500 = 7) SELECT (SELECT count(*) FROM f JOIN g USING (pid)) AS hits, (SELECT count(*) FROM f) AS flagged, (SELECT count(*) FROM g) AS planted, (SELECT count(*) FROM f JOIN g USING (pid)) / (SELECT count(*) FROM f) AS precision, (SELECT count(*) FROM f JOIN g USING (pid)) / (SELECT count(*) FROM g) AS recall")
def planted_outlier_pr(spark, sf_dir):
    p = src.events_planted(spark, sf_dir)
    return audit.outlier_pr(cost.farthest(p, first(p, 5), 20, "abs"), p.where("pid % 500 = 7"))


_DOC_STATS = "SELECT doc_id AS pid, [length(text) / 1000, len(ws) / 100, len(list_distinct(ws)) / greatest(len(ws), 1)] AS x, 1 AS w FROM (SELECT doc_id, text, [v for v in string_split_regex(lower(text), '[^a-z]+') if v <> ''] AS ws FROM documents)"


@query("WITH " + o.assigned(_DOC_STATS, o.first_centers(_DOC_STATS, 5), "l2") + ", f AS (SELECT pid FROM a ORDER BY dist DESC, pid LIMIT 100), g AS (SELECT doc_id AS pid FROM labels WHERE quality = 0), k AS (SELECT pid FROM f WHERE pid IN (SELECT doc_id FROM labels)) SELECT (SELECT count(*) FROM k JOIN g USING (pid)) AS hits, (SELECT count(*) FROM k) AS flagged, (SELECT count(*) FROM g) AS planted, (SELECT count(*) FROM k JOIN g USING (pid)) / (SELECT count(*) FROM k) AS precision, (SELECT count(*) FROM k JOIN g USING (pid)) / (SELECT count(*) FROM g) AS recall")
def quality_label_pr(spark, sf_dir):
    """The 100 documents farthest from five centers, as far as they are labelled, against those of bad quality."""
    p = src.doc_stats(spark, sf_dir)
    labels = src.table(spark, sf_dir, "labels").select(F.col("doc_id").cast("bigint").alias("pid"), "quality")
    far = cost.farthest(p, first(p, 5), 100, "l2").join(labels.select("pid"), "pid", "left_semi")
    return audit.outlier_pr(far, labels.where("quality = 0"))


@query("WITH " + o.assigned(o.LATTICE, o.first_centers(o.LATTICE, 4), "l2") + " SELECT cid, count(*) AS n, CAST(sum(w) AS BIGINT) AS w, round(max(dist), 6) AS radius, round(sum(w*dist*dist), 4) AS cost FROM a GROUP BY ROLLUP(cid)")
def cluster_profile_rollup(spark, sf_dir):
    p = src.lineitem_lattice(spark, sf_dir)
    a = cost.assign(p, first(p, 4), "l2")
    return a.rollup("cid").agg(F.count("*").alias("n"), F.sum("w").alias("w"), F.round(F.max("dist"), 6).alias("radius"), F.round(F.sum(F.col("w") * F.pow("dist", F.lit(2))), 4).alias("cost"))


QUERIES["report_flagship"] = lambda spark, sf_dir: report(src.events_scalar(spark, sf_dir), fit(src.events_scalar(spark, sf_dir), _SPEC))
