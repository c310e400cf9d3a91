"""Workloads on the given tables. Every one takes (spark, sf_dir, **overrides) and runs the complete algorithm over a whole table.

Rows are invariants that hold for any seeding: mass, center count, exact outlier mass, the certificate, and that the
solution beats the first ids.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..operators import cost
from ..sources import points as src
from . import audit
from .clustering_queries import first, ok_rows
from .oracles import checks
from .pipeline import RobustSpec, build, fit_by, model_of

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
CHECKS = ("mass", "centers", "certificate", "beats the first ids")


@dataclass
class Workload:
    points: Callable[[SparkSession, str], DataFrame]
    spec: RobustSpec
    about: str
    options: dict = field(default_factory=dict)

    def run(self, spark: SparkSession, sf_dir: str, **overrides) -> DataFrame:
        spec = replace(self.spec, **overrides)
        p = self.points(spark, sf_dir)
        c = build(p, spec)
        e = audit.proxy_distortion(cs.proxies(p, c, spec.metric), p, spec.power).first()[0]
        if self.options.get("coreset_only"):
            return ok_rows(spark, {"mass": audit.mass(c.rows) == p.agg(F.sum(cost.weight_of(p))).first()[0], "smaller": c.rows.count() < p.count()})
        start = first(p, spec.k)
        full, small = (cost.cost(x, start, spec.metric, spec.power).first()[0] for x in (p, c.rows))
        total = p.agg(F.sum(cost.weight_of(p))).first()[0]
        m = model_of(c.rows, spec)
        got, base = (cost.trimmed_cost(p, s, spec.z, spec.metric, spec.power).first()[0] for s in (m.centers, start))
        return ok_rows(spark, {"mass": audit.mass(c.rows) == total, "centers": 0 < len(m.centers) <= spec.k, "certificate": abs(full - small) <= audit.certificate(e, full, spec.power) * (1 + 1e-9) + 1e-6, "beats the first ids": got <= base * (1 + 1e-9)})


def S(k, z, parts, metric="l2", gamma=0.9, solver="alternate", **more) -> RobustSpec:
    return RobustSpec(k, z, gamma, metric=metric, parts=parts, solver=solver, **more)


WORKLOADS = {
    "w01": Workload(src.supplier_scalar, S(2, 3, 4, "abs", 0.1), "account balances"),
    "w02": Workload(src.events_scalar, S(5, 100, 4, "abs", 0.5), "heavy tail of event values"),
    "w02_direct": Workload(src.events_scalar, S(5, 100, 4, "abs", 0.5, variant="direct"), "the same, direct variant"),
    "w03": Workload(src.events_2d, S(5, 100, 4), "values by hour"),
    "w04": Workload(src.lineitem_lattice, S(4, 60, 8), "weighted lattice with duplicates"),
    "w05": Workload(src.lineitem_3d, S(6, 200, 16), "three dimensions", {"coreset_only": True}),
    "w05_l1": Workload(src.lineitem_3d, S(6, 200, 16, "l1"), "three dimensions, l1", {"coreset_only": True}),
    "w05_linf": Workload(src.lineitem_3d, S(6, 200, 16, "linf"), "three dimensions, linf", {"coreset_only": True}),
    "w07": Workload(src.orders_2d, S(4, 50, 8), "price and date"),
    "w09": Workload(src.customer_nation, S(5, 10, 4, "balance_and_place"), "balance plus hierarchy"),
    "w10": Workload(src.part_names, S(4, 40, 2, "edit", solver="multi_swap", options={"swap_size": 1, "eps": 0.1}), "weighted strings"),
    "w11": Workload(src.doc_words, S(8, 20, 8, "jaccard"), "word sets of documents"),
    "w12": Workload(src.embeddings, S(10, 5, 4, "angular"), "64 dimensions by angle"),
    "w13": Workload(lambda s, d: src.embeddings(s, d, 2), S(4, 5, 4), "two coordinates of the same ids"),
    "w14": Workload(src.user_types, S(3, 5, 2, "l1"), "event counts of users"),
    "w16": Workload(src.events_scalar, S(5, 0, 4, "abs", 0.5), "no outliers"),
    "w17": Workload(src.events_scalar, S(5, 50, 4, "abs", 0.5, power=1), "sum of distances"),
    "w24": Workload(src.conversations, S(3, 5, 2), "turns, length and share of user turns"),
    "w25": Workload(src.pages, S(4, 10, 4), "page sizes, tags and depth"),
    "w26": Workload(src.doc_stats, S(5, 20, 4), "document statistics"),
}
for _name, _w in WORKLOADS.items():
    QUERIES[_name], ORACLES[_name] = _w.run, checks(*(("mass", "smaller") if _w.options.get("coreset_only") else CHECKS))


def _sweep(name: str, *names: str):
    def add(f):
        QUERIES[name], ORACLES[name] = f, checks(*names)
        return f

    return add


def _sizes(p, spec) -> tuple[int, int]:
    c = build(p, spec)
    return c.rows.count(), c.reference.num_rows if c.reference is not None else 0


@_sweep("w08", "every nation", "at most two centers")
def w08(spark, sf_dir):
    c = src.table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("bigint").alias("pid"), F.col("c_acctbal").alias("pt"), "c_nationkey")
    rows = fit_by(c, "c_nationkey", RobustSpec(2, 3, metric="abs", solver="alternate")).groupBy("key").count().collect()
    return ok_rows(spark, {"every nation": len(rows) == c.select("c_nationkey").distinct().count(), "at most two centers": max(r["count"] for r in rows) <= 2})


@_sweep("w15", "noise drags centers without outliers", "centers stay with outliers")
def w15(spark, sf_dir):
    """A few planted values bias the solution that may not forget, not the one that may."""
    p = src.events_planted(spark, sf_dir)
    clean = p.where("pid % 500 <> 7")
    z = p.where("pid % 500 = 7").count()
    plain = model_of(build(p, S(5, 0, 4, "abs", 0.5)).rows, S(5, 0, 4, "abs", 0.5, solver="plain_then_trim"))
    robust = model_of(build(p, S(5, z, 4, "abs", 0.5)).rows, S(5, z, 4, "abs", 0.5, solver="trimmed_swap", options={"outlier_cap": 2 * z}))
    cost_of = lambda m: cost.cost(clean, m.centers, "abs").first()[0]
    return ok_rows(spark, {"noise drags centers without outliers": cost_of(plain) > cost_of(robust), "centers stay with outliers": max(x for _, x in robust.centers) < max(x for _, x in plain.centers)})


@_sweep("w18", "size falls as gamma grows", "refined reference is no larger")
def w18(spark, sf_dir):
    p, rows = src.events_scalar(spark, sf_dir), {}
    for g in (0.05, 0.11, 0.5, 0.9):
        rows[g] = _sizes(p, S(4, 20, 4, "abs", g)), _sizes(p, S(4, 20, 4, "abs", g, variant="direct"))
    t = [rows[g][0][0] for g in sorted(rows)]
    return ok_rows(spark, {"size falls as gamma grows": t == sorted(t, reverse=True), "refined reference is no larger": all(r[0][1] <= r[1][1] for r in rows.values())})


@_sweep("w19", "more k and z need more rows")
def w19(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    t = [_sizes(p, S(k, z, 4, "abs"))[0] for k, z in ((2, 0), (8, 50), (32, 400))]
    return ok_rows(spark, {"more k and z need more rows": t == sorted(t)})


@_sweep("w20", "direct reference grows with the parts", "refined reference grows less")
def w20(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    d, r = ([_sizes(p, S(4, 20, n, "abs", variant=v))[1] for n in (1, 4, 16)] for v in ("direct", "refined"))
    return ok_rows(spark, {"direct reference grows with the parts": d == sorted(d), "refined reference grows less": r[2] - r[0] <= d[2] - d[0]})


@_sweep("w21", "a larger assumed beta gives a larger coreset")
def w21(spark, sf_dir):
    p = src.events_scalar(spark, sf_dir)
    t = [_sizes(p, S(4, 20, 4, "abs", 0.5, beta=b))[0] for b in (1.0, 5.0, 25.0)]
    return ok_rows(spark, {"a larger assumed beta gives a larger coreset": t == sorted(t)})


@_sweep("w22", "all solvers keep the mass", "trimmed search takes passes", "search beats plain trimming or ties")
def w22(spark, sf_dir):
    from ..operators import solvers

    c = build(src.events_scalar(spark, sf_dir), S(4, 60, 4, "abs")).rows
    total, costs, kept = audit.mass(c), {}, True
    for s, options in (("trimmed_swap", {"outlier_cap": 120, "init": "dsq"}), ("multi_swap", {"swap_size": 1, "eps": 0.1, "max_moves": 60}), ("plain_then_trim", {}), ("alternate", {})):
        rows = solvers.solve(c, 4, 60, s, "abs", **options).collect()
        costs[s] = next(r["value"] for r in rows if r["kind"] == "cost")
        costs[s + "_passes"] = next((r["value"] for r in rows if r["kind"] == "stat:passes"), 0)
        kept &= abs(sum(r["value"] for r in rows if r["pid"] is not None) - total) < 1e-6
    return ok_rows(spark, {"all solvers keep the mass": kept, "trimmed search takes passes": costs["trimmed_swap_passes"] > 0, "search beats plain trimming or ties": max(costs["trimmed_swap"], costs["multi_swap"]) <= costs["plain_then_trim"] * (1 + 1e-9)})


@_sweep("w23", "all planted values are in one part", "mass", "certificate")
def w23(spark, sf_dir):
    """An adversary puts all outliers in one part; mass and certificate do not care."""
    planted = F.col("pid") % 500 == 7
    p = src.events_planted(spark, sf_dir).withColumn("part_id", F.when(planted, 3).otherwise(F.col("pid") % 3).cast("int"))
    z = p.where(planted).count()
    own = {r["part_id"]: r["count"] for r in p.where(planted).groupBy("part_id").count().collect()}
    out = Workload(lambda s, d: p, S(5, z, 4, "abs", 0.5, scheme="given"), "").run(spark, sf_dir)
    alone = ok_rows(spark, {"all planted values are in one part": own == {3: z} and p.where("part_id = 3").count() == z})
    return alone.unionByName(out.where("check_name IN ('mass', 'certificate')"))


def _exhaustive(make, metric):
    def run(spark, sf_dir):
        """Distortion bounds against the exact optimum for k', with exhaustive seeding so that beta is 1."""
        from ..functions import bounds

        p, found = cs.checkpoint(make(spark, sf_dir)), {}
        opt = cost.optimum(p, 3, 0, metric).first()["cost"]
        for name, variant, g in (("first", "one_round", 0.1), ("direct", "direct", 0.1), ("refined", "refined", 0.05)):
            c = cs.build(p, 2, 1, g, variant, metric, parts=2, seeding="exact", scheme="modulo", strict=True)
            e = c.stats["summaries"].agg(F.sum("distortion")).first()[0] if variant == "one_round" else audit.proxy_distortion(cs.proxies(p, c, metric)).first()[0]
            found[name] = c.certified and e <= bounds.distortion_factor(g, name) * opt + 1e-6
        return ok_rows(spark, found)

    return run


def _nation_features(*columns):
    def make(spark, sf_dir):
        balances = src.nation_balances(spark, sf_dir).withColumnRenamed("pid", "n_nationkey").withColumn("balance", F.col("pt") / 1000)
        return src.from_columns(balances.join(src.table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey"), "n_nationkey"), "n_nationkey", list(columns))

    return make


def _nation_names(spark, sf_dir):
    return src.table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("pid"), F.col("n_name").alias("pt"))


#: The same bounds on all nations (25 points at any size) by several metrics.
for _name, _make, _metric in (
    ("w29_exhaustive", lambda s, d: src.nation_balances(s, d).select("pid", "pt"), "abs"),
    ("w29_l2", _nation_features("balance", "n_regionkey"), "l2"),
    ("w29_l1", _nation_features("balance", "n_regionkey"), "l1"),
    ("w29_linf", _nation_features("balance", "n_regionkey"), "linf"),
    ("w29_ultra", _nation_features("n_nationkey", "n_regionkey"), "ultra"),
    ("w29_edit", _nation_names, "edit"),
):
    QUERIES[_name], ORACLES[_name] = _exhaustive(_make, _metric), checks("first", "direct", "refined")


def w06(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four continuous dimensions: the coreset alone, with its mass."""
    p = src.lineitem_4d(spark, sf_dir)
    return build(p, S(6, 200, 32)).rows.agg(F.sum("w").alias("w"))


QUERIES["w06"], ORACLES["w06"] = w06, "SELECT CAST(count(*) AS BIGINT) AS w FROM lineitem"
