"""The weighted coreset in two distributed rounds, in its direct, refined, one-round and multi-level forms.

Round 1 seeds and covers each part; a reference made of these covers, whole (direct) or compacted (refined), goes to
every part with the global radius, and round 2 covers the same parts again. Every group is a part of bounded size;
what is broadcast is the reference, whose bytes are checked.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType

from ..functions import bounds
from ..functions.metrics import Metric, get
from ..shared import checkpoint
from ..sources import points as sources
from . import kernels
from .cost import MAX_BROADCAST

#: Rows that one task compacts; more are an error.
MAX_COMPACT = 200_000


def _payload(points: DataFrame):
    return points.schema["pt"].dataType


def _schema(points: DataFrame, *more: StructField) -> StructType:
    return StructType([StructField("pid", LongType()), StructField("pt", _payload(points)), StructField("w", LongType()), StructField("part_id", IntegerType()), *more])


def _sorted(table: pa.Table) -> pa.Table:
    ids = table["pid"].to_numpy()
    return table if (ids[1:] >= ids[:-1]).all() else table.sort_by("pid")


def _rng(seed: int, part: int):
    return np.random.default_rng([seed, part & 0x7FFFFFFF])


def with_weight(points: DataFrame) -> DataFrame:
    return points if "w" in points.columns else points.withColumn("w", F.lit(1).cast("bigint"))


def narrow(points: DataFrame) -> DataFrame:
    """Just what a kernel reads, so that the scan is pruned to it."""
    return with_weight(points).select("pid", "pt", F.col("w").cast("bigint").alias("w"), F.col("part_id").cast("int").alias("part_id"))


def seed(points: DataFrame, k: int, method: str = "dsq", metric="l2", power: int = 2, seed_value: int = 42) -> DataFrame:
    """Seeds (pid, pt, w, part_id) of every part."""
    m, schema = get(metric), _schema(points)

    def run(table: pa.Table) -> pa.Table:
        table = _sorted(table)
        pts, w = m.load(table["pt"]), table["w"].to_numpy().astype("float64")
        part = table["part_id"][0].as_py()
        chosen = kernels.SEEDINGS[method](m, pts, w, k, power, _rng(seed_value, part))
        return table.take(pa.array(np.sort(chosen))).select(["pid", "pt", "w", "part_id"])

    return narrow(points).groupBy("part_id").applyInArrow(run, schema)


def seed_rounds(points: DataFrame, k: int, metric="l2", power: int = 2, rounds: int = 5, seed_value: int = 42, reduce: bool = False) -> list[tuple[int, object]]:
    """Oversampled seeding across the cluster for large k: every round keeps points by a hash against their share of the cost.

    With reduce, k of them are kept by weighted seeding on the mass that each one is nearest to.
    """
    from . import cost

    first = points.orderBy(F.xxhash64("pid", F.lit(seed_value))).limit(1).collect()[0]
    chosen = {first["pid"]: first["pt"]}
    w = cost.weight_of(points)
    for r in range(rounds):
        a = cost.assign(points, sorted(chosen.items()), metric)
        phi = a.agg(F.sum(w * F.pow("dist", F.lit(power)))).first()[0] or 0.0
        if phi <= 0:
            break
        u = F.pmod(F.xxhash64("pid", F.lit(seed_value + r)), F.lit(1 << 30)) / float(1 << 30)
        # 2k rows are expected; an excess that chance does not explain is an error and never cut
        picked = a.where(u < F.lit(2.0 * k) * w * F.pow("dist", F.lit(power)) / phi).select("pid", "pt").limit(20 * k + 1000).collect()
        if len(picked) == 20 * k + 1000:
            raise ValueError("far more seeds were drawn than expected; are ids repeated?")
        chosen.update({p["pid"]: p["pt"] for p in picked})
    if reduce and len(chosen) > k:
        m, rows = get(metric), sorted(chosen.items())
        mass = {r["cid"]: r["w"] for r in cost.assign(points, rows, metric).groupBy("cid").agg(F.sum(w).alias("w")).collect()}
        pts = m.load(pa.array([p for _, p in rows], to_arrow_schema(points.select("pt").schema)[0].type))
        weights = np.array([float(mass.get(i, 0)) for i, _ in rows])
        kept = kernels.SEEDINGS["swap"](m, pts, weights, k, power, _rng(seed_value, 0))
        return [rows[i] for i in kept.tolist()]
    return sorted(chosen.items())


def ball_cover(points: DataFrame, references: list | DataFrame, delta: float, radius: float, metric="l2", pick: str = "lowest_id", proxies: bool = False, seed_value: int = 42) -> DataFrame:
    """Cover each part against broadcast references: (pid, pt, w, part_id), or (pid, proxy_id, proxy_dist, threshold) rows."""
    m = get(metric)
    table = reference_table(points, references)
    shared = points.sparkSession.sparkContext.broadcast(m.load(table["pt"]))
    schema = StructType([StructField("pid", LongType()), StructField("proxy_id", LongType()), StructField("proxy_dist", DoubleType()), StructField("threshold", DoubleType())]) if proxies else _schema(points)

    def run(table: pa.Table) -> pa.Table:
        table = _sorted(table)
        pts, ids = m.load(table["pt"]), table["pid"].to_numpy()
        near = kernels.to_set(m, pts, shared.value)
        picked, mass, proxy, at = kernels.ball_cover(m, pts, near, table["w"].to_numpy(), delta, radius, pick, _rng(seed_value, table["part_id"][0].as_py()))
        if proxies:
            return pa.table({"pid": ids, "proxy_id": ids[proxy], "proxy_dist": at, "threshold": np.round(delta * np.maximum(radius, near), 9)})
        return _balls(table, picked, mass)

    return narrow(points).groupBy("part_id").applyInArrow(run, schema)


def _balls(table: pa.Table, picked: np.ndarray, mass: np.ndarray) -> pa.Table:
    out = table.take(pa.array(picked))
    return pa.table([out["pid"], out["pt"], pa.array(mass), out["part_id"]], names=["pid", "pt", "w", "part_id"])


def _bytes_of(points: DataFrame):
    """About how many bytes a payload takes."""
    kind = dict(points.dtypes)["pt"]
    if kind == "string":
        return F.octet_length("pt")
    if kind == "array<string>":
        return F.aggregate("pt", F.lit(0), lambda s, x: s + F.octet_length(x) + 4)
    return 8 * F.size("pt") if kind.startswith("array") else F.lit(8)


def reference_table(points: DataFrame, references) -> pa.Table:
    """References on the driver as an Arrow table; their bytes are checked, since they grow with k, z and the parts."""
    if isinstance(references, pa.Table):
        table = references
    elif isinstance(references, DataFrame):
        references = checkpoint(references.select("pid", "pt"))
        size = references.agg(F.coalesce(F.sum(16 + _bytes_of(references)), F.lit(0))).first()[0]
        if size > MAX_BROADCAST:
            raise ValueError(f"references of about {size} bytes are over the broadcast limit; use the refined variant, more levels or a larger gamma")
        table = references.toArrow()
    else:
        rows = sorted(references)
        table = pa.table({"pid": pa.array([r[0] for r in rows], pa.int64()), "pt": pa.array([r[1] for r in rows], to_arrow_schema(points.select("pt").schema)[0].type)})
    if table.nbytes > MAX_BROADCAST:
        raise ValueError(f"references of {table.nbytes} bytes are over the broadcast limit; use the refined variant, more levels or a larger gamma")
    return table


def round_one(points: DataFrame, k: int, delta: float, seeding: str = "dsq", metric="l2", power: int = 2, pick: str = "lowest_id", seed_value: int = 42) -> DataFrame:
    """One fused group per part: seed, radius, cover. Rows (pid, pt, w, part_id) and one summary row a part.

    The summary row has a null pid and carries n, cost, radius and the cover's distortion.
    """
    m = get(metric)
    schema = _schema(points, *[StructField(c, DoubleType()) for c in ("n", "cost", "radius", "distortion")])
    arrow = to_arrow_schema(schema)

    def run(table: pa.Table) -> pa.Table:
        table = _sorted(table)
        pts, w = m.load(table["pt"]), table["w"].to_numpy()
        part, mass = table["part_id"][0].as_py(), float(w.sum())
        chosen = kernels.SEEDINGS[seeding](m, pts, w.astype("float64"), k, power, _rng(seed_value, part))
        near = kernels.to_set(m, pts, pts[chosen])
        cost = float((w * near**power).sum())
        radius = (cost / mass) ** (1 / power) if mass else 0.0
        picked, masses, _, at = kernels.ball_cover(m, pts, near, w, delta, radius, pick, _rng(seed_value, part))
        balls = _balls(table, picked, masses)
        nulls = [pa.nulls(len(picked), pa.float64())] * 4
        own = pa.table([*balls.columns, *nulls], schema=arrow)
        summary = pa.table([pa.nulls(1, t.type) for t in list(arrow)[:2]] + [pa.nulls(1, pa.int64()), pa.array([part], pa.int32())] + [pa.array([x]) for x in (mass, cost, radius, float((w * at**power).sum()))], schema=arrow)
        return pa.concat_tables([own, summary])

    return narrow(points).groupBy("part_id").applyInArrow(run, schema)


def global_radius(summaries: DataFrame, power: int = 2) -> float:
    return float(summaries.agg(F.pow(F.sum(F.col("n") * F.pow("radius", F.lit(power))) / F.sum("n"), F.lit(1 / power))).first()[0] or 0.0)


def compact(first: DataFrame, k: int, delta: float, radius: float, seeding: str = "dsq", metric="l2", power: int = 2, seed_value: int = 42, fan_in: int | None = None) -> DataFrame:
    """Weighted seeding and cover of the union of first covers; with fan_in, in groups of so many parts (one level of a tree)."""
    m, schema = get(metric), _schema(first)
    group = F.lit(0) if fan_in is None else F.floor(F.col("part_id") / fan_in)

    def run(table: pa.Table) -> pa.Table:
        table = _sorted(table)
        pts, w = m.load(table["pt"]), table["w"].to_numpy()
        rng = _rng(seed_value, 1 << 20 | table["part_id"][0].as_py())
        chosen = kernels.SEEDINGS[seeding](m, pts, w.astype("float64"), k, power, rng)
        near = kernels.to_set(m, pts, pts[chosen])
        picked, mass, _, _ = kernels.ball_cover(m, pts, near, w, delta, radius)
        return _balls(table, picked, mass)

    grouped = first.select("pid", "pt", "w", group.cast("int").alias("part_id"))
    largest = grouped.groupBy("part_id").count().agg(F.max("count")).first()[0] or 0
    if largest > MAX_COMPACT:
        raise ValueError(f"{largest} rows are too many for one task; add levels, use a smaller fan_in or a larger gamma")
    return grouped.groupBy("part_id").applyInArrow(run, schema)


@dataclass
class Coreset:
    """(pid, pt, w, part_id) with what was measured on the way."""

    rows: DataFrame
    variant: str
    gamma: float
    delta: float
    radius: float
    k_prime: int
    parts: int
    certified: bool
    reference: pa.Table | None = None
    stats: dict = field(default_factory=dict)


def build(
    points: DataFrame, k: int, z: int, gamma: float, variant: str = "refined", metric="l2", power: int = 2, beta: float = 1.0, parts: int | None = None,
    seeding: str = "dsq", scheme: str = "hash", pick: str = "lowest_id", strict: bool = False, center_factor: float = 1.0, outlier_factor: float = 1.0,
    levels: int = 0, fan_in: int = 16, seed_value: int = 42, max_rows: int = 200_000,
) -> Coreset:
    """The coreset for k centers and z outliers. variant: direct, refined or one_round; z = 0 is the case without outliers."""
    m = get(metric)
    if strict and not m.is_metric:
        raise ValueError(f"{m.name} lacks the triangle inequality")
    proven = seeding in bounds.SEEDING_RATIO and beta >= bounds.SEEDING_RATIO[seeding]
    certified = bounds.check_gamma(gamma, variant, strict, power) and m.is_metric and proven
    k_prime = bounds.kprime(k, z, center_factor, outlier_factor)
    delta = bounds.delta(gamma, beta, power)
    if parts is None:
        parts = bounds.partitions(points.count(), k_prime, variant, max_rows)
    routed = narrow(points if scheme == "given" else sources.partition(points, parts, scheme))
    first = checkpoint(round_one(routed, k_prime, delta, seeding, m, power, pick, seed_value))
    covers = first.where("pid is not null").select("pid", "pt", "w", "part_id")
    summaries = first.where("pid is null").select("part_id", "n", "cost", "radius", "distortion")
    radius = global_radius(summaries, power)
    if variant == "one_round":
        return Coreset(covers, variant, gamma, delta, radius, k_prime, parts, certified, None, {"summaries": summaries})
    reference = covers
    for _ in range(levels):
        reference = checkpoint(compact(reference, k_prime, delta, radius, seeding, m, power, seed_value, fan_in))
    if variant == "refined":
        reference = compact(reference, k_prime, delta, radius, seeding, m, power, seed_value)
    elif variant != "direct":
        raise ValueError(variant)
    table = reference_table(points, reference)
    rows = checkpoint(ball_cover(routed, table, delta, radius, m, pick, seed_value=seed_value))
    return Coreset(rows, variant, gamma, delta, radius, k_prime, parts, certified, table, {"summaries": summaries, "first": covers, "routed": routed})


def proxies(points: DataFrame, coreset: Coreset, metric="l2", pick: str = "lowest_id") -> DataFrame:
    """(pid, proxy_id, proxy_dist, threshold): the map behind a direct or refined coreset."""
    return ball_cover(coreset.stats["routed"], coreset.reference, coreset.delta, coreset.radius, metric, pick, proxies=True)


def merge(*coresets: DataFrame) -> DataFrame:
    """Union of coresets of disjoint point sets."""
    out = coresets[0]
    for c in coresets[1:]:
        out = out.unionByName(c)
    return out


def recover(rows: DataFrame, k_prime: int, gamma: float, beta: float = 1.0, metric="l2", power: int = 2, seeding: str = "dsq", seed_value: int = 42) -> DataFrame:
    """Cover a weighted set again: proxies compose, mass is kept."""
    first = round_one(rows.withColumn("part_id", F.lit(0)), k_prime, bounds.delta(gamma, beta, power), seeding, metric, power, seed_value=seed_value)
    return first.where("pid is not null").select("pid", "pt", "w", "part_id")
