"""Accuracy and cost measures of a run, each an ordinary aggregate over the full table."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..operators import cost


def proxy_distortion(proxies: DataFrame, points: DataFrame | None = None, power: int = 2) -> DataFrame:
    """One row: total (weighted) distance to the proxies, to the power of the objective."""
    if points is not None and "w" in points.columns:
        proxies = proxies.join(points.select("pid", "w"), "pid")
    w = F.col("w") if "w" in proxies.columns else F.lit(1)
    return proxies.agg(F.sum(w * F.pow("proxy_dist", F.lit(power))).alias("distortion"))


def cover_violations(proxies: DataFrame) -> DataFrame:
    """One row: points farther from their proxy than their threshold; must be 0."""
    return proxies.agg(F.count_if(F.col("proxy_dist") > F.col("threshold") + 1e-9).alias("violations"))


def coreset_error(points: DataFrame, coreset: DataFrame, proxies: DataFrame, centers, outliers: DataFrame, metric, power: int = 2) -> DataFrame:
    """One row (full, small, error): relative error of the coreset's cost for one solution and one outlier set."""
    gone = proxies.join(outliers.select("pid"), "pid", "left_semi").groupBy(F.col("proxy_id").alias("pid")).agg(F.count("*").alias("gone"))
    small = coreset.join(gone, "pid", "left").withColumn("w", F.col("w") - F.coalesce("gone", F.lit(0))).drop("gone")
    full = cost.cost_without(points, outliers, centers, metric, power).select(F.col("cost").alias("full"))
    return full.crossJoin(cost.cost(small, centers, metric, power).select(F.col("cost").alias("small"))).select(
        "full", "small", F.when(F.col("full") > 0, F.abs(F.col("full") - F.col("small")) / F.col("full")).otherwise(0.0).alias("error")
    )


def certificate(distortion: float, full_cost: float, power: int = 2) -> float:
    """Bound on the absolute coreset error from measured distortion, without any optimum."""
    return distortion + 2 * math.sqrt(distortion * full_cost) if power == 2 else distortion


def ratio(points: DataFrame, centers, z: int, reference: float, metric, power: int = 2) -> float:
    """Trimmed cost of a solution on the full table over a reference cost."""
    return (cost.trimmed_cost(points, centers, z, metric, power).first()[0]) / reference if reference else math.nan


def sizes(c: cs.Coreset) -> dict[str, int]:
    out = {"coreset": c.rows.count()}
    if c.reference is not None:
        out |= {"reference": c.reference.num_rows, "first": c.stats["first"].count()}
    return out


def mass(rows: DataFrame) -> int:
    return int(rows.agg(F.sum("w")).first()[0] or 0)


def local_memory(points_parts: DataFrame, c: cs.Coreset) -> dict[str, int]:
    """Largest rows resident in one reducer by round."""
    largest = points_parts.groupBy("part_id").count().agg(F.max("count")).first()[0]
    return {"round_1": largest, "round_2": largest + (c.reference.num_rows if c.reference is not None else 0), "round_3": c.rows.count()}


def rounds(variant: str) -> dict[str, int]:
    return {"coreset": 1 if variant == "one_round" else 2, "complete": 2 if variant == "one_round" else 3}


def outlier_pr(flagged: DataFrame, planted: DataFrame) -> DataFrame:
    """One row (hits, flagged, planted, precision, recall) of two id sets."""
    both = flagged.select("pid", F.lit(1).alias("f")).join(planted.select("pid", F.lit(1).alias("p")), "pid", "full")
    hits, f, p = F.count_if(F.col("f").isNotNull() & F.col("p").isNotNull()), F.count("f"), F.count("p")
    return both.agg(hits.alias("hits"), f.alias("flagged"), p.alias("planted"), F.try_divide(hits, f).alias("precision"), F.try_divide(hits, p).alias("recall"))


def _nodes(plan):
    """All operators of a physical plan, through adaptive stages."""
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _nodes(plan.executedPlan())
        return
    yield name, plan
    if name.endswith("QueryStageExec"):
        yield from _nodes(plan.plan())
        return
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def exchanges(df: DataFrame) -> int:
    """Shuffles in the physical plan of a table."""
    return sum(name == "ShuffleExchangeExec" for name, _ in _nodes(df._jdf.queryExecution().executedPlan()))


def engine_cost(df: DataFrame) -> dict[str, int]:
    """Runs a table's plan and reads from it how many shuffles it had and how many rows and bytes they wrote."""
    df._jdf.queryExecution().executedPlan().execute().count()
    out = {"exchanges": 0, "rows_shuffled": 0, "bytes_shuffled": 0}
    for name, plan in _nodes(df._jdf.queryExecution().executedPlan()):
        if name == "ShuffleExchangeExec":
            metrics = plan.metrics()
            out["exchanges"] += 1
            out["rows_shuffled"] += metrics.apply("shuffleRecordsWritten").value()
            out["bytes_shuffled"] += metrics.apply("shuffleBytesWritten").value()
    return out


def _spread_line(points: DataFrame) -> DataFrame:
    """On a line the smallest distance is one of neighbours: sorted ranges, each with its ends and its smallest gap, then the gaps between ranges."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        found = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
        x = np.concatenate(found) if found else np.zeros(0)
        if len(x):
            gaps = np.diff(x)
            gaps = gaps[gaps > 0]
            yield pa.RecordBatch.from_pydict({"lo": [float(x[0])], "hi": [float(x[-1])], "gap": pa.array([float(gaps.min()) if len(gaps) else None], pa.float64())})

    tasks = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    values = points.where("pt is not null").select("pt").distinct()
    rows = values.repartitionByRange(tasks, "pt").sortWithinPartitions("pt").mapInArrow(run, "lo double, hi double, gap double").collect()
    rows.sort(key=lambda r: r["lo"])  # a row for each task
    gaps = [r["gap"] for r in rows if r["gap"] is not None] + [b["lo"] - a["hi"] for a, b in zip(rows, rows[1:]) if b["lo"] > a["hi"]]
    return points.sparkSession.createDataFrame([((rows[-1]["hi"] - rows[0]["lo"]) / min(gaps) if gaps else None,)], "spread double")


def spread(points: DataFrame, metric, most: int = 20_000) -> DataFrame:
    """One row: largest over smallest positive distance; by sorting on a line, else of a small table, whose size is checked."""
    from ..functions.metrics import ABS, get

    m = get(metric)
    if m.name == ABS.name:
        return _spread_line(points)
    n = points.count()
    if n > most:
        raise ValueError(f"all pairs of {n} points are over the limit of {most}")
    pairs = points.select(F.col("pid").alias("i"), F.col("pt").alias("x")).join(points.select(F.col("pid").alias("j"), F.col("pt").alias("y")), F.col("i") < F.col("j"))
    d = pairs.select(m.expr(F.col("x"), F.col("y")).alias("d")).where("d > 0")
    return d.agg((F.max("d") / F.min("d")).alias("spread"))


def doubling_dimension(points: DataFrame, metric, balls: int = 16, sample: int = 2000, seed: int = 42) -> float:
    """log2 of the most half-radius balls that a sampled ball needs (greedy); a diagnostic, never an argument of the algorithm."""
    import numpy as np

    from ..functions.metrics import get
    from ..operators.kernels import distances

    m = get(metric)
    table = points.select("pid", "pt").orderBy(F.xxhash64("pid", F.lit(seed))).limit(sample).toArrow()
    pts = m.load(table["pt"])
    if len(pts) < 2:
        return 0.0
    rng, worst = np.random.default_rng(seed), 1
    for c in rng.choice(len(pts), min(balls, len(pts)), replace=False):
        d = distances(m, pts, pts[c : c + 1])[:, 0]
        for share in (0.1, 0.3, 0.6):
            r = float(np.quantile(d, share))
            left, count = np.flatnonzero(d <= r), 0
            while len(left) and r > 0:
                near = distances(m, pts[left], pts[left[:1]])[:, 0]
                left, count = left[near > r / 2], count + 1
            worst = max(worst, count)
    return math.log2(worst)


def ball(points: DataFrame, center, radius: float, metric) -> DataFrame:
    """Members (pid, dist) of a ball."""
    from ..functions.metrics import get
    from ..operators.cost import _literal

    d = F.round(get(metric).expr(F.col("pt"), _literal(center)), 9)
    return points.select("pid", d.alias("dist")).where(F.col("dist") <= radius)


def memory_slope(rows: list[tuple[int, int]]) -> float:
    """Slope of log memory against log N."""
    xs, ys = [math.log(n) for n, _ in rows], [math.log(v) for _, v in rows]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / sum((x - mx) ** 2 for x in xs)
