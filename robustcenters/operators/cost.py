"""Assignment, cost, trimmed cost and the exact cut at an outlier mass.

Centers are few by definition, so they become one array literal and assignment is a narrow projection without a
shuffle. The cut at outlier mass z is found by zooming histograms (a few tiny aggregates) instead of a
global sort; ties at the threshold are filled by least pid. Distances tie at nine decimals everywhere.
"""

from __future__ import annotations


import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.metrics import ABS, Metric, get
from ..shared import checkpoint

#: More centers than this, or wider vectors, go through the block kernel instead of one expression for each center.
#: Measured on 600,000 points of three coordinates, see the README.
LITERAL_CENTERS, LITERAL_WIDTH = 8, 8
#: Centers that the driver takes; more are an error.
MOST_CENTERS = 1_000_000
#: Bytes of centers or references that are broadcast; more are an error.
MAX_BROADCAST = 256 << 20


def center_rows(centers: DataFrame | list) -> list[tuple[int, object]]:
    rows = centers if isinstance(centers, list) else [(r["pid"], r["pt"]) for r in centers.select("pid", "pt").limit(MOST_CENTERS + 1).collect()]
    if len(rows) > MOST_CENTERS:
        raise ValueError(f"more than {MOST_CENTERS} centers")
    return sorted(rows, key=lambda r: r[0])


def _literal(value) -> Column:
    if isinstance(value, (list, tuple, np.ndarray)):
        return F.array(*[F.lit(x) for x in value])
    return F.lit(value)


def assign(points: DataFrame, centers: DataFrame | list, metric: str | Metric) -> DataFrame:
    """points with cid and dist of the nearest center; ties go to the least id."""
    m, rows = get(metric), center_rows(centers)
    if not rows:
        raise ValueError("no centers")
    unrolled = m.near is not None and all(len(p) <= LITERAL_WIDTH for _, p in rows)
    if len(rows) > LITERAL_CENTERS or m.near is not None and not unrolled or m.kind == "set":
        return _assign_blocks(points, rows, m)
    to = lambda p: m.near(F.col("pt"), [float(x) for x in p]) if unrolled else m.expr(F.col("pt"), _literal(p))
    each = [F.struct(F.round(to(p), 9).alias("dist"), F.lit(int(i)).cast("bigint").alias("cid")) for i, p in rows]
    near = F.least(*each) if len(each) > 1 else each[0]
    return points.withColumn("_near", near).select(*points.columns, F.col("_near.cid").alias("cid"), F.col("_near.dist").alias("dist"))


def _assign_blocks(points: DataFrame, rows: list, m: Metric) -> DataFrame:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import DoubleType, LongType, StructField, StructType

    schema = StructType([*points.schema.fields, StructField("cid", LongType()), StructField("dist", DoubleType())])
    arrow, at = to_arrow_schema(schema), points.columns.index("pt")
    ids = np.array([i for i, _ in rows])
    payload = to_arrow_schema(points.select("pt").schema)[0].type
    column = pa.array([p for _, p in rows], payload)
    if column.nbytes > MAX_BROADCAST:
        raise ValueError(f"centers of {column.nbytes} bytes are over the broadcast limit")
    shared = points.sparkSession.sparkContext.broadcast(m.load(column))

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                own = m.load(batch.column(at))
                best, where = np.full(len(own), np.inf), np.zeros(len(own), dtype="int64")
                for lo in range(0, len(ids), 1024):
                    d = np.round(m.block(own, shared.value[lo : lo + 1024]), 9)
                    j = d.argmin(axis=1)
                    v = d[np.arange(len(own)), j]
                    new = v < best
                    best[new], where[new] = v[new], lo + j[new]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(ids[where]), pa.array(best)], schema=arrow)

    return points.mapInArrow(run, schema)


def weight_of(points: DataFrame) -> Column:
    return F.col("w") if "w" in points.columns else F.lit(1).cast("bigint")


def cost(points: DataFrame, centers, metric, power: int = 2) -> DataFrame:
    """One row: cost."""
    return assign(points, centers, metric).agg(F.coalesce(F.sum(weight_of(points) * F.pow("dist", F.lit(power))), F.lit(0.0)).alias("cost"))


def farthest(points: DataFrame, centers, z: int, metric) -> DataFrame:
    """The z farthest points (pid, dist), farthest first; ties by least pid."""
    return assign(points, centers, metric).select("pid", "dist").orderBy(F.desc("dist"), "pid").limit(z)


def range_cut(assigned: DataFrame, z: int, buckets: int = 4096, sort_rows: int = 50_000) -> tuple[float | None, int, int]:
    """(threshold, mass above, mass at the threshold) of the farthest mass z of (dist[, w]).

    Each round brackets the cut in one of ``buckets`` ranges with one small aggregate; it ends when the bracket holds
    one distance, or so few rows that they may be sorted.
    """
    w = weight_of(assigned)
    d = assigned.select("dist", w.alias("w")).where(w > 0)
    lo, hi, rows, total = d.agg(F.min("dist"), F.max("dist"), F.count("*"), F.sum("w")).first()
    if z <= 0 or rows == 0:
        return None, 0, 0
    if z > total:
        raise ValueError(f"outlier mass {z} exceeds the mass {total}")
    above = 0
    while lo < hi and rows > sort_rows:
        inside = d.where(F.col("dist").between(lo, hi))
        step = (hi - lo) / buckets
        bucket = F.least(F.floor((F.col("dist") - lo) / step), F.lit(buckets - 1)) if step > 0 else F.lit(0)
        found = inside.groupBy(bucket.alias("b")).agg(F.sum("w").alias("w"), F.count("*").alias("n"), F.min("dist").alias("lo"), F.max("dist").alias("hi")).collect()
        for r in sorted(found, key=lambda r: -r["b"]):
            if above + r["w"] >= z:
                lo, hi, rows = r["lo"], r["hi"], r["n"]
                break
            above += r["w"]
    if lo == hi:
        return hi, above, d.where(F.col("dist") == hi).agg(F.sum("w")).first()[0]
    for r in sorted(d.where(F.col("dist").between(lo, hi)).groupBy("dist").agg(F.sum("w").alias("w")).collect(), key=lambda r: -r["dist"]):
        if above + r["w"] >= z:
            return r["dist"], above, r["w"]
        above += r["w"]
    raise AssertionError("the cut lies inside the bracket")


def trimmed_cost(points: DataFrame, centers, z: int, metric, power: int = 2) -> DataFrame:
    """One row: the cost after the farthest mass z is forgotten; a point on the boundary is split."""
    a = assign(points, centers, metric)
    w = weight_of(points)
    if z <= 0:
        return a.agg(F.coalesce(F.sum(w * F.pow("dist", F.lit(power))), F.lit(0.0)).alias("cost"))
    if get(metric).kind == "set":
        # dear distances are made once, though the cut reads them several times
        a, w = checkpoint(a.select("dist", w.alias("w"))), F.col("w")
    threshold, above, at = range_cut(a, z)
    rest = at - (z - above)
    below = F.coalesce(F.sum(F.when(F.col("dist") < threshold, w * F.pow("dist", F.lit(power)))), F.lit(0.0))
    return a.agg((below + F.lit(float(rest) * threshold**power)).alias("cost"))


def trim_weights(points: DataFrame, centers, z: int, metric) -> DataFrame:
    """(pid, w, w_hat): weights after z units go from the farthest points, ties by least pid.

    Only the rows that tie at the threshold are ranked; all others follow from the cut.
    """
    a = assign(points, centers, metric)
    a = a if "w" in points.columns else a.withColumn("w", F.lit(1).cast("bigint"))
    if z <= 0:
        return a.select("pid", "w", F.col("w").alias("w_hat"))
    threshold, above, _ = range_cut(a, z)
    left = z - above
    before = Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)
    tied = a.where(F.col("dist") == threshold).withColumn("_b", F.coalesce(F.sum("w").over(before), F.lit(0)))
    tied = tied.select("pid", "w", (F.col("w") - F.greatest(F.lit(0), F.least("w", F.lit(left) - F.col("_b")))).cast("bigint").alias("w_hat"))
    other = a.where(F.col("dist") != threshold).select("pid", "w", F.when(F.col("dist") > threshold, 0).otherwise(F.col("w")).cast("bigint").alias("w_hat"))
    return other.unionByName(tied)


def cost_without(points: DataFrame, outliers: DataFrame, centers, metric, power: int = 2) -> DataFrame:
    """Cost of points minus a given outlier set (pid)."""
    return cost(points.join(outliers.select("pid"), "pid", "left_anti"), centers, metric, power)


def range_pairs(points: DataFrame, radius: float) -> DataFrame:
    """Pairs i < j of scalar points within the radius: grid cells joined with their neighbours, then checked exactly."""
    cell = F.floor(F.col("pt") / radius)
    a = points.select(F.col("pid").alias("i"), F.col("pt").alias("x"), cell.alias("cell"))
    b = points.select(F.col("pid").alias("j"), F.col("pt").alias("y"), F.explode(F.array(cell - 1, cell, cell + 1)).alias("cell"))
    return a.join(b, "cell").where((F.col("i") < F.col("j")) & (F.abs(F.col("x") - F.col("y")) <= radius)).select("i", "j", F.round(F.abs(F.col("x") - F.col("y")), 9).alias("dist"))


def line_optimum(x: np.ndarray, w: np.ndarray, ids: np.ndarray, k: int, z: int, power: int) -> tuple[list[int], float] | None:
    """(centers, cost): the optimum of distinct values x with weights w and least ids; None if nothing is left to pay, where all depends on ids.

    What is forgotten lies at the ends and, with two centers, around their middle. So the units that are kept are one or two
    intervals, each served by the point next to its mean or by its median: all of these are tried. The pairs within reach of rounding
    are then summed exactly; ties at six decimals go to the least ids.
    """
    from math import fsum

    order = np.argsort(x)
    x, w, ids = x[order], w[order].astype("int64"), ids[order]
    kind, n = np.repeat(np.arange(len(x)), w), int(w.sum())
    z = max(0, z)
    if n - z < k:
        return None
    u = (x - x.mean()).astype("longdouble")[kind]
    p1, p2 = (np.r_[np.longdouble(0), np.cumsum(v)] for v in (u, u * u))
    plain = u.astype("float64")

    def pay(lo, hi, at):
        c = u[at]
        if power == 2:
            return p2[hi] - p2[lo] - 2 * c * (p1[hi] - p1[lo]) + (hi - lo) * c * c
        return (2 * at - lo - hi) * c - 2 * p1[at] + p1[lo] + p1[hi]

    def serve(lo, hi):
        if power == 1:
            at = lo + (hi - lo - 1) // 2
            return at, pay(lo, hi, at)
        right = np.clip(np.searchsorted(plain, ((p1[hi] - p1[lo]) / (hi - lo)).astype("float64")), lo, hi - 1)
        left = np.maximum(right - 1, lo)
        a, b = pay(lo, hi, left), pay(lo, hi, right)
        return np.where(a <= b, left, right), np.minimum(a, b)

    def near(lo, hi, at, least):
        """Distinct values of an interval that serve it at no more than the least and what rounding may hide."""
        found, first = [kind[at]], lambda j: int(np.searchsorted(kind, j))
        for step in (-1, 1):
            j = kind[at] + step
            while kind[lo] <= j <= kind[hi - 1] and pay(lo, hi, max(lo, first(j))) <= least + slack:
                found.append(j)
                j += step
        return found

    slack = np.longdouble(1e-4) + np.longdouble(1e-15) * p2[-1]
    best, kept = np.longdouble(np.inf), []
    for a in range(z + 1):
        for gap in range(z - a + 1) if k == 2 else (0,):
            end = n - (z - a - gap)
            if k == 1:
                lo, hi = np.array([a]), np.array([end])
                parts = [(lo, hi, *serve(lo, hi))]
            else:
                cut = np.arange(a + 1, end - gap)
                if not len(cut):
                    continue
                parts = [(lo, hi, *serve(lo, hi)) for lo, hi in ((np.full(len(cut), a), cut), (cut + gap, np.full(len(cut), end)))]
            total = sum(p[3] for p in parts)
            best = min(best, total.min())
            kept += [(total[i], [tuple(y[i] for y in p) for p in parts]) for i in np.flatnonzero(total <= best + slack)]
    options: set = set()
    for total, parts in kept:
        if total <= best + slack:
            sides = [near(*p) for p in parts]
            options |= {(i,) for i in sides[0]} if k == 1 else {tuple(sorted((i, j))) for i in sides[0] for j in sides[1] if i != j}
    found = []
    for s in options:
        d = np.round(np.abs(x[:, None] - x[list(s)]).min(axis=1), 9)
        far = np.argsort(-d, kind="stable")
        left = w.copy()
        left[far] -= np.clip(z - (np.cumsum(w[far]) - w[far]), 0, w[far])
        found.append((round(fsum((left * d**power).tolist()), 6), sorted(int(ids[i]) for i in s)))
    return (min(found)[1], min(found)[0]) if found and min(found)[0] > 0 else None


def _optimum_line(points: DataFrame, k: int, z: int, power: int) -> list | None:
    """The row of ``optimum`` from the distinct values, which one task takes; null values and empty tables are left to the general way."""
    w = weight_of(points)
    values = points.groupBy("pt").agg(F.min("pid").cast("bigint").alias("pid"), F.sum(w).cast("bigint").alias("w"), F.min(w).alias("least"))

    def run(table: pa.Table) -> pa.Table:
        found = None
        if not table["pt"].null_count and not table["pid"].null_count and min(table["least"].to_pylist()) > 0:
            found = line_optimum(table["pt"].to_numpy().astype("float64"), table["w"].to_numpy(), table["pid"].to_numpy(), k, z, power)
        return pa.table({"centers": pa.array([found and ",".join(map(str, found[0]))], pa.string()), "cost": pa.array([found and found[1]], pa.float64())})

    rows = values.withColumn("all", F.lit(0)).groupBy("all").applyInArrow(lambda t: run(t), "centers string, cost double").collect()
    return [tuple(r) for r in rows if r["centers"] is not None] or None


def optimum(points: DataFrame, k: int, z: int, metric, power: int = 2, max_combinations: int = 2_000_000) -> DataFrame:
    """One row (centers, cost): the exact optimum over all k-subsets by a guarded k-fold join, for small tables; for one or two centers on a line by sorting."""
    from math import comb

    if get(metric).name == ABS.name and k in (1, 2) and power in (1, 2) and (found := _optimum_line(points, k, z, power)):
        return points.sparkSession.createDataFrame(found, "centers string, cost double")
    n = points.count()
    if comb(n, min(k, n)) > max_combinations:
        raise ValueError(f"{comb(n, k)} subsets of {n} points are over the limit of {max_combinations}")
    m, power_lit = get(metric), F.lit(power)
    k = min(k, n)
    weighted = "w" in points.columns
    base = points.select("pid", "pt", (F.col("w") if weighted else F.lit(1)).cast("bigint").alias("w"))
    # n * n distances: n is guarded above
    pairs = base.select(F.col("pid").alias("c"), F.col("pt").alias("x")).crossJoin(base).select("c", "pid", "w", F.round(m.expr(F.col("x"), F.col("pt")), 9).alias("d"))
    subsets = base.select(F.array("pid").alias("s"))
    for _ in range(k - 1):
        subsets = subsets.join(base.select(F.col("pid").alias("n")), F.element_at("s", -1) < F.col("n")).select(F.concat("s", F.array("n")).alias("s"))
    near = subsets.select("s", F.explode("s").alias("c")).join(pairs, "c").groupBy("s", "pid", "w").agg(F.min("d").alias("d"))
    before = Window.partitionBy("s").orderBy(F.desc("d"), "pid").rowsBetween(Window.unboundedPreceding, -1)
    left = F.col("w") - F.greatest(F.lit(0), F.least("w", F.lit(z) - F.coalesce(F.sum("w").over(before), F.lit(0))))
    totals = near.withColumn("left", left).groupBy("s").agg(F.sum(F.col("left") * F.pow("d", power_lit)).alias("cost"))
    return totals.orderBy(F.round("cost", 6), "s").limit(1).select(F.array_join(F.transform("s", lambda x: x.cast("string")), ",").alias("centers"), F.round("cost", 6).alias("cost"))


