"""What the coreset algorithm is compared with."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..operators import solvers
from ..sources import points as sources
from .pipeline import Model, RobustSpec, build, fit, model_of


def sequential(points: DataFrame, spec: RobustSpec) -> Model:
    """The solver on the whole (small) input."""
    return model_of(cs.with_weight(points).select("pid", "pt", "w"), spec)


def per_part_outlier_solver(points: DataFrame, spec: RobustSpec, parts: int = 4, solver: str = "trimmed_swap", **options) -> Model:
    """An outlier solver in every part; its weighted centers and kept outliers are solved again."""
    import numpy as np
    import pyarrow as pa

    from ..functions.metrics import get

    m = get(spec.metric)
    routed = cs.narrow(sources.partition(points, parts, spec.scheme))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("pid")
        w, pts = table["w"].to_numpy(), m.load(table["pt"])
        if len(w) > solvers.most_rows(m, spec.max_rows):
            raise ValueError(f"a part of {len(w)} rows is over {spec.max_rows}; take more parts")
        s, mass = solvers.solve_points(m, pts, w, spec.k, min(spec.z, int(w.sum()) - 1), solver, spec.power, **({"init": "dsq", "outlier_cap": 2 * spec.z, "max_passes": 3} | options))
        total = s.outliers.copy()
        total[s.centers] += mass.astype("int64")
        kept = np.flatnonzero(total)
        out = table.take(pa.array(kept))
        return pa.table([out["pid"], out["pt"], pa.array(total[kept]), out["part_id"]], names=["pid", "pt", "w", "part_id"])

    return model_of(cs.checkpoint(routed.groupBy("part_id").applyInArrow(run, routed.schema)), spec)


def outlier_blind_coreset(points: DataFrame, spec: RobustSpec) -> Model:
    """The coreset without outliers (k' = k), solved with z afterwards."""
    return model_of(build(points, replace(spec, z=0)).rows, spec)


def compare_variants(points: DataFrame, spec: RobustSpec) -> list[tuple[str, int, int, float, int]]:
    """(variant, reference rows, coreset rows, solution cost, mass) of direct, refined and one-round."""
    out = []
    for variant in ("direct", "refined", "one_round"):
        c = build(points, replace(spec, variant=variant))
        out.append((variant, c.reference.num_rows if c.reference is not None else 0, c.rows.count(), model_of(c.rows, spec).cost, int(c.rows.agg(F.sum("w")).first()[0])))
    return out


def replicated(coreset: DataFrame) -> DataFrame:
    """A weighted set as equal unweighted points."""
    copies = coreset.select("pid", "pt", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("w"))).alias("copy"))
    return copies.select((F.col("pid") * 100_000 + F.col("copy")).alias("pid"), "pt", F.lit(1).cast("bigint").alias("w"))


def uniform(points: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """A uniform sample by a hash of the id, weights N/n rounded so that the mass is kept."""
    total = points.count()
    rows = points.orderBy(F.xxhash64("pid", F.lit(seed)), "pid").limit(n).select("pid", "pt")
    each, more = divmod(total, max(1, min(n, total)))
    from pyspark.sql import Window

    rank = F.row_number().over(Window.orderBy("pid"))  # n rows at most
    return rows.withColumn("w", (F.lit(each) + F.when(rank <= more, 1).otherwise(0)).cast("bigint"))


def ignoring_outliers(points: DataFrame, spec: RobustSpec) -> Model:
    return fit(points, replace(spec, z=0))


def single_machine(points: DataFrame, spec: RobustSpec) -> cs.Coreset:
    return build(points, replace(spec, parts=1))


def lloyd(points: DataFrame, k: int, iterations: int = 10) -> list[list[float]]:
    """Means anywhere in the space (vectors): another feasible set, for comparison only."""
    first = points.orderBy("pid").limit(k).collect()
    centers = [list(r["pt"]) for r in first]
    dims = len(centers[0])
    for _ in range(iterations):
        from ..operators.cost import assign

        a = assign(points, list(enumerate(centers)), "l2")
        rows = a.groupBy("cid").agg(*[F.avg(F.col("pt")[i]).alias(f"x{i}") for i in range(dims)]).collect()
        new = [list(c) for c in centers]
        for r in rows:
            new[r["cid"]] = [r[f"x{i}"] for i in range(dims)]
        if new == centers:
            break
        centers = new
    return centers
