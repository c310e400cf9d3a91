"""The complete three-round algorithm, its model, grouped fits and parameter sweeps."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..operators import cost, solvers


@dataclass
class RobustSpec:
    k: int
    z: int
    gamma: float = 0.5
    variant: str = "refined"
    metric: str = "l2"
    power: int = 2
    beta: float = 1.0
    parts: int | None = None
    seeding: str = "dsq"
    scheme: str = "hash"
    solver: str = "trimmed_swap"
    #: Inflation of k and z before round 1; None: what the solver's extra centers or outliers need.
    center_factor: float | None = None
    outlier_factor: float | None = None
    strict: bool = False
    levels: int = 0
    seed: int = 42
    max_rows: int = solvers.MAX_ROWS
    options: dict = field(default_factory=dict)


    def factors(self) -> tuple[float, float]:
        """(centers, outliers): the search that forgets more gets twice z, the one that opens more 1 + eps times k."""
        extra = 1 + self.options.get("eps", 0.5) if self.solver == "multi_swap" else 1.0
        more = 2.0 if self.solver == "trimmed_swap" and self.z else 1.0
        return (extra if self.center_factor is None else self.center_factor), (more if self.outlier_factor is None else self.outlier_factor)


@dataclass
class Model:
    centers: list[tuple[int, object]]
    spec: RobustSpec
    cost: float
    stats: dict
    coreset: DataFrame | None = None

    def transform(self, points: DataFrame, outliers: int | None = None) -> DataFrame:
        """(pid, cid, dist, is_outlier[, w]): the z farthest points are flagged exactly, ties by least pid.

        The narrow assignment is checkpointed, as finding the cut reads it several times.
        """
        z = self.spec.z if outliers is None else outliers
        more = [c for c in ("w",) if c in points.columns]
        a = cost.assign(points, self.centers, self.spec.metric).select("pid", "cid", "dist", *more)
        if z <= 0:
            return a.select("pid", "cid", "dist", F.lit(False).alias("is_outlier"), *more)
        a = cs.checkpoint(a)
        threshold, above, _ = cost.range_cut(a.withColumn("w", F.lit(1)), z)
        tied = a.where(F.col("dist") == threshold).select("pid").orderBy("pid").limit(z - above).withColumn("_t", F.lit(True))
        flagged = (F.col("dist") > threshold) | F.coalesce("_t", F.lit(False))
        return a.join(tied, "pid", "left").select("pid", "cid", "dist", flagged.alias("is_outlier"), *more)

    def save(self, path: str) -> None:
        spark = self.coreset.sparkSession
        self.coreset.write.mode("overwrite").parquet(f"{path}/coreset")
        head = json.dumps({"centers": self.centers, "spec": asdict(self.spec), "cost": self.cost, "stats": self.stats})
        spark.createDataFrame([(head,)], "head string").coalesce(1).write.mode("overwrite").text(f"{path}/model")

    @staticmethod
    def load(spark: SparkSession, path: str) -> "Model":
        head = json.loads(spark.read.text(f"{path}/model").first()[0])
        return Model([(i, p) for i, p in head["centers"]], RobustSpec(**head["spec"]), head["cost"], head["stats"], spark.read.parquet(f"{path}/coreset"))


def model_of(coreset: DataFrame, spec: RobustSpec, extra: dict | None = None) -> Model:
    """Round 3 on a weighted set."""
    kept = coreset
    options = dict(spec.options)
    if spec.solver == "trimmed_swap":
        # the outlier inflation is fixed before round 1, so it also bounds what the search may forget
        options = {"outlier_cap": math.ceil(spec.factors()[1] * spec.z), "init": "dsq"} | options
    rows = solvers.solve(kept, spec.k, spec.z, spec.solver, spec.metric, spec.power, spec.max_rows, **options).collect()
    ids = [r["pid"] for r in rows if r["kind"] == "center"]
    found = {r["pid"]: r["pt"] for r in kept.where(F.col("pid").isin(ids)).select("pid", "pt").collect()}
    stats = {r["kind"].removeprefix("stat:"): r["value"] for r in rows if r["pid"] is None} | (extra or {})
    return Model(sorted(found.items()), spec, stats.pop("cost"), stats, kept)


def build(points: DataFrame, spec: RobustSpec) -> cs.Coreset:
    return cs.build(
        points, spec.k, spec.z, spec.gamma, spec.variant, spec.metric, spec.power, spec.beta, spec.parts, spec.seeding, spec.scheme,
        strict=spec.strict, center_factor=spec.factors()[0], outlier_factor=spec.factors()[1], levels=spec.levels, seed_value=spec.seed,
    )


def fit(points: DataFrame, spec: RobustSpec) -> Model:
    """Rounds 1 and 2 make the coreset for the inflated numbers, round 3 solves it for k and z."""
    c = build(points, spec)
    return model_of(c.rows, spec, {"radius": c.radius, "k_prime": c.k_prime, "parts": c.parts, "certified": c.certified, "beta_assumed": spec.beta})


def report(points: DataFrame, model: Model) -> DataFrame:
    """(center_id, n_points, weight, cost, n_outliers) over the full table."""
    joined = cs.with_weight(model.transform(points))
    inlier = ~F.col("is_outlier")
    return joined.groupBy(F.col("cid").alias("center_id")).agg(
        F.count_if(inlier).alias("n_points"),
        F.coalesce(F.sum(F.when(inlier, F.col("w"))), F.lit(0)).alias("weight"),
        F.round(F.coalesce(F.sum(F.when(inlier, F.col("w") * F.pow("dist", F.lit(model.spec.power)))), F.lit(0.0)), 6).alias("cost"),
        F.count_if(F.col("is_outlier")).alias("n_outliers"),
    )


def fit_by(points: DataFrame, key: str, spec: RobustSpec) -> DataFrame:
    """(key, center pid, mass, cost): one small fit for each key, each in its own group; groups are bounded by what a solver takes."""
    import pyarrow as pa

    from ..functions.metrics import get

    m = get(spec.metric)
    most = solvers.most_rows(m, spec.max_rows, spec.solver)
    kind = dict(points.dtypes)[key]
    weighted = cs.with_weight(points).select(F.col(key).alias("key"), "pid", "pt", F.col("w").cast("bigint").alias("w"))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("pid")
        if table.num_rows > most:
            raise ValueError(f"a group of {table.num_rows} rows is over {most}; fit it through a coreset")
        ids, w, pts = table["pid"].to_numpy(), table["w"].to_numpy(), m.load(table["pt"])
        s, mass = solvers.solve_points(m, pts, w, spec.k, min(spec.z, int(w.sum()) - 1), spec.solver, spec.power, **spec.options)
        return pa.table({"key": table["key"].take(pa.array([0] * len(s.centers))), "center_id": ids[s.centers], "weight": pa.array(mass.astype("int64")), "cost": pa.array([round(s.cost, 6)] * len(mass))})

    return weighted.groupBy("key").applyInArrow(run, f"key {kind}, center_id long, weight long, cost double")


def sweep(points: DataFrame, spec: RobustSpec, grid: list[tuple[int, int]]) -> list[tuple[int, int, float]]:
    """(k, z, cost) for many k and z on one coreset, built for the largest k + z of the grid."""
    from dataclasses import replace

    top = max(grid, key=lambda g: g[0] + g[1])
    c = build(points, replace(spec, k=top[0], z=top[1]))
    return [(k, z, model_of(c.rows, replace(spec, k=k, z=z)).cost) for k, z in grid]
