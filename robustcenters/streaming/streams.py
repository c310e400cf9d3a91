"""Structured Streaming: window coresets, merge-and-recover state, lateness, scoring and interval joins.

Proxy distortion is additive over disjoint parts and proxies compose, so coresets of panes can be united and covered
again.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..plans.pipeline import Model, RobustSpec, model_of
from ..shared import shared_folder
from ..sources import points as src


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream; timestamps without zone are read in the session's zone, as watermarks need."""
    schema = src.table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def in_files(events: DataFrame, path: str, groups: int, key) -> DataFrame:
    """The table as a stream of ``groups`` files, one in each micro-batch: first the rows whose key is 0, then 1, ..."""
    spark = events.sparkSession
    # only new files are added, each with a later time of its own; a repeated run finds its files written
    for i in range(groups):
        events.where(key == i).coalesce(1).write.mode("overwrite").parquet(f"{path}/part={i}")
    raw = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(path)
    return raw


def with_lateness(stream: DataFrame, delay: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", delay)


def unique_points(stream: DataFrame, key: str = "event_id", delay: str = "1 day") -> DataFrame:
    """One unit of mass for each id."""
    return with_lateness(stream, delay).dropDuplicatesWithinWatermark([key])


def tumbling(stream: DataFrame, width: str = "1 day") -> DataFrame:
    return with_lateness(stream).groupBy(F.window("ts", width).alias("win")).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("win.start").alias("start"), "n", "total")


def sliding(stream: DataFrame, width: str = "7 days", step: str = "1 day") -> DataFrame:
    return with_lateness(stream).groupBy(F.window("ts", width, step).alias("win")).agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), "n")


def session_points(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """A user's session becomes a point (events, total)."""
    s = with_lateness(stream).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return s.select("user_id", F.col("s.start").alias("start"), "n", "total")


def follow_ups(left: DataFrame, right: DataFrame) -> DataFrame:
    """Events and later events of the same user within an hour; both sides are watermarked."""
    a = with_lateness(left).select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = right.withWatermark("ts", "1 day").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, F.expr("ua = ub AND tb > ta AND tb <= ta + INTERVAL 1 HOUR")).select("a", "b")


def score(stream: DataFrame, model: Model, threshold: float) -> DataFrame:
    """Stateless labels: nearest center from a literal, outlier beyond the model's threshold."""
    from ..operators.cost import assign

    points = stream.select(F.col("event_id").cast("bigint").alias("pid"), F.col("value").alias("pt"))
    return assign(points, model.centers, model.spec.metric).select("pid", "cid", "dist", (F.col("dist") > threshold).alias("is_outlier"))


@dataclass
class CoresetState:
    """Binary counter of coresets in a shared folder: level i holds the union of 2^i batches.

    Every update writes new level tables and then a manifest that names them, so a restart goes on from the last complete
    one, and a batch that is delivered again changes nothing.
    """

    spark: SparkSession
    path: str
    spec: RobustSpec

    def _manifest(self) -> dict:
        """The last complete manifest: {"batch": its id, "levels": names of level tables or null}."""
        folder = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        if not folder.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(folder):
            return {"batch": -1, "levels": []}
        rows = self.spark.read.schema("head string").option("pathGlobFilter", "*.txt").option("recursiveFileLookup", "true").text(self.path)
        return max((json.loads(r["head"]) for r in rows.collect()), key=lambda m: m["batch"], default={"batch": -1, "levels": []})

    def update(self, batch: DataFrame, batch_id: int) -> None:
        """Batch ids rise, as Structured Streaming's do."""
        last = self._manifest()
        if batch_id <= last["batch"] or batch.isEmpty():
            return
        s, levels = self.spec, list(last["levels"])
        new = cs.build(batch, s.k, s.z, s.gamma, s.variant, s.metric, s.power, parts=s.parts or 2, seeding=s.seeding).rows.select("pid", "pt", "w", "part_id")
        at = 0
        while at < len(levels) and levels[at] is not None:
            new = cs.checkpoint(cs.recover(cs.merge(self._level(levels[at]), new), s.k + s.z, s.gamma, metric=s.metric, power=s.power))
            levels[at] = None
            at += 1
        levels += [None] * (at + 1 - len(levels))
        levels[at] = f"level-{at}-batch-{batch_id}"
        new.write.mode("overwrite").parquet(f"{self.path}/{levels[at]}")
        head = json.dumps({"batch": batch_id, "levels": levels})
        self.spark.createDataFrame([(head,)], "head string").coalesce(1).write.mode("overwrite").text(f"{self.path}/manifest-{batch_id}")

    def _level(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{name}")

    def union(self) -> DataFrame:
        return cs.merge(*[self._level(x) for x in self._manifest()["levels"] if x is not None])

    def levels(self) -> list[str | None]:
        return self._manifest()["levels"]

    def solve(self) -> Model:
        return model_of(cs.checkpoint(self.union()), self.spec)

    def follow(self, stream: DataFrame, name: str, **trigger) -> None:
        """Feed a stream of (pid, pt) to its end through foreachBatch; the log lies beside the levels."""
        q = stream.writeStream.foreachBatch(self.update).option("checkpointLocation", f"{self.path}-log-{name}").trigger(**(trigger or {"availableNow": True})).start()
        q.awaitTermination()


def fold_panes(panes: DataFrame, width: int, spec: RobustSpec) -> DataFrame:
    """(start, pid, pt, w): for each day a coreset of the ``width`` days that begin with it, from the days' coresets alone.

    panes: (start, pid, pt, w), a coreset for each day. Coresets of disjoint panes unite, and the union is covered again.
    """
    shift = F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("back")
    wide = panes.select("start", "pid", "pt", "w", shift).select((F.unix_seconds("start") - 86400 * F.col("back")).cast("int").alias("part_id"), "pid", "pt", "w")
    c = cs.build(wide, spec.k, spec.z, spec.gamma, "one_round", spec.metric, spec.power, parts=1, seeding=spec.seeding, scheme="given")
    return c.rows.select(F.timestamp_seconds("part_id").alias("start"), "pid", "pt", "w")


def window_coresets(points: DataFrame, width: str, spec: RobustSpec) -> DataFrame:
    """(start, pid, pt, w): one coreset for each closed window of (pid, pt, ts), windows being the parts of one build."""
    start = F.window("ts", width)["start"]
    parts = points.withColumn("start", start).withColumn("part_id", F.unix_seconds("start").cast("int"))
    c = cs.build(parts.select("pid", "pt", "part_id"), spec.k, spec.z, spec.gamma, "one_round", spec.metric, spec.power, parts=1, seeding=spec.seeding, scheme="given")
    return c.rows.select(F.timestamp_seconds("part_id").alias("start"), "pid", "pt", "w")


def run(spark: SparkSession, query: DataFrame, mode: str = "append", trigger: dict | None = None) -> DataFrame:
    """Run to the end of what is available and give the collected output as a table."""
    name = f"out_{abs(hash((id(query), spark.sparkContext.applicationId)))}"
    base = shared_folder(spark)
    where = f"{base}/{spark.sparkContext.applicationId}-{name}"
    if mode == "append":
        rows = query.writeStream.format("parquet").option("path", f"{where}/rows").option("checkpointLocation", f"{where}/log").trigger(**(trigger or {"availableNow": True})).start()
        rows.awaitTermination()
        return spark.read.schema(query.schema).parquet(f"{where}/rows")
    held: list[DataFrame] = []
    q = query.writeStream.foreachBatch(lambda df, _: held.append(cs.checkpoint(df))).outputMode(mode).option("checkpointLocation", f"{where}/log").trigger(**(trigger or {"availableNow": True})).start()
    q.awaitTermination()
    return held[-1]
