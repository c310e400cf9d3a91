"""Streams run to their end and compared with the same batch aggregate."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..operators import coreset as cs
from ..operators import cost
from ..plans.clustering_queries import first, ok_rows
from ..plans.oracles import checks
from ..plans.pipeline import Model, RobustSpec
from ..shared import shared_folder
from ..sources import points as src
from . import sqlapi, streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql, name=None):
    def add(f):
        QUERIES[name or f.__name__] = f
        ORACLES[name or f.__name__] = sql
        return f

    return add


@query("SELECT CAST(epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000 AS BIGINT) AS start, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def stream_tumbling(spark, sf_dir):
    out = streams.run(spark, streams.tumbling(streams.event_stream(spark, sf_dir)), "complete")
    return out.select(F.unix_seconds("start").alias("start"), "n", F.round("total", 4).alias("total"))


@query("SELECT CAST(epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000 AS BIGINT) - 86400 * d AS start, count(*) AS n FROM events, generate_series(0, 6) AS t(d) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    out = streams.run(spark, streams.sliding(streams.event_stream(spark, sf_dir)), "complete")
    return out.select(F.unix_seconds("start").alias("start"), "n")


@query("WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY user_id, sid")
def stream_session(spark, sf_dir):
    out = streams.run(spark, streams.session_points(streams.event_stream(spark, sf_dir)), "complete")
    return out.select("user_id", "n", F.round("total", 4).alias("total"))


@query("SELECT event_id FROM events")
def stream_dedup(spark, sf_dir):
    """The stream is fed its rows twice; each id stays once."""
    twice = streams.event_stream(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return streams.run(spark, streams.unique_points(twice).select("event_id"))


def _folder(spark, name: str) -> str:
    return f"{shared_folder(spark)}/{spark.sparkContext.applicationId}-{name}-{uuid.uuid4().hex[:8]}"


def _zoned(spark, sf_dir):
    return src.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("WITH m AS (SELECT max(ts) - INTERVAL 1 DAY AS w FROM events WHERE event_id % 4 = 0), l AS (SELECT count(*) AS n FROM events, m WHERE event_id % 2 = 1 AND ts <= m.w) SELECT (SELECT count(*) FROM events) AS received, (SELECT count(*) FROM events) - l.n AS kept, l.n AS dropped FROM l")
def stream_late_mass(spark, sf_dir):
    """Odd events come in the third micro-batch; those a day older than the newest of the first one are late and dropped.

    The watermark that drops late rows is the one that the micro-batch before worked with.
    """
    e = _zoned(spark, sf_dir)
    place = F.when(F.col("event_id") % 2 == 1, 2).otherwise(F.col("event_id") % 4 / 2)
    late = streams.in_files(e, _folder(spark, "late"), 3, place)
    kept = streams.run(spark, streams.unique_points(late).select("event_id")).count()
    return spark.createDataFrame([(e.count(), kept, e.count() - kept)], "received long, kept long, dropped long")


def _followed(spark, sf_dir):
    """All events as (pid, pt), in three micro-batches, through a durable state that is opened anew in between."""
    path = _folder(spark, "state")
    spec = RobustSpec(3, 10, 0.5, "refined", "abs", parts=2, solver="alternate")
    points = streams.in_files(_zoned(spark, sf_dir), f"{path}-in", 3, F.col("event_id") % 3).select(F.col("event_id").cast("bigint").alias("pid"), F.col("value").alias("pt"))
    streams.CoresetState(spark, path, spec).follow(points, "first")
    return path, spec, points


@query(checks("mass", "a restart adds nothing", "levels count batches", "a solution on demand", "certificate"))
def stream_merge_mass(spark, sf_dir):
    """Micro-batches through the merge-and-recover state; batches that are delivered again after a restart change nothing."""
    path, spec, points = _followed(spark, sf_dir)
    p = src.events_scalar(spark, sf_dir)
    state = streams.CoresetState(spark, path, spec)
    mass = state.union().agg(F.sum("w")).first()[0]
    before = state.levels()
    # without the log all batches come again, under the ids they had
    streams.CoresetState(spark, path, spec).follow(points, "again")
    again = state.union().agg(F.sum("w")).first()[0]
    m, start = state.solve(), first(p, 3)
    got, base = (cost.trimmed_cost(p, c, 10, "abs").first()[0] for c in (m.centers, start))
    full, small = (cost.cost(x, start, "abs").first()[0] for x in (p, state.union()))
    return ok_rows(spark, {
        "mass": mass == p.count(), "a restart adds nothing": again == mass and state.levels() == before, "levels count batches": [x is not None for x in before] == [True, True],
        "a solution on demand": len(m.centers) == 3 and got < base, "certificate": abs(full - small) <= 0.5 * full,
    })


@query("SELECT CAST(count(*) AS BIGINT) AS w FROM events")
def w28_stream(spark, sf_dir):
    """The mass of the state that followed the stream of all events."""
    path, spec, _ = _followed(spark, sf_dir)
    return streams.CoresetState(spark, path, spec).union().agg(F.sum("w").alias("w"))


@query("SELECT CAST(epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000 AS BIGINT) - 86400 * d AS start, count(*) AS w FROM events, generate_series(0, 6) AS t(d) GROUP BY 1")
def stream_sliding_coresets(spark, sf_dir):
    """Coresets of seven days, folded from those of single days."""
    e = _zoned(spark, sf_dir).select(F.col("event_id").cast("bigint").alias("pid"), F.col("value").alias("pt"), "ts")
    spec = RobustSpec(2, 2, 0.5, metric="abs")
    days = cs.checkpoint(streams.window_coresets(e, "1 day", spec))
    return streams.fold_panes(days, 7, spec).groupBy(F.unix_seconds("start").alias("start")).agg(F.sum("w").cast("bigint").alias("w"))


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_update_mode(spark, sf_dir):
    """Counts by type in update mode, a processing-time trigger between the micro-batches; the last value of each type counts."""
    stream = streams.in_files(_zoned(spark, sf_dir), _folder(spark, "update"), 2, F.col("event_id") % 2).groupBy("event_type").agg(F.count("*").alias("n"))
    held = []
    q = stream.writeStream.outputMode("update").trigger(processingTime="100 milliseconds").option("checkpointLocation", _folder(spark, "update-log"))
    q = q.foreachBatch(lambda df, i: held.append(cs.checkpoint(df.withColumn("at", F.lit(i))))).start()
    q.processAllAvailable()
    q.stop()
    return cs.merge(*held).groupBy("event_type").agg(F.max_by("n", "at").alias("n"))


@query("WITH c AS (SELECT event_id AS cid, value AS cx FROM events ORDER BY event_id LIMIT 5) SELECT e.event_id AS pid, round(min(abs(e.value - c.cx)), 6) AS dist, min(abs(e.value - c.cx)) > 100 AS is_outlier FROM events e, c GROUP BY e.event_id")
def stream_score(spark, sf_dir):
    m = Model(first(src.events_scalar(spark, sf_dir), 5), RobustSpec(5, 0, metric="abs"), 0.0, {})
    return streams.run(spark, streams.score(streams.event_stream(spark, sf_dir), m, 100.0)).select("pid", F.round("dist", 6).alias("dist"), "is_outlier")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_follow_ups(spark, sf_dir):
    return streams.run(spark, streams.follow_ups(streams.event_stream(spark, sf_dir), streams.event_stream(spark, sf_dir)))


@query("SELECT CAST(epoch_us(time_bucket(INTERVAL 1 DAY, ts)) // 1000000 AS BIGINT) AS start, count(*) AS w FROM events GROUP BY 1")
def stream_window_coresets(spark, sf_dir):
    e = src.table(spark, sf_dir, "events").select(F.col("event_id").cast("bigint").alias("pid"), F.col("value").alias("pt"), F.col("ts").cast("timestamp").alias("ts"))
    return streams.window_coresets(e, "1 day", RobustSpec(2, 2, 0.5, metric="abs")).groupBy(F.unix_seconds("start").alias("start")).agg(F.sum("w").alias("w"))


# SQL surface


@query("SELECT vec_id, round(sqrt(list_sum([CAST(v AS DOUBLE) * v for v in embedding])), 5) AS d FROM embeddings")
def rel_sql_function(spark, sf_dir):
    sqlapi.register(spark)
    return spark.sql("SELECT vec_id, round(l2(CAST(embedding AS ARRAY<DOUBLE>), array_repeat(0D, 64)), 5) AS d FROM {e}", e=src.table(spark, sf_dir, "embeddings"))


@query(checks("mass", "balls"))
def rel_udtf_cover(spark, sf_dir):
    sqlapi.register(spark)
    p = src.events_scalar(spark, sf_dir)
    near = cost.assign(p, first(p, 5), "abs").select("pid", F.col("pt").alias("x"), F.col("dist").alias("near"), F.lit(0).alias("part"))
    near.createOrReplaceTempView("cover_input")
    r = spark.sql("SELECT sum(w) AS w, count(*) AS n FROM ball_cover(TABLE(cover_input) PARTITION BY (part) ORDER BY (pid), 0.25D, 10.0D)").first()
    return ok_rows(spark, {"mass": r["w"] == p.count(), "balls": 0 < r["n"] < r["w"]})


@query(checks("centers"))
def rel_sql_entry(spark, sf_dir):
    sqlapi.register(spark)
    src.supplier_scalar(spark, sf_dir).select("pid", F.col("pt").alias("x"), F.lit(1).alias("w"), F.lit(0).alias("part")).createOrReplaceTempView("solver_input")
    return ok_rows(spark, {"centers": spark.sql("SELECT * FROM kmeans_out(TABLE(solver_input) PARTITION BY (part), 3, 2)").count() == 3})
