"""Shared pieces of the training-data operators.

Words are the maximal runs without ASCII white space (``bytes.split()``), lower-casing touches A-Z only
(``bytes.lower()``); both work on UTF-8 bytes, so no text is ever decoded just to be cut into words.
"""

from __future__ import annotations

import functools
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one step of a Python kernel looks at; a single longer text makes a step of its own.
CHUNK_BYTES = 4 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def checkpoint(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the folder that the cluster names.

    The folder is spark.checkpoint.dir; where a local session has none (tests), a temporary one is set.
    """
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder of the session; without one on a cluster an error, as no local folder would do there."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = context.getConf().get("spark.checkpoint.dir")
        if not named and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def written(df: DataFrame) -> DataFrame:
    """The table, written as Parquet in the shared folder and read again: a checkpoint that packs narrow columns well."""
    path = f"{shared_folder(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dense(df: DataFrame, rows: int, each: int = 50_000) -> DataFrame:
    """df in no more partitions than four for each core, or one for ``each`` of its ``rows``: many short jobs on a small table make few tasks."""
    return df.coalesce(max(16, 4 * df.sparkSession.sparkContext.defaultParallelism, rows // each))


def lowest_hashes(rows: DataFrame, key: Column, size: int, *ties: str) -> DataFrame:
    """The ``size`` rows of the lowest hash ``key`` (ties by columns): a bounded sample that does not depend on the layout.

    Rows are cut by a threshold on the hash first, about one and a half times ``size`` of them, so that what the tasks
    send to the final sort does not grow with the input. Keys should be unique.
    """
    total, share = rows.count(), 1.5
    marked = rows.withColumn("_hash", F.shiftrightunsigned(key, 1))
    while share * (size + 200) < total:
        part = marked.where(F.col("_hash") < int(share * (size + 200) / total * 2**63))
        if part.count() >= size:
            marked = part
            break
        share *= 2
    return marked.orderBy("_hash", *ties).limit(size).drop("_hash")


def join_hot(big: DataFrame, small: DataFrame, on: list[str], weight: str, share: int = 10_000) -> DataFrame:
    """big joined with small, whose ``weight`` says how many rows of big have the key (unique in small).

    Keys with more than a ``share``-th of all rows, of which there are fewer than ``share``, are broadcast, so that
    no task gathers them; all others meet in a shuffle. Both tables should be checkpointed.
    """
    total = small.agg(F.sum(weight)).first()[0] or 0
    hot = F.col(weight) * share > total
    rest = big.join(F.broadcast(small.where(hot).select(*on)), on, "left_anti")
    return big.join(F.broadcast(small.where(hot)), on).unionByName(rest.join(small.where(~hot), on))


def add_blocks(parts: DataFrame, schema: str, add: Callable[[pa.Table], pa.Table], together: int = 256) -> list:
    """Rows (block, ...), one for each block: ``add`` joins the tables of a block, at most ``together`` tasks' at first."""
    level = F.floor(F.spark_partition_id() / together).cast("int")
    first = parts.withColumn("_level", level).groupBy("block", "_level").applyInArrow(lambda t: add(t.drop_columns("_level")), schema)
    return sorted(first.groupBy("block").applyInArrow(add, schema).collect(), key=lambda r: r["block"])


def text_bytes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more) -> DataFrame:
    """(doc_id, body) with the text as bytes, null where the text is null; further columns may follow."""
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("binary").alias("body"), *more)


def chunks(batches: Iterator[pa.RecordBatch], column: str = "body", most: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches so that each piece holds about ``most`` bytes of the column, whatever the lengths are."""
    for batch in batches:
        at, n = 0, batch.num_rows
        if not n:
            continue
        lengths = pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_pylist()
        while at < n:
            size, end = lengths[at], at + 1
            while end < n and size + lengths[end] <= most:
                size += lengths[end]
                end += 1
            yield batch.slice(at, end - at)
            at = end


def map_chunks(df: DataFrame, kernel: Callable[[pa.RecordBatch], dict], schema: str, column: str = "body") -> DataFrame:
    """kernel: one piece of a batch -> dict of columns. State that a kernel needs is made once a task by ``start``."""
    arrow = arrow_schema(df.sparkSession, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in chunks(batches, column):
            yield pa.RecordBatch.from_pydict(kernel(piece), schema=arrow)

    return df.mapInArrow(run, schema)


def arrow_schema(spark: SparkSession, ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    return to_arrow_schema(_parse_datatype_string(ddl))


#: Values that are hashed at a time, and the odd base of the polynomial hash modulo 2**64.
HASHED, BASE = 1 << 17, 0x9E3779B97F4A7C15


@functools.cache
def _powers(n: int, base: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, modulo 2**64."""
    return tuple(np.cumprod(np.r_[np.uint64(1), np.full(n - 1, b, dtype="uint64")]) for b in (base, pow(base, -1, 1 << 64)))


def run_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: int = BASE) -> np.ndarray:
    """64-bit hashes of values[start:end] for runs in order (ends do not fall): differences of prefix sums."""
    out, at = np.empty(len(starts), dtype="uint64"), 0
    while at < len(starts):
        stop = max(at + 1, int(np.searchsorted(ends, starts[at] + HASHED, side="right")))
        low, high = int(starts[at]), int(ends[stop - 1])
        up, down = _powers(HASHED + 1, base) if high - low <= HASHED else _powers.__wrapped__(high - low + 1, base)
        sums = np.zeros(high - low + 1, dtype="uint64")
        np.cumsum(values[low:high] * up[: high - low], out=sums[1:], dtype="uint64")
        out[at:stop] = (sums[ends[at:stop] - low] - sums[starts[at:stop] - low]) * down[starts[at:stop] - low]
        at = stop
    out = (out ^ out >> np.uint64(29)) * np.uint64(BASE)
    return out ^ out >> np.uint64(32)
