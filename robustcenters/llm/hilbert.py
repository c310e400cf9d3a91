"""Sharding along a Hilbert curve.

Several metadata dimensions are quantised to a few bits each, a Hilbert curve runs through their grid, rows are
sorted by the curve index and the order is cut into shards, so that each shard covers few cells in every
dimension and files can be pruned by all of them. Ranks come from a range sort with a count for each
partition; no row is gathered.

Dimensions are the columns source, lang and n_chars and the size of the text; a column that docs lacks counts as null.

Defined results: null metadata take cell 0 of their dimension; a null text has no bytes and the checksum of the empty
string; texts of any length are read whole in the JVM; ties of the curve are broken by doc_id, size and checksum; repeated rows get slots of their own; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpoint

BITS = 6
SHARDS = 24


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """Curve index of integer cells, shape (n, d), with d * bits up to 62.

    Published transposed form: undo the excess rotations from the highest bit down, Gray-encode, then interleave.
    """
    x = [c.astype("uint64") for c in np.asarray(cells).T]
    d = len(x)
    one = np.uint64(1)
    for level in range(bits - 1, 0, -1):
        q = one << np.uint64(level)
        low = q - one
        for axis in x:
            on = (axis & q) != 0
            swap = np.where(on, np.uint64(0), (x[0] ^ axis) & low)
            flipped = np.where(on, low, np.uint64(0))
            if axis is x[0]:
                x[0] ^= flipped
            else:
                x[0] ^= flipped | swap
                axis ^= swap
    for k in range(1, d):
        x[k] ^= x[k - 1]
    turn = np.zeros_like(x[0])
    for level in range(bits - 1, 0, -1):
        q = one << np.uint64(level)
        turn ^= np.where((x[-1] & q) != 0, q - one, np.uint64(0))
    index = np.zeros_like(x[0])
    for level in range(bits - 1, -1, -1):
        for axis in x:
            index = (index << one) | (((axis ^ turn) >> np.uint64(level)) & one)
    return index.astype("int64")


def curve(*cells: Column, bits: int = BITS) -> Column:
    """The curve index of integer columns, as a column."""

    @F.pandas_udf("long")
    def of(cell):
        import pandas as pd

        return pd.Series(hilbert_index(cell.fillna(0).to_numpy("int64"), bits))

    return of(F.struct(*[c.cast("bigint").alias(f"d{k}") for k, c in enumerate(cells)]))


def by_hash(column: Column, bits: int = BITS) -> Column:
    """A cell for a category: equal values share it; null is cell 0."""
    return F.when(column.isNull(), 0).otherwise(F.pmod(F.xxhash64(column), F.lit(1 << bits)))


def by_log(column: Column, bits: int = BITS) -> Column:
    """A cell for a magnitude: thirds of an octave, capped at the last cell, which changes only the order's locality."""
    return F.coalesce(F.least(F.floor(F.log2(F.greatest(column.cast("double"), F.lit(0.0)) + 1) * 3), F.lit((1 << bits) - 1)), F.lit(0))


def global_rank(rows: DataFrame, order: list[str], partitions: int) -> tuple[DataFrame, int]:
    """rows with ``rank`` from 0 in the order, and their number: range partitions, sorted, each offset by the rows before it."""
    mark = F.monotonically_increasing_id()
    sorted_rows = checkpoint(rows.repartitionByRange(partitions, *order).sortWithinPartitions(*order).withColumn("_mark", mark))
    at = F.shiftright("_mark", 33).cast("int")
    sizes = {r[0]: r[1] for r in sorted_rows.groupBy(at.alias("p")).count().collect()}  # a row for each partition
    bases, total = [], 0
    for p in sorted(sizes):
        bases.append((p, total))
        total += sizes[p]
    table = F.broadcast(rows.sparkSession.createDataFrame(bases, "_at int, _base long"))  # as many rows as partitions
    ranked = sorted_rows.withColumn("_at", at).join(table, "_at")
    return ranked.withColumn("rank", F.col("_base") + F.col("_mark").bitwiseAND(F.lit((1 << 33) - 1))).select(*rows.columns, "rank"), total


def shard_documents(docs: DataFrame, shards: int = SHARDS, bits: int = BITS) -> DataFrame:
    """doc_id, size, text_crc32, law 'rows', shard, slot, grown_shard, hilbert_index: counts at most one apart."""
    body = F.coalesce(F.col("text").cast("binary"), F.lit(b""))
    size = (F.octet_length(body) + 8).cast("bigint")
    column = lambda name: F.col(name) if name in docs.columns else F.lit(None).cast("string")
    rows = docs.select(
        F.col("doc_id").cast("bigint").alias("doc_id"),
        size.alias("size"),
        F.crc32(body).alias("text_crc32"),
        curve(by_hash(column("source"), bits), by_hash(column("lang"), bits), by_log(size, bits), by_log(column("n_chars"), bits), bits=bits).alias("hilbert_index"),
    )
    counted = docs.sparkSession.conf.get("spark.sql.shuffle.partitions")
    ranked, total = global_rank(rows, ["hilbert_index", "doc_id", "size", "text_crc32"], max(int(counted), 1))
    each, more = divmod(total, shards)
    edge = more * (each + 1)
    rank = F.col("rank")
    early = rank < edge
    shard = F.when(early, F.floor(rank / (each + 1))).otherwise(more + F.floor((rank - edge) / max(each, 1))).cast("int")
    first = F.when(early, F.col("shard") * (each + 1)).otherwise(edge + (F.col("shard") - more) * each)
    return (
        ranked.withColumn("shard", shard)
        .withColumn("slot", (rank - first).cast("bigint"))
        .select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "hilbert_index")
    )
