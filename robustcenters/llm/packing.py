"""Best-fit packing planned on a histogram of lengths.

1. Each document is tokenised once, cut into pieces where it is longer than a sequence, and reduced to a
   digest of a few numbers; nothing but these narrow rows is ever shuffled.
2. The number of pieces of each length (at most ``capacity`` numbers, so a bounded driver table) goes through
   best-fit decreasing: whole runs of equally filled sequences are treated as one, so the plan's size depends
   on the capacity and never on the number of documents.
3. A piece's rank within its length comes from counts of (length, bucket) and the rank within the bucket;
   rank and length pick the planned slot. Every number is 64 bits wide.

Defined results: null text is empty and packs as the single end id; repeated rows are packed each; an empty
table gives no rows; other columns are not read. Ties of rank are broken by (bucket, doc_id, piece). Texts of any
length are tokenised whole, runs of white space of any length included; a task holds one long text and its ids.
"""

from __future__ import annotations

import functools
import json
import re
import zlib
from bisect import insort

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_schema, checkpoint, chunks, text_bytes

CAPACITY = 2048
END_ID = 0
#: Words kept with their ids in each Python worker.
CACHE_WORDS = 100_000
#: Special string of the tokenizer file, with its id (fixed values).
SPECIAL, SPECIAL_ID = "<|endoftext|>", 50256

#: A blank before a non-blank starts a pre-token whatever stands before it, so words between such blanks can be
#: tokenised alone. A blank before white space or at the end needs the whole text.
UNSAFE = re.compile(r" (?:\s|$)")
#: Runs of white space that a backtracking pattern may give up on; only texts over LONG_TEXT characters are searched for them.
LONG_RUN, LONG_TEXT = re.compile(r"\s{200}"), 20_000


@functools.cache
def _encoder(path: str):
    """Made once in a Python worker, as its tables take longer to make than most tasks."""
    import public_tokenizers
    import tiktoken

    return tiktoken.Encoding("words", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_ranks(path), special_tokens={}).encode_ordinary


@functools.cache
def _library(path: str):
    """Made once in a Python worker that meets a text for it."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def byte_ranks(path: str) -> dict[bytes, int]:
    """Token bytes and ids of a byte-level BPE file, whose ids are the order of its merges."""
    with open(path, encoding="utf-8") as file:
        vocabulary = json.load(file)["model"]["vocab"]
    # the file writes each byte as a character: printable ones as themselves, the rest from 256 on
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    other = [b for b in range(256) if b not in plain]
    byte_of = {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(other)}
    return {bytes(byte_of[c] for c in token): rank for token, rank in vocabulary.items() if token != SPECIAL}


class WordTokenizer:
    """Ids of the byte-level BPE tokenizer file as little-endian uint32 bytes, with a cache of words.

    Words come from the file's ranks; texts whose white space binds words together go whole through the ``tokenizers``
    library, which has no limit on the length of a run.
    """

    def __init__(self, path: str | None = None):
        import public_tokenizers

        self.path = path or public_tokenizers.path("byte_bpe_50k.json")
        self.encode = _encoder(self.path)
        self.cache: dict[str, bytes] = {}

    def _raw(self, text: str) -> bytes:
        return np.array(self.encode(text), dtype="<u4").tobytes()

    def _word(self, word: str) -> bytes:
        got = self._raw(" " + word)
        if len(word) < 40:
            if len(self.cache) >= CACHE_WORDS:
                self.cache.clear()
            self.cache[word] = got
        return got

    def ids(self, text: str) -> bytes:
        if UNSAFE.search(text) or len(text) > LONG_TEXT and LONG_RUN.search(text):
            return np.array(_library(self.path).encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        if SPECIAL in text:
            return np.array([SPECIAL_ID], dtype="<u4").tobytes().join(self.ids(x) for x in text.split(SPECIAL))
        if not text:
            return b""
        first, *rest = text.split(" ")
        get, word = self.cache.get, self._word
        return (self._raw(first) if first else b"") + b"".join([get(w) or word(w) for w in rest])


PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces(docs: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The digest of every piece; a document over ``capacity`` ids is cut so that only its first piece is short."""
    arrow = arrow_schema(docs.sparkSession, PIECE_SCHEMA)
    end = np.array([END_ID], dtype="<u4").tobytes()

    def run(batches):
        tokenizer = WordTokenizer()
        for part in chunks(batches):
            out = [], [], [], [], []
            for doc, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                ids = tokenizer.ids(body.decode("utf-8", "replace") if body else "") + end
                n = len(ids) // 4
                start = 0
                for piece in range(-(-n // capacity)):
                    length = capacity if n <= capacity or piece or not n % capacity else n % capacity
                    length = min(length, n - start)
                    for column, value in zip(out, (doc, piece, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]))):
                        column.append(value)
                    start += length
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, arrow.types)], schema=arrow)

    return text_bytes(docs, id_col, text_col).mapInArrow(run, PIECE_SCHEMA)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """Best-fit decreasing over counts: rows (length, first rank, count, first sequence, offset).

    The pieces of ``length`` with ranks first..first+count-1 go to consecutive sequences at ``offset``. Runs of
    sequences with the same room stay together, so the number of rows is bounded by the capacity alone.
    """
    slots: list[tuple[int, int, int, int, int]] = []
    runs: dict[int, list[tuple[int, int]]] = {}
    rooms: list[int] = []
    opened = 0

    def put(room: int, first: int, count: int) -> None:
        if room and count:
            if room not in runs:
                insort(rooms, room)
                runs[room] = []
            runs[room].append((first, count))

    from bisect import bisect_left

    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        while left:
            at = bisect_left(rooms, length)
            if at < len(rooms):
                room = rooms[at]
                first, count = runs[room].pop()
                if not runs[room]:
                    del runs[room], rooms[at]
            else:
                room, first, count = capacity, opened, -(-left // (capacity // length))
                opened += count
            take = min(left, count)
            slots.append((length, rank, take, first, capacity - room))
            put(room, first + take, count - take)
            put(room - length, first, take)
            rank, left = rank + take, left - take
    return slots


def pack(digests: DataFrame, capacity: int = CAPACITY, bucket_rows: int = 1000, most_buckets: int = 1_000_000) -> DataFrame:
    """Give every piece (any columns beside doc_id, piece, length) its sequence_id and offset."""
    spark = digests.sparkSession
    kept = checkpoint(digests.withColumn("_mark", F.monotonically_increasing_id()))
    total = kept.count()
    buckets = min(most_buckets, max(1, -(-total // bucket_rows)))  # a length has so many rows in the table of counts
    # repeated rows share doc_id and piece, so the mark spreads them
    kept = kept.withColumn("_bucket", F.pmod(F.xxhash64("_mark"), F.lit(buckets)).cast("int"))
    # per length, counts of buckets: at most capacity rows for each bucket
    counts = kept.groupBy("length", "_bucket").agg(F.count("*").alias("_n"))
    before = Window.partitionBy("length").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0))).select("length", "_bucket", "_base")
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("_n").alias("n")).collect()}
    slots = plan(histogram, capacity)
    within = Window.partitionBy("length", "_bucket").orderBy("doc_id", "piece")
    ranked = kept.withColumn("_at", F.row_number().over(within) - 1).join(bases, ["length", "_bucket"])
    table = np.array(sorted(slots), dtype="int64").reshape(-1, 5)
    shared = spark.sparkContext.broadcast(table)  # bounded by the capacity, see plan()

    @F.pandas_udf("sequence_id long, offset long")
    def slot(length, rank):
        import pandas as pd

        t = shared.value
        key = (t[:, 0] << 44) + t[:, 1]
        at = np.searchsorted(key, (length.to_numpy("int64") << 44) + rank.to_numpy("int64"), side="right") - 1
        return pd.DataFrame({"sequence_id": t[at, 3] + rank.to_numpy("int64") - t[at, 1], "offset": t[at, 4]})

    placed = ranked.withColumn("_slot", slot("length", F.col("_base") + F.col("_at")))
    return placed.select(*[c for c in digests.columns], "_slot.sequence_id", "_slot.offset")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: all documents in as few sequences as best fit finds."""
    return pack(pieces(docs, capacity, id_col, text_col), capacity)
