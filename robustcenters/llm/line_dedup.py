"""Line dedup by a fixed-depth tree of line templates.

A line's leaf is its number of tokens and its ``DEPTH`` leading tokens; tokens with digits are masked. Below the leaf the
rest of the line is cut into at most ``FIELDS`` fields (single tokens in short lines, runs of tokens in longer ones).
A template is a leaf, the fields that it leaves open and the values of all other ones; up to 1 - ``SIMILARITY`` of the
fields may be open, the leading tokens not counted, and ``LEAST_CLOSED`` closed ones have an unmasked token. A template recurs if ``LEAST`` documents or
more have a line that matches it in every closed field. A line that matches a recurring template of which another
document with a smaller doc_id has a line is dropped; a template's lines in its first document stay, unless they
match another recurring template that is older still.

Lines over ``LONG`` tokens are cut at anchors, tokens whose hash is the least within ``REACH`` tokens on both sides, so that
a passage inside longer lines is cut alike wherever it stands. The segments are verbatim templates; those that
recur are dropped where neighbours of ``RUN`` tokens together do, and the rest of the line stays. Of a passage at most
the segments at its two ends, in part other text, remain.

Rows of hashes travel, and equal lines are merged before templates are formed, so a line or template that a third
of all documents have is one row there; where its places are joined, frequent keys are broadcast. Texts are shuffled once,
packed, by the join with what is to be dropped.

Defined results: lines with fewer than ``MIN_TOKENS`` unmasked tokens stay; a null text stays null; repeated rows with one
doc_id count as one document; a null doc_id sorts first; an empty table gives no rows; texts of any length are read whole
(a task holds one, and eight bytes for each of its bytes while it is hashed); all columns of docs are kept, whatever
their names.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_schema, checkpoint, chunks, join_hot, run_hashes, written

DEPTH = 3
FIELDS = 8
SIMILARITY = 0.7
MIN_TOKENS = 3
#: Unmasked fields that a template with open fields has at least.
LEAST_CLOSED = 2
#: Documents that have a template before it recurs.
LEAST = 2
LONG, REACH, RUN = 24, 5, 20
#: Units that are sampled to find frequent ones, those with more than a FREQUENT-th of the places.
SAMPLED, FREQUENT = 1_000_000, 2000
#: Bytes of text that are parsed at a time; tokens, hashes and units take about thirty times as much.
PARSED_BYTES = 1 << 20
MASK = np.uint64(0x5851F42D4C957F2D)
#: Base of the second hash.
OTHER = 0xD1342543DE82EF95

UNITS = "row long, doc_id long, unit int, leaf long, whole long, open int, fields array<long>"


class Parsed:
    """The units (lines and segments of long lines) of several texts.

    For each unit: text, number within the text, line within the text, first and last token; ``long`` tells segments.
    Tokens have starts and ends in ``data`` and hashes.
    """

    def __init__(self, bodies: list[bytes | None]):
        bodies = [b or b"" for b in bodies]
        data = np.frombuffer(b"\n".join([*bodies, b""]), dtype="uint8")
        # the text ends with a line feed; before its first byte is nothing
        blank = (data == 32) | (data - np.uint8(9) < 5)
        flips = np.flatnonzero(blank[1:] != blank[:-1]) + 1
        flips = flips if blank[0] else np.r_[0, flips]
        self.data, self.starts, self.ends = data, flips[::2], flips[1::2]
        self.hashes = run_hashes(data, self.starts, self.ends)
        breaks = np.flatnonzero(data == 10)
        line = np.searchsorted(breaks, self.starts)
        lines = np.cumsum([0, *(b.count(b"\n") + 1 for b in bodies)])
        self.bases = np.cumsum([0, *(len(b) + 1 for b in bodies)])
        first = np.flatnonzero(np.diff(line, prepend=-1))
        last = np.r_[first[1:], len(line)]
        cut = np.zeros(len(line) + 1, dtype=bool)
        cut[first] = True
        of_long = np.repeat(last - first > LONG, last - first)
        cut[:-1] |= np.r_[False, self._anchors(line)[:-1]] & of_long if len(line) else False
        at = np.flatnonzero(cut[:-1])
        self.first, self.last = at, np.r_[at[1:], len(line)] if len(at) else at
        self.line = line[at]
        self.long = of_long[at]
        self.text = np.searchsorted(lines, self.line, side="right") - 1
        self.line = self.line - lines[self.text]
        self.unit = np.arange(len(at)) - np.searchsorted(self.text, self.text)

    def _anchors(self, line: np.ndarray) -> np.ndarray:
        """Whether a segment ends with the token."""
        h, found = self.hashes, np.ones(len(line), dtype=bool)
        for d in range(1, REACH + 1):
            same = line[d:] == line[:-d]
            found[d:] &= ~same | (h[d:] < h[:-d])
            found[:-d] &= ~same | (h[:-d] <= h[d:])
        return found

    def keys(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(units, leaf, open fields allowed, fields, list offsets) of the units that are compared."""
        digits = np.flatnonzero(self.data - np.uint8(48) < 10)
        hidden = np.searchsorted(digits, self.starts) < np.searchsorted(digits, self.ends)
        masked = np.r_[0, np.cumsum(hidden)]
        size = self.last - self.first
        unmasked = size - (masked[self.last] - masked[self.first])
        own = np.flatnonzero(self.long | (unmasked >= MIN_TOKENS))
        first, last, long, size = self.first[own], self.last[own], self.long[own], size[own]
        h = np.where(hidden, MASK, self.hashes)
        head = np.minimum(first + DEPTH, last)
        leaf = run_hashes(h, first, np.where(long, first, head), OTHER) ^ size.astype("uint64") * np.uint64(OTHER)
        leaf[long] = run_hashes(self.hashes, first[long], last[long], OTHER)
        rest = np.where(long, 0, last - head)
        count = np.where(long | (rest < 4), 1, np.minimum(rest, FIELDS))
        at = np.r_[0, np.cumsum(count)]
        of = np.repeat(np.arange(len(own)), count)
        k = np.arange(len(of)) - at[of]
        lo, hi = (np.where(long[of], x, head[of] + rest[of] * (k + j) // count[of]) for j, x in ((0, first[of]), (1, last[of])))
        fields = run_hashes(h, lo, hi)
        verbatim = long[of]
        fields[verbatim] = run_hashes(self.hashes, lo[verbatim], hi[verbatim])
        closed = np.add.reduceat((masked[hi] - masked[lo] < hi - lo).astype("int64"), at[:-1]) if len(of) else np.zeros(0, dtype="int64")
        allowed = np.clip(np.floor((1 - SIMILARITY) * count + 1e-9), 0, np.maximum(closed - LEAST_CLOSED, 0))
        return own, leaf, np.where(count > 1, allowed, 0).astype("int32"), fields, at


def unit_keys(docs: DataFrame, row: Column) -> DataFrame:
    """A row for each unit: hashes of its leaf and of all its fields; lines that may have open fields have the list as well."""
    arrow = arrow_schema(docs.sparkSession, UNITS)
    signed = lambda x: pa.array(np.ascontiguousarray(x).view("int64"))

    def run(batches):
        for part in chunks(batches, most=PARSED_BYTES):
            parsed = Parsed(part.column(1).to_pylist())
            own, leaf, allowed, fields, at = parsed.keys()
            text = pa.array(parsed.text[own])
            whole = run_hashes(fields, at[:-1], at[1:])
            size = np.where(allowed > 0, np.diff(at), 0)
            listed = fields[np.repeat(allowed > 0, np.diff(at))]
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)], pa.int32()), signed(listed))
            columns = [part.column(2).take(text), part.column(0).take(text), pa.array(parsed.unit[own], pa.int32()), signed(leaf), signed(whole), pa.array(allowed)]
            yield pa.RecordBatch.from_arrays([*columns, lists.cast(arrow.types[6])], schema=arrow)

    return docs.select(_order().alias("doc_id"), F.col("text").cast("binary").alias("body"), row.alias("row")).mapInArrow(run, UNITS)


def _order() -> Column:
    return F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(1 << 63)))


def _template_keys(lines: DataFrame) -> DataFrame:
    """lines with ``template``, a row for each choice of open fields: a hash of what is closed."""
    masks = F.array().cast("array<int>")
    for size in range(4, FIELDS + 1):
        for most in range(1, int((1 - SIMILARITY) * size + 1e-9) + 1):
            choices = [sum(1 << k for k in kept) for kept in combinations(range(size), size - most)]
            masks = F.when((F.size("fields") == size) & (F.col("open") == most), F.lit(choices)).otherwise(masks)
    closed = F.filter("fields", lambda _, i: F.getbit("mask", i) == 1)
    return lines.withColumn("mask", F.explode(masks)).withColumn("template", F.xxhash64("mask", closed)).drop("mask")


def recurring_units(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """(doc_id, row, unit): what is to be dropped; row is a hash of the text."""
    units = written(unit_keys(docs, F.xxhash64("text")))
    # equal lines are one row; the leaf of a line tells how many of its fields may be open
    lines = units.where("open > 0")
    line, key = ["leaf", "whole"], ["leaf", "template"]
    several = checkpoint(lines.groupBy(*line, "open", "fields").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), F.count("*").alias("n")))
    leaves = checkpoint(several.groupBy("leaf").agg(F.min("a").alias("a"), F.max("b").alias("b"), F.count("*").alias("lines")).where("a < b").select("leaf", "lines"))
    keyed = checkpoint(_template_keys(join_hot(several, leaves, ["leaf"], "lines")).select(*line, "n", "a", "b", "template"))
    templates = keyed.groupBy(*key).agg(F.min("a").alias("first"), F.max("b").alias("last"), F.count("*").alias("lines")).where("first < last")
    matched = join_hot(keyed, checkpoint(templates.select(*key, "first", "lines")), key, "lines").select(*line, "template", "first", "n")
    if least > 2:
        matched = _reached(lines, matched, least)
    found = checkpoint(matched.groupBy(*line).agg(F.min("first").alias("first"), F.max("n").alias("n")))
    place = ["doc_id", "row", "unit"]
    alike = join_hot(lines.select(*place, *line), found, line, "n").where("first < doc_id").select(*place)
    return alike.unionByName(_copies(units.where("open = 0").select(*place, *line), line, least).select(*place))


def _copies(units: DataFrame, key: list[str], least: int) -> DataFrame:
    """Units that equal one of an earlier document, if ``least`` documents have it.

    Frequent keys, as a bounded sample tells, are aggregated in parts and their first documents broadcast; the units of
    all others meet once, by key. Which keys the sample takes for frequent changes the work's layout and never the result.
    """
    every = max(1, units.count() // SAMPLED)
    sample = units.where(F.pmod(F.xxhash64("doc_id", "row", "unit"), F.lit(every)) == 0).groupBy(*key).agg(F.count("*").alias("n"))
    hot = checkpoint(sample.where(F.col("n") * FREQUENT > SAMPLED).select(*key))
    often = units.join(F.broadcast(hot), key)
    known = often.groupBy(*key, "doc_id").agg(F.lit(1).alias("one")) if least > 2 else often.withColumn("one", F.lit(least))
    known = known.groupBy(*key).agg(F.min("doc_id").alias("first"), F.sum("one").alias("documents")).where(F.col("documents") >= least)
    often = often.join(F.broadcast(known.select(*key, "first")), key)
    rest = units.join(F.broadcast(hot), key, "left_anti")
    if least > 2:
        rest = rest.withColumn("nth", F.dense_rank().over(Window.partitionBy(*key).orderBy("doc_id")))
        rest = rest.withColumn("documents", F.max("nth").over(Window.partitionBy(*key))).where(F.col("documents") >= least)
    rest = rest.withColumn("first", F.min("doc_id").over(Window.partitionBy(*key)))
    return often.unionByName(rest.select(*often.columns)).where("first < doc_id")


def _reached(units: DataFrame, matched: DataFrame, least: int) -> DataFrame:
    """Rows of matched whose template has lines of at least ``least`` documents."""
    matched = checkpoint(matched)
    lines = checkpoint(matched.groupBy("leaf", "whole").agg(F.max("n").alias("n"), F.collect_set("template").alias("templates")))
    documents = join_hot(units.select("doc_id", "leaf", "whole"), lines, ["leaf", "whole"], "n").select("doc_id", "leaf", F.explode("templates").alias("template"))
    reached = documents.distinct().groupBy("leaf", "template").agg(F.count("*").alias("documents")).where(F.col("documents") >= least)
    return matched.join(reached.select("leaf", "template"), ["leaf", "template"], "left_semi")


def without(bodies: list[bytes], gone: list) -> tuple[list[bytes], list[int]]:
    """The texts without their units, whole lines and runs of segments of at least RUN tokens; and how many units went."""
    parsed = Parsed(bodies)
    drop = np.zeros(len(parsed.text), dtype=bool)
    for base, units in zip(np.searchsorted(parsed.text, np.arange(len(bodies))).tolist(), gone):
        drop[base + np.asarray(units, dtype="int64")] = True
    heads = np.flatnonzero(np.diff(parsed.text * 2 + drop, prepend=-1).astype(bool) | (np.diff(parsed.line, prepend=-1) != 0))
    tails = np.r_[heads[1:], len(drop)]
    size = np.r_[0, np.cumsum(parsed.last - parsed.first)]
    cut = drop[heads] & (~parsed.long[heads] | (size[tails] - size[heads] >= RUN)) if len(heads) else np.zeros(0, dtype=bool)
    heads, tails = heads[cut], tails[cut]
    went = np.bincount(parsed.text[heads], weights=tails - heads, minlength=len(bodies)).astype("int64").tolist()
    cuts: dict[tuple[int, int], list[tuple[int, int]]] = {}
    spans = zip(parsed.text[heads].tolist(), parsed.line[heads].tolist(), parsed.starts[parsed.first[heads]].tolist(), parsed.ends[parsed.last[tails - 1] - 1].tolist())
    for text, line, lo, hi in spans:
        cuts.setdefault((text, line), []).append((lo - int(parsed.bases[text]), hi - int(parsed.bases[text])))
    out = []
    for text, body in enumerate(bodies):
        lines, base = [], 0
        for k, line in enumerate(body.split(b"\n")):
            found = cuts.get((text, k))
            if found is None:
                lines.append(line)
            else:
                kept, at = [], base
                for lo, hi in found:
                    kept.append(body[at:lo].strip())
                    at = hi
                kept.append(body[at : base + len(line)].strip())
                left = b" ".join(x for x in kept if x)
                if left:
                    lines.append(left)
            base += len(line) + 1
        out.append(b"\n".join(lines))
    return out, went


def drop_recurring_lines(docs: DataFrame, least: int = LEAST, report: bool = False) -> DataFrame:
    """docs with the recurring lines and segments taken out of text (and n_chars renewed, where there is one).

    With report: doc_id, text, n_lines (of the text as it was), n_dropped (lines and segments), chars_dropped.
    """
    gone = recurring_units(docs, least).groupBy("doc_id", "row").agg(F.collect_set("unit").alias("gone"))

    @F.arrow_udf("binary")
    def packed(body: pa.Array) -> pa.Array:
        from zstandard import ZstdCompressor

        pack = ZstdCompressor(level=1).compress
        return pa.array([None if b is None else pack(b) for b in body.to_pylist()], pa.binary())

    @F.arrow_udf("kept string, went long")
    def clean(body: pa.Array, units: pa.Array) -> pa.Array:
        from zstandard import ZstdDecompressor

        unpack = ZstdDecompressor().decompress
        texts = [None if b is None else unpack(b) for b in body.to_pylist()]
        units, went = units.to_pylist(), [0] * len(texts)
        rows = [i for i, (t, u) in enumerate(zip(texts, units)) if t is not None and u is not None]
        at = 0
        while at < len(rows):
            end, size = at, 0
            while end < len(rows) and (end == at or size + len(texts[rows[end]]) <= PARSED_BYTES):
                size += len(texts[rows[end]])
                end += 1
            for i, text, n in zip(rows[at:end], *without([texts[i] for i in rows[at:end]], [units[i] for i in rows[at:end]])):
                texts[i], went[i] = text, n
            at = end
        return pa.StructArray.from_arrays([pa.array(texts, pa.binary()).cast(pa.string()), pa.array(went, pa.int64())], ["kept", "went"])

    # texts are packed before they are shuffled, which more than halves what the join writes
    text = F.col("text")
    others = [F.struct(*[c for c in docs.columns if c != "text"]).alias("others"), _order().alias("doc_id"), F.xxhash64("text").alias("row")]
    sizes = [F.length("text").alias("chars"), (F.length(text) - F.length(F.replace(text, F.lit("\n"), F.lit(""))) + 1).alias("n_lines")]
    held = docs.select(*others, *(sizes if report else []), packed(text.cast("binary")).alias("body")).join(gone.hint("shuffle_hash"), ["doc_id", "row"], "left")
    held = held.withColumn("done", clean("body", "gone")).select("*", "done.kept", "done.went")
    if report:
        return held.select(F.col("others.doc_id").alias("doc_id"), F.col("kept").alias("text"), "n_lines", F.col("went").alias("n_dropped"), (F.col("chars") - F.length("kept")).alias("chars_dropped"))
    column = {"text": F.col("kept")} | {c: F.length("kept").cast(docs.schema[c].dataType) for c in docs.columns if c == "n_chars"}
    return held.select(*[column.get(c, F.col(f"others.`{c}`")).alias(c) for c in docs.columns])
