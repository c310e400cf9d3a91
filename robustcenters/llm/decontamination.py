"""Benchmark decontamination by latent semantic retrieval.

1. Every text becomes a row of hashed terms, written once; their document frequencies are one bounded table.
2. Randomised SVD of the TF-IDF matrix of passages: rows are all passages of the benchmark and of all documents;
   every power step multiplies by the whole matrix in the cluster and adds up bounded blocks.
3. Every passage of every document (32 words, every 16) is projected and compared with all benchmark passages by
   cosine, in units of what the projection keeps of the benchmark passage, so that a copy has 1 whatever the rank; a
   passage over ``CANDIDATE`` is a candidate. Items shorter than a passage have a threshold lower by the root of their
   share of it, which is what a copy between other words keeps. Independent of the projection, every passage that has
   ``RUN`` words in a row of an item is a candidate for it, so no copy depends on what the rank keeps.
4. A candidate counts if the longest common subsequence of words covers ``SURE`` of the item, or ``LIKELY`` of it with
   the item's answer (its last sentence) present; an answer of common words alone, in ``COMMON`` of the items, proves nothing. Before that, candidates with fewer than ``LIKELY`` of the item's
   words in any order are left, as no subsequence of theirs can be longer.

Benchmarks above ``ITEMS`` rows or ``ITEM_BYTES`` are searched in blocks, so what is sent out stays bounded.

Defined results: null or empty texts and items match nothing; items of fewer than ``MIN_ITEM_WORDS`` words must occur
word for word; texts are read whole; repeated rows are searched each, repeated items (same id) reported once; empty tables give no
rows; other columns are ignored.
"""

from __future__ import annotations

import functools
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import add_blocks, arrow_schema, checkpoint, chunks, text_bytes, written

TERMS = 1 << 14
RANK, OVERSAMPLE, POWER_STEPS = 96, 8, 2
#: A task of a product sends a whole table, so there is one for each core, or one for so many texts, these many at least and at most.
SVD_TASKS, SVD_TEXTS, SVD_MOST = 4, 200_000, 256
#: Each benchmark passage counts as so many rows of the matrix for so many passages of documents; at least this share of its square is taken as kept.
ITEM_ROWS, CORPUS_ROWS, LEAST_KEPT = 64, 24_000, 0.1
HALF = 16
#: Bytes of terms that a product looks at together.
TERM_BYTES = 1 << 20
CANDIDATE, SURE, LIKELY, ANSWER, COMMON = 0.45, 0.66, 0.5, 0.8, 0.1
ITEMS, ITEM_BYTES, MIN_ITEM_WORDS = 20_000, 32 << 20, 6
#: Words in a row that make a candidate by themselves; their terms fit in one key.
RUN = 3
#: Bytes that no word has; white space and capitals as words are compared.
MARKS = b".,;:!?\"'()[]"
PLAIN = bytes(32 if b in b"\t\n\v\f\r" else b for b in bytes(range(256)).lower())
#: Bytes that are hashed at a time, and the odd base of the words' polynomial hash modulo 2**64.
HASHED, BASE = 1 << 17, 0x9E3779B97F4A7C15
#: Rows of the projected table that are gathered at a time; cells of a block of cosines or of candidates' words.
SLICE, CELLS = 1 << 14, 1 << 20
#: Pieces of runs of rows that are added up at a time.
PIECES = 1 << 11


def words_of(body: bytes | None) -> list[bytes]:
    """Words in lower case without marks."""
    return (body or b"").translate(PLAIN, MARKS).split()


@functools.cache
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of BASE and of its inverse, modulo 2**64."""
    return tuple(np.cumprod(np.r_[np.uint64(1), np.full(n - 1, b, dtype="uint64")]) for b in (BASE, pow(BASE, -1, 1 << 64)))


def terms_of(bodies: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Term buckets of the words of all texts, text after text, and how many each text has.

    The hash of a word is a difference of prefix sums, so no word becomes a Python object.
    """
    plain = [(b or b"").translate(PLAIN, MARKS) for b in bodies]
    whole = b" ".join([b"", *plain, b""])
    bounds = np.cumsum([1, *[len(b) + 1 for b in plain]])
    data = np.frombuffer(whole, dtype="uint8")
    flips = np.flatnonzero(np.diff(data == 32)) + 1
    starts, ends = flips[::2], flips[1::2]
    out, at = np.empty(len(starts), dtype="int64"), 0
    while at < len(starts):
        stop = max(at + 1, int(np.searchsorted(ends, starts[at] + HASHED, side="right")))
        low, high = starts[at], ends[stop - 1]
        up, down = _powers(HASHED) if high - low <= HASHED else _powers.__wrapped__(high - low)
        sums = np.zeros(high - low + 1, dtype="uint64")
        np.cumsum(data[low:high] * up[: high - low], out=sums[1:])
        value = (sums[ends[at:stop] - low] - sums[starts[at:stop] - low]) * down[starts[at:stop] - low]
        out[at:stop] = ((value ^ value >> np.uint64(29)) * np.uint64(BASE)) >> np.uint64(64 - TERMS.bit_length() + 1)
        at = stop
    return out, np.diff(np.searchsorted(starts, bounds))


def term_rows(texts: DataFrame) -> DataFrame:
    """(terms binary): the term buckets of every text, two bytes each."""
    schema = "terms binary"
    arrow = arrow_schema(texts.sparkSession, schema)

    def run(batches):
        for part in chunks(batches):
            flat, lengths = terms_of(part.column(1).to_pylist())
            ends = 2 * np.cumsum(lengths)
            data = flat.astype("uint16").tobytes()
            yield pa.RecordBatch.from_arrays([pa.array([data[e - 2 * n : e] for e, n in zip(ends.tolist(), lengths.tolist())], pa.binary())], schema=arrow)

    return texts.mapInArrow(run, schema)


def _terms(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all rows of a piece of term_rows(), row after row, and how many each row has."""
    rows = part.column(part.schema.get_field_index("terms"))
    lengths = pa.compute.binary_length(rows).to_numpy(zero_copy_only=False).astype("int64") // 2
    return np.frombuffer(b"".join(rows.to_pylist()), dtype="uint16"), lengths


def passage_counts(lengths: np.ndarray) -> np.ndarray:
    """How many passages texts of so many words have."""
    return np.where(lengths > 0, np.maximum(1, -(-lengths // HALF) - 1), 0)


def document_frequencies(rows: DataFrame) -> tuple[np.ndarray, int, int]:
    """How many texts of term_rows() have each term, how many texts and how many passages there are."""
    schema = "block int, counts binary, n long, passages long"
    arrow = arrow_schema(rows.sparkSession, schema)
    blocks = 64

    def run(batches):
        total, n, passages = np.zeros(TERMS, dtype="int64"), 0, 0
        for part in chunks(batches, "terms", TERM_BYTES):
            flat, lengths = _terms(part)
            n, passages = n + len(lengths), passages + int(passage_counts(lengths).sum())
            for own in np.split(flat, np.cumsum(lengths)[:-1]):
                total[own] += 1  # a bucket that occurs twice counts once
        yield pa.RecordBatch.from_arrays([pa.array(range(blocks), pa.int32()), pa.array([x.tobytes() for x in np.split(total, blocks)]), pa.array([n] * blocks, pa.int64()), pa.array([passages] * blocks, pa.int64())], schema=arrow)

    def add(table):
        total = sum(np.frombuffer(x, dtype="int64") for x in table.column("counts").to_pylist())
        sums = {c: [sum(table.column(c).to_pylist())] for c in ("n", "passages")}
        return pa.Table.from_pydict({"block": [table.column("block")[0].as_py()], "counts": [total.tobytes()]} | sums, schema=arrow)

    found = add_blocks(rows.mapInArrow(run, schema), schema, add)
    if not found:
        return np.zeros(TERMS), 0, 0
    return np.concatenate([np.frombuffer(bytes(r["counts"]), dtype="int64") for r in found]).astype("float64"), found[0]["n"], found[0]["passages"]


def gram_product(terms: np.ndarray, lengths: np.ndarray, table: np.ndarray, weight: np.ndarray, out: np.ndarray, times: float = 1.0) -> None:
    """Add A'A times a table to out, for the rows A of all passages of the texts: idf-weighted terms, to unit length.

    table: the idf-weighted table and the square of the idf as last column. Words are added up by halves of passages,
    which two passages share, so every word is looked up once to project it and once to project back.
    """
    half, counts = half_passages(terms, lengths, table)
    doc = np.repeat(np.arange(len(lengths)), counts)
    follows = doc[1:] == doc[:-1]  # half i + 1 is in a passage with half i
    both = half[:-1] + half[1:]
    both = both[:, :-1] * (follows / np.maximum(both[:, -1], 1e-12))[:, None].astype("float32")
    back = np.zeros((len(half), table.shape[1] - 1), dtype="float32")
    back[:-1] += both
    back[1:] += both
    alone = np.cumsum(counts)[counts == 1] - 1
    back[alone] = half[alone, :-1] / np.maximum(half[alone, -1:], 1e-12)
    # the halves of the words of each term
    order = np.argsort(terms, kind="stable")
    place = np.repeat(np.arange(len(half)), half_sizes(lengths)[0])[order]
    sizes = np.bincount(terms, minlength=TERMS)
    found = np.flatnonzero(sizes)
    out[found] += row_sums(back, place, sizes[found]) * (times * weight[found])[:, None]


def right_vectors(rows: DataFrame, idf: np.ndarray, rank: int = RANK, steps: int = POWER_STEPS, seed: int = 42, tasks: int = SVD_TASKS) -> tuple[np.ndarray, np.ndarray]:
    """(TERMS, rank) right singular vectors and singular values of the TF-IDF matrix of all passages, rows of unit length.

    rows: (terms binary, times double), a text each; its passages count as so many. Every step reads all rows; only
    (TERMS, rank + oversample) tables travel, in blocks.
    """
    spark = rows.sparkSession
    width, blocks = rank + OVERSAMPLE, 64
    schema = "block int, part binary"
    arrow = arrow_schema(spark, schema)

    weight = idf.astype("float32")

    def multiply(table: np.ndarray | None) -> np.ndarray:
        """A'A times the table; without one, times a random table that every task draws from the seed."""
        shared = None if table is None else spark.sparkContext.broadcast(table.astype("float16"))

        def run(batches):
            out = None
            for part in chunks(batches, "terms", TERM_BYTES):
                if out is None:
                    q = np.random.default_rng(seed).normal(size=(TERMS, width)) if shared is None else shared.value
                    table = np.c_[q.astype("float32") * weight[:, None], weight * weight]
                    out = np.zeros((TERMS, width), dtype="float32")
                times = part.column(part.schema.get_field_index("times")).to_numpy()
                for k in np.unique(times).tolist():
                    gram_product(*_terms(part.filter(pa.array(times == k))), table, weight, out, k)
            if out is not None:
                yield pa.RecordBatch.from_arrays([pa.array(range(blocks), pa.int32()), pa.array([x.tobytes() for x in np.split(out, blocks)])], schema=arrow)

        def add(t):
            total = sum(np.frombuffer(x, dtype="float32").astype("float64") for x in t.column("part").to_pylist())
            return pa.Table.from_pydict({"block": [t.column("block")[0].as_py()], "part": [total.astype("float32").tobytes()]}, schema=arrow)

        found = add_blocks(rows.mapInArrow(run, schema), schema, add)
        if shared is not None:
            shared.destroy()
        return np.concatenate([np.frombuffer(bytes(r["part"]), dtype="float32").reshape(-1, width) for r in found]) if found else np.zeros((TERMS, width))

    rows = rows.coalesce(tasks)
    q, _ = np.linalg.qr(multiply(None))
    for _ in range(steps - 1):
        q, _ = np.linalg.qr(multiply(q))
    squares, turn = np.linalg.eigh(q.T @ multiply(q))
    order = np.argsort(squares)[::-1][:rank]
    return q @ turn[:, order], np.sqrt(np.maximum(squares[order], 0))


def runs_of(terms: np.ndarray) -> np.ndarray:
    """Keys of the runs of RUN terms that begin at each place but the last ones."""
    bits, n = TERMS.bit_length() - 1, max(0, len(terms) - RUN + 1)
    key = np.zeros(n, dtype="int64")
    for k in range(RUN):
        key = key << bits | terms[k : k + n]
    return key


def row_sums(table: np.ndarray, index: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of the rows table[index] of runs of ``sizes`` (none empty), one run after the other.

    Runs are cut into pieces of HALF rows at most; the k-th rows of many pieces are added at a time, and sums of pieces likewise.
    """
    pieces = -(-sizes // HALF)
    run = np.repeat(np.arange(len(sizes)), pieces)
    nth = np.arange(len(run)) - (np.cumsum(pieces) - pieces)[run]
    start, size = (np.cumsum(sizes) - sizes)[run] + HALF * nth, np.minimum(HALF, sizes[run] - HALF * nth)
    order = np.argsort(-size.astype("int8"), kind="stable")
    out = np.empty((len(start), table.shape[1]), dtype="float32")
    sums, found = np.empty((2, min(PIECES, len(start)), table.shape[1]), dtype="float32")
    for lo in range(0, len(order), PIECES):
        own = order[lo : lo + PIECES]
        first, longer = start[own], np.searchsorted(-size[own], -np.arange(int(size[own[0]])))
        np.take(table, index[first], axis=0, out=sums[: len(own)], mode="clip")
        for k, n in enumerate(longer.tolist()[1:], 1):
            np.take(table, index[first[:n] + k], axis=0, out=found[:n], mode="clip")
            sums[:n] += found[:n]
        out[own] = sums[: len(own)]
    return out if len(out) == len(sizes) else row_sums(out, np.arange(len(out)), pieces)


def half_sizes(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words of every half passage of HALF words (fewer at the end of a text), and how many each text has."""
    halves = -(-lengths // HALF)
    sizes = np.full(int(halves.sum()), HALF)
    some = lengths > 0
    sizes[np.cumsum(halves)[some] - 1] = (lengths - HALF * (halves - 1))[some]
    return sizes, halves


def half_passages(terms: np.ndarray, lengths: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Projected sums of HALF words, document after document, and how many each document has."""
    sizes, halves = half_sizes(lengths)
    return row_sums(table, terms, sizes), halves


def passage_vectors(terms: np.ndarray, lengths: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Projections of passages of two halves, over their length before projection; (vectors, document index, first half index)."""
    half, counts = half_passages(terms, lengths, table)
    doc = np.repeat(np.arange(len(lengths)), counts)
    base = np.r_[0, np.cumsum(counts)[:-1]] if len(counts) else np.zeros(0, dtype="int64")
    index = np.arange(len(half)) - base[doc] if len(half) else np.zeros(0, dtype="int64")
    last = index == counts[doc] - 1 if len(half) else np.zeros(0, dtype=bool)
    both = half.copy()
    both[:-1][~last[:-1]] += half[1:][~last[:-1]]
    keep = ~last | (counts[doc] == 1)
    both, doc, index = both[keep], doc[keep], index[keep]
    return both[:, :-1] / np.sqrt(np.maximum(both[:, -1:], 1e-9)), doc, index


def common_subsequence(item: list[bytes], region: list[bytes]) -> int:
    """Length of the longest common subsequence of words, 1 bit an item word."""
    places: dict[bytes, int] = {}
    for k, w in enumerate(item):
        places[w] = places.get(w, 0) | 1 << k
    full = (1 << len(item)) - 1
    row = full
    for w in region:
        match = row & places.get(w, 0)
        row = ((row + match) | (row - match)) & full
    return len(item) - row.bit_count()


def answer_of(text: bytes) -> list[bytes]:
    """The last sentence with at least three words, else the last words."""
    for part in reversed(re.split(rb"(?<=[.!?])\s+", text.strip())):
        found = [w for w in words_of(part) if w]
        if len(found) >= 3:
            return found
    return [w for w in words_of(text) if w][-5:]


class Items:
    """Benchmark items of one block: words, answers and projected passages."""

    def __init__(self, rows: list[tuple[int, bytes]], table: np.ndarray):
        self.ids = [r[0] for r in rows]
        self.words = [words_of(r[1]) for r in rows]
        self.answers = [answer_of(r[1]) for r in rows]
        self.lengths = np.array([len(w) for w in self.words], dtype="int64")
        held = Counter(w for words in self.words for w in set(words))
        self.telling = [any(held[w] < max(3, COMMON * len(rows)) for w in answer) for answer in self.answers]
        #: Of each item: its distinct terms, and how often it has each.
        self.content: list[tuple[np.ndarray, np.ndarray]] = []
        #: Items that are too short for a subsequence, by their words.
        self.short: dict[tuple[bytes, ...], list[int]] = {}
        terms, owner, runs = [], [], [np.zeros((2, 0), dtype="int64")]
        for k, (_, text) in enumerate(rows):
            own = terms_of([text])[0]
            n = len(own)
            self.content.append(np.unique(own, return_counts=True))
            if n < MIN_ITEM_WORDS:
                self.short.setdefault(tuple(self.words[k]), []).append(k)
                continue
            key = np.unique(runs_of(own))
            runs.append(np.stack([key, np.full(len(key), k)]))
            cuts = [(0, n)] if n <= 3 * HALF else [(a, min(n, a + 2 * HALF)) for a in range(0, n - HALF, HALF)]
            for a, b in cuts:
                terms.append(own[a:b])
                owner.append(k)
        self.short.pop((), None)
        vectors = np.stack([table[t].sum(axis=0) for t in terms]) if terms else np.zeros((0, table.shape[1]), dtype="float32")
        vectors, whole = vectors[:, :-1], np.maximum(vectors[:, -1:], 1e-9)
        kept = np.maximum((vectors**2).sum(axis=1, keepdims=True), LEAST_KEPT * whole)
        self.vectors = (vectors * np.sqrt(whole) / kept).astype("float32")
        self.owner = np.array(owner, dtype="int64")
        self.least = (CANDIDATE * np.sqrt(np.minimum(1, self.lengths[self.owner] / (2 * HALF)))).astype("float32")
        #: Runs in order, and the items of run i: run_items[run_at[i] : run_at[i + 1]].
        key, item = np.concatenate(runs, axis=1)
        order = np.argsort(key, kind="stable")
        self.runs, at = np.unique(key[order], return_index=True)
        self.run_items, self.run_at = item[order], np.r_[at, len(key)]

    def candidates(self, vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(passage, item, cosine) of the pairs over the threshold, in blocks of cosines of bounded size."""
        if not len(self.owner):
            return np.zeros(0, dtype="int64"), np.zeros(0, dtype="int64"), np.zeros(0, dtype="float32")
        found, step = [], max(1, CELLS // len(self.owner))
        for lo in range(0, len(vectors), step):
            cosine = vectors[lo : lo + step] @ self.vectors.T
            hit, query = np.nonzero(cosine >= self.least)
            found.append((hit + lo, self.owner[query], cosine[hit, query]))
        return tuple(np.concatenate(x) for x in zip(*found))

    def sharing_runs(self, flat: np.ndarray, ends: np.ndarray, vectors: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(passage, item, cosine) of the pairs that have a run of words in common."""
        if not len(self.runs) or len(flat) < RUN:
            return np.zeros(0, dtype="int64"), np.zeros(0, dtype="int64"), np.zeros(0, dtype="float32")
        key = runs_of(flat)
        known = np.minimum(np.searchsorted(self.runs, key), len(self.runs) - 1)
        place = np.flatnonzero(self.runs[known] == key)
        text = np.searchsorted(ends, place, side="right")
        inside = place + RUN <= ends[text]
        place, text, known = place[inside], text[inside], known[place[inside]]
        # the passage in which the run begins, the last one for the end of a text
        row = np.searchsorted(doc, text) + (place - np.r_[0, ends][text]) // HALF
        row = np.minimum(row, np.searchsorted(doc, text, side="right") - 1)
        row, known = np.divmod(np.unique(row * len(self.runs) + known), len(self.runs))
        sizes = self.run_at[known + 1] - self.run_at[known]
        total, pairs, lo = np.cumsum(sizes), [np.zeros(0, dtype="int64")], 0
        while lo < len(row):
            hi = max(lo + 1, int(np.searchsorted(total, total[lo] - sizes[lo] + CELLS, side="right")))
            own = sizes[lo:hi]
            at = np.repeat(self.run_at[known[lo:hi]] - np.cumsum(own) + own, own) + np.arange(own.sum())
            pairs.append(np.unique(np.repeat(row[lo:hi], own) * len(self.ids) + self.run_items[at]))
            lo = hi
        row, item = np.divmod(np.unique(np.concatenate(pairs)), len(self.ids))
        cosine = np.zeros(len(row), dtype="float32")
        first, last = np.searchsorted(self.owner, item), np.searchsorted(self.owner, item, side="right")
        for k in range(int((last - first).max(initial=0))):
            some = np.flatnonzero(first + k < last)
            for lo in range(0, len(some), SLICE):
                c = some[lo : lo + SLICE]
                cosine[c] = np.maximum(cosine[c], np.einsum("ij,ij->i", vectors[row[c]], self.vectors[first[c] + k]))
        return row, item, cosine

    def may_share(self, k: int, flat: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Whether flat[first:last] has LIKELY of item k's words at least, in any order and each as often as there.

        This bounds the common subsequence from above; words that share a term only raise it.
        """
        distinct, most = self.content[k]
        width = len(distinct) + 1
        place = np.full(TERMS, len(distinct))
        place[distinct] = np.arange(len(distinct))
        span = int(2 * self.lengths[k] + 4 * HALF)
        step, out = max(1, CELLS // max(span, width)), np.zeros(len(first), dtype=bool)
        for lo in range(0, len(first), step):
            at = first[lo : lo + step, None] + np.arange(span)
            found = np.where(at < last[lo : lo + step, None], place[flat[np.minimum(at, len(flat) - 1)]], len(distinct))
            found += width * np.arange(len(at))[:, None]
            there = np.bincount(found.ravel(), minlength=width * len(at)).reshape(-1, width)[:, :-1]
            out[lo : lo + step] = np.minimum(there, most).sum(axis=1) >= LIKELY * self.lengths[k]
        return out

    def check(self, k: int, region: list[bytes]) -> tuple[float, float, bool]:
        """(share of the item in common order, share of its answer, leaked) in a stretch of words."""
        share = common_subsequence(self.words[k], region) / len(self.words[k])
        if share < LIKELY:
            return share, 0.0, False
        answer = self.answers[k]
        part = common_subsequence(answer, region) / max(1, len(answer))
        return share, part, share >= SURE or part >= ANSWER and self.telling[k]

    def leaks(self, part: list[bytes | None], table: np.ndarray) -> list[tuple[int, int, float, float, float]]:
        """(row, item, cosine, share, answer share) of the leaked items of each text."""
        flat, lengths = terms_of(part)
        if not len(flat) or not self.ids:
            return []
        ends = np.cumsum(lengths)
        starts = ends - lengths
        vectors, doc, index = passage_vectors(flat, lengths, table)
        found = zip(self.candidates(vectors), self.sharing_runs(flat, ends, vectors, doc))
        hit, item, cosine = (np.concatenate(x) for x in found)
        # of candidates that begin in the same passage's length of words, the best stands for all
        order = np.lexsort((-cosine, index[hit] // 2, doc[hit], item))
        hit, item, cosine = hit[order], item[order], cosine[order]
        near = np.stack([item, doc[hit], index[hit] // 2])
        own = np.ones(len(hit), dtype=bool)
        own[1:] = (near[:, 1:] != near[:, :-1]).any(axis=0)
        hit, item, cosine = hit[own], item[own], cosine[own]
        at = index[hit] * HALF
        first = starts[doc[hit]] + np.maximum(0, at - self.lengths[item] - HALF)
        last = np.minimum(starts[doc[hit]] + at + self.lengths[item] + 3 * HALF, ends[doc[hit]])
        cuts = np.flatnonzero(np.r_[True, item[1:] != item[:-1]]) if len(item) else np.zeros(0, dtype="int64")
        held = [lo + np.flatnonzero(self.may_share(int(item[lo]), flat, first[lo:hi], last[lo:hi])) for lo, hi in zip(cuts, np.r_[cuts[1:], len(item)])]
        best: dict[tuple[int, int], tuple[float, float, float]] = {}
        bare: dict[int, list[bytes]] = {}
        for c in sorted(np.concatenate(held).tolist() if held else [], key=lambda c: -cosine[c]):
            row, k = int(doc[hit[c]]), int(item[c])
            if (row, k) in best:
                continue
            if row not in bare:
                bare[row] = words_of(part[row])
            share, answer, leaked = self.check(k, bare[row][first[c] - starts[row] : last[c] - starts[row]])
            if leaked:
                best[row, k] = float(cosine[c]), share, answer
        for n in {len(w) for w in self.short}:
            for row in np.flatnonzero(lengths >= n).tolist():
                words = words_of(part[row])
                for run in set(zip(*(words[i:] for i in range(n)))) & self.short.keys():
                    best |= {(row, k): (1.0, 1.0, 1.0) for k in self.short[run]}
        return [(row, k, *found) for (row, k), found in sorted(best.items())]


def fit(docs: DataFrame, benchmark: DataFrame) -> np.ndarray:
    """The projection: a (TERMS, RANK + 1) table of idf-weighted right singular vectors, and the square of the idf.

    All passages of all documents and of all items are rows of the matrix. A benchmark passage counts as ITEM_ROWS rows
    for every CORPUS_ROWS passages of documents (at least as ITEM_ROWS), so its share does not fall as the corpus grows.
    """
    own = written(term_rows(text_bytes(docs)))
    frequency, n, passages = document_frequencies(own)
    idf = np.log((n + 1) / (frequency + 1)) + 0.1
    items = checkpoint(term_rows(text_bytes(benchmark, "item_id").where("doc_id is not null").dropDuplicates(["doc_id"])))
    times = ITEM_ROWS * max(1.0, passages / CORPUS_ROWS)
    rows = own.withColumn("times", F.lit(1.0)).unionByName(items.withColumn("times", F.lit(times)))
    cores = docs.sparkSession.sparkContext.defaultParallelism
    vectors, _ = right_vectors(rows, idf, tasks=min(SVD_MOST, max(SVD_TASKS, cores, n // SVD_TEXTS)))
    return np.c_[idf[:, None] * vectors, idf * idf].astype("float32")


def item_blocks(benchmark: DataFrame):
    """Lists of (item_id, text) of at most about ITEMS rows and ITEM_BYTES of text (or one larger item)."""
    items = text_bytes(benchmark, "item_id").where("body is not null").dropDuplicates(["doc_id"])
    rows, size = items.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("body")), F.lit(0))).first()
    blocks = max(1, -(-rows // ITEMS), -(-size // ITEM_BYTES))
    for k in range(blocks):
        rows = items.where(F.pmod(F.xxhash64("doc_id"), F.lit(blocks)) == k).orderBy("doc_id").collect()
        yield [(r["doc_id"], bytes(r["body"])) for r in rows]


RESULT = "doc_id long, item_id long, cosine double, common_share double, answer_share double"


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, cosine, common_share, answer_share of every leaked item of every document."""
    spark = docs.sparkSession
    table = spark.sparkContext.broadcast(fit(docs, benchmark))
    arrow = arrow_schema(spark, RESULT)
    found = None
    for rows in item_blocks(benchmark):
        items = spark.sparkContext.broadcast(Items(rows, table.value))

        def run(batches, items=items):
            for part in chunks(batches):
                ids = part.column(0).to_pylist()
                leaks = items.value.leaks(part.column(1).to_pylist(), table.value)
                columns = list(zip(*[(ids[i], items.value.ids[k], c, s, a) for i, k, c, s, a in leaks])) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, arrow.types)], schema=arrow)

        block = text_bytes(docs).mapInArrow(run, RESULT)
        found = block if found is None else found.unionByName(block)
    return found


def drop_leaked(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without those that leak an item; the verdict is made where the text is read, so texts are not shuffled."""
    spark = docs.sparkSession
    table = spark.sparkContext.broadcast(fit(docs, benchmark))
    kept = docs
    for rows in item_blocks(benchmark):
        items = spark.sparkContext.broadcast(Items(rows, table.value))

        @F.pandas_udf("boolean")
        def clean(body):
            import pandas as pd

            out, at = np.ones(len(body), dtype=bool), 0
            for part in chunks([pa.RecordBatch.from_arrays([pa.array(body, pa.binary(), from_pandas=True)], ["body"])]):
                for i, *_ in items.value.leaks(part.column(0).to_pylist(), table.value):
                    out[at + i] = False
                at += part.num_rows
            return pd.Series(out)

        kept = kept.where(clean(F.col("text").cast("binary")))
    return kept
