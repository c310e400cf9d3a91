"""Hidden Markov language model.

1. Word counts over all training documents; the most common words, up to ``frequent`` of them, become symbols of the model
   (a bounded table), all other words share one symbol and are told apart by their own counts. Of these, the ones that
   are most common in all documents are looked up in a second bounded table, the rest are joined, not sent out.
2. Documents are encoded once as 16-bit symbols and checkpointed.
3. States start from a mixture fitted on a bounded sample; then Baum-Welch rounds run over every training document
   until the likelihood gains less than ``SETTLED`` a token, ``rounds`` at most; each task returns expected counts of starts,
   transitions and emissions, which are added up by symbol block. The counts are those of whole documents: a text is worked on in
   segments side by side, and what enters a segment from the left and from the right comes from the segments' products.
4. Scores come from the scaled forward recursion over each whole document, exact and uncut.

Defined results: a null or empty text is the end token alone; a null doc_id counts as the empty string in the split;
repeated rows are scored each and counted each; without training documents N and V are 0; an empty table gives no rows;
texts of any length are read whole, a task holds one text's symbols and a table of a few bytes for each; ties of word
counts fall on one side of the cut together; other columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import add_blocks, arrow_schema, checkpoint, chunks, lowest_hashes, text_bytes

STATES = 8
FREQUENT = 32_000
ROUNDS, SETTLED = 3, 2e-3
SAMPLE_DOCS, SAMPLE_TOKENS, SAMPLE_ROUNDS = 2000, 1000, 6
SEGMENT, GROUP = 64, 2048
#: Word counts up to here have a bin of their own in the histogram that finds the cut, larger ones a sixteenth of an octave.
EXACT_BINS = 1024
#: Weight of the corpus unigram in each state's emissions, in tokens.
PRIOR = 200.0
BLOCKS = 64
FOLDS, HELD_FOLD = 5, 1
END = b""


def held_out(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % FOLDS == HELD_FOLD


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, c, seen): occurrences in training documents and in all; the end token is the empty word."""
    schema = "word string, c long, seen long"
    arrow = arrow_schema(docs.sparkSession, schema)

    def batch(train, held):
        words = list(train.keys() | held.keys())
        c = [train[w] for w in words]
        return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()).cast(pa.string()), pa.array(c, pa.int64()), pa.array([n + held[w] for n, w in zip(c, words)], pa.int64())], schema=arrow)

    def run(batches):
        counters = Counter(), Counter()
        for part in chunks(batches):
            for doc, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                counter = counters[held_out(doc)]
                counter.update((body or b"").lower().split())
                counter[END] += 1
            if sum(map(len, counters)) > 400_000:
                yield batch(*counters)
                counters = Counter(), Counter()
        yield batch(*counters)

    return text_bytes(docs).mapInArrow(run, schema).groupBy("word").agg(F.sum("c").alias("c"), F.sum("seen").alias("seen"))


def most_common(counts: DataFrame, column: str, most: int) -> list:
    """The words over the smallest cut of ``column`` that at most ``most`` words exceed, the most common first.

    The cut comes from a histogram of counts, so only these words leave the cluster, whatever the number of tasks.
    """
    large = EXACT_BINS + F.floor(16 * F.log2(F.col(column) / EXACT_BINS))
    binned = counts.where((F.col("word") != "") & (F.col(column) > 0)).withColumn("bin", F.when(F.col(column) < EXACT_BINS, F.col(column)).otherwise(large).cast("int"))
    left, cut = most, None
    for r in sorted(binned.groupBy("bin").count().collect(), key=lambda r: -r["bin"]):
        if r["count"] > left:
            break
        left, cut = left - r["count"], r["bin"]
    if cut is None:
        return []
    return sorted(binned.where(F.col("bin") >= cut).collect(), key=lambda r: (-r[column], r["word"]))


ENCODED = "doc_id long, held boolean, n_tokens long, n_known long, base double, n_rare long, rare_log double, symbols binary, rare array<string>"


def encode(docs: DataFrame, tables, base_log: np.ndarray) -> DataFrame:
    """Documents as symbols. tables: broadcast ({word: symbol}, {other word: count}); base_log[symbol]: log10 base probability (rare: 0)."""
    arrow = arrow_schema(docs.sparkSession, ENCODED)
    other = len(base_log) - 1

    def run(batches):
        symbols, counted = tables.value
        get, logs = symbols.get, {w: math.log10(c + 0.5) for w, c in counted.items()}
        for part in chunks(batches):
            rows = []
            for doc, body in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                words = (body or b"").lower().split()
                words.append(END)
                ids = [get(w, other) for w in words]
                outside = [w for w, i in zip(words, ids) if i == other]
                rare = [w for w in outside if w not in counted]
                found = [w for w in outside if w in counted] if len(rare) < len(outside) else []
                known = len(ids) - len(outside) + sum(counted[w] > 0 for w in found)
                ids = np.array(ids, dtype="<u2")
                rows.append((doc, held_out(doc), len(ids), known, float(base_log[ids].sum()), len(outside), math.fsum(logs[w] for w in found), ids.tobytes(), rare))
            columns = list(zip(*rows))
            rare = pa.array(columns[8], pa.list_(pa.binary())).cast(pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([*(pa.array(c, t) for c, t in zip(columns[:8], arrow.types)), rare.cast(arrow.types[8])], schema=arrow)

    return text_bytes(docs).mapInArrow(run, ENCODED)


def groups_of(texts: list[np.ndarray], size: int = GROUP, length: int = SEGMENT):
    """Lists of texts of about ``size`` segments; a longer text is a list of its own. Texts of like lengths go together."""
    own, held = [], 0
    for x in sorted((x for x in texts if len(x)), key=len):
        n = -(-len(x) // length)
        if own and held + n > size:
            yield own
            own, held = [], 0
        own.append(x)
        held += n
    if own:
        yield own


def products(x: np.ndarray, sizes: np.ndarray, move: np.ndarray, emit: np.ndarray) -> np.ndarray:
    """(n, K, K) of each segment: what is expected to enter -> weights of its last state, up to a factor. Sizes fall."""
    n, k = len(x), len(move)
    out = np.zeros((n, k, k), dtype="float32")
    out[:, range(k), range(k)] = emit[x[:, 0]]
    for t in range(1, int(sizes.max(initial=0))):
        m = int((sizes > t).sum())
        out[:m] = (out[:m].reshape(m * k, k) @ move).reshape(m, k, k) * emit[x[:m, t]][:, None, :]
        if t % 2:
            out[:m] /= out[:m].max(axis=(1, 2), keepdims=True)
    return out / np.maximum(out.max(axis=(1, 2), keepdims=True), 1e-30)


def expected_counts(texts: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit: np.ndarray, length: int = SEGMENT) -> list[np.ndarray]:
    """Baum-Welch counts [starts (K), transitions (K, K), emissions (K, S)] of whole texts, and their log10 likelihood. emit: (S, K)."""
    k, s = emit.shape[1], emit.shape[0]
    starts, moves, emissions, total = np.zeros(k), np.zeros((k, k)), np.zeros((k, s)), 0.0
    back = np.ascontiguousarray(move.T)
    for own in groups_of(texts, length=length):
        own = own[::-1]  # the longest first, so that the texts that have a j-th segment are the first ones
        flat = np.concatenate(own)
        sizes = np.array([len(x) for x in own])
        counts = -(-sizes // length)
        base = np.cumsum(counts) - counts
        text = np.repeat(np.arange(len(own)), counts)
        place = np.arange(len(text)) - base[text]
        at = (np.cumsum(sizes) - sizes)[text] + length * place
        size = np.minimum(length, sizes[text] - length * place)
        enter = np.tile(start.astype("float32"), (len(text), 1))
        before, leave = np.zeros((len(text), k), dtype="float32"), np.ones((len(text), k), dtype="float32")
        order = np.argsort(-size, kind="stable")

        def cut(rows):
            return flat[np.minimum(at[rows, None] + np.arange(length), len(flat) - 1)]

        many = order[counts[text[order]] > 1]
        if len(many):
            table = np.zeros((len(text), k, k), dtype="float32")
            for lo in range(0, len(many), GROUP):
                rows = many[lo : lo + GROUP]
                table[rows] = products(cut(rows), size[rows], move, emit)
            for j in range(1, int(counts[0])):
                here = base[: int((counts > j).sum())] + j
                a = np.einsum("nk,nkl->nl", enter[here - 1], table[here - 1])
                before[here] = a / a.sum(axis=1, keepdims=True)
                enter[here] = before[here] @ move
            for j in range(int(counts[0]) - 1, 0, -1):
                here = base[: int((counts > j).sum())] + j
                b = np.einsum("nkl,nl->nk", table[here], leave[here]) @ back
                leave[here - 1] = b / b.max(axis=1, keepdims=True)
        for lo in range(0, len(order), GROUP):
            rows = order[lo : lo + GROUP]
            x, n = cut(rows), len(rows)
            # lengths fall, so the rows that are still running are always the first ones
            live = [int((size[rows] > t).sum()) for t in range(int(size[rows[0]]))]
            alpha = np.zeros((len(live), n, k), dtype="float32")
            scale = np.ones((len(live), n, 1), dtype="float32")
            a = enter[rows]
            for t, m in enumerate(live):
                a = (a if t == 0 else a[:m] @ move) * emit[x[:m, t]]
                c = a.sum(axis=1, keepdims=True)
                a = a / c
                alpha[t, :m], scale[t, :m] = a, c
            total += float(np.log10(scale, dtype="float64").sum())
            b = leave[rows]
            b /= (alpha[size[rows] - 1, np.arange(n)] * b).sum(axis=1, keepdims=True)
            for t in range(len(live) - 1, -1, -1):
                m = live[t]
                if t + 1 < len(live):
                    p = live[t + 1]
                    ahead = emit[x[:p, t + 1]] * b[:p] / scale[t + 1, :p]
                    moves += alpha[t, :p].T @ ahead
                    b[:p] = ahead @ back
                if t == 0:
                    later = place[rows] > 0
                    moves += before[rows[later]].T @ (emit[x[later, 0]] * b[later] / scale[0, later])
                gamma = alpha[t, :m] * b[:m]
                alpha[t, :m] = gamma / gamma.sum(axis=1, keepdims=True)
            starts += alpha[0][place[rows] == 0].sum(axis=0)
            for t0 in range(0, len(live), 16):
                steps = range(t0, min(len(live), t0 + 16))
                ids = np.concatenate([x[: live[t], t] for t in steps])
                weights = np.concatenate([alpha[t, : live[t]] for t in steps])
                for state in range(k):
                    emissions[state] += np.bincount(ids, weights=weights[:, state], minlength=s)
    return [starts, moves * move, emissions, np.array(total)]


def maximise(starts: np.ndarray, moves: np.ndarray, emissions: np.ndarray, unigram: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    start = (starts + 1) / (starts + 1).sum()
    move = (moves + 0.5) / (moves + 0.5).sum(axis=1, keepdims=True)
    emit = (emissions + PRIOR * unigram) / (emissions.sum(axis=1, keepdims=True) + PRIOR)
    return start.astype("float32"), move.astype("float32"), np.ascontiguousarray(emit.T.astype("float32"))


def starting_point(texts: list[np.ndarray], unigram: np.ndarray, states: int, seed: int = 42) -> tuple:
    """States from a mixture of unigrams on the sample, then a few Baum-Welch rounds on it."""
    random = np.random.default_rng(seed)
    s = len(unigram)
    emit = unigram * np.exp(random.normal(0, 0.3, (states, s)))
    for k, i in enumerate(random.permutation(len(texts))[:states]):
        emit[k] += np.bincount(texts[i], minlength=s) / max(1, len(texts[i]))
    emit /= emit.sum(axis=1, keepdims=True)
    share = np.full(states, 1 / states)
    rows = np.repeat(np.arange(len(texts)), [len(x) for x in texts])
    flat = np.concatenate(texts) if texts else np.zeros(0, dtype="uint16")
    for _ in range(12):
        logs = np.log(emit)
        like = np.stack([np.bincount(rows, weights=logs[k][flat], minlength=len(texts)) for k in range(states)], axis=1) + np.log(share)
        like = np.exp((like - like.max(axis=1, keepdims=True)) * 0.5)
        like /= like.sum(axis=1, keepdims=True)
        share = (like.sum(axis=0) + 1) / (like.sum() + states)
        counts = np.stack([np.bincount(flat, weights=like[rows, k], minlength=s) for k in range(states)])
        emit = (counts + PRIOR * unigram) / (counts.sum(axis=1, keepdims=True) + PRIOR)
    move = np.full((states, states), 0.2 / max(1, states - 1)) + np.eye(states) * (0.8 - 0.2 / max(1, states - 1)) if states > 1 else np.ones((1, 1))
    model = share.astype("float32"), move.astype("float32"), np.ascontiguousarray(emit.T.astype("float32"))
    for _ in range(SAMPLE_ROUNDS if texts else 0):
        model = maximise(*expected_counts(texts, *model)[:3], unigram)
    return model


def train_round(encoded: DataFrame, model: tuple, unigram: np.ndarray) -> tuple[tuple, float]:
    """One Baum-Welch round over every training document: the new model, and the log10 likelihood of the old one."""
    spark = encoded.sparkSession
    shared = spark.sparkContext.broadcast(model)
    s, k = model[2].shape
    size = -(-(s + 1 + k) // BLOCKS)
    schema = "block int, counts binary, likelihood double"
    arrow = arrow_schema(spark, schema)

    def run(batches):
        start, move, emit = shared.value
        totals = None
        for batch in batches:
            for at in range(0, batch.num_rows, 2000):
                texts = [np.frombuffer(x, dtype="<u2") for x in batch.column(0).slice(at, 2000).to_pylist()]
                found = expected_counts(texts, start, move, emit)
                totals = found if totals is None else [a + b for a, b in zip(totals, found)]
        if totals is not None:
            wide = np.zeros((k, BLOCKS * size), dtype="float32")
            wide[:, : s + 1 + k] = np.concatenate([totals[0][:, None], totals[1], totals[2]], axis=1)
            parts = [wide[:, i * size : (i + 1) * size].tobytes() for i in range(BLOCKS)]
            yield pa.RecordBatch.from_arrays([pa.array(range(BLOCKS), pa.int32()), pa.array(parts, pa.binary()), pa.array([float(totals[3])] * BLOCKS)], schema=arrow)

    def add(table):
        total = np.zeros(k * size)
        for x in table.column("counts").to_pylist():
            total += np.frombuffer(x, dtype="float32")
        return pa.Table.from_pydict({"block": [table.column("block")[0].as_py()], "counts": [total.astype("float32").tobytes()], "likelihood": [sum(table.column("likelihood").to_pylist())]}, schema=arrow)

    rows = add_blocks(encoded.where("not held").select("symbols").mapInArrow(run, schema), schema, add)
    shared.destroy()
    if not rows:
        return model, 0.0
    wide = np.zeros((k, BLOCKS * size))
    for r in rows:  # BLOCKS rows of a size that the model's tables bound
        wide[:, r["block"] * size : (r["block"] + 1) * size] = np.frombuffer(bytes(r["counts"]), dtype="float32").reshape(k, size)
    return maximise(wide[:, 0], wide[:, 1 : 1 + k], wide[:, 1 + k : 1 + k + s], unigram), rows[0]["likelihood"]


def train(encoded: DataFrame, unigram: np.ndarray, tokens: int, states: int = STATES, rounds: int = ROUNDS) -> tuple[tuple, list[float]]:
    """The model, and the training likelihood (log10) that each round began with."""
    texts = lowest_hashes(encoded.where("not held").select("row", "symbols"), F.xxhash64("row"), SAMPLE_DOCS, "row").select(F.substring("symbols", 1, 2 * SAMPLE_TOKENS).alias("symbols"))
    model = starting_point([np.frombuffer(bytes(r["symbols"]), dtype="<u2") for r in texts.collect()], unigram, states)
    history: list[float] = []
    while len(history) < rounds and (len(history) < 2 or history[-1] - history[-2] > SETTLED * max(1, tokens)):
        model, likelihood = train_round(encoded, model, unigram)
        history.append(likelihood)
    return model, history


def log10_likelihoods(texts: list[np.ndarray], start: np.ndarray, move: np.ndarray, emit: np.ndarray) -> np.ndarray:
    """Scaled forward recursion over whole texts; texts advance together, longest first."""
    order = np.argsort([-len(x) for x in texts], kind="stable")
    lengths = np.array([len(texts[i]) for i in order])
    offsets = np.r_[0, np.cumsum(lengths)[:-1]] if len(texts) else np.zeros(0, dtype="int64")
    flat = np.concatenate([texts[i] for i in order]) if texts else np.zeros(0, dtype="uint16")
    total = np.zeros(len(texts))
    live = len(texts)
    a = np.tile(start, (live, 1))
    for t in range(int(lengths[0]) if live else 0):
        while lengths[live - 1] <= t:
            live -= 1
        a = (a if t == 0 else a[:live] @ move) * emit[flat[offsets[:live] + t]]
        c = a.sum(axis=1)
        a /= c[:, None]
        total[:live] += np.log10(c)
    out = np.zeros(len(texts))
    out[order] = total
    return out


def score_documents(docs: DataFrame, states: int = STATES, frequent: int = FREQUENT, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10) of every document.

    Besides rounds, the Baum-Welch rounds that were run, and train_log10, the training likelihood that the last began with.
    """
    spark = docs.sparkSession
    counts = checkpoint(word_counts(docs))
    n, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") > 0)).first()
    top = most_common(counts, "c", frequent)
    end = counts.where("word = '' and c > 0").collect()
    own = [(END, end[0]["c"])] if end else []
    own += [(r["word"].encode(), r["c"]) for r in top]
    inside = {w for w, _ in own}
    # of the other words the most common of all documents: no word that is left to the join is frequent anywhere
    counted = {r["word"].encode(): r["c"] for r in most_common(counts, "seen", 2 * frequent)}
    counted = {w: c for w, c in counted.items() if w not in inside}
    if not end:
        counted[END] = 0
    divisor = n + 0.5 * (v + 1)
    c = np.array([x for _, x in own] + [0.0])
    base_log = np.r_[np.log10((c[:-1] + 0.5) / divisor), 0.0]
    rare_mass, rare_words = n - c.sum(), v - len(own)
    c[-1] = rare_mass
    unigram = (c + 0.5) / (c + 0.5).sum()
    tables = spark.sparkContext.broadcast(({w: i for i, (w, _) in enumerate(own)}, counted))
    encoded = checkpoint(encode(docs, tables, base_log).withColumn("row", F.monotonically_increasing_id()))
    model, history = train(encoded, unigram, n, states, rounds)

    shared = spark.sparkContext.broadcast(model)
    kept = ["row", "doc_id", "held", "n_tokens", "n_known", "base", "n_rare", "rare_log"]
    schema = "row long, doc_id long, held boolean, n_tokens long, n_known long, base double, n_rare long, rare_log double, likelihood double"
    arrow = arrow_schema(spark, schema)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 5000):
                part = batch.slice(at, 5000)
                found = log10_likelihoods([np.frombuffer(x, dtype="<u2") for x in part.column(8).to_pylist()], *shared.value)
                yield pa.RecordBatch.from_arrays([*part.columns[:8], pa.array(found)], schema=arrow)

    scored = encoded.select(*kept, "symbols").mapInArrow(run, schema)
    # words outside both tables: their counts come by a join on the word, summed for each document
    words = encoded.select("row", F.explode("rare").alias("word")).join(counts.select("word", "c").where("c > 0"), "word", "left")
    found = words.groupBy("row").agg(F.count("c").alias("rare_known"), F.sum(F.log10(F.coalesce("c", F.lit(0)) + 0.5)).alias("joined_log"))
    outside = float(np.log10(rare_mass + 0.5 * (rare_words + 1)))
    rare_log = F.col("rare_log") + F.coalesce("joined_log", F.lit(0.0))
    return scored.join(found, "row", "left").select(
        "doc_id",
        F.col("held").alias("held_out"),
        "n_tokens",
        (F.col("n_known") + F.coalesce("rare_known", F.lit(0))).cast("bigint").alias("n_known"),
        F.lit(int(n)).cast("bigint").alias("train_tokens"),
        (F.col("base") + rare_log - F.col("n_rare") * float(np.log10(divisor))).alias("base_score"),
        (F.col("likelihood") + rare_log - F.col("n_rare") * outside).alias("score"),
        F.lit(len(history)).alias("rounds"),
        F.lit(history[-1] if history else 0.0).alias("train_log10"),
    )
