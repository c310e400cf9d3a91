"""Quality classifier by co-training.

Two views of a document that share nothing: its text content (words and shapes of words, hashed) and its page metadata
(source, language and recorded length; the text is not looked at). A logistic model of each view starts from all
labelled documents but the quarter that is kept aside. In each round both score every other document; the most confident
``SHARE`` at either end, by thresholds over all of them, become pseudo-labels, all of which the other view is given; the
first label that a view is told of a document stays. Both are then calibrated on all labelled documents kept aside, and
their calibrated log odds are added for all documents.

Nothing is sampled: a fit is a descent of which every step adds up the gradient over all examples in the cluster. What tasks
add are whole multiples of 1 / ``FINE``, so the sums are exact and the models do not depend on the layout.
Texts are read once: what the views see is written as a narrow table that the rounds work on.

Defined results: null metadata are a value of their own; a null or empty text has only the empty-text feature; texts of any
length are read whole; repeated rows are scored each and labelled ones with one doc_id learned once (the least view); if there are
fewer than 8 labelled documents or none of a class everything is kept with probability 1; if all of a class would be kept
aside or none of it, all labelled documents serve for the fit and for the calibration; an empty table gives no rows; labels that are null or belong to no document
are not used, of several labels the largest counts; other columns are ignored, missing metadata columns count as null.
"""

from __future__ import annotations

import math
import re
import uuid
import zlib
from collections.abc import Callable, Generator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_schema, chunks, shared_folder

#: Buckets of word shapes, of words and of a text's shares; buckets of metadata.
SHAPES, WORDS, SHARES, META_SIZE = 512, 2048, 4, 192
TEXT_SIZE = SHAPES + WORDS + SHARES
ROUNDS, SHARE, CONFIDENT = 3, 0.05, 1.5
#: What a pseudo-label counts beside a label, and the penalty on squared weights.
TOLD, RIDGE = 0.3, 1e-3
#: A descent ends at this norm of the gradient or after so many steps; pairs of steps that it remembers.
FLAT, STEPS, PAIRS = 1e-4, 150, 12
#: Sums of tasks are in steps of 1 / FINE; so many tasks for each core, at least the first and at most the last number in all, send theirs to the driver.
FINE, TASKS = 2.0**24, (16, 4, 256)
#: Rows of the table of views: without a label, to fit on, kept aside, repeated rows of labelled documents.
OTHER, FIT, ASIDE, AGAIN = range(4)
#: A document is rejected below this probability of good quality.
KEEP = 0.5
#: Bins of the log odds, from -LOGIT to LOGIT.
LOGIT, BINS = 30.0, 1200

CLASSES = bytes(65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 48 if 48 <= b <= 57 else b for b in range(256))
RUNS = re.compile(rb"(.)\1+", re.S)
#: A value of a view: its bucket and its size.
VALUE = np.dtype([("at", "<u2"), ("x", "<f2")])


def word_buckets(word: bytes) -> int:
    """Buckets of a word's shape, runs of letters, digits and signs each as one character, and of the word in lower case, in one number."""
    return (zlib.crc32(RUNS.sub(rb"\1", word.translate(CLASSES))[:8]) % SHAPES) << 16 | SHAPES + zlib.crc32(word.lower()) % WORDS


def text_view(body: bytes | None, cache: dict[bytes, int]) -> np.ndarray:
    """Roots of the shares of shapes and words, and shares of repeated words and windows."""
    words = (body or b"").split()
    n = len(words)
    if not n:
        return np.array([(TEXT_SIZE - 1, 1)], dtype=VALUE)
    if len(cache) > 100_000:
        cache.clear()
    for w in set(words).difference(cache):
        cache[w] = word_buckets(w)
    # a word is one number: its shape's bucket in the upper bits, its own in the lower ones
    pairs = np.fromiter(map(cache.__getitem__, words), dtype="int64", count=n)
    buckets = np.concatenate([pairs >> 16, pairs & 0xFFFF])
    counts = np.bincount(buckets, minlength=SHAPES + WORDS)
    own = np.flatnonzero(counts)
    # windows of four words, told apart by the words' buckets
    mixed = pairs[3:].copy() if n > 3 else np.zeros(0, dtype="int64")
    for k in range(3):
        mixed = mixed * 0x1000193 + pairs[k : k + len(mixed)]
    windows = np.sort(mixed)
    again = float((windows[1:] == windows[:-1]).sum()) / max(1, n - 3)
    shares = (again, 1 - len(set(words)) / n, float(n < 10))
    view = np.empty(len(own) + 3, dtype=VALUE)
    view["at"][:-3], view["x"][:-3] = own, np.sqrt(counts[own] / n)
    view["at"][-3:], view["x"][-3:] = range(TEXT_SIZE - 4, TEXT_SIZE - 1), shares
    return view


def meta_view(lang: str | None, source: str | None, size: int | None) -> np.ndarray:
    """Source, language, both, and the recorded length in steps of half an octave."""
    step = 63 if size is None else min(62, int(2 * math.log2(max(0, size) + 1)))
    at = [zlib.crc32(f"{name}={value}".encode()) % 128 for name, value in (("lang", lang), ("source", source), ("both", f"{lang}/{source}"))]
    return np.array([(k, 1) for k in [*at, 128 + step]], dtype=VALUE)


def unpacked(views: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(buckets, values, number of values of each view) of packed views, none of which is empty."""
    flat = np.frombuffer(b"".join(views), dtype=VALUE)
    return flat["at"].astype("int64"), flat["x"].astype("float64"), np.array([len(v) for v in views], dtype="int64") // VALUE.itemsize


class Logistic:
    """Weights of a view's buckets and, last, the intercept."""

    def __init__(self, w: np.ndarray):
        self.w = w

    def logit(self, at: np.ndarray, x: np.ndarray, size: np.ndarray) -> np.ndarray:
        sums = np.add.reduceat(self.w[at] * x, np.cumsum(size) - size) if len(size) else np.zeros(0)
        return np.clip(sums + self.w[-1], -LOGIT, LOGIT)

    def sparse_logit(self, views: list[bytes]) -> np.ndarray:
        """Log odds of packed views, none of which is empty."""
        return self.logit(*unpacked(views))

    def slope(self, views: list[bytes], y: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Sums over the rows of each class, times FINE: gradient by weights, by the intercept, and loss."""
        at, x, size = unpacked(views)
        z = self.logit(at, x, size)
        err = weight * (1 / (1 + np.exp(-z)) - y)
        loss = weight * (np.log1p(np.exp(-abs(z))) + np.maximum(np.where(y > 0, -z, z), 0))
        n = len(self.w)
        out = np.bincount(at + (n + 1) * np.repeat(y, size), np.rint(np.repeat(err, size) * x * FINE), minlength=2 * (n + 1)).reshape(2, n + 1)
        out[:, -2] = np.bincount(y, np.rint(err * FINE), minlength=2)
        out[:, -1] = np.bincount(y, np.rint(loss * FINE), minlength=2)
        return out


def descent(w: np.ndarray, steps: int = STEPS) -> Generator[np.ndarray, tuple[float, np.ndarray], np.ndarray]:
    """Quasi-Newton descent with limited memory: yields points, is sent value and gradient there, returns the last point."""
    value, g = yield w
    moves: list[tuple[np.ndarray, np.ndarray]] = []
    for _ in range(steps):
        if np.linalg.norm(g) <= FLAT:
            break
        d, shares = -g, []
        for s, t in reversed(moves):
            shares.append(s @ d / (s @ t))
            d = d - shares[-1] * t
        d = d * (moves[-1][0] @ moves[-1][1] / (moves[-1][1] @ moves[-1][1]) if moves else 4.0)  # a logistic loss bends a quarter at most
        for (s, t), share in zip(moves, reversed(shares)):
            d = d + (share - t @ d / (s @ t)) * s
        step = 1.0
        while True:
            there, slope = yield w + step * d
            if there <= value + 1e-4 * step * (g @ d):
                break
            step /= 2
            if step < 1e-4:
                return w
        if (s := step * d) @ (t := slope - g) > 1e-12:
            moves = [*moves, (s, t)][-PAIRS:]
        w, value, g = w + s, there, slope
    return w


def summed(rows: DataFrame, size: int, kernel: Callable[[pa.RecordBatch], np.ndarray], column: str) -> np.ndarray:
    """The sum of the kernel's ``size`` whole numbers over all pieces of the table.

    A fit makes this pass many times, and the driver holds each task's sums and keeps a record of each task, so the tasks
    follow the cores and not the partitions of the table.
    """
    arrow = arrow_schema(rows.sparkSession, "sums binary")
    least, each, most = TASKS
    tasks = min(most, max(least, each * rows.sparkSession.sparkContext.defaultParallelism))

    def run(batches):
        total = np.zeros(size)
        for part in chunks(batches, column):
            total += kernel(part).ravel()
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], schema=arrow)

    return sum((np.frombuffer(bytes(r["sums"])) for r in rows.coalesce(tasks).mapInArrow(run, "sums binary").collect()), np.zeros(size))


def calibrate(logit: np.ndarray, y: np.ndarray, n: np.ndarray) -> tuple[float, float]:
    """Slope and intercept of the true log odds on the model's, by short Newton steps with a weak prior on slope 1; n: rows of each value."""
    a, b = 1.0, 0.0
    x = np.c_[logit, np.ones(len(logit))]
    for _ in range(200):
        p = 1 / (1 + np.exp(-np.clip(a * logit + b, -30, 30)))
        g = x.T @ (n * (y - p)) - np.array([a - 1, b]) * 0.5
        h = (x * (n * p * (1 - p))[:, None]).T @ x + np.eye(2) * 0.5
        step = np.clip(np.linalg.solve(h, g), -0.25, 0.25)
        a, b = a + step[0], b + step[1]
        if abs(step).max() < 1e-8:
            break
    return max(a, 0.0), b


def calibrations(aside: DataFrame, models: list[Logistic]) -> list[tuple[float, float]]:
    """calibrate() of each view on all rows kept aside, which count in bins of log odds with their mean."""

    def kernel(part):
        y = part.column("y").to_numpy().astype("int64")
        out = np.zeros((2, 2, 2 * BINS))
        for k, model in enumerate(models):
            logit = model.sparse_logit(part.column(VIEW_NAMES[k]).to_pylist())
            at = y * BINS + bin_of(logit)
            out[k] = np.bincount(at, minlength=2 * BINS), np.bincount(at, np.rint(logit * FINE), minlength=2 * BINS)
        return out

    out = []
    for n, total in summed(aside, 8 * BINS, kernel, "text").reshape(2, 2, 2 * BINS):
        there = np.flatnonzero(n)
        out.append(calibrate(total[there] / FINE / n[there], there // BINS, n[there]))
    return out


def fitted(labelled: DataFrame, told: DataFrame | None, last: list[Logistic] | None) -> list[Logistic]:
    """A model of each view by all labelled rows and all that the view was told, which count less; both classes weigh the same. It goes on from the last ones."""
    examples = [labelled.select(F.lit(k).alias("told"), "y", F.lit(1.0).alias("weight"), F.col(c).alias("view")) for k, c in enumerate(VIEW_NAMES)]
    if told is not None:
        examples.append(told.select("told", "y", F.lit(TOLD).alias("weight"), "view"))
    rows = examples[0]
    for each in examples[1:]:
        rows = rows.unionByName(each)

    def counted(part):
        own, y, weight = (part.column(c).to_numpy() for c in ("told", "y", "weight"))
        return np.bincount(4 * (weight < 1) + 2 * own + y, minlength=8)

    full, less = summed(rows, 8, counted, "view").reshape(2, 2, 2)
    weights = full + TOLD * less
    sizes = [2 * (n + 2) for n in VIEW_SIZES]
    runs = [descent(np.zeros(n + 1) if last is None else last[k].w) for k, n in enumerate(VIEW_SIZES)]
    points: list[np.ndarray | None] = [next(run) for run in runs]
    done: list[np.ndarray | None] = [None, None]
    while any(p is not None for p in points):

        def kernel(part, points=tuple(points)):
            own, y, weight = (part.column(c).to_numpy() for c in ("told", "y", "weight"))
            views, out = part.column("view"), []
            for k, point in enumerate(points):
                at = np.flatnonzero(own == k) if point is not None else []
                out.append(Logistic(point).slope(views.take(pa.array(at)).to_pylist(), y[at].astype("int64"), weight[at]).ravel() if len(at) else np.zeros(sizes[k]))
            return np.concatenate(out)

        total = np.split(summed(rows, sum(sizes), kernel, "view") / FINE, [sizes[0]])
        for k, w in enumerate(points):
            if w is None:
                continue
            mean = (total[k].reshape(2, -1) / weights[k][:, None]).sum(axis=0) / 2
            g = mean[:-1] + RIDGE * np.r_[w[:-1], 0]
            try:
                points[k] = runs[k].send((mean[-1] + RIDGE / 2 * (w[:-1] @ w[:-1]), g))
            except StopIteration as end:
                done[k], points[k] = end.value, None
    return [Logistic(w) for w in done]


def bin_of(logit: np.ndarray) -> np.ndarray:
    return np.minimum(((logit + LOGIT) * (BINS / (2 * LOGIT))).astype("int64"), BINS - 1)


def thresholds(bins: np.ndarray, prior: float, share: float = SHARE) -> tuple[float, float]:
    """Evidence below and above which a view is confident: beyond CONFIDENT without the prior log odds and with them."""
    edges = np.linspace(-LOGIT, LOGIT, BINS + 1)
    most = share * bins.sum()
    low = int(np.searchsorted(np.cumsum(bins), most, side="right"))
    high = BINS - int(np.searchsorted(np.cumsum(bins[::-1]), most, side="right"))
    low = min(max(low, 1), int(np.searchsorted(edges, -CONFIDENT - max(0.0, prior))))
    high = max(min(high, BINS - 1), int(np.searchsorted(edges, CONFIDENT - min(0.0, prior))))
    return float(edges[low]), float(edges[high])


#: A turn's models with slope and intercept of each view's evidence, the log odds beyond the prior ones.
Turn = list[tuple[Logistic, float, float]]
EXAMPLES = "told int, y int, view binary"


def evidence(part: pa.RecordBatch, models: Turn) -> list[np.ndarray]:
    """Bins of the evidence of each view."""
    return [bin_of(np.clip(a * m.sparse_logit(part.column(c).to_pylist()) + b, -LOGIT, LOGIT)) for c, (m, a, b) in zip(VIEW_NAMES, models)]


def cuts_of(others: DataFrame, models: Turn, prior: float) -> list[tuple[float, float]]:
    """thresholds() of each view over all documents without a label."""
    bins = summed(others, 2 * BINS, lambda part: np.stack([np.bincount(b, minlength=BINS) for b in evidence(part, models)]), "text")
    return [thresholds(b, prior) for b in bins.reshape(2, BINS)]


def pseudo_labels(others: DataFrame, turns: list[tuple[Turn, list[tuple[float, float]]]]) -> DataFrame:
    """(view to be told, label, that view) of all that the other view is confident of in the last turn and was not in an earlier one."""
    arrow = arrow_schema(others.sparkSession, EXAMPLES)
    edges = np.linspace(-LOGIT, LOGIT, BINS + 1)

    def run(batches):
        for part in chunks(batches, "text"):
            known = np.zeros((2, part.num_rows), dtype=bool)
            for models, cuts in turns:
                out = []
                for k, (bins, (low, high)) in enumerate(zip(evidence(part, models), cuts)):
                    good, bad = edges[bins] >= high, edges[bins] < low
                    new = np.flatnonzero((good | bad) & ~known[k])
                    known[k] |= good | bad
                    out.append((np.full(len(new), 1 - k), good[new], part.column(VIEW_NAMES[1 - k]).take(pa.array(new))))
            for told, label, view in out:
                yield pa.RecordBatch.from_arrays([pa.array(told, pa.int32()), pa.array(label.astype("int32")), view.cast(arrow.types[2])], schema=arrow)

    return others.select("text", "meta").mapInArrow(run, EXAMPLES)


def co_train(labelled: DataFrame, aside: DataFrame, others: DataFrame, prior: float, rounds: int = ROUNDS):
    """((model, slope, intercept) of text, of metadata, log prior odds). labelled, aside: (y, text, meta), others: (text, meta)."""
    spark = others.sparkSession
    folder = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    turns: list[tuple[Turn, list[tuple[float, float]]]] = []
    models, told = None, None
    for turn in range(rounds + 1):
        models = fitted(labelled, told, models)
        calibrated = [(m, *ab) for m, ab in zip(models, calibrations(aside, models))]
        if turn == rounds:
            return calibrated, prior
        beyond = [(m, a, b - prior) for m, a, b in calibrated]
        turns.append((beyond, cuts_of(others, beyond, prior)))
        pseudo_labels(others, turns).write.parquet(f"{folder}/{turn}")
        told = spark.read.schema(EXAMPLES).parquet(*(f"{folder}/{t}" for t in range(turn + 1)))


def combine(text_logit: np.ndarray, meta_logit: np.ndarray, prior: float) -> np.ndarray:
    """Log odds of both calibrated views, the prior counted once."""
    return 1 / (1 + np.exp(-np.clip(text_logit + meta_logit - prior, -30, 30)))


VIEWS = "doc_id long, text binary, meta binary"
VIEW_NAMES, VIEW_SIZES = ("text", "meta"), (TEXT_SIZE, META_SIZE)


def views_of(docs: DataFrame) -> DataFrame:
    """(doc_id, text, meta) with both views packed."""
    arrow = arrow_schema(docs.sparkSession, VIEWS)

    def run(batches):
        cache: dict[bytes, int] = {}
        for part in chunks(batches):
            doc, body, *meta = (c.to_pylist() for c in part.columns)
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array([text_view(b, cache).tobytes() for b in body]), pa.array([meta_view(*m).tobytes() for m in zip(*meta)])], schema=arrow)

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("binary").alias("body"), *_metadata(docs)).mapInArrow(run, VIEWS)


def _metadata(docs: DataFrame) -> list[Column]:
    kinds = {"lang": "string", "source": "string", "n_chars": "bigint"}
    return [(F.col(c) if c in docs.columns else F.lit(None)).cast(t).alias(c) for c, t in kinds.items()]


def with_labels(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, text, meta, y, kind) of every row, written in the shared folder in a part for each kind."""
    spark = docs.sparkSession
    known = labels.where("quality is not null and doc_id is not null").groupBy(F.col("doc_id").cast("bigint").alias("id")).agg((F.max("quality").cast("int") > 0).cast("int").alias("y"))
    views = views_of(docs).withColumn("key", F.coalesce("doc_id", F.monotonically_increasing_id()))  # null ids, which have no label, are spread
    rows = views.join(known, (F.col("key") == F.col("id")) & F.col("doc_id").isNotNull(), "left")
    first = F.row_number().over(Window.partitionBy("key").orderBy(F.col("y").isNull(), "text", "meta")) == 1
    aside = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 0
    kind = F.when(F.col("y").isNull(), OTHER).when(~first, AGAIN).when(aside, ASIDE).otherwise(FIT)
    path = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    rows.select("doc_id", "text", "meta", "y", kind.alias("kind")).write.partitionBy("kind").parquet(path)
    return spark.read.schema(f"{VIEWS}, y int, kind int").parquet(path)


def fit(views: DataFrame):
    """Models by all rows of with_labels(); None if there are too few labels or a class has none."""
    n = np.zeros((4, 2), dtype="int64")
    for r in views.where("y is not null").groupBy("kind", "y").count().collect():
        n[r["kind"], r["y"]] = r["count"]
    if n[[FIT, ASIDE]].sum() < 8 or not n[[FIT, ASIDE]].sum(axis=0).all():
        return None
    parts = [[FIT], [ASIDE]] if n[[FIT, ASIDE]].all() else [[FIT, ASIDE]] * 2
    labelled, aside = (views.where(F.col("kind").isin(p)).select("y", "text", "meta") for p in parts)
    bad, good = n[parts[1]].sum(axis=0).tolist()
    return co_train(labelled, aside, views.where(F.col("kind") == OTHER).select("text", "meta"), math.log((good + 1) / (bad + 1)))


RESULT = "doc_id long, p_text double, p_meta double, quality double, kept boolean"


def score(docs: DataFrame, labels: DataFrame, keep: float = KEEP) -> DataFrame:
    """doc_id, p_text, p_meta, quality, kept of every document."""
    spark = docs.sparkSession
    views = with_labels(docs, labels)
    shared = spark.sparkContext.broadcast(fit(views))
    arrow = arrow_schema(spark, RESULT)
    sigmoid = lambda x: 1 / (1 + np.exp(-np.clip(x, -LOGIT, LOGIT)))

    def run(batches):
        for part in chunks(batches, "text"):
            if shared.value is None:
                found = [np.ones(part.num_rows)] * 3
            else:
                models, prior = shared.value
                logits = [a * m.sparse_logit(part.column(k).to_pylist()) + b for k, (m, a, b) in enumerate(models, 1)]
                found = [sigmoid(logits[0]), sigmoid(logits[1]), combine(*logits, prior)]
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(x) for x in found), pa.array(found[2] >= keep)], schema=arrow)

    return views.select("doc_id", "text", "meta").mapInArrow(run, RESULT)


def keep_good(docs: DataFrame, labels: DataFrame, keep: float = KEEP) -> DataFrame:
    """docs without the rejected rows; the verdict is made where the text is read, so texts are not shuffled."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(fit(with_labels(docs, labels)))

    @F.pandas_udf("boolean")
    def good(body, lang, source, size):
        import pandas as pd

        if shared.value is None:
            return pd.Series(np.ones(len(body), dtype=bool))
        models, prior = shared.value
        cache: dict[bytes, int] = {}
        out = np.zeros(len(body), dtype=bool)
        sizes = [None if pd.isna(x) else int(x) for x in size]
        for at in range(0, len(body), 512):
            cut = slice(at, at + 512)
            data = [text_view(b, cache).tobytes() for b in body[cut]], [meta_view(*x).tobytes() for x in zip(lang[cut], source[cut], sizes[cut])]
            out[cut] = combine(*(a * m.sparse_logit(x) + b for (m, a, b), x in zip(models, data)), prior) >= keep
        return pd.Series(out)

    return docs.where(good(F.col("text").cast("binary"), *_metadata(docs)))
