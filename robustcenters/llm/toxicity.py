"""Toxicity by cumulative-link ordinal regression.

P(grade <= j) is a logistic function of a threshold minus one linear score, so all ordered thresholds share the
weights. Features are words and word beginnings; the ones that set toxic documents apart are selected by
counts over a bounded sample of labelled documents that is reduced in the cluster. Labels say toxic or not, so severity
grades have to be derived: toxic training documents of either half of the sample are graded by the thirds of their share of
words that the other half's counts call toxic. The share of words that the counts of all call toxic is one feature among the
others, so the grade is not a number that the model is given, but it is no independent judgement either. All documents are scored; the output is the distribution's mean (expected severity) and the likeliest grade.

Defined results: a null or empty text has no features and scores as the intercept does; texts are read whole; repeated
rows are scored each, equal labelled texts learned once; without toxic or clean labels every document has severity 0; an empty table gives no rows; labels that are
null or belong to no document are not used; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_schema, checkpoint, chunks, lowest_hashes, text_bytes

GRADES = 4
#: Labelled documents to fit on (half of them toxic, if there are so many), and features to keep.
SAMPLE, FEATURES = 12_000, 2000
STRIP = b".,;:!?\"'()[]*#$%&|<>"
PREFIXES = (4, 5)
#: A feature is kept if at least so many toxic documents, and this share of them, have it, at odds of at least e to this power.
LEAST_DOCS, LEAST_SHARE, LEAST_LOG_ODDS = 4, 0.01, 2.0


def features_of(word: bytes) -> list[bytes]:
    word = word.strip(STRIP)
    if not word or not word[:1].isalpha() and word[0] < 128:
        return []
    text = word.decode("utf-8", "replace")
    return [b"w=" + word] + [b"p=" + text[:k].encode() for k in PREFIXES if len(text) > k + 1]


def sampled(docs: DataFrame, labels: DataFrame, label: str, size: int) -> DataFrame:
    """(doc_id, label) of at most ``size`` labelled documents, in the order of a hash, half of each class first."""
    known = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("bigint").alias("doc_id")).agg(F.max(label).cast("int").alias("label"))
    parts = [lowest_hashes(known.where(F.col("label") == k), F.xxhash64("doc_id"), size // 2, "doc_id") for k in (0, 1)]
    return parts[0].unionByName(parts[1])


class Ordinal:
    """weights (features), first threshold and the logs of the steps between thresholds."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray):
        self.weights, self.thresholds = weights, thresholds

    def distribution(self, score: np.ndarray) -> np.ndarray:
        below = 1 / (1 + np.exp(-np.clip(self.thresholds[None, :] - score[:, None], -35, 35)))
        return np.diff(np.c_[np.zeros(len(score)), below, np.ones(len(score))], axis=1)

    @staticmethod
    def fit(rows: np.ndarray, columns: np.ndarray, values: np.ndarray, grades: np.ndarray, size: int, ridge: float = 2e-3, steps: int = 400) -> "Ordinal":
        """Adaptive-moment ascent of the likelihood on sparse rows (row, column, value)."""
        n, cuts = len(grades), GRADES - 1
        params = np.r_[np.zeros(size), 2.0, np.zeros(cuts - 1)]
        m, v = np.zeros_like(params), np.zeros_like(params)
        for step in range(1, steps + 1):
            w, steps_log = params[:size], params[size + 1 :]
            theta = params[size] + np.r_[0, np.cumsum(np.exp(steps_log))]
            score = np.bincount(rows, weights=values * w[columns], minlength=n)
            below = 1 / (1 + np.exp(-np.clip(theta[None, :] - score[:, None], -35, 35)))
            cumulative = np.c_[np.zeros(n), below, np.ones(n)]
            slope = np.c_[np.zeros(n), below * (1 - below), np.zeros(n)]
            i = np.arange(n)
            p = np.maximum(cumulative[i, grades + 1] - cumulative[i, grades], 1e-12)
            up, low = slope[i, grades + 1] / p, slope[i, grades] / p
            by_score = low - up
            by_theta = np.array([(up[grades == j]).sum() - (low[grades == j + 1]).sum() for j in range(cuts)])
            grad = np.r_[
                np.bincount(columns, weights=values * by_score[rows], minlength=size) / n - ridge * w / 10,
                by_theta.sum() / n,
                np.array([by_theta[j:].sum() for j in range(1, cuts)]) * np.exp(steps_log) / n,
            ]
            m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad * grad
            params = params + 0.05 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
        return Ordinal(params[:size], params[size] + np.r_[0, np.cumsum(np.exp(params[size + 1 :]))])


def feature_kernel(index_of, grown: int = 300_000):
    """word -> indices of its kept features, remembered for a bounded number of words."""
    cache: dict[bytes, tuple[int, ...]] = {}

    def find(word: bytes) -> tuple[int, ...]:
        got = cache.get(word)
        if got is None:
            got = tuple(index_of[f] for f in features_of(word) if f in index_of)
            if len(cache) >= grown:
                cache.clear()
            cache[word] = got
        return got

    return find


def sparse(body: bytes | None, find, words: frozenset, extra: int) -> dict[int, float]:
    """Feature values of a text; feature ``extra`` is its share of words whose own feature is kept."""
    hits: dict[int, int] = {}
    tokens, toxic = (body or b"").lower().split(), 0
    for word in tokens:
        got = find(word)
        if got:
            toxic += not words.isdisjoint(got)
            for k in got:
                hits[k] = hits.get(k, 0) + 1
    values = {k: float(np.log1p(c)) for k, c in hits.items()}
    if toxic:
        values[extra] = float(2.5 * np.log1p(100 * toxic / len(tokens)))
    return values


def words_in(index: dict[bytes, int]) -> frozenset:
    return frozenset(i for f, i in index.items() if f.startswith(b"w="))


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> tuple[dict[bytes, int], Ordinal]:
    spark = docs.sparkSession
    chosen = sampled(docs, labels, "toxic", sample)
    # at most ``sample`` rows of two numbers; copies of one text are one example
    texts = text_bytes(docs).join(F.broadcast(chosen), "doc_id").groupBy("body").agg(F.max("label").alias("label"))
    texts = checkpoint(texts.withColumn("half", F.pmod(F.xxhash64("body"), F.lit(2)).cast("int")))
    schema = "feature binary, label int, half int"
    arrow = arrow_schema(spark, schema)

    def explode(batches):
        for part in chunks(batches):
            columns: tuple[list, list, list] = [], [], []
            for body, label, half in zip(*(c.to_pylist() for c in part.columns)):
                own = {f for w in set((body or b"").lower().split()) for f in features_of(w)}
                for column, values in zip(columns, (own, [label] * len(own), [half] * len(own))):
                    column.extend(values)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, arrow.types)], schema=arrow)

    sizes = {(r["label"], r["half"]): r["count"] for r in texts.groupBy("label", "half").count().collect()}
    totals = [[sum(sizes.get((label, h), 0) for h in halves) for label in (0, 1)] for halves in ((0, 1), (0,), (1,))]
    if not all(totals[0]):
        return {}, Ordinal(np.zeros(1), np.array([35.0] * (GRADES - 1)))
    sums = [F.sum(((F.col("label") == label) & F.col("half").isin(halves)).cast("int")).alias(f"n{label}_{k}") for k, halves in enumerate(([0, 1], [0], [1])) for label in (0, 1)]
    counts = checkpoint(texts.mapInArrow(explode, schema).groupBy("feature").agg(*sums))
    found = []
    for k, (clean, toxic) in enumerate(totals):
        odds = F.log((F.col(f"n1_{k}") + 0.5) / (toxic + 1)) - F.log((F.col(f"n0_{k}") + 0.5) / (clean + 1))
        able = counts.where(F.col(f"n1_{k}") >= max(LEAST_DOCS, LEAST_SHARE * toxic)).withColumn("odds", odds).where(F.col("odds") > LEAST_LOG_ODDS)
        found.append([bytes(r["feature"]) for r in able.orderBy(F.desc(F.col("odds") * F.sqrt(f"n1_{k}")), "feature").limit(FEATURES).collect()])
    index = {f: i for i, f in enumerate(found[0])}
    # the words by which a text is graded are those of the other half
    lexicon = [frozenset(f[2:] for f in found[2 - half] if f.startswith(b"w=")) for half in (0, 1)]
    shared = spark.sparkContext.broadcast((index, lexicon))
    schema = "label int, share double, columns array<int>, values array<double>"
    narrow = arrow_schema(spark, schema)

    def encode(batches):
        index, lexicon = shared.value
        find, own = feature_kernel(index), words_in(index)
        for part in chunks(batches):
            rows = []
            for body, label, half in zip(*(c.to_pylist() for c in part.columns)):
                words = [w.strip(STRIP) for w in (body or b"").lower().split()] if label else []
                share = sum(w in lexicon[half] for w in words) / max(1, len(words))
                values = sparse(body, find, own, len(index))
                rows.append((label, share, list(values), list(values.values())))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), narrow.types)], schema=narrow)

    rows = texts.select("body", "label", "half").mapInArrow(encode, schema).collect()  # at most ``sample`` rows of the kept features
    label = np.array([r["label"] for r in rows])
    share = np.array([r["share"] for r in rows])
    cuts = np.quantile(share[label == 1], [1 / 3, 2 / 3])
    grades = np.where(label == 1, 1 + (share > cuts[0]) + (share > cuts[1]), 0).astype("int64")
    at = np.repeat(np.arange(len(rows)), [len(r["columns"]) for r in rows]).astype("int64")
    columns = np.array([c for r in rows for c in r["columns"]], dtype="int64")
    values = np.array([x for r in rows for x in r["values"]], dtype="float64")
    return index, Ordinal.fit(at, columns, values, grades, len(index) + 1)


RESULT = "doc_id long, toxic boolean, severity int, expected_severity double, p_toxic double"


def score(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, toxic, severity, expected_severity, p_toxic of every document."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(fit(docs, labels, sample))
    arrow = arrow_schema(spark, RESULT)

    def run(batches):
        index, model = shared.value
        find, own = feature_kernel(index), words_in(index)
        for part in chunks(batches):
            scores = np.zeros(part.num_rows)
            for i, body in enumerate(part.column(1).to_pylist()):
                scores[i] = sum(model.weights[k] * x for k, x in sparse(body, find, own, len(index)).items())
            p = model.distribution(scores)
            mean = p @ np.arange(GRADES)
            columns = [part.column(0), pa.array(p[:, 0] < 0.5), pa.array(p.argmax(axis=1).astype("int32")), pa.array(mean), pa.array(1 - p[:, 0])]
            yield pa.RecordBatch.from_arrays(columns, schema=arrow)

    return text_bytes(docs).mapInArrow(run, RESULT)
