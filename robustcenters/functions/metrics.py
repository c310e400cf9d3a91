"""Distances with two faces: a Catalyst column and a numpy block kernel.

``Metric.expr(a, b)`` keeps a distance inside whole-stage code; ``Metric.block(A, B)`` gives the matrix that the
covering and solving kernels use on Arrow batches. Only functions with the triangle inequality are marked as metrics;
certified runs refuse the others.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Metric:
    name: str
    kind: str  # scalar, vector, string, set
    is_metric: bool
    expr: Callable[[Column, Column], Column]
    block: Callable[[np.ndarray, np.ndarray], np.ndarray]
    #: The column against a vector that is known, coordinate by coordinate; without higher-order functions.
    near: Callable[[Column, list[float]], Column] | None = None

    def load(self, column: pa.Array | pa.ChunkedArray) -> np.ndarray:
        """Payload column to a numpy array of n entries (objects for strings), sets to Sets."""
        if isinstance(column, pa.ChunkedArray):
            column = column.combine_chunks()
        n = len(column)
        if self.kind == "scalar":
            return column.to_numpy(zero_copy_only=False).astype("float64")
        if self.kind == "vector":
            flat = column.flatten().to_numpy(zero_copy_only=False).astype("float64")
            return flat.reshape(n, -1) if n else flat.reshape(0, 1)
        if self.kind == "set":
            return Sets.of(column)
        out = np.empty(n, dtype=object)
        values = column.to_pylist()
        for i in range(n):
            out[i] = values[i]
        return out


def _fold(a: Column, b: Column, term) -> Column:
    return F.aggregate(F.zip_with(a, b, term), F.lit(0.0), lambda s, x: s + x)


def _sum(terms) -> Column:
    total = F.lit(0.0)
    for x in terms:
        total = total + x
    return total


def _chunked(step: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """Keep the (rows, columns, dimension) temporary of a vector kernel under about 32 MB."""

    def run(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        rows = max(1, int(4e6 // max(1, b.size)))
        if len(a) <= rows:
            return step(a, b)
        return np.concatenate([step(a[i : i + rows], b) for i in range(0, len(a), rows)])

    return run


def _distinct(step: Callable[[list, list], np.ndarray]) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """A kernel on the distinct values of both sides, spread to all pairs."""

    def run(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        x, i = np.unique(a.astype(str), return_inverse=True)
        y, j = np.unique(b.astype(str), return_inverse=True)
        return step(x.tolist(), y.tolist()).reshape(len(x), len(y))[np.ix_(i, j)]

    return run


def edit_distances(a: list[str], b: list[str]) -> np.ndarray:
    """Levenshtein distances of every string of a to all of b at once.

    A row of the usual table is taken for all of b together; the step along a row is a running minimum.
    """
    sizes = np.array([len(y) for y in b], dtype="int64")
    width = int(sizes.max(initial=0))
    codes = np.full((len(b), width), -1, dtype="int64")
    for j, y in enumerate(b):
        codes[j, : len(y)] = [ord(c) for c in y]
    along, out = np.arange(width + 1), np.zeros((len(a), len(b)))
    for i, x in enumerate(a):
        row = np.tile(along, (len(b), 1))
        for at, c in enumerate(x, 1):
            new = np.empty_like(row)
            new[:, 0] = at
            new[:, 1:] = np.minimum(row[:, 1:] + 1, row[:, :-1] + (codes != ord(c)))
            row = np.minimum.accumulate(new - along, axis=1) + along
        out[i] = row[np.arange(len(b)), sizes]
    return out


def jaccard(x: frozenset, y: frozenset) -> float:
    both = len(x & y)
    union = len(x) + len(y) - both
    return 1 - both / union if union else 0.0


class Sets:
    """Sets of words as numbers: row i has the ascending ``codes[at[i]:at[i + 1]]``, which count in ``words``. Indexed like an array of sets."""

    def __init__(self, words: pa.Array, codes: np.ndarray, at: np.ndarray):
        self.words, self.codes, self.at = words, codes, at

    @staticmethod
    def of(values) -> "Sets":
        if isinstance(values, Sets):
            return values
        column = values if isinstance(values, pa.Array) else pa.array([sorted(x) for x in values], pa.list_(pa.string()))
        sizes = pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype("int64")
        found = column.flatten().dictionary_encode(null_encoding="encode")
        most, numbers, at = max(1, len(found.dictionary)), found.indices.to_numpy(zero_copy_only=False), np.r_[0, np.cumsum(sizes)]
        codes, counts, lo = [np.zeros(0, dtype="int32")], [np.zeros(0, dtype="int64")], 0
        while lo < len(sizes):
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + CELLS, side="right")) - 1)
            key = np.unique(np.repeat(np.arange(hi - lo) * most, sizes[lo:hi]) + numbers[at[lo] : at[hi]])
            codes.append((key % most).astype("int32"))
            counts.append(np.bincount(key // most, minlength=hi - lo))
            lo = hi
        return Sets(found.dictionary, np.concatenate(codes), np.r_[0, np.cumsum(np.concatenate(counts))].astype("int64"))

    def __len__(self) -> int:
        return len(self.at) - 1

    def sizes(self) -> np.ndarray:
        return np.diff(self.at)

    def rows(self) -> np.ndarray:
        """The row of each code."""
        return np.repeat(np.arange(len(self)), self.sizes())

    def __getitem__(self, rows) -> "Sets":
        rows = np.arange(len(self))[rows].reshape(-1)
        sizes = self.sizes()[rows]
        return Sets(self.words, self.codes[runs(self.at[rows], sizes)], np.r_[0, np.cumsum(sizes)].astype("int64"))

    def like(self, other: "Sets") -> "Sets":
        """The same sets with the other's numbers; words that it lacks follow after its own."""
        if self.words is other.words:
            return self
        place = pc.index_in(self.words, value_set=other.words)
        new = place.is_null().to_numpy(zero_copy_only=False)
        number = pc.fill_null(place, -1).to_numpy(zero_copy_only=False).astype("int64")
        number[new] = len(other.words) + np.arange(new.sum())
        return Sets(other.words, number[self.codes].astype("int32"), self.at)


def runs(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers from each start on, as many as its size says."""
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())


#: Common words of set distances that are held in matrices at a time, pairs of sets with a rarer word that are counted at a time, and what such a pair costs more than one in a matrix.
CELLS, PAIRS, DEARER = 1 << 22, 1 << 21, 285


def _jaccard_block(a, b) -> np.ndarray:
    """Set distances: words in many pairs are counted by one matrix product, all others along the lists of their sets."""
    a = Sets.of(a)
    b = Sets.of(b).like(a)
    if len(a) < len(b):
        return _jaccard_block(b, a).T
    sizes, other, out = a.sizes(), b.sizes(), np.zeros((len(a), len(b)))
    if not out.size:
        return out
    n = int(max(a.codes.max(initial=-1), b.codes.max(initial=-1))) + 1
    by = np.argsort(b.codes, kind="stable")
    b_rows, held = b.rows()[by], np.bincount(b.codes, minlength=n)
    first = np.cumsum(held) - held
    often = np.flatnonzero(np.bincount(a.codes, minlength=n) * held * DEARER >= out.size)
    column = np.full(n, -1)
    column[often] = np.arange(len(often))
    marks = np.zeros((len(b), len(often)), dtype="float32")
    at = column[b.codes]
    marks[b.rows()[at >= 0], at[at >= 0]] = 1
    step = max(1, min(CELLS // max(1, len(often)), CELLS // len(b)))
    for lo in range(0, len(a), step):
        size = min(step, len(a) - lo)
        r, c = np.repeat(np.arange(size), sizes[lo : lo + size]), a.codes[a.at[lo] : a.at[lo + size]]
        r, c = r[held[c] > 0], c[held[c] > 0]
        at = column[c]
        own = np.zeros((size, len(often)), dtype="float32")
        own[r[at >= 0], at[at >= 0]] = 1
        both = (own @ marks.T).astype("float64")
        r, c = r[at < 0], c[at < 0]
        until = np.cumsum(held[c])
        begin = 0
        while begin < len(c):
            end = max(begin + 1, int(np.searchsorted(until, (until[begin - 1] if begin else 0) + PAIRS, side="right")))
            places = np.repeat(r[begin:end] * len(b), held[c[begin:end]]) + b_rows[runs(first[c[begin:end]], held[c[begin:end]])]
            if 20 * len(places) > both.size:
                both += np.bincount(places, minlength=both.size).reshape(both.shape)
            else:
                np.add.at(both.reshape(-1), places, 1.0)
            begin = end
        union = sizes[lo : lo + size, None] + other[None] - both
        out[lo : lo + size] = np.where(union > 0, 1 - both / np.maximum(union, 1), 0.0)
    return out


def _unit(a: np.ndarray) -> np.ndarray:
    return a / np.maximum(np.linalg.norm(a, axis=1, keepdims=True), 1e-300)


def _cos(a: Column, b: Column) -> Column:
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
    return F.greatest(F.lit(-1.0), F.least(F.lit(1.0), _fold(a, b, lambda x, y: x * y) / (norm(a) * norm(b))))


EARTH_KM = 6371.0088


def _haversine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    p, q = np.radians(a)[:, None], np.radians(b)[None]
    h = np.sin((q[..., 0] - p[..., 0]) / 2) ** 2 + np.cos(p[..., 0]) * np.cos(q[..., 0]) * np.sin((q[..., 1] - p[..., 1]) / 2) ** 2
    return 2 * EARTH_KM * np.arcsin(np.sqrt(np.clip(h, 0, 1)))


def _haversine_expr(a: Column, b: Column) -> Column:
    lat1, lon1, lat2, lon2 = (F.radians(c) for c in (a[0], a[1], b[0], b[1]))
    h = F.pow(F.sin((lat2 - lat1) / 2), 2) + F.cos(lat1) * F.cos(lat2) * F.pow(F.sin((lon2 - lon1) / 2), 2)
    return F.asin(F.sqrt(F.least(F.lit(1.0), h))) * (2 * EARTH_KM)


def lp(p: float) -> Metric:
    if p < 1:
        raise ValueError("p must be at least 1")
    return Metric(
        f"l{p:g}", "vector", True,
        lambda a, b: F.pow(_fold(a, b, lambda x, y: F.pow(F.abs(x - y), F.lit(p))), F.lit(1 / p)),
        _chunked(lambda a, b: (np.abs(a[:, None] - b[None]) ** p).sum(-1) ** (1 / p)),
    )


def weighted_sum(name: str, parts: list[tuple[float, "Metric", list[int]]]) -> Metric:
    """Nonnegative combination of metrics on groups of coordinates of a vector payload."""
    if any(c < 0 for c, _, _ in parts):
        raise ValueError("coefficients must not be negative")

    def pick(m: Metric, v: Column, at: list[int]) -> Column:
        return v[at[0]] if m.kind == "scalar" else F.array(*[v[i] for i in at])

    def expr(a: Column, b: Column) -> Column:
        total = F.lit(0.0)
        for c, m, at in parts:
            total = total + F.lit(float(c)) * m.expr(pick(m, a, at), pick(m, b, at))
        return total

    def block(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return sum(c * m.block(*(v[:, at[0]] if m.kind == "scalar" else v[:, at] for v in (a, b))) for c, m, at in parts)

    return Metric(name, "vector", all(m.is_metric for _, m, _ in parts), expr, block)


ABS = Metric("abs", "scalar", True, lambda a, b: F.abs(a - b), lambda a, b: np.abs(a[:, None] - b[None]))
L1 = Metric("l1", "vector", True, lambda a, b: _fold(a, b, lambda x, y: F.abs(x - y)), _chunked(lambda a, b: np.abs(a[:, None] - b[None]).sum(-1)), lambda a, c: _sum(F.abs(a[i] - x) for i, x in enumerate(c)))
L2 = Metric("l2", "vector", True, lambda a, b: F.sqrt(_fold(a, b, lambda x, y: (x - y) * (x - y))), _chunked(lambda a, b: np.sqrt(((a[:, None] - b[None]) ** 2).sum(-1))), lambda a, c: F.sqrt(_sum((a[i] - x) * (a[i] - x) for i, x in enumerate(c))))
LINF = Metric("linf", "vector", True, lambda a, b: F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y))), _chunked(lambda a, b: np.abs(a[:, None] - b[None]).max(-1)), lambda a, c: F.greatest(*[F.abs(a[i] - x) for i, x in enumerate(c)], F.lit(0.0)))
SQUARED = Metric("squared_l2", "vector", False, lambda a, b: _fold(a, b, lambda x, y: (x - y) * (x - y)), _chunked(lambda a, b: ((a[:, None] - b[None]) ** 2).sum(-1)))
ANGULAR = Metric("angular", "vector", True, lambda a, b: F.acos(_cos(a, b)), lambda a, b: np.arccos(np.clip(_unit(a) @ _unit(b).T, -1, 1)))
COSINE = Metric("one_minus_cos", "vector", False, lambda a, b: 1 - _cos(a, b), lambda a, b: 1 - np.clip(_unit(a) @ _unit(b).T, -1, 1))
HAMMING = Metric("hamming", "vector", True, lambda a, b: F.size(F.filter(F.zip_with(a, b, lambda x, y: x != y), lambda x: x)).cast("double"), _chunked(lambda a, b: (a[:, None] != b[None]).sum(-1).astype("float64")))
DISCRETE = Metric("discrete", "string", True, lambda a, b: (a != b).cast("double"), _distinct(lambda x, y: (np.array(x)[:, None] != np.array(y)[None]).astype("float64")))
EDIT = Metric("edit", "string", True, lambda a, b: F.levenshtein(a, b).cast("double"), _distinct(edit_distances))
JACCARD = Metric(
    "jaccard", "set", True,
    lambda a, b: F.when(F.size(F.array_union(a, b)) == 0, 0.0).otherwise(1 - F.size(F.array_intersect(a, b)) / F.size(F.array_union(a, b))),
    _jaccard_block,
)
HAVERSINE = Metric("haversine", "vector", True, _haversine_expr, _haversine)
#: Payload (nation, region): 0 in a nation, 1 in a region, 2 beyond.
ULTRA = Metric(
    "ultra", "vector", True,
    lambda a, b: F.when(a[0] == b[0], 0.0).when(a[1] == b[1], 1.0).otherwise(2.0),
    lambda a, b: np.where(a[:, None, 0] == b[None, :, 0], 0.0, np.where(a[:, None, 1] == b[None, :, 1], 1.0, 2.0)),
)
BALANCE_AND_PLACE = weighted_sum("balance_and_place", [(1.0, ABS, [0]), (1.0, ULTRA, [1, 2])])

REGISTRY = {m.name: m for m in (ABS, L1, L2, LINF, SQUARED, ANGULAR, COSINE, HAMMING, DISCRETE, EDIT, JACCARD, HAVERSINE, ULTRA, BALANCE_AND_PLACE)}


def lookup(name: str, table: list[list[float]], most: int = 1000) -> Metric:
    """A metric given by its matrix; payloads are indices. Small matrices only, as the table becomes a literal."""
    matrix = np.array(table, dtype="float64")
    if matrix.shape != (len(table), len(table)) or len(table) > most or (matrix != matrix.T).any() or matrix.diagonal().any() or (matrix < 0).any():
        raise ValueError("need a symmetric matrix without negative entries, zero on the diagonal, of a bounded size")
    triangle = bool((matrix[:, None, :] <= matrix[:, :, None] + matrix[None, :, :] + 1e-9).all()) if len(table) <= 200 else False
    at = lambda a, b: F.element_at(F.lit(matrix.ravel().tolist()), (a * len(table) + b + 1).cast("int"))
    return Metric(name, "scalar", triangle, at, lambda a, b: matrix[np.ix_(a.astype("int64"), b.astype("int64"))])


def get(metric: str | Metric) -> Metric:
    return metric if isinstance(metric, Metric) else REGISTRY[metric]


def register(metric: Metric) -> Metric:
    """Make a metric of one's own known by name."""
    REGISTRY[metric.name] = metric
    return metric


#: Points of which all triples are looked at.
MOST_TRIPLES = 400


def axiom_violations_along(points: DataFrame, metric: str | Metric, slack: float = 1e-9) -> DataFrame:
    """One row (identity, symmetry, triangle, triples): violations over a whole table, each point with the next two ids."""
    m = get(metric)
    one, two = (points.select((F.col("pid") - n).alias("pid"), F.col("pt").alias(c)) for n, c in ((1, "y"), (2, "z")))
    d = lambda a, b: m.expr(F.col(a), F.col(b))
    t = points.select("pid", F.col("pt").alias("x")).join(one, "pid").join(two, "pid")
    t = t.select(d("x", "x").alias("xx"), d("x", "y").alias("xy"), d("y", "x").alias("yx"), d("y", "z").alias("yz"), d("x", "z").alias("xz"))
    return t.agg(
        F.count_if(F.abs("xx") > 1e-6).alias("identity"), F.count_if(F.abs(F.col("xy") - F.col("yx")) > slack).alias("symmetry"),
        F.count_if(F.col("xz") > F.col("xy") + F.col("yz") + slack).alias("triangle"), F.count("*").alias("triples"),
    )


def axiom_violations(points: DataFrame, metric: str | Metric, slack: float = 1e-9) -> DataFrame:
    """One row (identity, symmetry, triangle): violations over all triples of a small point table, whose size is checked."""
    m, n = get(metric), points.count()
    if n > MOST_TRIPLES:
        raise ValueError(f"{n} points are over {MOST_TRIPLES}; use axiom_violations_along")
    a, b = points.select(F.col("pid").alias("i"), F.col("pt").alias("x")), points.select(F.col("pid").alias("j"), F.col("pt").alias("y"))
    d = a.crossJoin(b).select("i", "j", m.expr(F.col("x"), F.col("y")).alias("d"))
    there, back, on = d, d.select(F.col("j").alias("i"), F.col("i").alias("j"), F.col("d").alias("r")), d.select(F.col("i").alias("j"), F.col("j").alias("h"), F.col("d").alias("e"))
    direct = d.select("i", F.col("j").alias("h"), F.col("d").alias("f"))
    triples = there.join(on, "j").join(direct, ["i", "h"])
    return (
        d.agg(F.count_if((F.col("i") == F.col("j")) & (F.abs("d") > 1e-6)).alias("identity"))
        .crossJoin(there.join(back, ["i", "j"]).agg(F.count_if(F.abs(F.col("d") - F.col("r")) > slack).alias("symmetry")))
        .crossJoin(triples.agg(F.count_if(F.col("f") > F.col("d") + F.col("e") + slack).alias("triangle")))
    )
