"""Weighted solvers with outliers for the last round, on the distance matrix of a coreset.

Each takes (distances (n, n), weights, k, z) and returns a Solution of indices. Outliers are a mass per point
(0..w), so a heavy point may be forgotten in part. The gathered coreset runs as one Arrow group, whose size is checked.
Many points on a line need no matrix: equal ones are one weighted point, and sums over all candidates come from a sweep.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import ABS, Metric, get

MAX_ROWS = 8000
#: Points on a line from which no matrix is made, and how many one task takes.
DENSE, MAX_LINE = 2000, 8_000_000
#: Points of any metric that the solvers without a matrix take in one task.
MATRIX_FREE, MAX_FREE = {"alternate"}, 200_000
STARTS = 3
#: Entries of a distance table that are held at a time beside the matrix.
CELLS = 1 << 22


@dataclass
class Solution:
    centers: np.ndarray
    outliers: np.ndarray
    cost: float
    stats: dict = field(default_factory=dict)


def _power(x: np.ndarray, power: int) -> np.ndarray:
    return x if power == 1 else x * x if power == 2 else x**power


class Line:
    """Distances of points on a line; the parts of the matrix that are asked for are made then."""

    def __init__(self, x: np.ndarray):
        self.x, self.order = x, np.argsort(x, kind="stable")
        self.middle = float(x.mean())
        self.sorted = x[self.order] - self.middle

    def __getitem__(self, at):
        rows, columns = at if isinstance(at, tuple) else (at, slice(None))
        return np.round(np.abs(self.x[rows][:, None] - self.x[columns][None]), 9)

    def served(self, own: np.ndarray, w: np.ndarray, limit: np.ndarray, power: int) -> np.ndarray:
        """Each of ``own`` is counted with a difference of running sums over the candidates that are nearer than its limit."""
        n, v, w, limit = len(self.x), self.x[own] - self.middle, w[own].astype("float64"), limit[own]
        lo, hi = np.searchsorted(self.sorted, v - limit), np.searchsorted(self.sorted, v + limit, side="right")
        within = lambda a, b, y: np.cumsum(np.bincount(a, y, n + 1) - np.bincount(b, y, n + 1))[:n]
        else_ = np.where(np.isfinite(limit), w * _power(np.where(np.isfinite(limit), limit, 0.0), power), 0.0)
        sums = else_.sum() - within(lo, hi, else_)
        if power == 2:
            sums += within(lo, hi, w * v * v) - 2 * self.sorted * within(lo, hi, w * v) + self.sorted**2 * within(lo, hi, w)
        else:
            at = np.searchsorted(self.sorted, v)
            sums += within(lo, at, w * v) - self.sorted * within(lo, at, w) + self.sorted * within(at, hi, w) - within(at, hi, w * v)
        out = np.empty(n)
        out[self.order] = np.maximum(sums, 0.0)
        return out


class Apart:
    """Distances of many points of any metric; the parts of the matrix that are asked for are made then."""

    def __init__(self, m: Metric, points):
        self.m, self.points = m, points

    def __getitem__(self, at):
        rows, columns = at if isinstance(at, tuple) else (at, slice(None))
        return np.round(self.m.block(self.points[rows], self.points[columns]), 9)

    def sums(self, own: np.ndarray, w: np.ndarray, power: int) -> np.ndarray:
        """For each of ``own``, what it costs to serve all of them."""
        points, mass, total = self.points[own], w[own].astype("float64"), np.zeros(len(own))
        step = max(1, CELLS // max(1, len(own)))
        for lo in range(0, len(own), step):
            total += mass[lo : lo + step] @ _power(np.round(self.m.block(points[lo : lo + step], points), 9), power)
        return total


def served(d, own: np.ndarray, w: np.ndarray, limit: np.ndarray, power: int) -> np.ndarray:
    """For every candidate, what ``own`` costs if each goes to the candidate or pays its limit."""
    if isinstance(d, Line) and power in (1, 2):
        return d.served(own, w, limit, power)
    step = max(1, CELLS // len(w))
    parts = [own[i : i + step] for i in range(0, len(own), step)] or [own]
    return sum(w[x] @ _power(np.minimum(limit[x, None], d[x]), power) for x in parts)


def trim(dist: np.ndarray, w: np.ndarray, z: int) -> np.ndarray:
    """Outlier mass of each point: z units from the farthest on, ties by index."""
    order = np.lexsort((np.arange(len(dist)), -np.round(dist, 9)))
    before = np.cumsum(w[order]) - w[order]
    out = np.zeros(len(w), dtype="int64")
    out[order] = np.clip(z - before, 0, w[order])
    return out


def trimmed_cost(d: np.ndarray, w: np.ndarray, centers, z: int, power: int) -> float:
    near = d[:, centers].min(axis=1)
    return float(((w - trim(near, w, z)) * near**power).sum())


def _finish(d, w, centers, z, power, stats, outliers=None) -> Solution:
    centers = np.array(sorted(centers))
    near = d[:, centers].min(axis=1)
    outliers = trim(near, w, z) if outliers is None else outliers
    return Solution(centers, outliers, float(((w - outliers) * near**power).sum()), stats)


def exhaustive(d, w, k, z, power=2, max_combinations=300_000, **_) -> Solution:
    """The optimum (ratio 1)."""
    n = len(w)
    k = min(k, n)
    if math.comb(n, k) > max_combinations:
        raise ValueError(f"{math.comb(n, k)} subsets are over the limit of {max_combinations}")
    best, chosen = np.inf, None
    for s in combinations(range(n), k):
        c = trimmed_cost(d, w, list(s), z, power)
        if c < best - 1e-9:
            best, chosen = c, s
    return _finish(d, w, chosen, z, power, {"trials": math.comb(n, k), "alpha": 1})


def starting_centers(d, w, k, init="first_ids", seed=42, power=2) -> list[int]:
    n = len(w)
    k = min(k, n)
    if init == "first_ids":
        return list(range(k))
    rng = np.random.default_rng(seed)
    chosen = [0] if init == "farthest" else [int(rng.choice(n, p=w / w.sum()))]
    while len(chosen) < k:
        near = d[:, chosen].min(axis=1)
        mass = near if init == "farthest" else w * near**power
        if mass.sum() <= 0:
            break
        chosen.append(int(mass.argmax()) if init == "farthest" else int(rng.choice(n, p=mass / mass.sum())))
    return chosen


def swap_search(d, w, centers, power, gain: float, stats: dict, max_moves: int = 500) -> list[int]:
    """Single swaps without outliers on the mass w, until none improves the cost by the factor 1 - gain."""
    centers = list(centers)
    for _ in range(max_moves):
        table = d[:, centers]
        order = np.sort(table, axis=1)
        owner, first = table.argmin(axis=1), order[:, 0]
        second = order[:, 1] if len(centers) > 1 else np.full(len(w), np.inf)
        now = float((w * first**power).sum())
        # of every cluster: what its points cost if a point is opened, with their center kept and with it closed
        kept, closed = np.empty((len(centers), len(w))), np.empty((len(centers), len(w)))
        for c in range(len(centers)):
            own = np.flatnonzero((owner == c) & (w > 0))
            kept[c], closed[c] = (served(d, own, w, limit, power) for limit in (first, second))
        totals = np.stack([closed[c] + kept[:c].sum(axis=0) + kept[c + 1 :].sum(axis=0) for c in range(len(centers))])
        stats["trials"] = stats.get("trials", 0) + totals.size
        out, new = np.unravel_index(int(totals.argmin()), totals.shape)
        if not totals[out, new] < (1 - gain) * now or now <= 0:
            break
        centers[out] = int(new)
        stats["moves"] = stats.get("moves", 0) + 1
    return centers


def _opened(d, candidates: np.ndarray, near: np.ndarray, w: np.ndarray, some: np.ndarray, z: int, power: int) -> np.ndarray:
    """The trimmed cost with each candidate opened; near: what every point has without it, some: the points of positive mass."""
    table = np.minimum(near[:, None], d[:, candidates])
    terms = w[:, None] * _power(table, power)
    if z > 0:
        # z units lie on the z farthest points of positive mass at most
        most = min(z, len(some))
        far = some[np.argpartition(table[some], len(some) - most, axis=0)[len(some) - most :]] if most < len(some) else np.tile(some[:, None], (1, table.shape[1]))
        dist = np.take_along_axis(table, far, axis=0)
        order = np.argsort(-dist, axis=0, kind="stable")
        far, dist = np.take_along_axis(far, order, axis=0), np.take_along_axis(dist, order, axis=0)
        ww = w[far]
        left = ww - np.clip(z - (np.cumsum(ww, axis=0) - ww), 0, ww)
        np.put_along_axis(terms, far, left * _power(dist, power), axis=0)
    return terms.sum(axis=0)


def best_swap(d, w, centers, z, power, stats: dict) -> list[int]:
    """The best single swap over all points under the trimmed cost.

    On a line a candidate costs no less than its untrimmed cost without the z dearest units of the points' limits, so candidates
    are tried in the order of this bound until it is no better than what was found.
    """
    best, found, some = np.inf, list(centers), np.flatnonzero(w > 0)
    step = max(1, CELLS // len(w))
    for c in range(len(centers)):
        rest = centers[:c] + centers[c + 1 :]
        near = d[:, rest].min(axis=1) if rest else np.full(len(w), np.inf)
        order, bound = np.arange(len(w)), np.full(len(w), -np.inf)
        if isinstance(d, Line) and rest:
            whole = served(d, some, w, near, power)
            bound = whole - float((trim(near, w, z) * _power(near, power)).sum()) - 1e-9 * np.abs(whole)
            order = np.argsort(bound, kind="stable")
        for at in range(0, len(order), step):
            own = order[at : at + step]
            if bound[own[0]] >= best:
                break
            totals = _opened(d, own, near, w, some, z, power)
            stats["trials"] = stats.get("trials", 0) + len(totals)
            if totals.min() < best - 1e-12:
                best, found = float(totals.min()), rest + [int(own[totals.argmin()])]
    return found


def trimmed_swap(d, w, k, z, power=2, eps=0.1, init="first_ids", max_passes=60, outlier_cap: int | None = None, seed=42, **_) -> Solution:
    """Local search whose outlier mass only grows (ratio 274 with k centers, if it ends by itself).

    A pass takes the cheaper of two options: swaps on the inliers and z more units forgotten (masses add up, they do
    not overlap), or the best swap over everything, joined with its own z farthest units (the larger mass counts). It is
    kept if the cost falls by the factor 1 - eps / k against the pair that the pass began with. With ``outlier_cap`` only
    options within it are open, the swaps with the mass as it was among them; if a better one was closed, no ratio is reported.
    """
    stats: dict = {"alpha": 274, "passes": 0, "trials": 0, "moves": 0, "stopped_by_cap": False}
    centers = starting_centers(d, w, k, init, seed, power)
    out = trim(d[:, centers].min(axis=1), w, z)
    value = lambda c, o: float(((w - o) * d[:, c].min(axis=1) ** power).sum())
    now, stop = value(centers, out), eps / max(1, k)
    stats["start_cost"], settled = now, False
    for _ in range(max_passes):
        swapped = swap_search(d, w - out, centers, power, stop, stats)
        more = out + trim(np.where(w > out, d[:, swapped].min(axis=1), -1), w - out, z)
        moved = best_swap(d, w, swapped, z, power, stats)
        joined = np.maximum(out, trim(d[:, moved].min(axis=1), w, z))
        options = [(value(swapped, more), swapped, more), (value(moved, joined), moved, joined), (value(swapped, out), swapped, out)]
        able = [x for x in options if outlier_cap is None or x[2].sum() <= max(outlier_cap, out.sum())]
        cost, new, mass = min(able, key=lambda x: x[0])
        stats["stopped_by_cap"] |= len(able) < len(options) and min(x[0] for x in options) < (1 - stop) * min(now, cost)
        settled = not cost < (1 - stop) * now
        if cost <= now:
            centers, out, now = new, mass, cost
        if settled:
            break
        stats["passes"] += 1
    # for the final centers the farthest units of the same mass are never dearer
    out = trim(d[:, centers].min(axis=1), w, int(out.sum()))
    stats["outlier_mass"] = int(out.sum())
    if stats["stopped_by_cap"] or not settled:
        stats["alpha"] = None
    return _finish(d, w, centers, z, power, stats, out)


def multi_swap(d, w, k, z, power=2, eps=0.5, swap_size=2, max_moves=200, candidate_cap: int | None = 400, allow=("swap", "add", "drop"), init="dsq", seed=42, dimension: float | None = None, **_) -> Solution:
    """Exchange up to swap_size centers for up to swap_size points under the trimmed cost, with at most (1 + eps) k centers.

    Single exchanges are searched in full; larger ones over the points with the largest share of the cost, as many as
    ``candidate_cap`` allows (a heuristic, reported), or over all with candidate_cap=None. The ratio 1 + eps is reported only for
    a search that was not capped, ended by itself and exchanged as many points as the doubling dimension, if given, asks for.
    """
    n, most = len(w), max(k, math.floor((1 + eps) * k))
    stats: dict = {"alpha": None, "trials": 0, "moves": 0, "capped": False, "settled": False}
    centers = starting_centers(d, w, k, init, seed, power)
    now, stop = trimmed_cost(d, w, centers, z, power), eps / max(1, k)
    stats["start_cost"] = now

    def moves():
        near = d[:, centers].min(axis=1)
        rank = [int(i) for i in np.argsort(-((w - trim(near, w, z)) * near**power), kind="stable") if i not in centers]
        wide = [i for i in range(n) if i not in centers]
        for q in range(swap_size + 1):
            for u in range(swap_size + 1):
                kind = "add" if not q else "drop" if not u else "swap"
                if q == u == 0 or kind not in allow or not 1 <= len(centers) - q + u <= most:
                    continue
                pool = wide if u <= 1 and q <= 1 or candidate_cap is None else rank[: max(2, int(candidate_cap ** (1 / max(1, u))))]
                stats["capped"] |= len(pool) < len(wide)
                for gone in combinations(range(len(centers)), q):
                    rest = [c for i, c in enumerate(centers) if i not in gone]
                    for new in combinations(pool, u):
                        yield rest + list(new)

    for _ in range(max_moves):
        best, found = (1 - stop) * now, None
        for option in moves():
            stats["trials"] += 1
            c = trimmed_cost(d, w, option, z, power)
            if c < best - 1e-12:
                best, found = c, option
                break
        if found is None:
            stats["settled"] = True
            break
        centers, now = found, best
        stats["moves"] += 1
    if stats["settled"] and not stats["capped"] and dimension is not None and swap_size >= max(1.0, dimension / eps) ** (dimension / eps):
        stats["alpha"] = 1 + eps
    return _finish(d, w, centers, z, power, stats)


def plain_then_trim(d, w, k, z, power=2, eps=0.1, init="dsq", seed=42, **_) -> Solution:
    """Swaps that ignore outliers, trimmed at the end."""
    stats: dict = {"alpha": None}
    centers = swap_search(d, w, starting_centers(d, w, k, init, seed, power), power, eps / max(1, k), stats)
    return _finish(d, w, centers, z, power, stats)


def alternate(d, w, k, z, power=2, iterations=30, init="dsq", seed=42, **_) -> Solution:
    """Trim, then move every center to its cluster's medoid; the cost never rises. Sampled starts are drawn ``STARTS`` times, the cheapest or the first ids begin."""
    starts = [starting_centers(d, w, k, init, seed + i, power) for i in range(STARTS if init == "dsq" else 1)]
    if init == "dsq":
        starts.append(starting_centers(d, w, k, "first_ids"))
    centers = min(starts, key=lambda s: trimmed_cost(d, w, s, z, power))
    now, stats = trimmed_cost(d, w, centers, z, power), {"alpha": None, "passes": 0}
    for _ in range(iterations):
        table = d[:, centers]
        owner, left = table.argmin(axis=1), w - trim(table.min(axis=1), w, z)
        new = []
        for c in range(len(centers)):
            own = np.flatnonzero((owner == c) & (left > 0))
            if len(own) and isinstance(d, Line):
                new.append(int(own[served(d, own, left, np.full(len(w), np.inf), power)[own].argmin()]))
            elif len(own) and isinstance(d, Apart):
                new.append(int(own[d.sums(own, left, power).argmin()]))
            else:
                new.append(int(own[(d[np.ix_(own, own)] ** power * left[own][:, None]).sum(axis=0).argmin()]) if len(own) else centers[c])
        c = trimmed_cost(d, w, new, z, power)
        if not c < now - 1e-12:
            break
        centers, now = new, c
        stats["passes"] += 1
    return _finish(d, w, centers, z, power, stats)


SOLVERS: dict[str, Callable[..., Solution]] = {f.__name__: f for f in (exhaustive, trimmed_swap, multi_swap, plain_then_trim, alternate)}


def register(name: str, solver: Callable[..., Solution]) -> None:
    """Any weighted solver with the same signature fits the slot."""
    SOLVERS[name] = solver


def most_rows(metric: str | Metric, max_rows: int, solver: str = "") -> int:
    """How many points one task solves."""
    return max(max_rows, MAX_LINE if get(metric).name == ABS.name else MAX_FREE if solver in MATRIX_FREE else 0)


def solve_points(m: Metric, pts: np.ndarray, w: np.ndarray, k: int, z: int, solver: str, power: int = 2, **options) -> tuple[Solution, np.ndarray]:
    """(solution, mass of each center) of points in the order of their ids. Many points on a line are solved as weighted distinct ones."""
    back, own, mass = None, pts, w
    if m.name == ABS.name and len(pts) > DENSE:
        _, head, back = np.unique(pts, return_index=True, return_inverse=True)
        rank = np.empty(len(head), dtype="int64")
        rank[np.argsort(head)] = np.arange(len(head))
        head, back = np.sort(head), rank[back]
        own, mass = pts[head], np.bincount(back, weights=w, minlength=len(head)).astype("int64")
    if m.name == ABS.name and len(own) > DENSE:
        d = Line(own)
    elif solver in MATRIX_FREE and len(own) > MAX_ROWS:
        d = Apart(m, own)
    else:
        d = np.empty((len(own), len(own)))
        for i in range(0, len(own), 256):
            d[i : i + 256] = np.round(m.block(own[i : i + 256], own), 9)
    s = SOLVERS[solver](d, mass, min(k, len(own)), z, power, **options)
    held = np.bincount(d[:, s.centers].argmin(axis=1), weights=mass - s.outliers, minlength=len(s.centers))
    if back is not None:
        # what is forgotten of a distinct point is taken from its copies in their order
        order = np.argsort(back, kind="stable")
        before = np.cumsum(w[order]) - w[order]
        starts = np.searchsorted(back[order], np.arange(len(head)))
        before -= before[starts][back[order]]
        outliers = np.zeros(len(w), dtype="int64")
        outliers[order] = np.clip(s.outliers[back[order]] - before, 0, w[order])
        s = Solution(head[s.centers], outliers, s.cost, s.stats)
    return s, held


SOLUTION = "kind string, pid long, value double"


def solve(coreset: DataFrame, k: int, z: int, solver: str = "trimmed_swap", metric="l2", power: int = 2, max_rows: int = MAX_ROWS, **options) -> DataFrame:
    """Rows (kind, pid, value): center (value: its mass), outlier (value: forgotten mass), stat (cost, passes, trials, ...)."""
    m = get(metric)
    rows = coreset.count()
    if rows > most_rows(m, max_rows, solver):
        raise ValueError(f"a coreset of {rows} rows is over {most_rows(m, max_rows, solver)}; raise gamma, add a level or project to fewer dimensions")

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("pid")
        ids, w, pts = table["pid"].to_numpy(), table["w"].to_numpy(), m.load(table["pt"])
        s, mass = solve_points(m, pts, w, k, z, solver, power, **options)
        out = np.flatnonzero(s.outliers)
        stats = [("cost", s.cost)] + [(f"stat:{key}", float(v)) for key, v in s.stats.items() if v is not None]
        kinds = ["center"] * len(s.centers) + ["outlier"] * len(out) + [x for x, _ in stats]
        values = [*mass.tolist(), *s.outliers[out].astype(float).tolist(), *[v for _, v in stats]]
        return pa.table({"kind": kinds, "pid": pa.array([*ids[s.centers].tolist(), *ids[out].tolist(), *[None] * len(stats)], pa.int64()), "value": pa.array(values, pa.float64())})

    whole = coreset.select("pid", "pt", F.col("w").cast("bigint").alias("w"), F.lit(0).alias("all"))
    return whole.groupBy("all").applyInArrow(run, SOLUTION)
