"""Numpy kernels that run inside one Arrow group: seeding and ball covering.

All take points in the order of their ids and use distances rounded to nine decimals, so that a retry, a rerun and the
SQL oracles agree.
"""

from __future__ import annotations

import math
from bisect import bisect
from dataclasses import replace
from itertools import combinations

import numpy as np

from ..functions.metrics import ABS, JACCARD, Metric, Sets, runs

#: Distances that are held at a time; points on a line that are looked up at a time.
CELLS, LINE_ROWS = 1 << 22, 1 << 18
#: Points on a line from which seeding keeps sums of blocks of so many.
LINE_SEEDS, LINE_BLOCK = 4096, 256


def distances(m: Metric, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.round(m.block(a, b), 9)


#: Metrics under which equal vectors are at distance zero exactly, and how many points and coordinates make a search for equal ones worth it.
EXACT, MANY, NARROW = {"l1", "l2", "linf", "hamming"}, 50_000, 8


def _kinds(*columns: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(order, starts, first, kind) of rows that are equal in all columns but the first one, by which the first of each kind is told."""
    by = np.lexsort(columns)
    new = np.arange(len(by)) == 0
    for y in columns[1:]:
        y = y[by]
        new[1:] |= y[1:] != y[:-1]
    starts = np.flatnonzero(new)
    kind = np.empty(len(by), dtype="int64")
    kind[by] = np.cumsum(new) - 1
    return by, starts, by[starts], kind


def _copied(m: Metric, points: np.ndarray) -> bool:
    return m.name in EXACT and len(points) > MANY and points.shape[1] <= NARROW


def to_set(m: Metric, points: np.ndarray, refs: np.ndarray, block: int = 512) -> np.ndarray:
    """d(p, refs) for every point; no temporary has more than CELLS distances. On a line, by search among the sorted references."""
    best = np.full(len(points), np.inf)
    if m.name == ABS.name and len(refs):
        line = np.sort(refs)
        for lo in range(0, len(points), LINE_ROWS):
            own = points[lo : lo + LINE_ROWS]
            at = np.searchsorted(line, own)
            near = np.minimum(np.abs(own - line[np.maximum(at - 1, 0)]), np.abs(own - line[np.minimum(at, len(line) - 1)]))
            best[lo : lo + LINE_ROWS] = np.round(near, 9)
        return best
    if len(refs) > 32 and _copied(m, points):
        _, _, first, kind = _kinds(np.arange(len(points)), *points.T)
        if 2 * len(first) < len(points):
            return to_set(m, points[first], refs, block)[kind]
    if isinstance(points, Sets) and len(refs):
        refs = Sets.of(refs).like(points)
        if m.name == JACCARD.name and len(refs) > 32:
            # sets that are among the references need no distance
            text = lambda sets: [sets.codes[a:b].tobytes() for a, b in zip(sets.at[:-1], sets.at[1:])]
            known = set(text(Sets(refs.words, *_ordered(refs))))
            best[[x in known for x in text(points)]] = 0.0
            own = np.flatnonzero(best > 0)
            if len(own) < len(points):
                best[own] = to_set(replace(m, name="sets"), points[own], refs, block)
                return best
    rows = max(1, CELLS // max(1, min(block, len(refs))))
    for lo in range(0, len(points), rows):
        for at in range(0, len(refs), block):
            best[lo : lo + rows] = np.minimum(best[lo : lo + rows], distances(m, points[lo : lo + rows], refs[at : at + block]).min(axis=1))
    return best


def _ordered(sets: Sets) -> tuple[np.ndarray, np.ndarray]:
    """Codes in order within each set."""
    return sets.codes[np.lexsort((sets.codes, sets.rows()))], sets.at


def seed_first(m, points, w, k, power, rng):
    return np.arange(min(k, len(points)))


def seed_farthest(m, points, w, k, power, rng):
    """Farthest-first traversal from the least id; ties go to the least id."""
    chosen = [0]
    near = distances(m, points, points[:1])[:, 0]
    while len(chosen) < min(k, len(points)) and near.max() > 0:
        nxt = int(near.argmax())
        chosen.append(nxt)
        near = np.minimum(near, distances(m, points, points[nxt : nxt + 1])[:, 0])
    return np.array(chosen)


def seed_dsq(m, points, w, k, power, rng):
    """Sampling in proportion to weight times distance to the chosen, to the power of the objective."""
    chosen = [int(rng.choice(len(points), p=w / w.sum()))]
    near = to_set(m, points, points[chosen])
    if m.name == ABS.name and len(points) > LINE_SEEDS:
        return _seed_line(points, w, k, power, rng, chosen, near)
    while len(chosen) < min(k, len(points)):
        mass = w * near**power
        total = mass.sum()
        if total <= 0:
            break
        mass /= total
        nxt = int(rng.choice(len(points), p=mass))
        chosen.append(nxt)
        np.minimum(near, to_set(m, points, points[nxt : nxt + 1]), out=near)
    return np.array(chosen)


def _seed_line(points, w, k, power, rng, chosen, near):
    """seed_dsq on a line, with its draws: a new center changes only points between its neighbours, and sums of blocks tell where a draw falls."""
    order = np.argsort(points, kind="stable")
    line, picked, n = points[order], [float(points[chosen[0]])], len(points)
    mass = np.zeros((-(-n // LINE_BLOCK), LINE_BLOCK))
    flat = mass.ravel()
    flat[:n] = w * near**power
    sums = mass.sum(axis=1)
    while len(chosen) < min(k, n):
        upto = np.cumsum(sums)
        if upto[-1] <= 0:
            break
        draw = rng.random() * upto[-1]
        block = min(int(np.searchsorted(upto, draw, side="right")), int(np.flatnonzero(sums)[-1]))
        own = np.cumsum(mass[block])
        draw -= upto[block - 1] if block else 0.0
        nxt = min(int(np.searchsorted(own, draw, side="right")), int(np.flatnonzero(mass[block])[-1])) + block * LINE_BLOCK
        x = float(points[nxt])
        at = bisect(picked, x)
        lo = np.searchsorted(line, picked[at - 1]) if at else 0
        hi = np.searchsorted(line, picked[at], side="right") if at < len(picked) else n
        some = order[lo:hi]
        closer = np.round(np.abs(points[some] - x), 9)
        less = closer < near[some]
        some = some[less]
        near[some] = closer[less]
        flat[some] = w[some] * near[some] ** power
        touched = np.unique(some // LINE_BLOCK)
        sums[touched] = mass[touched].sum(axis=1)
        picked.insert(at, x)
        chosen.append(nxt)
    return np.array(chosen)


def seed_swap(m, points, w, k, power, rng, rounds: int = 40):
    """The sampled seed, improved by single swaps with sampled candidates."""
    chosen = list(seed_dsq(m, points, w, k, power, rng))
    table = distances(m, points, points[chosen])
    cost = float((w * table.min(axis=1) ** power).sum())
    for _ in range(rounds if len(chosen) > 1 else 0):
        mass = w * table.min(axis=1) ** power
        if mass.sum() <= 0:
            break
        c = int(rng.choice(len(points), p=mass / mass.sum()))
        column = distances(m, points, points[c : c + 1])[:, 0]
        order = np.sort(table, axis=1)
        owner, first, second = table.argmin(axis=1), order[:, 0], order[:, 1]
        base = w * np.minimum(first, column) ** power
        extra = w * (np.minimum(second, column) ** power) - base
        totals = base.sum() + np.bincount(owner, weights=extra, minlength=len(chosen))
        out = int(totals.argmin())
        if totals[out] < cost - 1e-12:
            cost = float(totals[out])
            chosen[out] = c
            table[:, out] = column
    return np.array(sorted(set(chosen)))


def seed_exact(m, points, w, k, power, rng, limit: int = 200_000):
    from math import comb

    n = len(points)
    k = min(k, n)
    if comb(n, k) > limit:
        raise ValueError("too many subsets for exhaustive seeding")
    table = distances(m, points, points) ** power
    best, chosen = np.inf, None
    for s in combinations(range(n), k):
        c = float((w * table[:, s].min(axis=1)).sum())
        if c < best - 1e-12:
            best, chosen = c, s
    return np.array(chosen)


SEEDINGS = {"first_ids": seed_first, "farthest": seed_farthest, "dsq": seed_dsq, "swap": seed_swap, "exact": seed_exact}


def _takers(m: Metric, points: np.ndarray, covered: np.ndarray, centers: np.ndarray, threshold: np.ndarray, block: int = 256) -> np.ndarray:
    """Of each of ``centers``, how many of ``covered`` it takes; the others have 0."""
    out = np.zeros(len(points), dtype="int64")
    for at in range(0, len(covered), block):
        own = covered[at : at + block]
        out[centers] += (distances(m, points[own], points[centers]) <= threshold[own][:, None]).sum(axis=0)
    return out


def _ranges(values: np.ndarray, threshold: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each of the sorted values, the range of places whose rounded distance is within its threshold."""
    n, own = len(values), np.arange(len(values))
    within = lambda i: np.round(np.abs(values[np.clip(i, 0, n - 1)] - values), 9) <= threshold
    lo = np.minimum(np.searchsorted(values, values - threshold), own)
    hi = np.maximum(np.searchsorted(values, values + threshold, side="right"), own + 1)
    # the search knows no rounding, so the ends are moved until they are right
    for end, step, out in ((lo, -1, -1), (hi, 1, 0)):
        while (more := (end + out >= 0) & (end + out < n) & within(end + out)).any():
            end[more] += step
        while (less := (end - step + out != own) & ~within(end - step + out)).any():
            end[less] -= step
    return lo, hi


def _cover_line(x: np.ndarray, reference: np.ndarray, w: np.ndarray, threshold: np.ndarray, delta: float, radius: float, order: np.ndarray, densest: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The same balls for points on a line: equal points with equal thresholds go together, and a pick looks only at its reach.

    A taken point's threshold is delta times max(radius, d(p, X)), and d(p, X) is at most d(q, X) + d(p, q), so d(p, q) is at
    most max(delta * radius, delta * d(q, X) / (1 - delta)).
    """
    n, index = len(x), "int32" if len(x) < 1 << 31 else "int64"
    place = np.empty(n, dtype=index)
    place[order] = np.arange(n, dtype=index)
    del order
    by = np.lexsort((place, threshold, x)).astype(index)
    new = np.arange(n) == 0
    for y in (x, threshold):
        y = y[by]
        new[1:] |= y[1:] != y[:-1]
    starts = np.flatnonzero(new)
    kind = np.empty(n, dtype=index)
    kind[by] = np.cumsum(new, dtype=index) - 1
    head = by[starts]  # of each kind the point that comes first
    v, t, near, turn = x[head], threshold[head], reference[head], place[head]
    held = np.add.reduceat(w[by], starts) if n else np.zeros(0, dtype="int64")
    del by, new, place
    reach = np.maximum(delta * radius, delta * near / (1 - delta)) * (1 + 1e-9) + 1e-6
    if (np.abs(np.diff(near)) > np.diff(v) + 2e-9 + 1e-12 * np.abs(v[1:])).any():
        reach[:] = np.inf  # what was given is no distance to a set, so a pick may take from anywhere
    left, right = np.searchsorted(v, v - reach), np.searchsorted(v, v + reach, side="right")
    alive, proxy, at = np.ones(len(v), dtype=bool), np.full(len(v), -1), np.zeros(len(v))
    picked: list[int] = []
    mass: list[int] = []
    if densest:
        lo, hi = _ranges(v, t)
        copies = np.diff(np.r_[starts, n])
        takes = np.cumsum(np.bincount(lo, copies, len(v) + 1) - np.bincount(hi, copies, len(v) + 1))[:-1].round().astype("int64")
    queue, gone = iter(np.argsort(turn, kind="stable").tolist()), 0
    while gone < len(v):
        if densest:
            most = np.flatnonzero(takes == takes.max())
            q = int(most[turn[most].argmin()])
        else:
            q = next(queue)
            if not alive[q]:
                continue
        a, b = left[q], right[q]
        own = a + np.flatnonzero(alive[a:b])
        d = np.round(np.abs(v[own] - v[q]), 9)
        take = (d <= t[own]) | (own == q)
        own = own[take]
        proxy[own], at[own], alive[own] = q, d[take], False
        gone += len(own)
        picked.append(int(head[q]))
        mass.append(int(held[own].sum()))
        if densest:
            a, b = lo[own].min(), hi[own].max()
            takes[a:b] -= np.cumsum(np.bincount(lo[own] - a, copies[own], b - a + 1) - np.bincount(hi[own] - a, copies[own], b - a + 1))[:-1].round().astype("int64")
            takes[own] = -(1 << 60)
    return np.array(picked, dtype="int64"), np.array(mass, dtype="int64"), head[proxy[kind]], at[kind]


def ball_cover(m: Metric, points: np.ndarray, reference: np.ndarray, w: np.ndarray, delta: float, radius: float, pick: str = "lowest_id", rng=None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Greedy balls: (picked indices, their masses, proxy index of every point, proxy distance).

    reference holds d(p, X). A point's threshold is fixed at the start; a picked point takes all uncovered points within
    their own thresholds, itself included, and its mass is exactly what it takes.
    """
    n = len(points)
    threshold = np.round(delta * np.maximum(radius, reference), 9)
    order = rng.permutation(n) if pick == "random" else np.argsort(-reference, kind="stable") if pick == "farthest" else np.arange(n)
    if m.name == ABS.name and delta < 1:
        return _cover_line(points, reference, w, threshold, delta, radius, order, pick == "densest")
    if m.name == JACCARD.name and isinstance(points, Sets) and pick != "densest" and n and threshold.max() < 1 - 1e-6:
        return _cover_sets(points, threshold, w, order)
    place = np.empty(n, dtype="int64")
    place[order] = np.arange(n)
    if pick != "densest" and _copied(m, points):
        # equal points with equal thresholds go together
        by, starts, first, kind = _kinds(place, threshold, *points.T)
        if 2 * len(first) < n:
            picked, mass, proxy, at = _cover(m, points[first], threshold[first], np.add.reduceat(w[by], starts), place[first], False)
            return first[picked], mass, first[proxy[kind]], at[kind]
    return _cover(m, points, threshold, w, place, pick == "densest")


def _cover(m: Metric, points: np.ndarray, threshold: np.ndarray, w: np.ndarray, place: np.ndarray, densest: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    n = len(points)
    proxy, at = np.full(n, -1), np.zeros(n)
    picked: list[int] = []
    mass: list[int] = []
    alive = np.arange(n)
    alive = alive[np.argsort(place[alive], kind="stable")]
    takes = _takers(m, points, alive, alive, threshold) if densest else None
    block = 1
    while takes is None and len(alive):
        # the next picks' distances together, as long as most of them are not taken by those before
        ahead = alive[: max(1, min(block, CELLS // len(alive)))]
        table, free, before = distances(m, points[alive], points[ahead]), np.ones(len(alive), dtype=bool), len(picked)
        for j, q in enumerate(ahead.tolist()):
            if free[j]:
                take = free & (table[:, j] <= threshold[alive])
                take[j] = True
                own = alive[take]
                proxy[own], at[own] = q, table[take, j]
                picked.append(q)
                mass.append(int(w[own].sum()))
                free &= ~take
        alive = alive[free]
        block = min(256, 2 * block) if 2 * (len(picked) - before) > len(ahead) else max(1, block // 2)
    while len(alive):
        q = alive[int(takes[alive].argmax())]
        d = distances(m, points[alive], points[q : q + 1])[:, 0]
        take = (d <= threshold[alive]) | (alive == q)
        own = alive[take]
        proxy[own], at[own] = q, d[take]
        picked.append(int(q))
        mass.append(int(w[own].sum()))
        alive = alive[~take]
        if len(alive):
            takes -= _takers(m, points, own, alive, threshold)
    return np.array(picked, dtype="int64"), np.array(mass, dtype="int64"), proxy, at


def _cover_sets(points: Sets, threshold: np.ndarray, w: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The same balls for sets under the Jaccard distance: a pick looks only at sets that have one of its rare words among their own rare ones.

    Sets within a threshold share at least (1 - threshold) of the words of each. With all words in the order of their frequency, the
    first word that two such sets share is then among the first of either, so many that the others would be too few. These are listed by word
    and size; pairs that share too few of them are not compared.
    """
    n, size = len(points), points.sizes()
    often = np.bincount(points.codes, minlength=1)
    rank = np.empty(len(often), dtype="int32")
    rank[np.argsort(often, kind="stable")] = np.arange(len(often))
    codes = rank[points.codes]
    for a, b in zip(points.at[:-1].tolist(), points.at[1:].tolist()):
        codes[a:b].sort()
    alike = 1 - threshold - 1e-8  # distances are rounded
    least = alike.min()
    rare = lambda x: np.minimum(size, size - np.ceil(x * size - 1e-6).astype("int64") + 1)
    own, asked = rare(alike), rare(least)
    at, who = runs(points.at[:-1], own), np.repeat(np.arange(n), own)
    listed = codes[at].astype("int64") << 24 | size[who]
    del at
    by = np.argsort(listed, kind="stable")
    listed, who, rest, share = listed[by], who[by], size - own, alike / (1 + alike)
    empty, marks, alive = np.flatnonzero(size == 0), np.zeros(len(often), dtype=bool), np.ones(n, dtype=bool)
    proxy, dist = np.full(n, -1), np.zeros(n)
    picked: list[int] = []
    mass: list[int] = []
    for q in order.tolist():
        if not alive[q]:
            continue
        words = codes[points.at[q] : points.at[q + 1]]
        own, some = int(size[q]), words[: asked[q]].astype("int64")
        near = empty[alive[empty]]
        if own:
            lo = np.searchsorted(listed, some << 24 | math.ceil(least * own - 1e-6))
            hi = np.searchsorted(listed, some << 24 | math.floor(own / least + 1e-6), side="right")
            hits = np.bincount(who[runs(lo, hi - lo)], minlength=n)
            near = np.flatnonzero(alive & (hits > 0))
            # what is not among the rare words of one of them can add no more than its other words
            near = near[hits[near] + np.maximum(rest[near], own - len(some)) >= share[near] * (size[near] + own) - 1e-6]
        d = np.zeros(len(near))
        if len(words) and len(near):
            marks[words] = True
            both = np.add.reduceat(marks[codes[runs(points.at[near], size[near])]], np.cumsum(size[near]) - size[near], dtype="int64")
            marks[words] = False
            d = np.round(1 - both / (size[near] + len(words) - both), 9)
        take = (d <= threshold[near]) | (near == q)
        near = near[take]
        proxy[near], dist[near], alive[near] = q, d[take], False
        picked.append(q)
        mass.append(int(w[near].sum()))
    return np.array(picked, dtype="int64"), np.array(mass, dtype="int64"), proxy, dist
