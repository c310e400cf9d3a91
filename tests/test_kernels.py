"""Kernels, solvers and bounds on hand-made points with known answers."""

import itertools
import time

import numpy as np
import pytest

from robustcenters.functions import bounds, metrics
from robustcenters.operators import kernels, solvers

P = np.array([0.0, 1.0, 2.0, 10.0, 11.0, 100.0])
D = np.abs(P[:, None] - P[None])
ONE = np.ones(6, dtype="int64")


def test_ball_cover_known_balls():
    near = kernels.to_set(metrics.ABS, P, np.array([1.0, 10.0]))
    picked, mass, proxy, at = kernels.ball_cover(metrics.ABS, P, near, ONE, 0.5, 2.0)
    assert dict(zip(P[picked], mass)) == {0.0: 2, 2.0: 1, 10.0: 2, 100.0: 1}
    assert mass.sum() == 6 and (at**2).sum() == 2


def test_weighted_ball_cover():
    w = np.array([3, 1, 2, 1, 1, 4])
    near = kernels.to_set(metrics.ABS, P, np.array([1.0, 10.0]))
    picked, mass, _, _ = kernels.ball_cover(metrics.ABS, P, near, w, 0.5, 2.0)
    assert dict(zip(P[picked], mass)) == {0.0: 4, 2.0: 2, 10.0: 2, 100.0: 4}


@pytest.mark.parametrize("pick", ["lowest_id", "random", "farthest", "densest"])
def test_cover_keeps_mass_and_thresholds(pick):
    rng = np.random.default_rng(0)
    x = rng.exponential(30, 300)
    near = kernels.to_set(metrics.ABS, x, x[:5])
    picked, mass, proxy, at = kernels.ball_cover(metrics.ABS, x, near, np.ones(300, dtype="int64"), 0.3, 20, pick, np.random.default_rng(1))
    assert mass.sum() == 300 and (proxy[picked] == picked).all()
    assert (at <= 0.3 * np.maximum(20, near) + 1e-9).all()


def test_trim_splits_the_boundary():
    w = np.array([3, 1, 2, 1, 1, 4])
    near = D[:, [1, 3]].min(axis=1)
    assert (w - solvers.trim(near, w, 5)).tolist() == [2, 1, 2, 1, 1, 0]
    assert solvers.trimmed_cost(D, w, [1, 3], 2, 2) == 16206
    assert solvers.trimmed_cost(D, w, [1, 3], 5, 2) == 5


def test_exhaustive_known_optima():
    s = solvers.exhaustive(D, ONE, 2, 1)
    assert s.cost == 3 and P[s.centers].tolist() == [1.0, 10.0]
    s = solvers.exhaustive(D, ONE, 2, 0)
    assert s.cost == 150 and P[s.centers].tolist() == [2.0, 100.0]


@pytest.mark.parametrize("seed", range(6))
def test_local_searches_against_the_optimum(seed):
    rng = np.random.default_rng(seed)
    x = np.r_[rng.normal(0, 1, 9), rng.normal(20, 1, 4), 500]
    d, w = np.abs(x[:, None] - x[None]), rng.integers(1, 4, 14)
    best = solvers.exhaustive(d, w, 2, 3).cost
    t = solvers.trimmed_swap(d, w, 2, 3)
    assert t.cost <= 274 * best + 1e-9 and t.outliers.sum() >= 3 and len(t.centers) == 2
    m = solvers.multi_swap(d, w, 2, 3, eps=0.5, swap_size=1)
    assert m.outliers.sum() == 3 and len(m.centers) <= 3
    for move in itertools.product(range(len(m.centers)), range(14)):
        option = [c for i, c in enumerate(m.centers) if i != move[0]] + [move[1]]
        assert solvers.trimmed_cost(d, w, option, 3, 2) >= (1 - 0.25) * m.cost - 1e-9
    for f in (solvers.plain_then_trim, solvers.alternate):
        s = f(d, w, 2, 3)
        assert s.cost >= best - 1e-9 and s.outliers.sum() == 3


def test_constants_and_caps():
    assert all(ok for _, ok in bounds.constants_hold())
    with pytest.raises(ValueError):
        bounds.check_gamma(0.12, "direct")
    with pytest.raises(ValueError):
        bounds.check_gamma(0.06, "refined")
    assert not bounds.check_gamma(0.06, "refined", strict=False)


def test_coreset_error_on_all_solutions():
    rng = np.random.default_rng(3)
    x = np.sort(rng.exponential(10, 12))
    near = kernels.to_set(metrics.ABS, x, x[:2])
    _, _, proxy, at = kernels.ball_cover(metrics.ABS, x, near, np.ones(12, dtype="int64"), 0.2, 3)
    e = float((at**2).sum())
    for s in itertools.combinations(range(12), 2):
        full = (np.abs(x[:, None] - x[list(s)]).min(axis=1) ** 2).sum()
        small = (np.abs(x[proxy][:, None] - x[list(s)]).min(axis=1) ** 2).sum()
        assert abs(full - small) <= e + 2 * np.sqrt(e * full) + 1e-9


def test_metric_blocks_agree_with_one_pair_functions():
    a = np.array([frozenset("abc"), frozenset("bd"), frozenset()], dtype=object)
    got = metrics.JACCARD.block(a, a)
    assert np.allclose(got, [[metrics.jaccard(x, y) for y in a] for x in a])
    assert metrics.edit_distances(["kitten", ""], ["sitting", "kitten"]).tolist() == [[3, 0], [7, 6]]


def test_densest_picks_what_takes_most():
    """Every pick is a point that takes most of what is left, by counting anew each time."""
    from robustcenters.functions.metrics import ABS
    from robustcenters.operators import kernels

    rng = np.random.default_rng(7)
    pts = np.round(rng.exponential(5, 120), 3)
    near, w = np.abs(pts), np.ones(120, dtype="int64")
    picked, mass, proxy, _ = kernels.ball_cover(ABS, pts, near, w, 0.5, 1.0, "densest")
    threshold = np.round(0.5 * np.maximum(1.0, near), 9)
    left = np.arange(120)
    for q, m in zip(picked, mass):
        takes = [int(((np.round(np.abs(pts[left] - pts[c]), 9) <= threshold[left]) | (left == c)).sum()) for c in left]
        own = (np.round(np.abs(pts[left] - pts[q]), 9) <= threshold[left]) | (left == q)
        assert own.sum() == m >= max(takes) - 1
        left = left[~own]
    assert not len(left)


def test_edit_distances_equal_the_table():
    from robustcenters.functions.metrics import EDIT, edit_distances

    def plain(x, y):
        row = list(range(len(y) + 1))
        for i, c in enumerate(x, 1):
            last, row[0] = row[0], i
            for j, d in enumerate(y, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (c != d))
        return row[-1]

    rng = np.random.default_rng(3)
    words = ["".join(rng.choice(list("abcé"), n)) for n in rng.integers(0, 9, 40)]
    assert edit_distances(words, words[:17]).tolist() == [[plain(x, y) for y in words[:17]] for x in words]
    many = np.array([*words, *words], dtype=object)
    assert EDIT.block(many, many[:5]).tolist() == [[plain(x, y) for y in many[:5]] for x in many]


def test_lookup_metric_refuses_what_is_none():
    from robustcenters.functions.metrics import lookup

    assert lookup("ring", [[0, 1, 1], [1, 0, 1], [1, 1, 0]]).is_metric and not lookup("far", [[0, 1, 9], [1, 0, 1], [9, 1, 0]]).is_metric
    for bad in ([[0, 1], [2, 0]], [[1, 1], [1, 0]], [[0, -1], [-1, 0]]):
        with pytest.raises(ValueError):
            lookup("bad", bad)


def test_trimmed_search_reports_what_it_earned():
    """Passes are taken when the cap allows, within it; the ratio is reported only if nothing was closed to the search."""
    from robustcenters.operators import solvers

    rng = np.random.default_rng(11)
    pts = np.r_[rng.normal(0, 1, 60), rng.normal(50, 1, 60), rng.normal(500, 200, 8)]
    d, w = np.round(np.abs(pts[:, None] - pts[None]), 9), np.ones(128, dtype="int64")
    free = solvers.trimmed_swap(d, w, 2, 4)
    assert free.stats["passes"] > 0 and free.stats["alpha"] == 274 and free.cost <= free.stats["start_cost"]
    for cap in (4, 8):
        capped = solvers.trimmed_swap(d, w, 2, 4, outlier_cap=cap)
        assert capped.outliers.sum() <= cap and capped.cost <= capped.stats["start_cost"]
        assert capped.stats["alpha"] is None or not capped.stats["stopped_by_cap"]
    assert solvers.trimmed_swap(d, w, 2, 4, outlier_cap=8).stats["passes"] > 0
    found = solvers.multi_swap(d, w, 2, 8, eps=0.5, swap_size=1, candidate_cap=None)
    assert found.stats["alpha"] is None and not found.stats["capped"]
    exact = solvers.exhaustive(d, w, 2, 8)
    full = solvers.multi_swap(d[::4, ::4], w[::4], 2, 2, eps=0.4, swap_size=2, candidate_cap=None, dimension=0.4)
    assert full.stats["alpha"] == 1.4 and full.cost <= 1.4 * solvers.exhaustive(d[::4, ::4], w[::4], 2, 2).cost + 1e-9
    assert found.cost >= exact.cost - 1e-9 or len(found.centers) > 2


def test_metric_axioms_on_all_triples(spark):
    """What the registered queries check along the ids of whole tables, on all triples of small ones."""
    from robustcenters.functions import metrics

    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(size=3)]) for i in range(25)]
    vectors = spark.createDataFrame(rows, "pid long, pt array<double>")
    for m in ("l1", "l2", "linf", "angular", metrics.lp(3), "hamming", "ultra"):
        assert tuple(metrics.axiom_violations(vectors, m).first()) == (0, 0, 0)
    sets = spark.createDataFrame([(i, ["abcdefgh"[j] for j in range(8) if rng.random() < 0.5]) for i in range(20)], "pid long, pt array<string>")
    assert tuple(metrics.axiom_violations(sets, "jaccard").first()) == (0, 0, 0)
    assert metrics.axiom_violations(vectors, "squared_l2").first()["triangle"] > 0
    assert metrics.axiom_violations_along(vectors, "l2").first()["triples"] == 23


def test_ranks_and_even_parts(spark):
    from robustcenters.sources import points

    p = spark.createDataFrame([(int(i), 1.0) for i in np.random.default_rng(2).permutation(997)], "pid long, pt double")
    assert sorted((r["rank"], r["pid"]) for r in points.ranked(p).collect()) == [(i, i) for i in range(997)]
    sizes = [r["count"] for r in points.partition(p, 7, "even").groupBy("part_id").count().collect()]
    assert max(sizes) - min(sizes) <= 1 and sum(sizes) == 997


def test_swap_tables_equal_trying_every_swap():
    """The best swap and the swap search's first move, with weights, ties and zero masses, for both powers."""
    from robustcenters.operators import solvers

    rng = np.random.default_rng(13)
    for power in (1, 2):
        for z in (0, 1, 5, 40):
            pts = np.round(rng.exponential(10, 40))
            d, w = np.abs(pts[:, None] - pts[None]), rng.integers(0, 4, 40)
            centers = [0, 7, 19]
            options = [[*centers[:c], *centers[c + 1 :], i] for c in range(3) for i in range(40)]
            if z < w.sum():
                found = solvers.best_swap(d, w, centers, z, power, {})
                assert abs(solvers.trimmed_cost(d, w, found, z, power) - min(solvers.trimmed_cost(d, w, o, z, power) for o in options)) < 1e-9
            moved = solvers.swap_search(d, w, centers, power, 1e-9, {}, max_moves=1)
            assert abs(solvers.trimmed_cost(d, w, moved, 0, power) - min(solvers.trimmed_cost(d, w, o, 0, power) for o in [centers, *options])) < 1e-9


def test_seeding_on_a_line_draws_as_in_general(monkeypatch):
    from robustcenters.functions.metrics import ABS

    rng = np.random.default_rng(5)
    for points in (rng.lognormal(3, 1, 6_000), np.round(rng.normal(size=6_000), 1)):
        w = rng.integers(1, 5, len(points)).astype("float64")
        fast = kernels.seed_dsq(ABS, points, w, 300, 2, np.random.default_rng(1))
        with monkeypatch.context() as general:
            general.setattr(kernels, "LINE_SEEDS", 1 << 60)
            assert kernels.seed_dsq(ABS, points, w, 300, 2, np.random.default_rng(1)).tolist() == fast.tolist()
        assert len(set(points[fast])) == len(fast)
    # each of 12,000 centers looked at all 500,000 points before
    many, began = rng.lognormal(3, 1, 500_000), time.monotonic()
    assert len(kernels.seed_dsq(ABS, many, np.ones(len(many)), 12_000, 2, np.random.default_rng(1))) == 12_000
    assert time.monotonic() - began < 60
