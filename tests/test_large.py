"""What must hold when a part or a coreset is large: bounded temporaries and the same results by the short ways."""

from dataclasses import replace

import numpy as np
import pytest

from robustcenters.functions import metrics
from robustcenters.operators import kernels, solvers


def test_distances_to_references_are_made_in_pieces():
    seen = []

    def block(a, b):
        seen.append(len(a) * len(b))
        return np.abs(a[:, None] - b[None])

    x = np.random.default_rng(0).exponential(10, 60_000)
    near = kernels.to_set(replace(metrics.ABS, name="plain", block=block), x, x[:700])
    assert max(seen) <= kernels.CELLS and (near == kernels.to_set(metrics.ABS, x, x[:700])).all()


@pytest.mark.parametrize("pick", ["lowest_id", "random", "farthest", "densest"])
def test_cover_on_a_line_equals_the_general_one(pick):
    rng, plain = np.random.default_rng(1), replace(metrics.ABS, name="plain")
    for trial in range(40):
        x = np.round(rng.exponential(5, int(rng.integers(1, 150))), trial % 4)
        w, refs = rng.integers(1, 5, len(x)), x[:4] if trial % 3 else x
        near = kernels.to_set(metrics.ABS, x, refs)
        one, two = (kernels.ball_cover(m, x, near, w, 0.3, (0.0, 1.0, 9.0)[trial % 3], pick, np.random.default_rng(3)) for m in (metrics.ABS, plain))
        assert all((a == b).all() for a, b in zip(one, two))


def test_a_line_is_scanned_once_and_not_once_a_pick():
    """Every value its own ball: the general way would look at 5 * 10^9 distances here."""
    x = np.random.default_rng(2).permutation(100_000).astype("float64")
    picked, mass, proxy, at = kernels.ball_cover(metrics.ABS, np.r_[x, x], np.zeros(200_000), np.ones(200_000, dtype="int64"), 0.25, 0.0)
    assert len(picked) == 100_000 and (mass == 2).all() and (picked == np.arange(100_000)).all() and not at.any()
    assert (proxy == np.r_[np.arange(100_000), np.arange(100_000)]).all()


def test_solvers_on_a_line_equal_those_on_the_matrix():
    rng = np.random.default_rng(3)
    for _ in range(30):
        x, k = np.round(rng.exponential(10, 60), 1), int(rng.integers(1, 5))
        d, line, w, centers = np.round(np.abs(x[:, None] - x[None]), 9), solvers.Line(x), rng.integers(1, 4, 60), rng.choice(60, k, replace=False).tolist()
        for power in (1, 2):
            own = np.flatnonzero(rng.random(60) < 0.7)
            for limit in (d[:, centers].min(axis=1), np.full(60, np.inf)):
                assert np.allclose(solvers.served(d, own, w, limit, power), solvers.served(line, own, w, limit, power), atol=1e-6)
            for z in (0, 1, 20):
                a, b = (solvers.trimmed_cost(d, w, solvers.best_swap(t, w, centers, z, power, {}), z, power) for t in (d, line))
                assert abs(a - b) < 1e-6


@pytest.mark.parametrize("solver", ["plain_then_trim", "alternate", "trimmed_swap"])
def test_many_copies_on_a_line_are_solved_as_weighted_points(spark, solver):
    x = np.round(np.random.default_rng(4).exponential(10, 300))
    rows = [(i, float(v), 1) for i, v in enumerate(np.tile(x, 40))]
    table = spark.createDataFrame(rows, "pid long, pt double, w long")
    found = solvers.solve(table, 3, 50, solver, "abs").collect()
    out = {r["pid"]: r["value"] for r in found if r["kind"] == "outlier"}
    centers = np.array([rows[r["pid"]][1] for r in found if r["kind"] == "center"])
    assert set(out.values()) == {1.0} and len(out) + sum(r["value"] for r in found if r["kind"] == "center") == len(rows)
    near = np.abs(np.tile(x, 40)[:, None] - centers).min(axis=1) ** 2
    assert abs(np.delete(near, list(out)).sum() - next(r["value"] for r in found if r["kind"] == "cost")) < 1e-6


def test_a_group_of_many_rows_is_fitted(spark):
    from robustcenters.plans.pipeline import RobustSpec, fit_by

    p = spark.range(9000).selectExpr("id AS pid", "CAST(id * 37 % 4001 AS DOUBLE) AS pt", "1 AS g")
    rows = fit_by(p, "g", RobustSpec(2, 3, metric="abs", solver="plain_then_trim")).collect()
    assert len(rows) == 2 and sum(r["weight"] for r in rows) == 8997


def test_optimum_on_a_line_equals_trying_all(spark):
    """Ties, weights, forgotten units and both powers; then a table of more pairs than the general way takes."""
    import itertools
    import math

    from robustcenters.operators import cost

    rng = np.random.default_rng(5)

    def best_of(x, w, ids, k, z, power):
        found = []
        for s in itertools.combinations(range(len(x)), k):
            d = np.round(np.abs(x[:, None] - x[list(s)]).min(axis=1), 9)
            found.append((round(math.fsum(((w - solvers.trim(d, w, z)) * d**power).tolist()), 6), sorted(int(ids[i]) for i in s)))
        return min(found)

    for _ in range(150):
        x = np.unique(np.round(rng.normal(0, 5, 12), int(rng.integers(0, 3))))
        w, ids = rng.integers(1, 4, len(x)), rng.permutation(1000)[: len(x)]
        for k, z, power in itertools.product((1, 2), (0, 3), (1, 2)):
            want, got = best_of(x, w, ids, k, z, power), cost.line_optimum(x, w, ids, k, z, power)
            assert (got[1], got[0]) == want if want[0] > 0 else got is None
    table = spark.range(3000).selectExpr("id AS pid", "CAST(pow(id % 1000, 2) AS DOUBLE) AS pt")
    assert [int(i) < 1000 for i in cost.optimum(table, 2, 3, "abs").first()["centers"].split(",")] == [True, True]


def test_spread_on_a_line_takes_any_number_of_points(spark):
    from robustcenters.plans import audit

    rng = np.random.default_rng(6)
    x = np.r_[np.round(rng.normal(0, 100, 25_000), 2), 0.5, 0.5]
    u = np.unique(x)
    got = audit.spread(spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "pid long, pt double"), "abs").first()[0]
    assert got == (u[-1] - u[0]) / np.diff(u).min()


def test_kmeans_out_makes_no_matrix():
    from robustcenters.streaming.table_functions import KMeansOut

    f = KMeansOut()
    for i in range(60_000):  # a matrix of 29 GB
        f.eval({"pid": i, "x": float(i * 7919 % 20_011), "w": 1}, 3, 2)
    assert len(list(f.terminate())) == 3


@pytest.mark.parametrize("name", ["bounds_table", "constants_table", "non_metrics_flagged", "rel_range_literal", "rel_recursive"])
def test_small_queries_read_a_given_table(spark, tmp_path, name):
    """Without tables they fail; with them they give what their SQL does."""
    import duckdb

    from robustcenters import catalog

    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        catalog.queries()[name](spark, str(tmp_path)).collect()
    con, path = duckdb.connect(), "/root/testdata/sf0.001"
    for t in ("lineitem", "events"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path}/{t}.parquet'")
    rows = lambda found: sorted(repr([round(float(v), 6) if isinstance(v, float) else v for v in r]) for r in found)
    df, sql = catalog.queries()[name](spark, path), con.sql(catalog.oracle_sql()[name])
    assert df.columns == sql.columns and rows(map(tuple, df.collect())) == rows(sql.fetchall())


@pytest.mark.parametrize("pick", ["lowest_id", "random", "farthest"])
def test_covers_of_copies_equal_those_of_the_points(monkeypatch, pick):
    monkeypatch.setattr(kernels, "MANY", 100)
    rng, seen = np.random.default_rng(8), []

    def block(a, b):
        seen.append(len(a))
        return metrics.L2.block(a, b)

    x = np.round(rng.exponential(5, (120, 2)), 1)[rng.integers(0, 120, 1000)]
    w, refs = rng.integers(1, 5, 1000), np.round(rng.exponential(5, (40, 2)), 1)
    found = []
    for m in (replace(metrics.L2, block=block), replace(metrics.L2, name="plain")):
        near = kernels.to_set(m, x, refs)
        found.append((near, *kernels.ball_cover(m, x, near, w, 0.3, 1.0, pick, np.random.default_rng(3))))
    assert all((a == b).all() for a, b in zip(*found)) and max(seen) <= 120


def test_an_alternating_solution_needs_no_matrix(spark, monkeypatch):
    """w12: more rows than a matrix may have; then the same solution with and without it."""
    rng = np.random.default_rng(9)
    rows = [(i, [float(v) for v in x], 1) for i, x in enumerate(rng.normal(0, 1, (8200, 3)))]
    table = spark.createDataFrame(rows, "pid long, pt array<double>, w long")
    found = solvers.solve(table, 3, 5, "alternate", "angular", iterations=2).collect()
    assert sum(r["value"] for r in found if r["kind"] in ("center", "outlier")) == 8200
    x, w = rng.normal(0, 1, (700, 5)), rng.integers(1, 4, 700)
    one, _ = solvers.solve_points(metrics.ANGULAR, x, w, 4, 9, "alternate")
    monkeypatch.setattr(solvers, "MAX_ROWS", 100)
    two, _ = solvers.solve_points(metrics.ANGULAR, x, w, 4, 9, "alternate")
    assert (one.centers == two.centers).all() and (one.outliers == two.outliers).all() and abs(one.cost - two.cost) < 1e-6


def _words(rng, n):
    """Sets of common and rare words, with copies, near copies and empty ones."""
    out = [frozenset(f"w{int(v)}" for v in rng.zipf(1.3, int(rng.integers(0, 30))) % 400) for _ in range(n)]
    return out + [x - {"w1"} | {"w2"} for x in out[: n // 3]] + out[:5]


def test_covers_of_sets_equal_the_general_ones():
    """w11: a pick compares few sets by their rare words and takes the same ones."""
    rng = np.random.default_rng(10)
    plain = replace(metrics.JACCARD, name="plain")
    for trial in range(30):
        x = _words(rng, int(rng.integers(1, 80)))
        sets, w = metrics.Sets.of(x), rng.integers(1, 5, len(x))
        refs = metrics.Sets.of([x[i] for i in rng.integers(0, len(x), 40)] + [frozenset({"new"})])
        near = kernels.to_set(metrics.JACCARD, sets, refs)
        assert (near == kernels.to_set(plain, sets, refs)).all()
        assert np.allclose(sets_block := metrics.JACCARD.block(sets, sets), [[metrics.jaccard(a, b) for b in x] for a in x]) and (sets_block == sets_block.T).all()
        for pick in ("lowest_id", "random", "farthest"):
            one, two = (kernels.ball_cover(m, sets, near, w, (0.3, 0.6, 0.9)[trial % 3], (0.3, 0.8)[trial % 2], pick, np.random.default_rng(3)) for m in (metrics.JACCARD, plain))
            assert all((a == b).all() for a, b in zip(one, two))


def test_covers_look_at_several_picks_together():
    calls = []

    def block(a, b):
        calls.append(len(b))
        return metrics.L2.block(a, b)

    x = np.random.default_rng(11).normal(0, 1, (3000, 3))
    picked, mass, *_ = kernels.ball_cover(replace(metrics.L2, name="plain", block=block), x, np.zeros(3000), np.ones(3000, dtype="int64"), 0.5, 1e-9)
    assert len(picked) == mass.sum() == 3000 and len(calls) < 100


def test_sets_are_numbered_in_pieces(monkeypatch):
    x = _words(np.random.default_rng(12), 60)
    whole = metrics.Sets.of(x)
    monkeypatch.setattr(metrics, "CELLS", 7)
    parts = metrics.Sets.of(x)
    assert (whole.codes == parts.codes).all() and (whole.at == parts.at).all()
    assert (metrics.JACCARD.block(parts, parts[:9]) == metrics.JACCARD.block(whole, whole[:9])).all()
