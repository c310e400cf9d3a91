"""DuckDB SQL builders: assignment, trims, brute-force optima, and recursive seeding and covering."""

from __future__ import annotations

#: point sets as SQL (pid, x[, w])
SUPPLIER = "SELECT s_suppkey AS pid, s_acctbal AS x, 1 AS w FROM supplier"
EVENTS = "SELECT event_id AS pid, value AS x, 1 AS w FROM events"
NATIONS = "SELECT n_nationkey AS pid, round(avg(c_acctbal), 2) AS x, count(*) AS w FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"
LATTICE = "SELECT CAST(100*q+d AS BIGINT) AS pid, [q, d] AS x, w FROM (SELECT l_quantity AS q, round(100*l_discount) AS d, count(*) AS w FROM lineitem GROUP BY 1, 2)"
PARTS = "SELECT min(p_partkey) AS pid, p_name AS x, count(*) AS w FROM part GROUP BY p_name"
EMBEDDINGS = "SELECT vec_id AS pid, CAST(embedding AS DOUBLE[]) AS x, 1 AS w FROM embeddings"

#: distances between {a} and {b}
DIST = {
    "abs": "abs({a} - {b})",
    "l2": "sqrt(list_sum([(t[1]-t[2])*(t[1]-t[2]) for t in list_zip({a}, {b})]))",
    "l1": "list_sum([abs(t[1]-t[2]) for t in list_zip({a}, {b})])",
    "linf": "list_max([abs(t[1]-t[2]) for t in list_zip({a}, {b})])",
    "edit": "CAST(levenshtein({a}, {b}) AS DOUBLE)",
    "angular": "acos(greatest(-1.0, least(1.0, list_sum([t[1]*t[2] for t in list_zip({a}, {b})]) / sqrt(list_sum([v*v for v in {a}])) / sqrt(list_sum([v*v for v in {b}])))))",
    "jaccard": "1 - len(list_intersect({a}, {b})) / (len({a}) + len({b}) - len(list_intersect({a}, {b})))",
    "ultra": "CASE WHEN {a}[1] = {b}[1] THEN 0.0 WHEN {a}[2] = {b}[2] THEN 1.0 ELSE 2.0 END",
}


def dist(metric: str, a: str, b: str) -> str:
    return f"round({DIST[metric].format(a=a, b=b)}, 9)"


def first_centers(points: str, k: int) -> str:
    return f"SELECT pid AS cid, x AS cx FROM ({points}) ORDER BY pid LIMIT {k}"


def assigned(points: str, centers: str, metric: str) -> str:
    """(pid, w, cid, dist) as common tables ending in ``a``."""
    return (
        f"p AS ({points}), c AS ({centers}), d AS (SELECT pid, w, cid, {dist(metric, 'x', 'cx')} AS dist FROM p, c), "
        "a AS (SELECT pid, w, cid, dist FROM (SELECT *, row_number() OVER (PARTITION BY pid ORDER BY dist, cid) AS r FROM d) WHERE r = 1)"
    )


def trimmed(points: str, centers: str, metric: str, z: int) -> str:
    """Common tables ending in ``t`` (pid, w, dist, w_hat)."""
    return assigned(points, centers, metric) + (
        f", t AS (SELECT pid, w, dist, w - greatest(0, least(w, {z} - before)) AS w_hat FROM (SELECT *, coalesce(sum(w) OVER "
        "(ORDER BY dist DESC, pid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM a))"
    )


def optimum(points: str, metric: str, k: int, z: int, power: int = 2) -> str:
    ids = [f"c{i}.pid" for i in range(k)]
    joins = " JOIN ".join(["p c0"] + [f"p c{i} ON c{i - 1}.pid < c{i}.pid" for i in range(1, k)])
    near = f"least({', '.join(dist(metric, 'q.x', f'c{i}.x') for i in range(k))})" if k > 1 else dist(metric, "q.x", "c0.x")
    return (
        f"WITH p AS ({points}), s AS (SELECT [{', '.join(ids)}] AS s, q.pid, q.w, {near} AS d FROM {joins} CROSS JOIN p q), "
        "b AS (SELECT *, coalesce(sum(w) OVER (PARTITION BY s ORDER BY d DESC, pid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM s), "
        f"t AS (SELECT s, sum((w - greatest(0, least(w, {z} - before))) * power(d, {power})) AS cost FROM b GROUP BY s) "
        "SELECT array_to_string(s, ',') AS centers, round(cost, 6) AS cost FROM t ORDER BY round(cost, 6), s LIMIT 1"
    )


def cover(name: str, base: str, metric: str) -> str:
    """Recursive greedy cover of ``base`` (part, pid, x, w, thr): {name}(part, pid, w, proxy, pd) and {name}_y(part, pid, w)."""
    return (
        f"{name}_run AS (SELECT part, pid, x, w, thr, CAST(NULL AS BIGINT) AS proxy, CAST(NULL AS DOUBLE) AS pd FROM {base} UNION ALL "
        f"SELECT r.part, r.pid, r.x, r.w, r.thr, CASE WHEN {dist(metric, 'r.x', 'q.x')} <= r.thr THEN q.pid END, {dist(metric, 'r.x', 'q.x')} "
        f"FROM {name}_run r JOIN (SELECT part, min(pid) AS pid, arg_min(x, pid) AS x FROM {name}_run WHERE proxy IS NULL GROUP BY part) q ON r.part = q.part WHERE r.proxy IS NULL), "
        f"{name} AS (SELECT part, pid, w, proxy, pd, thr FROM {name}_run WHERE proxy IS NOT NULL), "
        f"{name}_y AS (SELECT c.part, c.proxy AS pid, any_value(b.x) AS x, CAST(sum(c.w) AS BIGINT) AS w FROM {name} c JOIN {base} b ON b.pid = c.proxy GROUP BY c.part, c.proxy)"
    )


def farthest_seeds(name: str, base: str, metric: str, k: int) -> str:
    """Recursive farthest-first traversal from the least id of ``base`` (pid, x): {name}(step, cid, cx)."""
    d = dist(metric, "b.x", "f.cx")
    return (
        f"{name}_run AS (SELECT 1 AS step, b.pid, b.x, {dist(metric, 'b.x', 'z.x')} AS near, z.pid AS cid, z.x AS cx FROM {base} b, (SELECT min(pid) AS pid, arg_min(x, pid) AS x FROM {base}) z UNION ALL "
        f"SELECT b.step + 1, b.pid, b.x, least(b.near, {d}), f.cid, f.cx FROM {name}_run b, (SELECT arg_max(pid, row(near, -pid)) AS cid, arg_max(x, row(near, -pid)) AS cx FROM {name}_run) f WHERE b.step < {k}), "
        f"{name} AS (SELECT DISTINCT step, cid, cx FROM {name}_run)"
    )


def round_one(points: str, metric: str, k: int, delta: float, parts: int, power: int = 2) -> str:
    """Common tables pts, seeds, near, sums (part, n, cost, radius), one_base, one (cover) with the k least ids of a part as seeds."""
    return (
        f"pts AS (SELECT *, pid % {parts} AS part FROM ({points})), "
        f"seeds AS (SELECT part, pid, x FROM (SELECT *, row_number() OVER (PARTITION BY part ORDER BY pid) AS r FROM pts) WHERE r <= {k}), "
        f"near AS (SELECT p.part, p.pid, any_value(p.x) AS x, any_value(p.w) AS w, min({dist(metric, 'p.x', 's.x')}) AS d FROM pts p JOIN seeds s ON p.part = s.part GROUP BY p.part, p.pid), "
        f"sums AS (SELECT part, CAST(sum(w) AS DOUBLE) AS n, sum(w * power(d, {power})) AS cost, power(sum(w * power(d, {power})) / sum(w), 1.0 / {power}) AS radius FROM near GROUP BY part), "
        f"one_base AS (SELECT n.part, n.pid, n.x, n.w, round({delta!r} * greatest(s.radius, n.d), 9) AS thr FROM near n JOIN sums s ON n.part = s.part), " + cover("one", "one_base", metric)
    )


def radius(power: int = 2) -> str:
    return f"rad AS (SELECT power(sum(n * power(radius, {power})) / sum(n), 1.0 / {power}) AS r FROM sums)"


def round_two(reference: str, metric: str, delta: float) -> str:
    """Common tables rad, two_base, two: the second cover against ``reference`` (pid, x)."""
    return (
        f"far AS (SELECT p.part, p.pid, any_value(p.x) AS x, any_value(p.w) AS w, min({dist(metric, 'p.x', 'c.x')}) AS d FROM pts p, {reference} c GROUP BY p.part, p.pid), "
        f"two_base AS (SELECT f.part, f.pid, f.x, f.w, round({delta!r} * greatest(rad.r, f.d), 9) AS thr FROM far f, rad), " + cover("two", "two_base", metric)
    )


def compact(metric: str, k: int, delta: float) -> str:
    """Common tables mini_base, mini: the union of first covers, covered against its k least ids."""
    return (
        f"mini_seeds AS (SELECT pid, x FROM one_y ORDER BY pid LIMIT {k}), "
        f"mini_near AS (SELECT c.pid, any_value(c.x) AS x, any_value(c.w) AS w, min({dist(metric, 'c.x', 's.x')}) AS d FROM one_y c, mini_seeds s GROUP BY c.pid), "
        f"mini_base AS (SELECT 0 AS part, m.pid, m.x, m.w, round({delta!r} * greatest(rad.r, m.d), 9) AS thr FROM mini_near m, rad), " + cover("mini", "mini_base", metric)
    )


def checks(*names: str) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS check_name, TRUE AS ok" for n in names)
