"""Table functions of the SQL surface; a module of their own, since workers import it."""

from __future__ import annotations

from ..functions import metrics
from ..operators import kernels


class BallCover:
    """ball_cover(TABLE(t) PARTITION BY p ORDER BY pid, delta, radius): scalar points (pid, x, near) to balls (pid, w)."""

    def __init__(self):
        self.rows: list[tuple[int, float, float]] = []
        self.delta = self.radius = 0.0

    def eval(self, row, delta: float, radius: float):
        self.rows.append((row["pid"], row["x"], row["near"]))
        self.delta, self.radius = delta, radius

    def terminate(self):
        import numpy as np

        if self.rows:
            ids, x, near = (np.array(c) for c in zip(*sorted(self.rows)))
            picked, mass, _, _ = kernels.ball_cover(metrics.ABS, x.astype(float), near.astype(float), np.ones(len(x), dtype="int64"), self.delta, self.radius)
            yield from ((int(ids[i]), int(m)) for i, m in zip(picked, mass))


class KMeansOut:
    """kmeans_out(TABLE(t) PARTITION BY p, k, z): weighted scalar points (pid, x, w) to centers (pid, cost)."""

    def __init__(self):
        self.rows: list[tuple[int, float, int]] = []
        self.k, self.z = 1, 0

    def eval(self, row, k: int, z: int):
        self.rows.append((row["pid"], row["x"], row["w"]))
        self.k, self.z = k, z

    def terminate(self):
        import numpy as np

        from ..operators import solvers

        if self.rows:
            ids, x, w = (np.array(c) for c in zip(*sorted(self.rows)))
            s, _ = solvers.solve_points(metrics.ABS, x.astype("float64"), w.astype("int64"), self.k, self.z, "alternate")
            yield from ((int(ids[c]), float(s.cost)) for c in s.centers)
