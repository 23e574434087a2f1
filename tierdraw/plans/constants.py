"""Constants of a least-squares problem over the given rows: what bounds and step sizes are made of."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..oracle.training import ROWS


@dataclass
class LeastSquares:
    """Normal equations of the mean of (a x - y)^2 / 2, and the second moments of the samples' gradients at zero."""

    h: np.ndarray
    b: np.ndarray
    c: float
    at_zero: float

    @classmethod
    def of(cls, samples: DataFrame, d: int) -> LeastSquares:
        """One pass over ``samples`` (a, y); one row comes back, of d squared sums."""
        a, y = F.col("a"), F.col("y")
        sums = [F.avg(a[i] * a[j]) for i in range(d) for j in range(d)] + [F.avg(a[i] * y) for i in range(d)]
        row = samples.agg(*sums, F.avg(y * y), sum(F.avg(a[i] * y * a[i] * y) for i in range(d))).first()
        return cls(np.array(row[: d * d]).reshape(d, d), np.array(row[d * d : d * d + d]), float(row[-2]), float(row[-1]))

    def loss(self, x: np.ndarray) -> float:
        return float(0.5 * (x @ self.h @ x - 2 * self.b @ x + self.c))

    def grad(self, x: np.ndarray) -> np.ndarray:
        return self.h @ x - self.b

    def best(self) -> np.ndarray:
        return np.linalg.lstsq(self.h, self.b, rcond=None)[0]

    def smoothness(self, rounds: int = 200) -> float:
        """Largest eigenvalue, by power iteration."""
        v = np.ones(len(self.b))
        for _ in range(rounds):
            v = self.h @ v
            v = v / np.linalg.norm(v)
        return float(v @ self.h @ v)

    def noise2(self) -> float:
        """Variance of one sample's gradient at zero."""
        return self.at_zero - float(self.b @ self.b)


def _solved() -> str:
    """CTEs of the normal equations (mat), their solution by conjugate gradients (best) and the largest eigenvalue by power iteration (top)."""
    times = lambda v: f"list_transform(h, lambda row: list_dot_product(row, {v}))"
    add = lambda x, s, p: f"list_transform(range(1, 5), lambda i: {x}[i] + ({s}) * {p}[i])"
    return f"""{ROWS.format(m=1)},
cells AS (SELECT i, j, avg(a[i + 1] * a[j + 1]) AS h, avg(a[i + 1] * y) AS b, avg(a[i + 1] * y * a[i + 1] * y) AS s FROM samples, (SELECT unnest(range(4)) AS i), (SELECT unnest(range(4)) AS j) GROUP BY i, j),
rows_of AS (SELECT i, list(h ORDER BY j) AS h, any_value(b) AS b, any_value(s) AS s FROM cells GROUP BY i),
mat AS MATERIALIZED (SELECT list(h ORDER BY i) AS h, list(b ORDER BY i) AS b, sum(s) AS at_zero, (SELECT avg(y * y) FROM samples) AS c FROM rows_of),
cg AS (
    SELECT 0 AS k, [0.0, 0.0, 0.0, 0.0]::DOUBLE[] AS x, b AS r, b AS p FROM mat
    UNION ALL
    SELECT k + 1, x, r, {add("r", "list_dot_product(r, r) / rr", "p")} FROM (
        SELECT k, rr, p, {add("x", "step", "p")} AS x, {add("r", "-step", "hp")} AS r FROM (
            SELECT *, list_dot_product(r, r) AS rr, list_dot_product(r, r) / list_dot_product(p, hp) AS step FROM (SELECT cg.*, {times("p")} AS hp FROM cg, mat WHERE k < 8 AND list_dot_product(r, r) > 1e-26)))),
best AS MATERIALIZED (SELECT x FROM cg ORDER BY k DESC LIMIT 1),
power AS (
    SELECT 0 AS k, [0.5, 0.5, 0.5, 0.5]::DOUBLE[] AS v
    UNION ALL SELECT k + 1, list_transform(hv, lambda z: z / sqrt(list_dot_product(hv, hv))) FROM (SELECT k, {times("v")} AS hv FROM power, mat WHERE k < 200)),
top AS MATERIALIZED (SELECT list_dot_product(v, {times("v")}) AS l FROM power, mat WHERE k = 200)"""


def _loss_sql(x: str) -> str:
    return f"0.5 * (list_dot_product({x}, list_transform(h, lambda row: list_dot_product(row, {x}))) - 2 * list_dot_product(b, {x}) + c)"


def constants_sql() -> str:
    return f"""WITH RECURSIVE {_solved()}
SELECT round(l, 6) AS smoothness, round(at_zero - list_dot_product(b, b), 6) AS noise2, round(c / 2 - {_loss_sql("x")}, 6) AS gap, round(list_dot_product(x, x), 6) AS distance2 FROM mat, best, top"""


def self_bound_sql(steps: int, eta: float) -> str:
    return f"""WITH RECURSIVE {_solved()},
gd AS (
    SELECT 0 AS step, [0.0, 0.0, 0.0, 0.0]::DOUBLE[] AS z
    UNION ALL SELECT step + 1, list_transform(range(1, 5), lambda i: z[i] - {eta} * (list_dot_product(h[i], z) - b[i])) FROM gd, mat WHERE step < {steps}),
log AS (
    SELECT step, {_loss_sql("z")} AS loss, list_sum(list_transform(range(1, 5), lambda i: pow(list_dot_product(h[i], z) - b[i], 2))) AS grad_norm2, l, {_loss_sql("x")} AS least
    FROM gd, mat, best, top)
SELECT step::INT AS step, round(loss, 9) AS loss, round(grad_norm2, 9) AS grad_norm2, grad_norm2 <= 2 * l * (loss - least) * (1 + 1e-9) + 1e-12 AS holds FROM log"""
