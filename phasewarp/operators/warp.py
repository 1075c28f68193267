"""Dynamic time warping over packed cost matrices, in Catalyst expressions or in numpy.

The Catalyst form keeps one row per pair of series: the cumulated matrix is folded row by row by
nested ``aggregate`` calls and the path by one more.  It suits series up to about a thousand
points; longer or banded ones take the Arrow form, which must agree with it.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

INFINITE = float("inf")


def cumulate(cells: Column, bias: tuple[float, float, float] = (1.0, 1.0, 1.0), third: str = "cumulated") -> Column:
    """Cumulated costs of an ``array<array<double>>``: running sums on the borders, inside the
    local cost plus the least of three predecessors (above, diagonal, left), each times its bias.
    With ``third='local'`` the left predecessor is taken before cumulation."""
    up, diagonal, left = (F.lit(float(b)) for b in bias)

    def first_row(row: Column) -> Column:
        return F.aggregate(row, F.array().cast("array<double>"), lambda acc, d: F.array_append(acc, F.coalesce(F.get(acc, F.size(acc) - 1), F.lit(0.0)) + d))

    def next_row(above: Column, row: Column) -> Column:
        def put(acc: Column, d: Column) -> Column:
            j = F.size(acc)
            before = F.get(acc, j - 1) if third == "cumulated" else F.get(row, j - 1)
            inside = d + F.least(up * F.get(above, j), diagonal * F.get(above, j - 1), left * before)
            return F.array_append(acc, F.when(j == 0, d + F.get(above, F.lit(0))).otherwise(inside))

        return F.aggregate(row, F.array().cast("array<double>"), put)

    empty = F.array().cast("array<array<double>>")
    return F.aggregate(cells, empty, lambda rows, row: F.array_append(rows, F.when(F.size(rows) == 0, first_row(row)).otherwise(next_row(F.get(rows, F.size(rows) - 1), row))))


def backtrack(costs: Column) -> Column:
    """Path ``array<struct<i, j>>`` (1-based, in order) from the last cell to the first: borders
    are forced, inside the least predecessor, ties to the diagonal, then i-1, then j-1."""
    at = lambda i, j: F.get(F.get(costs, i - 1), j - 1)
    n, m = F.size(costs), F.size(F.get(costs, F.lit(0)))
    step = lambda i, j: F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"))

    def previous(p: Column) -> Column:
        i, j = p["i"], p["j"]
        d, u, left = at(i - 1, j - 1), at(i - 1, j), at(i, j - 1)
        inside = F.when((d <= u) & (d <= left), step(i - 1, j - 1)).when(u <= left, step(i - 1, j)).otherwise(step(i, j - 1))
        return F.when(i == 1, step(i, j - 1)).when(j == 1, step(i - 1, j)).otherwise(inside)

    def walk(path: Column, _: Column) -> Column:
        last = F.get(path, F.size(path) - 1)
        return F.when((last["i"] == 1) & (last["j"] == 1), path).otherwise(F.array_append(path, previous(last)))

    return F.reverse(F.aggregate(F.sequence(F.lit(0), n + m - 2), F.array(step(n, m)), walk))


def cumulate_numpy(d: np.ndarray, bias=(1.0, 1.0, 1.0), third: str = "cumulated", band: int | None = None) -> np.ndarray:
    """The same by anti-diagonals; cells further than ``band`` off the diagonal stay infinite."""
    n, m = d.shape
    g = np.full((n, m), INFINITE)
    g[:, 0], g[0, :] = np.cumsum(d[:, 0]), np.cumsum(d[0, :])
    if band is not None:
        off = np.abs(np.arange(n)[:, None] - np.arange(m)[None, :]) > band
        g[off] = INFINITE
    for s in range(2, n + m - 1):
        lo, hi = max(1, s - m + 1), min(n - 1, s - 1)
        if band is not None:
            lo, hi = max(lo, -((band - s) // 2)), min(hi, (s + band) // 2)
        if lo > hi:
            continue
        i = np.arange(lo, hi + 1)
        j = s - i
        left = g[i, j - 1] if third == "cumulated" else d[i, j - 1]
        g[i, j] = d[i, j] + np.minimum(np.minimum(bias[0] * g[i - 1, j], bias[1] * g[i - 1, j - 1]), bias[2] * left)
    return g


def backtrack_numpy(g: np.ndarray) -> list[tuple[int, int]]:
    i, j = g.shape
    path = [(i, j)]
    while (i, j) != (1, 1):
        if i == 1:
            j -= 1
        elif j == 1:
            i -= 1
        else:
            d, u, left = g[i - 2, j - 2], g[i - 2, j - 1], g[i - 1, j - 2]
            if d <= u and d <= left:
                i, j = i - 1, j - 1
            elif u <= left:
                i -= 1
            else:
                j -= 1
        path.append((i, j))
    return path[::-1]


def safe_band(local: np.ndarray, omega_of) -> int:
    """Largest offset that an optimal path can use: all distances are non-negative, so a cell
    whose offset penalty alone exceeds the cost of one legal path is out of reach."""
    n, m = local.shape
    i = np.arange(max(n, m))
    legal = local[np.minimum(i, n - 1), np.minimum(i, m - 1)].sum()
    band = abs(n - m)
    while band < max(n, m) - 1 and omega_of(band + 1) <= legal:
        band += 1
    return band
