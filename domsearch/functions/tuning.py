"""Choice of bands b and rows r by the areas of false positives and false negatives."""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .convert import jaccard_of
from .scores import _d

STEPS = 400
# ratios u/q at which the offline table is kept; a ratio takes the greatest one not above it
RATIO_EDGES = (0.0, 0.25, 0.5, 0.75, 1.0, 1.25, 1.5, 2.0, 3.0, 4.0, 6.0, 8.0, 12.0, 16.0, 24.0, 32.0, 48.0, 64.0, 96.0, 128.0, 256.0, 512.0, 1024.0)


def candidate_prob(s, b, r) -> Column:
    return 1 - F.pow(1 - F.pow(_d(s), _d(r)), _d(b))


def candidate_prob_t(t, x, q, b, r) -> Column:
    return candidate_prob(jaccard_of(t, x, q), b, r)


def static_threshold(b, r) -> Column:
    return F.pow(1 / _d(b), 1 / _d(r))


def static_params(s: float, m: int) -> tuple[int, int]:
    """The shape with b*r <= m whose static threshold is nearest to s."""
    return min(((m // r, r) for r in range(1, m + 1)), key=lambda x: (abs((1 / x[0]) ** (1 / x[1]) - s), x))


def shapes(m: int, layout: str | tuple[int, int] = "free") -> list[tuple[int, int]]:
    """All (b, r) with b*r <= m, or those that a forest of (trees, depth) can take."""
    if layout == "free":
        return [(b, r) for r in range(1, m + 1) for b in range(1, m // r + 1)]
    trees, depth = layout
    return [(b, r) for r in range(1, depth + 1) for b in range(1, trees + 1)]


def _prob(ratio: float, t: np.ndarray, b: np.ndarray, r: np.ndarray) -> np.ndarray:
    s = t / (ratio + 1 - t)
    each, at = np.unique(r, return_inverse=True)
    return 1 - (1 - s[None, :] ** each[:, None])[at] ** b[:, None]


def _area(values: np.ndarray, grid: np.ndarray) -> np.ndarray:
    return ((values[:, 1:] + values[:, :-1]) / 2 * np.diff(grid)).sum(axis=1)


def fp_area(ratio: float, t_star: float, b, r, steps: int = STEPS) -> np.ndarray:
    """Chance of being a candidate, over containments below the threshold; ``ratio`` is x/q."""
    b, r = np.atleast_1d(b), np.atleast_1d(r)
    grid = np.linspace(0, min(t_star, ratio, 1.0), steps + 1)
    return _area(_prob(ratio, grid, b, r), grid)


def fn_area(ratio: float, t_star: float, b, r, steps: int = STEPS) -> np.ndarray:
    """Chance of not being a candidate, over containments from the threshold up to the greatest possible one."""
    b, r = np.atleast_1d(b), np.atleast_1d(r)
    if ratio < t_star:
        return np.zeros(len(b))
    grid = np.linspace(t_star, min(1.0, ratio), steps + 1)
    return _area(1 - _prob(ratio, grid, b, r), grid)


def _live(ratio: float, t_star: float, b: np.ndarray, r: np.ndarray, fn_weight: float, cells: int) -> np.ndarray:
    """Shapes that may have the least weighted sum: the chance grows with the containment, so sums over a few cells bound both areas."""
    low, high = np.zeros((2, len(b)))
    for a, z, weight, missed in ((0.0, min(t_star, ratio, 1.0), 1.0, False), (t_star, min(1.0, ratio), fn_weight, True)):
        if z > a:
            p = _prob(ratio, np.linspace(a, z, cells + 1), b, r)
            p = 1 - p[:, ::-1] if missed else p
            low += weight * p[:, :-1].sum(axis=1) * ((z - a) / cells)
            high += weight * p[:, 1:].sum(axis=1) * ((z - a) / cells)
    return low <= high.min() + 1e-8


@lru_cache(maxsize=100_000)
def optimal_params(ratio: float, t_star: float, m: int, layout: str | tuple[int, int] = "free", fn_weight: float = 1.0, steps: int = STEPS) -> tuple[int, int, float, float]:
    """(b, r, fp, fn) of the least weighted sum; ties take the least b*r, then the least b."""
    pairs = shapes(m, layout)
    b, r = (np.array(x) for x in zip(*pairs, strict=True))
    for cells in (8, 40):  # a grid within that of all steps
        if steps % cells == 0 and fn_weight >= 0:
            live = _live(ratio, t_star, b, r, fn_weight, cells)
            b, r = b[live], r[live]
    fp, fn = fp_area(ratio, t_star, b, r, steps), fn_area(ratio, t_star, b, r, steps)
    total = np.round(fp + fn_weight * fn, 9)
    k = np.lexsort((b, b * r, total))[0]
    return int(b[k]), int(r[k]), float(fp[k]), float(fn[k])


def regret(x: int, u: int, q: int, t_star: float, m: int) -> float:
    """Extra error of tuning for the bound u instead of the size x; 0 at u = x."""
    b, r, *_ = optimal_params(u / q, t_star, m)
    best = optimal_params(x / q, t_star, m)
    return float(fp_area(x / q, t_star, b, r)[0] + fn_area(x / q, t_star, b, r)[0] - best[2] - best[3])


def precompute(m: int, thresholds: list[float], edges: tuple[float, ...] = RATIO_EDGES, layout="free", fn_weight: float = 1.0) -> list[tuple[int, float, float, int, int, float, float]]:
    """The offline table: (bin, ratio, t_star, b, r, fp, fn)."""
    out = []
    for k, edge in enumerate(edges):
        for t in thresholds:
            out.append((k, edge, t, *optimal_params(max(edge, 0.125), t, m, layout, fn_weight)))
    return out


def ratio_bin(u: Column, q: Column, edges: tuple[float, ...] = RATIO_EDGES) -> Column:
    """Number of the greatest edge not above u/q, by comparisons only."""
    ratio = _d(u) / _d(q)
    return sum(((ratio >= F.lit(e)).cast("int") for e in edges[1:]), F.lit(0))
