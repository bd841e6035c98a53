"""Rectangles of a pair's count matrix: heavy cells, empty cells, and variance-minimising K-D trees.

A leaf is (x_codes, y_codes, n, sse). Matrices here are dense and small (a pair of domains), so the
searches are numpy; many pairs run side by side through kd_for_pairs().
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Leaf:
    x_codes: tuple[int, ...]
    y_codes: tuple[int, ...]
    n: int
    sse: float


def heavy_cells(contingency: DataFrame, budget: int) -> DataFrame:
    """(x, y, n) of the `budget` most frequent cells of one pair, ties by x, then y."""
    return contingency.orderBy(F.desc("n"), "x", "y").limit(budget).select("x", "y", "n")


def empty_cells(contingency: DataFrame, x_codes: DataFrame, y_codes: DataFrame, budget: int) -> DataFrame:
    """(x, y, n): up to `budget` cells without rows, in order, topped up by the heaviest cells.

    The grid is the product of two domains (x_codes and y_codes, one column each), never of data.
    """
    grid = x_codes.select("x").crossJoin(y_codes.select("y"))
    none = grid.join(contingency.select("x", "y"), ["x", "y"], "left_anti").orderBy("x", "y").limit(budget)
    empty = none.select("x", "y", F.lit(0).cast("long").alias("n"))
    ranked = empty.withColumn("g", F.lit(0)).unionByName(heavy_cells(contingency, budget).withColumn("g", F.lit(1)))
    return ranked.orderBy("g", F.desc("n"), "x", "y").limit(budget).select("x", "y", "n")


class Prefix:
    """Sums of counts and of their squares over any rectangle of positions, in constant time."""

    def __init__(self, matrix: np.ndarray):
        self.shape = matrix.shape
        m = matrix.astype(np.float64)
        self.s, self.q = (np.pad(np.cumsum(np.cumsum(z, 0), 1), ((1, 0), (1, 0))) for z in (m, m * m))

    def sse(self, x0, x1, y0, y1):
        """Squared error about the mean of [x0, x1) x [y0, y1); arrays broadcast."""
        area = (x1 - x0) * (y1 - y0)
        s, q = (t[x1, y1] - t[x0, y1] - t[x1, y0] + t[x0, y0] for t in (self.s, self.q))
        return np.maximum(q - s * s / np.maximum(area, 1), 0)

    def total(self, x0, x1, y0, y1) -> float:
        t = self.s
        return t[x1, y1] - t[x0, y1] - t[x1, y0] + t[x0, y0]


def best_split(pre: Prefix, rect: tuple[int, int, int, int], axis: int) -> tuple[float, int] | None:
    """(error, cut) of the split of a rectangle on one axis with least summed error about both means; the first on ties."""
    x0, x1, y0, y1 = rect
    lo, hi = (x0, x1) if axis == 0 else (y0, y1)
    if hi - lo < 2:
        return None
    cut = np.arange(lo + 1, hi)
    if axis == 0:
        err = pre.sse(x0, cut, y0, y1) + pre.sse(cut, x1, y0, y1)
    else:
        err = pre.sse(x0, x1, y0, cut) + pre.sse(x0, x1, cut, y1)
    i = int(np.argmin(err))
    return float(err[i]), int(cut[i])


def median_split(pre: Prefix, rect: tuple[int, int, int, int], axis: int) -> tuple[float, int] | None:
    """The classic cut: where half of the rectangle's count lies on either side."""
    x0, x1, y0, y1 = rect
    lo, hi = (x0, x1) if axis == 0 else (y0, y1)
    if hi - lo < 2:
        return None
    cut = np.arange(lo + 1, hi)
    left = np.array([pre.total(x0, c, y0, y1) if axis == 0 else pre.total(x0, x1, y0, c) for c in cut])
    at = int(cut[np.argmin(np.abs(left - pre.total(*rect) / 2))])
    halves = ((x0, at, y0, y1), (at, x1, y0, y1)) if axis == 0 else ((x0, x1, y0, at), (x0, x1, at, y1))
    return float(sum(pre.sse(*h) for h in halves)), at


def kd_rectangles(
    matrix: np.ndarray, budget: int, rule: str = "variance", order: str = "breadth",
    x_order=None, y_order=None, seed_x: list[int] | None = None,
) -> list[Leaf]:
    """Up to `budget` disjoint leaves that cover a matrix, split alternately on x and y.

    rule: "variance" or "median". order: "breadth" splits level by level; "best_first" splits the leaf of
    largest error. A leaf without error, or without a cut on either axis, is left alone. x_order and y_order
    list the codes by position (orderings); seed_x fixes the cuts of x in advance, after which only y is split.
    """
    x_order = np.arange(matrix.shape[0]) if x_order is None else np.asarray(x_order)
    y_order = np.arange(matrix.shape[1]) if y_order is None else np.asarray(y_order)
    pre = Prefix(matrix[np.ix_(x_order, y_order)])
    split = {"variance": best_split, "median": median_split}[rule]
    nx, ny = pre.shape
    edges = [0, *(seed_x or []), nx]
    start = [(a, b, 0, ny) for a, b in zip(edges, edges[1:])]
    heap: list[tuple] = []
    leaves = set()
    serial = 0

    def add(rect, depth, axis):
        nonlocal serial
        err = float(pre.sse(*rect))
        leaves.add(rect)
        if err > 1e-9:
            heapq.heappush(heap, (depth if order == "breadth" else -err, serial, rect, depth, axis))
            serial += 1

    for r in start:
        add(r, 0, 1 if seed_x is not None else 0)
    while heap and len(leaves) < budget:
        _, _, rect, depth, axis = heapq.heappop(heap)
        found = split(pre, rect, axis)
        if found is None and seed_x is None:
            axis = 1 - axis
            found = split(pre, rect, axis)
        if found is None:
            continue
        x0, x1, y0, y1 = rect
        c = found[1]
        halves = ((x0, c, y0, y1), (c, x1, y0, y1)) if axis == 0 else ((x0, x1, y0, c), (x0, x1, c, y1))
        leaves.remove(rect)
        for h in halves:
            add(h, depth + 1, 1 if seed_x is not None else 1 - axis)
    return [
        Leaf(
            tuple(sorted(x_order[a:b].tolist())), tuple(sorted(y_order[c:d].tolist())),
            int(round(pre.total(a, b, c, d))), float(pre.sse(a, b, c, d)),
        )
        for a, b, c, d in sorted(leaves)
    ]


def axis_cuts(counts: np.ndarray, budget: int) -> list[int]:
    """Positions at which a single axis is cut into up to `budget` groups of similar counts."""
    leaves = kd_rectangles(np.asarray(counts).reshape(-1, 1), budget, order="best_first")
    return sorted(min(leaf.x_codes) for leaf in leaves)[1:]


def merge_rects(a: dict[str, set[int]], b: dict[str, set[int]]) -> dict[str, set[int]]:
    """Attribute-wise union of two rectangles."""
    return {k: set(a.get(k, ())) | set(b.get(k, ())) for k in a.keys() | b.keys()}


def kd_error(matrix: np.ndarray, leaves: list[Leaf], mode: str = "mean") -> float:
    """Mean over leaves of the root of a leaf's squared error, or "pooled": root of the total over the number of leaves."""
    sse = []
    for leaf in leaves:
        cells = matrix[np.ix_(leaf.x_codes, leaf.y_codes)].astype(np.float64)
        sse.append(float(((cells - cells.mean()) ** 2).sum()))
    return float(np.mean(np.sqrt(sse))) if mode == "mean" else float(np.sqrt(np.sum(sse)) / len(sse))


def kd_error_trials(matrix: np.ndarray, budgets, ordering: str, shuffles: int = 10) -> pd.DataFrame:
    """(leaves, mean, std) of the K-D error over deterministic shuffles of both axes."""
    from probsum.operators.ordering import order_axes, shuffled

    rows = []
    for budget in budgets:
        errors = []
        for seed in range(shuffles):
            m = shuffled(matrix, seed)
            x, y = order_axes(m, ordering)
            errors.append(kd_error(m, kd_rectangles(m, budget, x_order=x, y_order=y)))
        rows.append((budget, float(np.mean(errors)), float(np.std(errors))))
    return pd.DataFrame(rows, columns=["leaves", "mean", "std"])


def kd_for_pairs(contingency: DataFrame, sizes: dict[str, int], budget: int, ordering: str = "natural", **options) -> DataFrame:
    """(a, b, leaf_id, x_codes, y_codes, n, sse) of every pair of a contingency frame, one task per pair.

    A group holds the non-empty cells of a pair, bounded by the product of the two domains.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        from probsum.operators.ordering import order_axes

        a, b = pdf["a"].iloc[0], pdf["b"].iloc[0]
        m = np.zeros((sizes[a], sizes[b]), dtype=np.int64)
        m[pdf["x"], pdf["y"]] = pdf["n"]
        x, y = order_axes(m, ordering)
        leaves = kd_rectangles(m, budget, x_order=x, y_order=y, **options)
        return pd.DataFrame(
            [(a, b, i, list(z.x_codes), list(z.y_codes), z.n, z.sse) for i, z in enumerate(leaves)],
            columns=["a", "b", "leaf_id", "x_codes", "y_codes", "n", "sse"],
        )

    return contingency.groupBy("a", "b").applyInPandas(
        run, "a string, b string, leaf_id int, x_codes array<int>, y_codes array<int>, n long, sse double"
    )
