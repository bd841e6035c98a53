"""Orderings of a count matrix's axes ahead of the K-D tree, and one pass of each as a DataFrame."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("natural", "zero_index", "one_index", "weighted_index")


def _scores(m: np.ndarray, kind: str) -> np.ndarray:
    """Score of every row of `m`; columns are numbered from 1 in their present order."""
    at = np.arange(1, m.shape[1] + 1, dtype=np.float64)
    if kind == "weighted_index":
        return m @ at
    marked = (m == 0) if kind == "zero_index" else (m != 0)
    count = marked.sum(axis=1)
    return np.where(count > 0, marked @ at / np.maximum(count, 1), 0.0)


def order_axes(matrix: np.ndarray, kind: str = "weighted_index", most: int = 200) -> tuple[np.ndarray, np.ndarray]:
    """Codes of x and of y by position: rows and columns are sorted in turn until neither moves, or `most` passes.

    zero_index: mean position of the empty cells; one_index: of the others; weighted_index: sum of
    position times count. Equal scores keep their positions.
    """
    if kind not in KINDS:
        raise ValueError(kind)
    x, y = np.arange(matrix.shape[0]), np.arange(matrix.shape[1])
    if kind == "natural":
        return x, y
    for _ in range(most):
        rows = np.argsort(_scores(matrix[np.ix_(x, y)], kind), kind="stable")
        x = x[rows]
        cols = np.argsort(_scores(matrix[np.ix_(x, y)].T, kind), kind="stable")
        y = y[cols]
        if (np.diff(rows) == 1).all() and (np.diff(cols) == 1).all():
            break
    return x, y


def shuffled(matrix: np.ndarray, seed: int) -> np.ndarray:
    """The matrix with both axes shuffled by integer mixing, the same on every machine."""

    def perm(n: int, salt: int) -> np.ndarray:
        key = [((i + 1) * 7919 + (seed + 1) * 104_729 + salt * 1_299_709) * 2_654_435_761 % 1_000_003 for i in range(n)]
        return np.argsort(key, kind="stable")

    return matrix[np.ix_(perm(matrix.shape[0], 1), perm(matrix.shape[1], 2))]


def ordering_pass(cells: DataFrame, x_codes: DataFrame, y_codes: DataFrame, kind: str) -> DataFrame:
    """(x, pos): rows ordered once, columns in natural order (code + 1), from the non-empty cells (x, y, n).

    x_codes and y_codes are the domains, one column each.
    """
    from pyspark.sql import Window as W

    at = F.col("y") + 1
    if kind == "zero_index":
        grid = x_codes.crossJoin(y_codes).join(cells.select("x", "y"), ["x", "y"], "left_anti")
        score = grid.groupBy("x").agg(F.avg(at.cast("double")).alias("s"))
    elif kind == "one_index":
        score = cells.where("n > 0").groupBy("x").agg(F.avg(at.cast("double")).alias("s"))
    else:
        score = cells.groupBy("x").agg(F.sum(at * F.col("n")).cast("double").alias("s"))
    ranked = x_codes.join(score, "x", "left").select("x", F.coalesce("s", F.lit(0.0)).alias("s"))
    return ranked.select("x", (F.row_number().over(W.orderBy("s", "x")) - 1).alias("pos"))
