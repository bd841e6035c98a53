"""Near-duplicate vectors by an epsilon grid order join.

Cosine c or more between unit vectors is a distance of at most eps = sqrt(2 - 2c). Vectors are rotated to
principal axes, sorted by their grid cells of width eps on the leading axes (cells in lexicographic order), and cut
into blocks. Two blocks meet only if some of their cells are neighbours and their bounding boxes are
within eps; inside a pair of blocks the sequence intervals are halved recursively, intervals whose boxes are
farther apart being skipped, down to small matrix products in double precision.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import components, written

SLACK = 1e-9


def principal_axes(sample: np.ndarray) -> np.ndarray:
    """Orthonormal axes (columns) of a sample of unit vectors, by falling variance."""
    value, axes = np.linalg.eigh(np.cov(sample.T) if len(sample) > 1 else np.eye(sample.shape[1]))
    return np.ascontiguousarray(axes[:, ::-1])


def box_distance2(lo_a, hi_a, lo_b, hi_b) -> float:
    gap = np.maximum(np.maximum(lo_b - hi_a, lo_a - hi_b), 0)
    return float((gap * gap).sum())


def interval_join(a: np.ndarray, b: np.ndarray, ra: np.ndarray, rb: np.ndarray, least: float, same: bool, leaf: int = 256):
    """(rows of a, rows of b) linked, leaf by leaf, as boolean matrices with their offsets.

    a, b: the vectors; ra, rb: their rotated unit forms, in grid order. For `same` only pairs i < j are given.
    """
    eps2 = 2 - 2 * least + SLACK
    na, nb = np.sqrt((a * a).sum(axis=1)), np.sqrt((b * b).sum(axis=1))

    def visit(i0, i1, j0, j1):
        if same and j1 <= i0:
            return
        x, y = ra[i0:i1], rb[j0:j1]
        if box_distance2(x.min(axis=0), x.max(axis=0), y.min(axis=0), y.max(axis=0)) > eps2:
            return
        if i1 - i0 <= leaf and j1 - j0 <= leaf:
            hit = (a[i0:i1] @ b[j0:j1].T) / na[i0:i1, None] / nb[None, j0:j1] >= least
            if same:
                hit &= np.arange(i0, i1)[:, None] < np.arange(j0, j1)[None, :]
            if hit.any():
                yield i0, j0, hit
            return
        im, jm = (i0 + i1) // 2, (j0 + j1) // 2
        for p in ([(i0, im), (im, i1)] if i1 - i0 > leaf else [(i0, i1)]):
            for q in ([(j0, jm), (jm, j1)] if j1 - j0 > leaf else [(j0, j1)]):
                yield from visit(*p, *q)

    yield from visit(0, len(a), 0, len(b))


def leaf_forest(hit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Component label (a row number) of the rows and columns of a matrix of links; -1 without a link."""
    rows, cols = hit.any(axis=1), hit.any(axis=0)
    big = hit.shape[0]
    row = np.where(rows, np.arange(big), big)
    while True:
        col = np.where(hit, row[:, None], big).min(axis=0)
        new = np.where(rows, np.minimum(row, np.where(hit, col[None, :], big).min(axis=1)), big)
        if (new == row).all():
            break
        row = new
    return np.where(rows, row, -1), np.where(cols, col, -1)


def near_duplicates(
    vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", least: float = 0.9,
    block: int | None = None, cells: int = 3, sample: int = 20_000,
) -> DataFrame:
    """One row (id, n_links, component, kept) per input row.

    Rows link if the cosine of their vectors is `least` or more; component is the least id reachable, n_links
    counts the other rows linked directly. Equal vectors are one node that counts as often as it occurs, so copies
    cost no pairs. A vector that is null, empty, zero, or has a null or non-finite component links with nothing, and vectors of different
    length do not link. Ids are taken to name vectors; rows repeating an id and a vector count each. The
    axes are fitted on the `sample` vectors with the least hash, which bounds what the driver sees (20,000 vectors, 10 MB
    at 64 components) and only affects speed. A block has `block` vectors, or what 8 MB of doubles hold; a pair of blocks is
    one task's work at a time. Links stay where they are found: a block pair reports counts and a forest.
    """
    v = F.col("v")
    rows = vectors.select(
        F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")
    ).withColumn(
        "ok",
        F.coalesce(
            F.expr("size(v) > 0 and forall(v, x -> x is not null and not isnan(x) and abs(x) < double('infinity'))"),
            F.lit(False),
        )
        & F.coalesce(F.expr("exists(v, x -> x <> 0)"), F.lit(False)),
    )
    nodes = written(
        rows.where("ok").groupBy("v").agg(F.min("id").alias("cls"), F.count(F.lit(1)).alias("mult")).select(
            "cls", "mult", F.size("v").alias("dim"), "v"
        ),
        "vectors",
    )
    first = nodes.groupBy("dim").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "dim").first()
    dim = first["dim"] if first else 1
    drawn = nodes.where(F.col("dim") == dim).orderBy(F.xxhash64("cls"), "cls").limit(sample).select("v").collect()
    unit = np.array([r["v"] for r in drawn], dtype=np.float64).reshape(-1, dim)
    unit /= np.maximum(np.abs(unit).max(axis=1, keepdims=True), 1e-300)
    axes = principal_axes(unit / np.sqrt((unit * unit).sum(axis=1, keepdims=True)))
    block = block or max(256, (1 << 23) // (8 * dim))
    kind = "f4" if vectors.select(vector_col).dtypes[0][1] == "array<float>" else "f8"  # floats travel as they came
    eps = float(np.sqrt(2 - 2 * least))
    width = max(eps, 1e-6)

    def rotate(x: np.ndarray) -> np.ndarray:
        x = x / np.abs(x).max(axis=1, keepdims=True)
        x = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
        return x @ axes if x.shape[1] == len(axes) else x

    def place(batches):
        for pdf in batches:
            for d, part in pdf.groupby("dim", sort=False):
                x = np.stack(part["v"].to_numpy())
                c = np.floor(rotate(x)[:, : 2 * cells] / width).astype(np.int32)
                yield pd.DataFrame(
                    {"cls": part["cls"], "mult": part["mult"], "dim": d, "cell": list(np.pad(c, ((0, 0), (0, 2 * cells - c.shape[1])))), "v": list(x)}
                )

    placed = nodes.mapInPandas(place, "cls long, mult long, dim int, cell array<int>, v array<double>")
    order = ["dim", *[F.col("cell")[k] for k in range(2 * cells)], "cls"]

    def cut(batches):
        from pyspark import TaskContext

        base, seq, hold = TaskContext.get().partitionId() << 32, 0, None

        def packed(part):
            nonlocal seq
            x = np.stack(part["v"].to_numpy())
            r = rotate(x)
            lead = np.stack(part["cell"].to_numpy())[:, :cells]
            out = {
                "block": base + seq, "dim": int(part["dim"].iloc[0]), "n": len(part), "lo": r.min(axis=0).tolist(), "hi": r.max(axis=0).tolist(),
                "cells": np.unique(lead, axis=0).tolist(), "cls": part["cls"].tolist(), "mult": part["mult"].tolist(), "data": x.astype(kind).tobytes(),
            }
            seq += 1
            return pd.DataFrame([out])

        for pdf in batches:
            hold = pdf if hold is None else pd.concat([hold, pdf], ignore_index=True)
            while len(hold):
                size = int(np.searchsorted(hold["dim"].to_numpy(), hold["dim"].iloc[0], side="right"))
                if size < block and size == len(hold):
                    break
                size = min(size, block)
                yield packed(hold.iloc[:size])
                hold = hold.iloc[size:]
        if hold is not None and len(hold):
            yield packed(hold)

    total = nodes.count()
    blocks = written(
        placed.repartitionByRange(max(1, -(-total // (8 * block))), *order).sortWithinPartitions(*order).mapInPandas(
            cut,
            "block long, dim int, n int, lo array<double>, hi array<double>, cells array<array<int>>,"
            " cls array<long>, mult array<long>, data binary",
        ),
        "vector-blocks",
    )
    meta = blocks.select("block", "dim", "lo", "hi", "cells")
    around = F.expr(
        "flatten(transform(cells, c -> "
        + "transform(sequence(0, %d), k -> transform(c, (x, i) -> cast(x + pmod(floor(k / pow(3, i)), 3) - 1 as int)))))"
        % (3**cells - 1)
    )
    here = meta.select("block", "dim", F.explode("cells").alias("cell"))
    there = meta.select(F.col("block").alias("other"), F.col("dim").alias("d2"), F.explode(F.array_distinct(around)).alias("near"))
    met = (
        here.join(there, F.expr("dim = d2 and cell = near and block <= other"))
        .select("block", "other")
        .distinct()
    )
    boxes = meta.select(F.col("block").alias("b"), "lo", "hi")
    gap2 = F.expr(
        "aggregate(zip_with(zip_with(lo, hi2, (x, y) -> x - y), zip_with(lo2, hi, (x, y) -> x - y),"
        " (p, q) -> pow(greatest(p, q, 0D), 2)), 0D, (s, x) -> s + x)"
    )
    pairs = (
        met.join(boxes, F.col("block") == F.col("b"))
        .drop("b")
        .join(boxes.select(F.col("b").alias("b2"), F.col("lo").alias("lo2"), F.col("hi").alias("hi2")), F.expr("other = b2"))
        .where(gap2 <= eps * eps + SLACK)
        .select("block", "other")
    )
    sides = pairs.select("block", "other", F.explode(F.array_distinct(F.array("block", "other"))).alias("own"))
    full = blocks.select(F.col("block").alias("own"), "dim", "cls", "mult", "data")
    loaded = full.join(sides, "own").select("block", "other", "own", "dim", "cls", "mult", "data")

    def compare(batches):
        held = None  # the first block of a pair; the second comes next
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                if r.own == r.block:
                    held = r
                if r.own == r.other:
                    yield from joined(held, r)

    def joined(r, other):
        same = r.block == r.other
        a, b = (np.frombuffer(x.data, dtype=kind).astype(np.float64).reshape(-1, x.dim) for x in (r, other))
        a, b = a / np.abs(a).max(axis=1, keepdims=True), b / np.abs(b).max(axis=1, keepdims=True)
        ca, cb, ma, mb = (np.asarray(x, dtype=np.int64) for x in (r.cls, other.cls, r.mult, other.mult))
        got_a, got_b, edges = np.zeros(len(a), np.int64), np.zeros(len(b), np.int64), []
        for i0, j0, hit in interval_join(a, b, rotate(a), rotate(b), least, same):
            i1, j1 = i0 + hit.shape[0], j0 + hit.shape[1]
            got_a[i0:i1] += hit @ mb[j0:j1]
            got_b[j0:j1] += ma[i0:i1] @ hit
            row, col = leaf_forest(hit)
            for ids, lab in ((ca[i0:i1], row), (cb[j0:j1], col)):
                own = lab >= 0
                edges.append(np.c_[ids[own], ca[i0:i1][lab[own]]])
        for ids, got in ((ca, got_a), (cb, got_b)):
            keep = got > 0
            if keep.any():
                yield pd.DataFrame({"a": ids[keep], "b": ids[keep], "n": got[keep]})
        if edges:
            e = np.unique(np.concatenate(edges), axis=0)
            e = e[e[:, 0] != e[:, 1]]
            yield pd.DataFrame({"a": e[:, 0], "b": e[:, 1], "n": np.zeros(len(e), np.int64)})

    # a block pair is heavy: few to a task
    found = written(
        loaded.repartition("block", "other")
        .sortWithinPartitions("block", "other", F.col("own") != F.col("block"))
        .mapInPandas(compare, "a long, b long, n long"),
        "vector-links",
    )
    counts = found.where("n > 0").groupBy("a").agg(F.sum("n").alias("got"))
    comp = written(components(found.where("n = 0").select("a", "b")), "vector-components")
    named = (
        nodes.join(counts, F.col("cls") == F.col("a"), "left")
        .drop("a")
        .join(comp, F.col("cls") == F.col("node"), "left")
        .select(
            F.col("v").alias("v2"),
            (F.coalesce("got", F.lit(0)) + F.col("mult") - 1).alias("n_links"),
            F.coalesce("component", "cls").alias("component"),
        )
    )
    linked = rows.where("ok").join(named, v == F.col("v2")).select("id", "n_links", "component")
    alone = rows.where("not ok").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component"))
    return linked.union(alone).withColumn("kept", F.expr("id <=> component"))
