"""Keeping a summary current: statistic deltas, warm refits, rebuild triggers, and a stream sink."""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.functions.domain import encode
from probsum.plans.summary import Summary, summarise


def as_delta(old: DataFrame | None, new: DataFrame | None) -> DataFrame:
    """Signed rows (.., op): deletes of `old` and inserts of `new`; a changed value is one of each."""
    parts = []
    if old is not None:
        parts.append(old.withColumn("op", F.lit(-1)))
    if new is not None:
        parts.append(new.withColumn("op", F.lit(1)))
    return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])


def coded_delta(summary: Summary, delta: DataFrame) -> DataFrame:
    """(code columns, op): net changes per code tuple under the summary's pinned domains; unknown values get code -1."""
    names = [a.name for a in summary.attrs]
    keyed = delta.select(*names, "op")
    plus, _ = encode(keyed.where("op > 0"), summary.attrs, summary.domain, unknown="mark")
    minus, _ = encode(keyed.where("op < 0"), summary.attrs, summary.domain, unknown="mark")
    codes = plus.withColumn("op", F.lit(1)).unionByName(minus.withColumn("op", F.lit(-1)))
    return codes.groupBy(*names).agg(F.sum("op").alias("op")).where("op <> 0")


@dataclass
class Pending:
    """Accumulated changes of every statistic that a refit has not seen; as large as the statistics."""

    values: dict[str, np.ndarray]
    targets: list[np.ndarray]
    cells: dict[tuple[str, str], np.ndarray]
    n: float = 0.0
    rows: int = 0
    unknown: int = 0


@dataclass
class Maintained:
    """A summary with its pending changes and the contingencies that drift is judged by."""

    summary: Summary
    cells: dict[tuple[str, str], np.ndarray] = field(default_factory=dict)
    pending: Pending | None = None

    def __post_init__(self):
        self.reset()

    def reset(self) -> None:
        m = self.summary.model
        self.pending = Pending(
            {a: np.zeros(s) for a, s in m.sizes.items()}, [np.zeros(f.size) for f in m.families],
            {p: np.zeros_like(c) for p, c in self.cells.items()},
        )

    def apply_delta(self, delta: DataFrame) -> None:
        """Add signed rows to the pending statistics: predicates stay, counts and n change.

        Aggregated to distinct code tuples first; each statistic is one sum over those.
        """
        m, p = self.summary.model, self.pending
        changed = coded_delta(self.summary, delta).persist()
        known = changed.where(" and ".join(f"{a} >= 0" for a in m.attrs))
        p.unknown += int(changed.where(" or ".join(f"{a} < 0" for a in m.attrs)).agg(F.coalesce(F.sum(F.abs("op")), F.lit(0))).first()[0])
        for a in m.attrs:
            for r in known.groupBy(a).agg(F.sum("op").alias("op")).collect():
                p.values[a][r[a]] += r["op"]
        wanted = {tuple(f.attrs) for f in m.families} | set(self.cells)
        for attrs in wanted:
            rows = known.groupBy(*attrs).agg(F.sum("op").alias("op")).collect()  # as many as distinct cells
            for r in rows:
                point = tuple(r[a] for a in attrs)
                if attrs in p.cells:
                    p.cells[attrs][point] += r["op"]
                for f, fam in enumerate(m.families):
                    if tuple(fam.attrs) == attrs:
                        inside = np.logical_and.reduce([fam.masks[a][:, x] for a, x in zip(attrs, point)])
                        p.targets[f] += np.where(inside, r["op"], 0)
        total = known.agg(F.coalesce(F.sum("op"), F.lit(0)), F.coalesce(F.sum(F.abs("op")), F.lit(0))).first()
        p.n += total[0]
        p.rows += int(total[1])
        changed.unpersist()

    def refresh(self, **solver) -> Summary:
        """Refit from the present parameters with the pending changes, which are then done."""
        m, p = self.summary.model, self.pending
        values = {a: np.maximum(m.values[a] + p.values[a], 0) for a in m.attrs}
        targets = [np.maximum(f.targets + t, 0) for f, t in zip(m.families, p.targets, strict=True)]
        self.summary.model = self.summary.warm_model(values, targets, m.n + p.n)
        for pair, c in p.cells.items():
            self.cells[pair] = self.cells[pair] + c
        self.reset()
        self.summary.solve(**solver)
        return self.summary

    def rebuild(self, df: DataFrame, **options) -> Summary:
        self.summary = summarise(df, self.summary.attrs, **options)
        self.reset()
        return self.summary

    def sink(self, refit_rows: int = 1, **solver):
        """A foreachBatch function: batches accumulate one at a time, and a refit takes what is pending by then."""

        def each(batch: DataFrame, batch_id: int) -> None:
            self.apply_delta(batch)
            if self.pending.rows >= refit_rows:
                self.refresh(**solver)

        return each


def chi2_of(matrix: np.ndarray) -> float:
    n = matrix.sum()
    r, c = matrix.sum(axis=1, keepdims=True), matrix.sum(axis=0, keepdims=True)
    with np.errstate(divide="ignore", invalid="ignore"):
        return float(n * (np.nansum(matrix.astype(float) ** 2 / (r * c)) - 1)) if n else 0.0


@dataclass(frozen=True)
class RebuildPolicy:
    """When a summary should be built anew instead of refitted."""

    max_updates: int = 100_000
    chi2_low: float = 2.0  # per degree of freedom: a chosen pair that became this uniform
    chi2_high: float = 10.0  # an unchosen pair that became this dependent
    max_unknown: int = 0  # rows outside the pinned domains

    def reasons(self, kept: Maintained, idle: bool = False) -> list[str]:
        out = []
        p = kept.pending
        if p.rows >= self.max_updates:
            out.append("updates")
        if idle and p.rows:
            out.append("idle")
        if p.unknown > self.max_unknown:
            out.append("unknown values")
        chosen = {tuple(f.attrs) for f in kept.summary.model.families}
        for pair, cells in kept.cells.items():
            now = cells + p.cells[pair]
            rows, cols = (now.sum(axis=1) > 0).sum(), (now.sum(axis=0) > 0).sum()
            per_df = chi2_of(now) / max((rows - 1) * (cols - 1), 1)
            if pair in chosen and per_df <= self.chi2_low:
                out.append(f"uniform {pair}")
            if pair not in chosen and per_df >= self.chi2_high:
                out.append(f"dependent {pair}")
        return out


def all_pairs(summary: Summary) -> list[tuple[str, str]]:
    return list(combinations(summary.model.attrs, 2))
