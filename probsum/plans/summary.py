"""The summary of a relation: domains, statistics and a fitted model behind one query interface."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from probsum.functions.domain import Attr, codes_matching, encode
from probsum.operators.ordering import order_axes
from probsum.operators.pairs import pair_scores, pick_pairs
from probsum.operators.rectangles import kd_rectangles
from probsum.operators.stats import matrix_of, pair_counts
from probsum.plans import infer
from probsum.plans.forest import build_model
from probsum.plans.model import Family, Model


def family_of_cells(a: str, b: str, cells, sizes: dict[str, int]) -> Family:
    """A family of single cells (x, y, n)."""
    cells = list(cells)
    masks = {a: np.zeros((len(cells), sizes[a]), dtype=bool), b: np.zeros((len(cells), sizes[b]), dtype=bool)}
    for i, (x, y, _) in enumerate(cells):
        masks[a][i, x] = masks[b][i, y] = True
    return Family((a, b), masks, np.array([c[2] for c in cells], dtype=np.float64))


def family_of_leaves(a: str, b: str, leaves, sizes: dict[str, int]) -> Family:
    masks = {a: np.zeros((len(leaves), sizes[a]), dtype=bool), b: np.zeros((len(leaves), sizes[b]), dtype=bool)}
    for i, leaf in enumerate(leaves):
        masks[a][i, list(leaf.x_codes)] = True
        masks[b][i, list(leaf.y_codes)] = True
    return Family((a, b), masks, np.array([leaf.n for leaf in leaves], dtype=np.float64))


def family_of_sets(rects: list[dict[str, set[int]]], targets, sizes: dict[str, int]) -> Family:
    """Rectangles over any number of attributes, as sets of codes."""
    attrs = tuple(sorted({a for r in rects for a in r}))
    masks = {a: np.zeros((len(rects), sizes[a]), dtype=bool) for a in attrs}
    for i, r in enumerate(rects):
        for a in attrs:
            masks[a][i, list(r[a])] = True
    return Family(attrs, masks, np.asarray(targets, dtype=np.float64))


def choose_family(matrix: np.ndarray, a: str, b: str, budget: int, rects: str, ordering: str, sizes: dict[str, int], **options) -> Family:
    """The rectangles of a pair: "kd", "heavy" or "empty" (with heavy cells for the rest of the budget)."""
    if rects == "kd":
        x, y = order_axes(matrix, ordering)
        return family_of_leaves(a, b, kd_rectangles(matrix, budget, x_order=x, y_order=y, **options), sizes)
    xs, ys = np.nonzero(matrix)
    heavy = sorted(zip(xs.tolist(), ys.tolist(), matrix[xs, ys].tolist()), key=lambda c: (-c[2], c[0], c[1]))
    if rects == "heavy":
        return family_of_cells(a, b, heavy[:budget], sizes)
    if rects == "empty":
        ex, ey = np.nonzero(matrix == 0)
        none = [(x, y, 0) for x, y in zip(ex.tolist(), ey.tolist())][:budget]
        return family_of_cells(a, b, (none + heavy)[:budget], sizes)
    raise ValueError(rects)


@dataclass
class Summary:
    """A fitted summary; `where` arguments map attributes to SQL predicates over their values."""

    spark: SparkSession
    domain: DataFrame
    model: Model
    attrs: list[Attr] = field(default_factory=list)
    pairs: list[tuple[str, str]] = field(default_factory=list)
    phases: dict[str, float] = field(default_factory=dict)

    # -- building -----------------------------------------------------------

    @classmethod
    def from_histograms(cls, spark, values: dict[str, np.ndarray], families=(), n=None, **options) -> "Summary":
        """A summary without data access, from supplied counts; codes serve as values."""
        rows = [(a, i, str(i), None, None, int(v)) for a, vs in values.items() for i, v in enumerate(vs)]
        domain = spark.createDataFrame(rows, "attr string, code int, label string, lo double, hi double, n long")
        return cls(spark, domain, Model(values, families, n, **options), [Attr(a) for a in values])

    # -- asking -------------------------------------------------------------

    def weights(self, where: dict[str, str] | None) -> infer.Weights:
        out = {}
        for a, predicate in (where or {}).items():
            if a not in self.model.sizes:
                raise KeyError(a)
            out[a] = infer.mask(self.model, a, codes_matching(self.domain, a, predicate))
        return out

    def count(self, where: dict[str, str] | None = None, method: str = "mask", with_variance: bool = False):
        w = self.weights(where)
        est = infer.estimate(self.model, w, method)
        return (est, infer.variance(self.model, w)) if with_variance else est

    def count_any(self, clauses: list[dict[str, str]]) -> float:
        return infer.estimate_any(self.model, [self.weights(c) for c in clauses])

    def midpoints(self, attr: str) -> np.ndarray:
        """Bucket midpoints, or the values themselves for numeric dictionaries."""
        rows = self.domain.where(f"attr = '{attr}'").orderBy("code").collect()
        return np.array([(r["lo"] + r["hi"]) / 2 if r["lo"] is not None else float(r["label"]) for r in rows])

    def sum(self, attr: str, where=None, values: np.ndarray | None = None) -> float:
        return infer.estimate_sum(self.model, attr, self.midpoints(attr) if values is None else values, self.weights(where))

    def avg(self, attr: str, where=None, values: np.ndarray | None = None) -> float:
        return infer.estimate_avg(self.model, attr, self.midpoints(attr) if values is None else values, self.weights(where))

    def group_array(self, by: list[str], where=None) -> np.ndarray:
        return infer.estimate_groups(self.model, by, self.weights(where))

    def groups(self, by: list[str], where=None, most: int = 5_000_000) -> DataFrame:
        """(by.., est, est_rounded): every group's expected count, decoded to the values' labels."""
        cells = math.prod(self.model.sizes[a] for a in by)
        if cells > most:
            raise ValueError(f"{cells} groups; ask for fewer attributes or raise `most`")
        est = self.group_array(by, where)
        labels = {a: np.empty(self.model.sizes[a], dtype=object) for a in by}
        for r in self.domain.where(self.domain.attr.isin(list(by))).collect():
            labels[r["attr"]][r["code"]] = r["label"]
        grid = np.meshgrid(*[labels[a] for a in by], indexing="ij")
        pdf = pd.DataFrame({a: g.ravel() for a, g in zip(by, grid)})
        pdf["est"] = est.ravel()
        pdf["est_rounded"] = infer.rounded(pdf["est"])
        return self.spark.createDataFrame(pdf, ", ".join(f"{a} string" for a in by) + ", est double, est_rounded long")

    def top(self, by: list[str], k: int, where=None) -> DataFrame:
        from pyspark.sql import functions as F

        return self.groups(by, where).orderBy(F.desc("est"), *by).limit(k)

    def probability(self, point: dict[str, int]) -> float:
        return infer.tuple_probability(self.model, point)

    # -- keeping ------------------------------------------------------------

    def solve(self, **options) -> "Summary":
        began = time.perf_counter()
        self.model.solve(**options)
        self.phases["solve"] = self.phases.get("solve", 0.0) + time.perf_counter() - began
        return self

    def residuals(self) -> DataFrame:
        rows = [(str(k), v) for k, v in self.model.residuals().items()]
        return self.spark.createDataFrame(rows, "family string, residual double")

    def save(self, path: str) -> None:
        """domain, values, families and parameters as parquet tables under `path`."""
        m = self.model
        self.domain.write.mode("overwrite").parquet(f"{path}/domain")
        meta = [(m.n, ",".join(m.attrs), repr([(a.name, a.width, a.lo, a.size) for a in self.attrs]), repr(self.pairs))]
        self.spark.createDataFrame(meta, "n double, attrs string, spec string, pairs string").write.mode("overwrite").parquet(f"{path}/meta")
        rows = [(a, i, float(m.values[a][i]), float(m.alpha[a][i])) for a in m.attrs for i in range(m.sizes[a])]
        self.spark.createDataFrame(rows, "attr string, code int, target double, alpha double").write.mode("overwrite").parquet(f"{path}/params")
        rects = [
            (f, r, list(fam.attrs), {a: np.flatnonzero(fam.masks[a][r]).tolist() for a in fam.attrs}, float(fam.targets[r]), float(m.delta[f][r]))
            for f, fam in enumerate(m.families)
            for r in range(fam.size)
        ]
        schema = "family int, rect int, attrs array<string>, codes map<string, array<int>>, target double, delta double"
        self.spark.createDataFrame(rects, schema).write.mode("overwrite").parquet(f"{path}/rects")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> "Summary":
        import ast

        meta = spark.read.parquet(f"{path}/meta").first()
        params = spark.read.parquet(f"{path}/params").toPandas()
        values, alpha = {}, {}
        for a in meta["attrs"].split(","):
            own = params[params["attr"] == a].sort_values("code")
            values[a], alpha[a] = own["target"].to_numpy(), own["alpha"].to_numpy()
        sizes = {a: len(v) for a, v in values.items()}
        rects = sorted(spark.read.parquet(f"{path}/rects").collect(), key=lambda r: (r["family"], r["rect"]))
        families, delta = [], []
        for f in sorted({r["family"] for r in rects}):
            own = [r for r in rects if r["family"] == f]
            fam = family_of_sets([{a: set(c) for a, c in r["codes"].items()} for r in own], [r["target"] for r in own], sizes)
            families.append(Family(tuple(own[0]["attrs"]), fam.masks, fam.targets))
            delta.append(np.array([r["delta"] for r in own]))
        model = build_model(values, families, meta["n"])
        model.alpha, model.delta = alpha, delta
        attrs = [Attr(*x) for x in ast.literal_eval(meta["spec"])]
        domain = spark.read.parquet(f"{path}/domain")
        return cls(spark, domain, model, attrs, ast.literal_eval(meta["pairs"]))

    def storage(self) -> dict[str, int]:
        """Bytes of the parameters and of the terms that evaluation holds."""
        m = self.model
        params = 8 * (sum(m.sizes.values()) + sum(f.size for f in m.families))
        terms = sum(c.rects.nbytes + sum(c.index[a].nbytes + c.factors[a].nbytes for a in c.attrs) for c in m.components)
        return {"parameters": params, "terms": terms}

    def warm_model(self, values: dict[str, np.ndarray], targets: list[np.ndarray], n: float) -> Model:
        """A model with new targets that starts from the present parameters."""
        fams = [Family(f.attrs, f.masks, np.asarray(t, dtype=np.float64)) for f, t in zip(self.model.families, targets, strict=True)]
        new = type(self.model)(values, fams, n)
        for a in new.attrs:
            old = self.model.alpha[a]
            new.alpha[a] = np.where(new.values[a] > 0, np.where(old > 0, old, new.alpha[a]), 0.0)
        for f, d in enumerate(self.model.delta):
            new.delta[f] = np.where(new.families[f].targets > 0, np.where(d > 0, d, 1.0), 0.0)
        return new


@dataclass
class Counts:
    """What the fit needs of a relation: domains, sizes, complete one-attribute counts and a table of pair counts."""

    attrs: list[Attr]
    domain: DataFrame
    sizes: dict[str, int]
    values: dict[str, np.ndarray]
    table: DataFrame
    n: int
    seconds: float
    cached: DataFrame | None = None  # the table of `table` and `values`, as persisted

    def release(self) -> None:
        if self.cached is not None:
            self.cached.unpersist()


def sizes_of(domain: DataFrame, attrs: list[Attr]) -> dict[str, int]:
    """Number of codes of every attribute, from a domain table or the attributes' pinned sizes."""
    sizes = {a.name: a.size or 0 for a in attrs}
    for r in domain.groupBy("attr").agg({"code": "max"}).collect():  # a row an attribute
        sizes[r[0]] = max(sizes[r[0]], r[1] + 1)
    return sizes


def collect_counts(df: DataFrame, attrs: list[Attr], pairs: list[tuple[str, str]] | None = None, domain: DataFrame | None = None) -> Counts:
    """Count the attributes and `pairs` (all pairs if None) in one pass over the codes; only cells are shuffled and kept."""
    t0 = time.perf_counter()
    codes, domain = encode(df, attrs, domain)
    domain = domain.persist()
    sizes = sizes_of(domain, attrs)
    names = [a.name for a in attrs]
    table = pair_counts(codes, sizes, list(combinations(names, 2)) if pairs is None else pairs).persist()
    values = {a: np.zeros(s) for a, s in sizes.items()}
    for r in table.where("a = b").collect():  # as many rows as there are values in the domains
        values[r["a"]][r["x"]] = r["n"]
    return Counts(attrs, domain, sizes, values, table.where("a <> b"), int(next(iter(values.values())).sum()), time.perf_counter() - t0, table)


def summarise(
    df: DataFrame | Counts, attrs: list[Attr] | None = None, pairs: str | list[tuple[str, str]] = "cover", n_pairs: int = 2,
    per_pair: int = 100, rects: str = "kd", ordering: str = "natural", exclude=(), score: str = "chi2", domain: DataFrame | None = None,
    fit: bool = True, **solver,
) -> Summary:
    """Build a summary: encode, count values and pairs in one pass, pick pairs and rectangles, fit.

    Counts taken before may be given in place of the relation, for several summaries of one pass.
    """
    named = not isinstance(pairs, str)
    counts = df if isinstance(df, Counts) else collect_counts(df, attrs, list(pairs) if named else None if n_pairs else [], domain)
    t1 = time.perf_counter()
    chosen: list[tuple[str, str]] = []
    families = []
    if n_pairs or named:
        chosen = list(pairs) if named else pick_pairs(pair_scores(counts.table, counts.n), n_pairs, pairs, exclude, score)
        for a, b in chosen:
            matrix = matrix_of(counts.table, a, b, (counts.sizes[a], counts.sizes[b]))
            families.append(choose_family(matrix, a, b, per_pair, rects, ordering, counts.sizes))
    if counts is not df:
        counts.release()
    model = build_model(counts.values, families, counts.n)
    out = Summary(counts.domain.sparkSession, counts.domain, model, counts.attrs, chosen, {"load": counts.seconds, "build": time.perf_counter() - t1})
    return out.solve(**solver) if fit else out
