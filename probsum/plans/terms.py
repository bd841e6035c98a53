"""The terms and factors of a model as tables, and evaluation of P as a Spark job over them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probsum.plans.model import Model


def factor_frame(spark: SparkSession, model: Model) -> DataFrame:
    """(comp_id, attr, factor_id, members, value): distinct restricted sums with their values at the present parameters."""
    rows = []
    for i, c in enumerate(model.components):
        for a in c.attrs:
            values = c.factors[a] @ model.alpha[a]
            rows += [
                (i, a, j, np.flatnonzero(m).tolist(), float(v))
                for j, (m, v) in enumerate(zip(c.factors[a], values, strict=True))
            ]
    return spark.createDataFrame(rows, "comp_id int, attr string, factor_id int, members array<int>, value double")


def term_frame(spark: SparkSession, model: Model) -> DataFrame:
    """(comp_id, term_id, set_mask, attr_mask, factors map<attr, id>, rects array, value).

    set_mask has a bit per family taken, attr_mask one per attribute of a true restriction: a
    query on other attributes may reuse the stored value.
    """
    parts = []
    at = {a: i for i, a in enumerate(model.attrs)}
    for i, c in enumerate(model.components):
        value = model._component(c, {})
        coef = model._coefficients(c)
        sets = sum(((c.rects[:, k] >= 0).astype(np.int64) << f for k, f in enumerate(c.families)), np.zeros(c.terms, np.int64))
        attrs = sum(((~c.factors[a].all(axis=1))[c.index[a]].astype(np.int64) << at[a] for a in c.attrs), np.zeros(c.terms, np.int64))
        parts.append(
            pd.DataFrame(
                {
                    "comp_id": i, "term_id": np.arange(c.terms), "set_mask": sets, "attr_mask": attrs,
                    "factors": [[int(c.index[a][t]) for a in c.attrs] for t in range(c.terms)],
                    "rects": c.rects.tolist(), "coef": coef, "value": value,
                }
            )
        )
    schema = "comp_id int, term_id long, set_mask long, attr_mask long, factors array<int>, rects array<long>, coef double, value double"
    return spark.createDataFrame(pd.concat(parts), schema) if parts else spark.createDataFrame([], schema)


def evaluate_distributed(terms: DataFrame, model: Model, weights: dict[str, np.ndarray]) -> float:
    """P as one pass over the terms: the factor sums travel to the tasks, partial sums come back per component.

    Terms whose component the weights do not touch add their stored values; a term is dropped as soon as one
    of its restricted sums is 0.
    """
    sums = [
        {a: c.factors[a] @ (model.alpha[a] * weights.get(a, 1.0)) for a in c.attrs} for c in model.components
    ]
    touched = [any(a in weights for a in c.attrs) for c in model.components]
    attrs = [c.attrs for c in model.components]

    def run(batches):
        for pdf in batches:
            out = []
            for i, part in pdf.groupby("comp_id"):
                if not touched[i]:
                    out.append((i, float(part["value"].sum())))
                    continue
                index = np.stack(part["factors"].to_numpy())
                term = part["coef"].to_numpy().copy()
                for k, a in enumerate(attrs[i]):
                    live = np.flatnonzero(term)
                    term[live] *= sums[i][a][index[live, k]]
                out.append((i, float(term.sum())))
            yield pd.DataFrame(out, columns=["comp_id", "p"])

    rows = terms.mapInPandas(run, "comp_id int, p double").groupBy("comp_id").agg(F.sum("p").alias("p")).collect()
    return float(np.prod([r["p"] for r in rows]) * model._free(weights))
