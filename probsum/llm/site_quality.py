"""Document quality with hierarchical empirical-Bayes evidence from the host and the path."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import written
from probsum.llm.quality_rules import counted

#: What the classifier sees of a document: measures over the counted columns.
MEASURES = (
    "ln(1 + n_words)",
    "if(n_words = 0, 0D, word_chars / n_words)",
    "if(n_words = 0, 0D, least(n_symbols / n_words, 2D))",
    "if(n_words = 0, 0D, least(10D * n_dup_lines / n_words, 2D))",
    "if(n_words = 0, 0D, n_repeat_words / n_words)",
    "cast(n_words < 50 as double)",
    "cast(n_symbols * 10 > n_words as double)",
    "cast(n_repeat_words * 2 > n_words as double)",
    "cast(n_dup_lines > 0 as double)",
)


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 50):
    """(centre, scale, weights with the bias last) by Newton steps; one class only gives a constant near its rate."""
    centre, scale = x.mean(axis=0), x.std(axis=0)
    scale[scale == 0] = 1
    z = np.c_[(x - centre) / scale, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    penalty = np.r_[np.full(x.shape[1], ridge), 1e-3]
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), z.T @ (y - p) - penalty * w)
        w += step
        if np.abs(step).max() < 1e-9:
            break
    return centre, scale, w


def scored(
    docs: DataFrame, labels: DataFrame, host, path, id_col: str = "doc_id", text_col: str = "text",
    label_col: str = "quality", train_docs: int = 20_000, folds: int = 5,
) -> DataFrame:
    """One row per document: id, held_out, doc_score, path_score, host_score, score, predicted.

    `host` and `path` are columns. A logistic model of the document's measures is fitted on the `train_docs`
    labelled rows with the least hash of the id among those whose crc32(id as text) mod `folds` is not 0 (the bound
    of what the driver sees). Its scores, or the labels of those rows, are
    the evidence of a site: hosts shrink to the global rate and paths to their host, by Beta priors whose
    strengths come from the spread of the hosts about the global rate and of the paths about their own host (method of moments). A document's odds are those of its
    own evidence times the odds ratio of its path to the global rate, itself left out of the path.
    Null hosts and paths are groups of their own; a null text counts as empty; without labels every score is 0.5.
    """
    stats = written(
        counted(
            docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), host.alias("host"), path.alias("path"))
        )
        .select("id", "host", "path", F.array(*[F.expr(f"cast({m} as double)") for m in MEASURES]).alias("x")),
        "site-measures",
    )
    y = (
        labels.select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("y"))
        .where(f"y is not null and _id is not null and crc32(cast(_id as string)) % {folds} <> 0")
        .groupBy("_id")
        .agg(F.min("y").alias("y"))
    )
    sample = y.orderBy(F.xxhash64("_id"), "_id").limit(train_docs)
    rows = stats.join(F.broadcast(sample), F.col("id") == F.col("_id")).select("x", "y", "id").orderBy("id").collect()
    if rows:
        centre, scale, w = fit_logistic(
            np.array([r["x"] for r in rows]), np.array([r["y"] for r in rows], dtype=float)
        )
    else:
        centre, scale, w = np.zeros(len(MEASURES)), np.ones(len(MEASURES)), np.zeros(len(MEASURES) + 1)
    logit = F.lit(float(w[-1]))
    for i in range(len(MEASURES)):
        logit = logit + (F.col("x")[i] - float(centre[i])) / float(scale[i]) * float(w[i])
    logit = F.least(F.greatest(logit, F.lit(-12.0)), F.lit(12.0))
    own = (
        stats.join(y, F.col("id") == F.col("_id"), "left")
        .withColumn("logit", logit)
        .withColumn("doc_score", 1 / (1 + F.exp(-F.col("logit"))))
        .withColumn("evidence", F.coalesce(F.col("y").cast("double"), F.col("doc_score")))
        .select("id", "host", "path", "logit", "doc_score", "evidence")
    )
    paths = written(
        own.groupBy("host", "path").agg(F.count(F.lit(1)).alias("n"), F.sum("evidence").alias("s")), "paths"
    )
    hosts = paths.groupBy("host").agg(F.sum("n").alias("hn"), F.sum("s").alias("hs"))

    def inner(groups: DataFrame) -> float:
        """The strength of the paths' prior: the hosts' rate (1 - rate) over the paths' spread about their own host beyond chance, less 1."""
        inside = groups.alias("p").join(hosts.alias("h"), F.expr("p.host <=> h.host")).selectExpr("n", "s", "hs / hn as r", "hn", "h.host as h")
        each = inside.groupBy("h").agg(
            F.first("hn").alias("hn"), F.first("r").alias("r"), F.count(F.lit(1)).alias("g"),
            F.sum(F.col("s") * F.col("s") / F.col("n")).alias("q"), F.sum(F.col("n") * F.col("n")).alias("n2"),
        )
        row = each.agg(
            F.sum(F.expr("q - hn * r * r")).alias("between"), F.sum(F.expr("(g - 1) * r * (1 - r)")).alias("chance"),
            F.sum(F.expr("hn - n2 / hn")).alias("weight"), (F.sum(F.expr("hn * r * (1 - r)")) / F.sum("hn")).alias("spread"),
        ).first()
        if not row["weight"] or row["weight"] <= 0 or not row["spread"]:
            return 1e6
        tau2 = (row["between"] - row["chance"]) / row["weight"]
        return float(min(max(row["spread"] / tau2 - 1, 1.0), 1e6)) if tau2 > 0 else 1e6

    def strength(groups: DataFrame, n: str, s: str) -> tuple[float, float]:
        """Global rate, and the prior's strength: rate (1 - rate) over the spread beyond chance, less 1."""
        row = groups.agg(
            F.sum(n).alias("n"), F.sum(s).alias("s"), F.count(F.lit(1)).alias("g"),
            F.sum(F.col(s) * F.col(s) / F.col(n)).alias("q"), F.sum(F.col(n) * F.col(n)).alias("n2"),
        ).first()
        if not row["n"]:
            return 0.5, 1e6
        rate = min(max(row["s"] / row["n"], 1e-6), 1 - 1e-6)
        between = row["q"] - row["n"] * rate * rate  # weighted squares of the groups' means
        spread = rate * (1 - rate)
        weight = row["n"] - row["n2"] / row["n"]
        tau2 = (between - (row["g"] - 1) * spread) / weight if weight > 0 else 0.0
        return rate, float(min(max(spread / tau2 - 1, 1.0), 1e6)) if tau2 > 0 else 1e6

    rate, k_host = strength(hosts, "hn", "hs")
    k_path = inner(paths)
    sites = written(
        paths.alias("p")
        .join(hosts.alias("h"), F.expr("p.host <=> h.host"))
        .selectExpr(
            "p.host as _host", "p.path as _path", "n", "s", f"(hs + {k_host!r}D * {rate!r}D) / (hn + {k_host!r}D) as host_score"
        ),
        "sites",
    )
    both = own.join(sites, F.expr("host <=> _host and path <=> _path"))
    path_score = F.expr(f"(s - evidence + {k_path!r}D * host_score) / (n - 1 + {k_path!r}D)")
    bounded = F.least(F.greatest(path_score, F.lit(1e-6)), F.lit(1 - 1e-6))
    prior = F.lit(float(np.log(rate / (1 - rate))))
    return (
        both.withColumn("path_score", bounded)
        .withColumn(
            "score", 1 / (1 + F.exp(-(F.col("logit") + F.ln(F.col("path_score") / (1 - F.col("path_score"))) - prior)))
        )
        .select(
            "id",
            F.expr(f"crc32(cast(id as string)) % {folds} = 0").alias("held_out"),
            "doc_score",
            "path_score",
            "host_score",
            "score",
            (F.col("score") >= 0.5).cast("int").alias("predicted"),
        )
    )
