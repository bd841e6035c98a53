"""Toxicity by multiple-instance learning: a document is toxic if at least one of its sentences is.

A sentence scores sigmoid(bias + weights of its words and word beginnings); a document scores by noisy-or,
1 - prod(1 - p). Only documents are labelled; the weights are fitted through the noisy-or, so that
the sentences that explain the label come out of the training.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import give_back

_SENTENCE = re.compile(r"[^.!?\n]+")
_WORD = re.compile(r"[^\W_]+")


def sentences(text: str | None):
    """(start, end, words) of the sentences that hold a word; they end at . ! ? or a line feed."""
    for m in _SENTENCE.finditer(text or ""):
        words = _WORD.findall(m.group().lower())
        if words:
            yield m.start(), m.end(), words


def clues(words: list[str]) -> set[str]:
    """Features of a sentence: its words and their beginnings of four and five letters, each once."""
    out = set(words)
    out.update(["^" + w[:4] for w in words if len(w) > 4])
    out.update(["^" + w[:5] for w in words if len(w) > 5])
    return out


@dataclass
class SentenceModel:
    """Word weights and a bias; at most `features` words, so it is small enough for any closure."""

    bias: float = -20.0
    weights: dict[str, float] = field(default_factory=dict)

    def logits(self, text: str | None) -> np.ndarray:
        get = self.weights
        return self.bias + np.array(
            [sum([get[w] for w in clues(ws) & get.keys()]) for _, _, ws in sentences(text)], dtype=np.float64
        )

    def score(self, text: str | None) -> tuple[float, int, int, float]:
        """(document score, sentences, worst sentence or -1, its score); a text without words scores 0."""
        z = self.logits(text)
        if not len(z):
            return 0.0, 0, -1, 0.0
        worst = int(z.argmax())
        total = float(np.logaddexp(0, z).sum())
        return float(-np.expm1(-total)), len(z), worst, float(1 / (1 + np.exp(-z[worst])))


def fit(
    texts: list[str | None], toxic: list[int], features: int = 2000, least_docs: int = 4,
    rounds: int = 600, rate: float = 0.1, ridge: float = 1e-3,
) -> SentenceModel:
    """Fit the noisy-or model on labelled documents by full-batch gradient steps (Adam).

    Features are the words and word beginnings with the largest chi-squared against the label among those in `least_docs`
    or more documents. One class only, or no row, gives a model that calls nothing toxic.
    """
    y = np.array(toxic, dtype=np.int64)
    if not len(y) or y.min() == y.max():
        return SentenceModel()
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    for t, label in zip(texts, y, strict=True):
        seen[label].update(clues([w for _, _, ws in sentences(t) for w in ws]))
    n0, n1 = int((y == 0).sum()), int((y == 1).sum())
    words = sorted(w for w in seen[0].keys() | seen[1].keys() if seen[0][w] + seen[1][w] >= least_docs)
    a = np.array([seen[1][w] for w in words], dtype=np.float64)
    b = np.array([seen[0][w] for w in words], dtype=np.float64)
    n, d = n0 + n1, a + b
    chi2 = n * (a * (n0 - b) - b * (n1 - a)) ** 2 / np.maximum(d * (n - d) * n0 * n1, 1e-300)
    top = np.argsort(-chi2, kind="stable")[:features]
    index = {words[i]: k for k, i in enumerate(top)}
    # sentences with a feature as sparse rows; the others of a document share the bias
    cols, rows, doc_of = [], [], []
    plain = np.zeros(len(texts))
    for i, t in enumerate(texts):
        for _, _, ws in sentences(t):
            hit = [index[w] for w in clues(ws) & index.keys()]
            if hit:
                rows += [len(doc_of)] * len(hit)
                cols += sorted(hit)
                doc_of.append(i)
            else:
                plain[i] += 1
    cols, rows, doc_of = (np.array(x, dtype=np.int64) for x in (cols, rows, doc_of))
    theta = np.r_[np.zeros(len(index)), -6.0]
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, rounds + 1):
        w, bias = theta[:-1], theta[-1]
        z = bias + np.bincount(rows, w[cols], minlength=len(doc_of))
        total = np.bincount(doc_of, np.logaddexp(0, z), minlength=len(y)) + plain * np.logaddexp(0, bias)
        # loss: the total for a clean document, -log(1 - exp(-total)) for a toxic one
        slope = np.where(y == 1, -1 / np.expm1(np.clip(total, 1e-9, 50)), 1.0) / len(y)
        dz = slope[doc_of] / (1 + np.exp(-z))
        grad = np.r_[
            np.bincount(cols, dz[rows], minlength=len(index)) + ridge * w / len(y) * 10,
            dz.sum() + (slope * plain).sum() / (1 + np.exp(-bias)),
        ]
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad**2
        theta = theta - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
    return SentenceModel(float(theta[-1]), {w: float(theta[k]) for w, k in index.items()})


def trained(
    docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic",
    train_docs: int = 6000, train_chars: int = 20_000, folds: int = 5,
) -> SentenceModel:
    """Fit on labelled rows whose crc32(id as text) mod `folds` is not 0.

    The sample is bounded: the `train_docs` labelled rows with the least hash of the id; of those the
    texts up to `train_chars` characters. That is the most that reaches the driver. A label that is null is no label.
    """
    chosen = (
        labels.select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("_y"))
        .where(f"_id is not null and _y is not null and crc32(cast(_id as string)) % {folds} <> 0")
        .groupBy("_id")
        .agg(F.max("_y").alias("_y"))
        .orderBy(F.xxhash64("_id"), "_id")
        .limit(train_docs)
    )
    rows = (
        docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
        .where(F.col("_text").isNotNull() & (F.char_length("_text") <= train_chars))
        .join(F.broadcast(chosen), "_id")
        .orderBy("_id", "_text")
        .limit(2 * train_docs)
        .collect()
    )
    return fit([r["_text"] for r in rows], [r["_y"] for r in rows])


def scored(docs: DataFrame, model: SentenceModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, score, predicted, n_sentences, worst_sentence, worst_score; null texts count as empty."""

    def run(batches):
        for pdf in batches:
            got = [model.score(t) for t in pdf["text"]]
            out = pd.DataFrame(got, columns=["score", "n_sentences", "worst_sentence", "worst_score"])
            out.insert(0, "id", pdf["id"].to_numpy())
            out.insert(2, "predicted", (out["score"] >= 0.5).astype("int32"))
            yield out

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInPandas(
        run,
        f"id {docs.schema[id_col].dataType.simpleString()}, score double, predicted int, n_sentences long,"
        " worst_sentence long, worst_score double",
    )


def offending(
    docs: DataFrame, model: SentenceModel, id_col: str = "doc_id", text_col: str = "text", least: float = 0.5
) -> DataFrame:
    """The sentences that score `least` or more: id, sentence, start, end, text, score."""

    def run(batches):
        for pdf in batches:
            out = []
            for key, text in zip(pdf["id"], pdf["text"], strict=True):
                p = 1 / (1 + np.exp(-model.logits(text)))
                out += [
                    (key, i, s, e, text[s:e], p[i])
                    for i, (s, e, _) in enumerate(sentences(text))
                    if p[i] >= least
                ]
            yield pd.DataFrame(out, columns=["id", "sentence", "start", "end", "text", "score"])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInPandas(
        run,
        f"id {docs.schema[id_col].dataType.simpleString()}, sentence long, start long, end long, text string, score double",
    )


def without_toxic(docs: DataFrame, model: SentenceModel, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of `docs` that score below `least`, with all their columns."""
    def run(texts: pd.Series) -> pd.Series:
        out = texts.map(lambda t: model.score(t)[0]).astype("float64")
        give_back()
        return out

    score = F.pandas_udf(run, "double")
    return docs.where(score(F.col(text_col)) < least)
