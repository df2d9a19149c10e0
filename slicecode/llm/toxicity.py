"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Hashed character n-grams (three to five characters, lower case, white space runs as one space) are binary features;
each is multiplied by the log ratio of its smoothed frequency in toxic and other training texts; a logistic
regression is fitted on the scaled features. The features without weight are not stored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, filter_pass, fold_of
from slicecode.llm.language import bounded_sample

_SPREAD = np.uint32(2654435761)


def gram_buckets(text: str | None, bits: int, shortest: int = 3, longest: int = 5) -> np.ndarray:
    """The distinct buckets of the text's n-grams, ascending; a space is put at both ends."""
    low = " ".join((text or "").lower().split())
    if not low:
        return np.zeros(0, np.int64)
    codes = np.frombuffer(f" {low} ".encode("utf-32-le", "surrogatepass"), np.uint32)
    seen = np.zeros(1 << bits, bool)
    for at in range(0, len(codes), 1 << 20):  # bounded memory for very long texts
        part = codes[at : at + (1 << 20) + longest - 1]
        h = part
        for k in range(2, longest + 1):
            if len(part) < k:
                break
            h = h[: len(part) - k + 1] * np.uint32(0x01000193) + part[k - 1 :]
            if k >= shortest:
                seen[((h ^ np.uint32(k)) * _SPREAD) >> np.uint32(32 - bits)] = True
    return np.flatnonzero(seen)


@dataclass
class ToxicityModel:
    weights: np.ndarray  # of each bucket: log-count ratio times regression weight
    bias: float
    bits: int

    def score(self, text: str | None) -> float:
        z = float(self.weights[gram_buckets(text, self.bits)].sum()) + self.bias
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, z))))


def train(texts: list[str | None], labels: list[int], bits: int = 18, alpha: float = 1.0, least_docs: int = 4, least_ratio: float = 1.0, ridge: float = 1e-3, steps: int = 250) -> ToxicityModel:
    """Ratios from all rows, then full-batch Adam on the logistic loss with a ridge on the regression weights.

    An n-gram counts if at least ``least_docs`` texts have it and its absolute log ratio is ``least_ratio`` or more.
    With one class only, the score is that class's smoothed share; without any row nothing is called toxic.
    """
    y = np.array(labels, np.float64)
    share = (y.sum() + 0.5) / (len(y) + 1)
    weights = np.zeros(1 << bits, np.float32)
    if not len(y):
        return ToxicityModel(weights, -50.0, bits)
    if y.min() == y.max():
        return ToxicityModel(weights, math.log(share / (1 - share)), bits)
    grams = [gram_buckets(t, bits).astype(np.int32) for t in texts]
    size = np.array([len(g) for g in grams])
    column, row = np.concatenate(grams), np.repeat(np.arange(len(y)), size)
    in_pos = np.bincount(column[y[row] == 1], minlength=1 << bits).astype(np.float64)
    in_neg = np.bincount(column[y[row] == 0], minlength=1 << bits).astype(np.float64)
    ratio = np.log((in_pos + alpha) / (y.sum() + 2 * alpha)) - np.log((in_neg + alpha) / ((1 - y).sum() + 2 * alpha))
    used = (in_pos + in_neg >= least_docs) & (np.abs(ratio) >= least_ratio)
    index = np.cumsum(used) - 1
    hold = used[column]
    column, row = index[column[hold]], row[hold]
    r, n = ratio[used], int(used.sum())
    value = r[column]
    w, b, m, v = np.zeros(n), 0.0, np.zeros(n + 1), np.zeros(n + 1)
    balance = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean()))
    for k in range(1, steps + 1):
        z = np.bincount(row, weights=value * w[column], minlength=len(y)) + b
        e = balance * (1 / (1 + np.exp(-np.clip(z, -50, 50))) - y) / len(y)
        g = np.append(np.bincount(column, weights=value * e[row], minlength=n) + ridge * w, e.sum())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = 0.05 * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.999**k)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    weights[used] = (w * r).astype(np.float32)
    return ToxicityModel(weights, float(b), bits)


def fit(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", toxic: str = "toxic", per_label: int = 1500) -> ToxicityModel:
    """Train on about ``per_label`` labelled rows of each class, of those outside fold 0. A doc_id with several labels counts as
    toxic if any says so; labels that are null, or have no document, do not count."""
    marks = labels.select(F.col(doc_id).alias("label_id"), F.col(toxic).cast("int").alias("toxic")).where("label_id is not null and toxic is not null").where(fold_of(F.col("label_id")) != 0).groupBy("label_id").agg(F.max("toxic").alias("toxic"))
    chosen = bounded_sample(marks, "toxic", per_label, F.col("label_id"))
    # about 2 * per_label ids are broadcast, so no text is shuffled to find them
    rows = F.broadcast(chosen).join(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")), F.col("label_id") == F.col("doc_id")).select("doc_id", "toxic", "text")
    found = sorted(((r["doc_id"], r["toxic"], r["text"] or "") for r in rows.collect()))
    return train([t for _, _, t in found], [int(y > 0) for _, y, _ in found])


def score(docs: DataFrame, model: ToxicityModel, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each input row: doc_id, held_out, score (0 to 1), predicted (1 if score >= 0.5).

    Null and empty texts have no feature and get the score of the bias. A null id is in fold 0. Empty table: no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # 2 ** bits floats

    def rows(_: list, __: list, texts: list) -> list:
        found = [sent.value.score(t) for t in texts]
        return [found, [int(s >= 0.5) for s in found]]

    narrow = docs.select(F.col(doc_id).alias("doc_id"), (fold_of(F.col(doc_id)) == 0).alias("held_out"), F.col(text).cast("string").alias("text"))
    return arrow_pass(narrow, rows, "score double, predicted int", keep=["doc_id", "held_out"])


def toxicity(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", per_label: int = 1500) -> DataFrame:
    """Fit on labelled rows outside fold 0, score every row."""
    return score(docs, fit(docs, labels, doc_id, text, per_label=per_label), doc_id, text)


def without_toxic(docs: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """The rows of ``docs`` that score under 0.5, whole and unchanged; all of them if the model has no weight, as labels of
    fewer than two classes tell no text from another."""
    if not model.weights.any():
        return docs
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return filter_pass(docs, text, lambda texts: [sent.value.score(t) < 0.5 for t in texts])
