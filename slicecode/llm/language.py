"""Language identification: averaged hashed subword embeddings with a linear softmax.

A text is the average of the embeddings of its hashed character n-grams (one to four characters; letters in lower
case, everything else a word border); a linear layer and a softmax follow. Embeddings and layer are trained
together by stochastic gradient descent in numpy on a bounded sample of labelled rows. A validation part of the
training rows sets the temperature of the softmax and the score under which a prediction is rejected.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, fold_of

UNDETERMINED = "und"
_SPREAD = np.uint32(2654435761)  # 2**32 over the golden ratio: spreads neighbouring codes over the buckets


@functools.cache
def _letters() -> np.ndarray:
    """All code points: themselves if a letter or a mark of U+0300 to U+036F, else a space."""
    codes = np.arange(0x110000, dtype=np.uint32)
    alpha = np.fromiter((chr(c).isalpha() or 0x300 <= c < 0x370 for c in range(0x110000)), bool, 0x110000)
    return np.where(alpha, codes, 32).astype(np.uint32)


def codes_of(text: str | None) -> np.ndarray:
    """Lower-case letters as code points, each run of anything else one space, a space at both ends."""
    raw = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    low = _letters()[raw]
    low = np.concatenate(([32], low, [32])).astype(np.uint32)
    keep = np.ones(len(low), bool)
    keep[1:] = (low[1:] != 32) | (low[:-1] != 32)
    return low[keep]


def bag(text: str | None, bits: int, longest: int = 4) -> np.ndarray | None:
    """Counts of the n-grams in 2**``bits`` buckets; None if the text has no letter."""
    codes = codes_of(text)
    if not ((codes != 32) & ((codes < 0x300) | (codes >= 0x370))).any() and not any(c.isalpha() for c in map(chr, np.unique(codes))):
        return None
    counts = np.zeros(1 << bits, np.float32)
    for at in range(0, len(codes), 1 << 20):  # bounded memory for very long texts
        part = codes[at : at + (1 << 20) + longest - 1]
        h, n = part, min(1 << 20, len(part))
        for k in range(1, longest + 1):
            if k > 1:
                if len(part) < k:
                    break
                h = h[: len(part) - k + 1] * np.uint32(0x01000193) + part[k - 1 :]
            counts += np.bincount(((h[:n] + np.uint32(k)) * _SPREAD) >> np.uint32(32 - bits), minlength=1 << bits)
    return counts


@dataclass
class LanguageModel:
    labels: list[str]
    table: np.ndarray  # bucket x label: embedding times layer
    bias: np.ndarray
    temperature: float
    reject_under: float
    bits: int

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(label, probability, accepted); ('und', 0, False) for a text without a letter."""
        counts = bag(text, self.bits)
        if counts is None or not self.labels:
            return UNDETERMINED, 0.0, False
        z = ((counts @ self.table) / counts.sum() + self.bias) / self.temperature
        p = np.exp(z - z.max())
        p /= p.sum()
        k = int(p.argmax())
        return self.labels[k], float(p[k]), bool(p[k] >= self.reject_under)


def train(texts: list[str], labels: list[str], bits: int = 14, width: int = 12, epochs: int = 12, rate: float = 4.0, seed: int = 7, reject_precision: float = 0.99) -> LanguageModel:
    """Mini-batch SGD on averaged embeddings; every tenth row is held back for temperature and rejection."""
    rng = np.random.default_rng(seed)
    names = sorted(set(labels))
    found = [(c / c.sum(), names.index(y)) for t, y in zip(texts, labels, strict=True) if (c := bag(t, bits)) is not None]
    if not found:
        return LanguageModel([], np.zeros((1 << bits, 0), np.float32), np.zeros(0, np.float32), 1.0, 0.0, bits)
    x, y = np.stack([c for c, _ in found]), np.array([k for _, k in found])
    held = np.arange(len(x)) % 10 == 9
    learn = np.flatnonzero(~held)
    weight = len(y) / (len(names) * np.maximum(np.bincount(y, minlength=len(names)), 1))  # rare languages weigh as much
    emb = rng.normal(0, 1.0, (1 << bits, width)).astype(np.float32) / np.sqrt(width)
    layer, bias = np.zeros((width, len(names)), np.float32), np.zeros(len(names), np.float32)
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for at in np.array_split(rng.permutation(learn), max(1, len(learn) // 32)):
            mean = x[at] @ emb
            z = mean @ layer + bias
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(at)), y[at]] -= 1
            g = (p * weight[y[at], None] / len(at)).astype(np.float32)
            back = x[at].T @ (g @ layer.T)
            layer -= step * mean.T @ g
            bias -= step * g.sum(0)
            emb -= step * 50 * back
    table = emb @ layer
    check = np.flatnonzero(held) if held.any() else learn
    z, truth = x[check] @ table + bias, y[check]

    def loss(t: float) -> float:
        s = z / t
        s = s - s.max(1, keepdims=True)
        return float(-(s[np.arange(len(s)), truth] - np.log(np.exp(s).sum(1))).mean()) + 1e-4 * abs(np.log(t))

    temperature = min(np.geomspace(0.05, 5, 60), key=loss)
    p = np.exp((z - z.max(1, keepdims=True)) / temperature)
    p /= p.sum(1, keepdims=True)
    top, right = p.max(1), p.argmax(1) == truth
    reject = next((float(t) for t in sorted(top) if right[top >= t].mean() >= reject_precision), 1.0)
    return LanguageModel(names, table.astype(np.float32), bias, float(temperature), reject, bits)


def bounded_sample(rows: DataFrame, label: str, per_label: int, key: Column) -> DataFrame:
    """About ``per_label`` rows of each label, chosen by the hash of ``key``: a threshold per label, from the labels'
    counts. Nothing is ranked, and no label's rows meet in one task."""
    counts = {r[label]: r["n"] for r in rows.groupBy(label).agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a label
    draw = F.pmod(F.xxhash64(F.lit("sample"), key), F.lit(1 << 32))
    chosen = F.lit(False)
    for value, n in sorted(counts.items(), key=str):
        chosen = chosen | ((F.col(label) == F.lit(value)) & (draw < int(min(1.0, per_label / n) * (1 << 32))))
    return rows.where(chosen)


def fit(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", per_label: int = 500) -> LanguageModel:
    """Train on about ``per_label`` rows per language of those outside fold 0."""
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"), F.col(lang).cast("string").alias("lang"))
    rows = rows.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (fold_of(F.col("doc_id")) != 0))
    found = sorted((r["doc_id"], r["lang"], r["text"]) for r in bounded_sample(rows, "lang", per_label, F.col("doc_id")).collect())
    return train([t for _, _, t in found], [y for _, y, _ in found])


def identify(docs: DataFrame, model: LanguageModel, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each input row: doc_id, held_out, lang_pred, score (0 to 1), accepted.

    ``lang_pred`` is a learned label, or 'und' (score 0) for null texts and texts without a letter; ``accepted`` is
    false where the score lies under the calibrated limit. A null id is in fold 0. Empty table: no rows.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the number of buckets and labels

    def rows(_: list, __: list, texts: list) -> list:
        found = [sent.value.predict(t) for t in texts]
        return [[f[i] for f in found] for i in range(3)]

    narrow = docs.select(F.col(doc_id).alias("doc_id"), (fold_of(F.col(doc_id)) == 0).alias("held_out"), F.col(text).cast("string").alias("text"))
    return arrow_pass(narrow, rows, "lang_pred string, score double, accepted boolean", keep=["doc_id", "held_out"])


def language_id(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", per_label: int = 500) -> DataFrame:
    """Fit on the rows outside fold 0, predict every row."""
    return identify(docs, fit(docs, doc_id, text, lang, per_label), doc_id, text)
