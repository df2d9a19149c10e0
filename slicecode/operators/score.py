"""Likelihood as code length: sums of exact micro-bits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicecode.functions.exprs import MICRO, bits, micro_bits


def sequence_nll(scored: DataFrame, by: list[str], unit: str = "bits", p: str = "p") -> DataFrame:
    """Negative log-likelihood of each group, in bits or nats, with its tokens."""
    total = F.sum(micro_bits(F.col(p)))
    value = bits(total) if unit == "bits" else F.round(total / MICRO * F.log(F.lit(2.0)), 3)
    return scored.groupBy(*by).agg(F.count(F.lit(1)).alias("tokens"), value.alias(unit))


def code_length(scored: DataFrame, by: list[str], p: str = "p") -> DataFrame:
    """bits, and whole bits a coder needs: the rounded-up bits and one more."""
    out = sequence_nll(scored, by, "bits", p)
    return out.withColumn("code_bits", (F.ceil("bits") + 1).cast("long"))


def gram_pushdown(grams: DataFrame, scored: DataFrame, by: list[str]) -> DataFrame:
    """Code length of each group from grams counted before scoring: sum of n times the gram's cost. Equal to scoring every
    position, as costs are integers."""
    joined = grams.join(scored, ["ctx", "sym"])
    return joined.groupBy(*by).agg(F.sum(F.col("n") * micro_bits(F.col("p"))).alias("micro"), F.sum("n").alias("raw_bytes"))


def adaptive(n_w: Column, m: Column, alphabet: int = 256, alpha: float = 0.5) -> Column:
    """The law that learns inside its window: (n_w + a) / (m + a V)."""
    return (n_w + alpha) / (m + alpha * alphabet)


def cached(n_w: Column, m: Column, static: Column, strength: float = 64.0) -> Column:
    """A static law mixed with what its window has shown so far."""
    return (n_w + strength * static) / (m + strength)
