"""The Spark side of what many queries start from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slicecode.functions.exprs import MICRO, byte_symbols
from slicecode.operators import metrics, models
from slicecode.plans.base import RATE_MODELS
from slicecode.sources.tables import text_slices

TEXTS = ("reference_articles", "news_articles")


def reference_grams(spark: SparkSession, sf_dir: str, order: int = 2, chunk: int | None = 2048, sources: tuple[str, ...] = ("reference_articles",)) -> DataFrame:
    """Grams of some sources. Kept in memory or on local disk while several models read them; lost parts are made anew."""
    return models.month_grams(text_slices(spark, sf_dir, sources), order, chunk).persist()


def rate_series(spark: SparkSession, sf_dir: str, which: tuple[str, ...] | None = None) -> DataFrame:
    """source, model_id, m, micro, raw_bytes, rate of the rate models and the uniform law, over two text sources and code."""
    grams = reference_grams(spark, sf_dir, 2, 2048, (*TEXTS, "code_files"))
    cards = [(x, k, until, ["code_files"] if code else []) for x, (k, until, code, _) in RATE_MODELS.items() if not which or x in which]
    got = models.score_models(grams, spark.createDataFrame(cards, "model_id string, order int, until int, extra array<string>"), TEXTS, 2)
    flat = grams.groupBy("source", "m").agg((F.sum("n") * 8 * MICRO).alias("micro"), F.sum("n").alias("raw_bytes")).select("source", F.lit("uniform").alias("model_id"), "m", "micro", "raw_bytes")
    # a row for each source, model and month: kept, as reports read it several times
    return metrics.monthly_rate(got.unionByName(flat)).persist()


def rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.robustness(metrics.period_rates(rate_series(spark, sf_dir)))


def classes(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(x, c) for x, (_, _, _, c) in RATE_MODELS.items()], "model_id string, size_class string")


def byte_tokens(df: DataFrame, keep: list[str], body: str = "body") -> DataFrame:
    return df.select(*keep, F.posexplode(byte_symbols(F.col(body))).alias("pos", "sym"))
