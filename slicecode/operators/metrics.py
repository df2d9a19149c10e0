"""Rates over calendar time: periods, robustness, projection and ranks, the plane, divergence, agreement."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import MICRO, TEST_FROM, rate


def monthly_rate(totals: DataFrame) -> DataFrame:
    """source, model_id, m, micro, raw_bytes -> with the month's rate in percent."""
    return totals.withColumn("rate", rate(F.col("micro"), F.col("raw_bytes")))


def split_common(df: DataFrame, month: str = "m", test_from: int = TEST_FROM) -> DataFrame:
    return df.withColumn("period", F.when(F.col(month) < test_from, "train").otherwise("test"))


def split_by_cutoff(df: DataFrame, cards: DataFrame, month: str = "m", default: int = TEST_FROM - 1) -> DataFrame:
    """Each model's own periods: a range join with the few cards; an unknown cutoff falls back to the common split."""
    cut = F.coalesce((F.months_between("cutoff_month", F.lit("2017-01-01").cast("date"))).cast("int"), F.lit(default))
    few = F.broadcast(cards.select("model_id", cut.alias("last_train")))  # one row a model
    train = df.join(few, F.col(month) <= F.col("last_train")).withColumn("period", F.lit("train"))
    test = df.join(few, F.col(month) > F.col("last_train")).withColumn("period", F.lit("test"))
    return train.unionByName(test).drop("last_train")


def period_rates(series: DataFrame, how: str = "month_mean", test_from: int = TEST_FROM) -> DataFrame:
    """source, model_id, r_all, r_train, r_test: unweighted means over months, or pooled bytes."""
    train, test = F.col("m") < test_from, F.col("m") >= test_from
    if how == "month_mean":
        units = F.round(F.col("rate") * 10000).cast("long")  # whole units, so that the mean does not depend on the order
        made = [F.round(F.try_divide(F.sum(F.when(c, units)).cast("double"), F.count(F.when(c, units))) / 10000, 8) for c in (F.lit(True), train, test)]
    else:
        made = [F.round(F.try_divide(F.sum(F.when(c, F.col("micro"))) * (100.0 / 8 / MICRO), F.sum(F.when(c, F.col("raw_bytes")))), 4) for c in (F.lit(True), train, test)]
    return series.groupBy("source", "model_id").agg(*[x.alias(n) for x, n in zip(made, ("r_all", "r_train", "r_test"), strict=True)])


def robustness(rates: DataFrame) -> DataFrame:
    """gap = test minus train, its share of the training rate, and its direction (up is worse)."""
    gap = F.round(F.col("r_test") - F.col("r_train"), 8)
    out = rates.withColumn("gap", gap).withColumn("gap_rel", F.round(F.try_divide(F.col("gap"), F.col("r_train")), 6))
    return out.withColumn("arrow", F.when(F.col("gap") > 0, "up").when(F.col("gap") < 0, "down").otherwise("flat"))


def project_and_rank(rates: DataFrame, classes: DataFrame) -> DataFrame:
    """Projected rate one period on, its rank inside (source, size class), and the marks of the first two."""
    few = F.broadcast(classes.select("model_id", "size_class"))
    got = rates.where(F.col("r_test").isNotNull()).join(few, "model_id").withColumn("projected", F.round(F.col("r_test") + F.col("gap"), 8))
    w = Window.partitionBy("source", "size_class").orderBy("projected")
    ranked = got.withColumn("rank", F.rank().over(w).cast("long"))
    return ranked.withColumn("mark", F.when(F.col("rank") == 1, "best").when(F.col("rank") == 2, "second").otherwise(""))


def plane(rates: DataFrame) -> DataFrame:
    """Quadrants of (rate, gap) by the source's medians; 'good' means low."""
    mid = rates.groupBy("source").agg(F.median("r_test").alias("mid_rate"), F.median("gap").alias("mid_gap"))
    name = F.concat(F.when(F.col("r_test") <= F.col("mid_rate"), "low_rate").otherwise("high_rate"), F.lit("/"), F.when(F.col("gap") <= F.col("mid_gap"), "small_gap").otherwise("large_gap"))
    return rates.join(F.broadcast(mid), "source").withColumn("quadrant", name).drop("mid_rate", "mid_gap")


def pareto(rates: DataFrame) -> DataFrame:
    """on_front: no model of the source is at least as good in both and better in one. An anti join on dominance."""
    o = rates.select(F.col("source").alias("s"), F.col("r_test").alias("a"), F.col("gap").alias("b"))
    dominated = (F.col("source") == F.col("s")) & (F.col("a") <= F.col("r_test")) & (F.col("b") <= F.col("gap")) & ((F.col("a") < F.col("r_test")) | (F.col("b") < F.col("gap")))
    front = rates.join(o, dominated, "left_anti").select("source", "model_id", F.lit(True).alias("on_front"))
    return rates.join(front, ["source", "model_id"], "left").withColumn("on_front", F.coalesce("on_front", F.lit(False)))


def divergence(series: DataFrame, early: str, late: str, shared_until: int, runs: int = 3, sigmas: float = 3.0) -> DataFrame:
    """First month from which early minus late stays above mean + ``sigmas`` deviations of the shared months, for ``runs`` months
    at least: islands by a difference of row numbers. Columns source, month_no (null: none)."""
    a = series.where(F.col("model_id") == early).select("source", "m", F.col("rate").alias("ra"))
    b = series.where(F.col("model_id") == late).select("source", "m", F.col("rate").alias("rb"))
    d = a.join(b, ["source", "m"]).withColumn("d", F.round(F.col("ra") - F.col("rb"), 4))
    base = d.where(F.col("m") <= shared_until).groupBy("source").agg(F.avg("d").alias("mu"), F.coalesce(F.stddev_samp("d"), F.lit(0.0)).alias("sd"))
    flagged = d.join(F.broadcast(base), "source").where((F.col("m") > shared_until) & (F.col("d") > F.col("mu") + sigmas * F.col("sd")))
    isle = flagged.withColumn("isle", F.col("m") - F.row_number().over(Window.partitionBy("source").orderBy("m")))
    runs_found = isle.groupBy("source", "isle").agg(F.min("m").alias("first"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= runs)
    first = runs_found.groupBy("source").agg(F.min("first").alias("month_no"))
    return d.select("source").distinct().join(first, "source", "left").select("source", F.col("month_no").cast("long").alias("month_no"))


def trend(series: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """Slope of the rate per month before and after each model's cutoff (columns model_id, last_train)."""
    j = series.join(F.broadcast(cutoffs), "model_id")
    before, after = F.col("m") <= F.col("last_train"), F.col("m") > F.col("last_train")
    return j.groupBy("source", "model_id").agg(*[F.round(F.regr_slope(F.when(c, F.col("rate")), F.when(c, F.col("m"))), 6).alias(n) for c, n in ((before, "slope_before"), (after, "slope_after"))])


def rank_agreement(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Spearman, Pearson, and Kendall (pairs in the same order minus the others, over all) of two columns; both ascending. Null where a
    side has no spread."""
    w = lambda c: Window.orderBy(c)  # noqa: E731  a handful of models
    r = pairs.select(F.col("model_id"), F.col(a).alias("a"), F.col(b).alias("b")).withColumn("ra", F.rank().over(w("a"))).withColumn("rb", F.rank().over(w("b")))
    o = r.select(F.col("model_id").alias("other"), F.col("a").alias("a2"), F.col("b").alias("b2"))
    kendall = r.join(o, F.col("model_id") < F.col("other")).agg(F.round(F.avg(F.signum((F.col("a") - F.col("a2")) * (F.col("b") - F.col("b2")))), 6).alias("kendall"))
    corr = lambda x, y: F.round(F.try_divide(F.covar_pop(F.col(x).cast("double"), F.col(y).cast("double")), F.stddev_pop(x) * F.stddev_pop(y)), 6)
    both = r.agg(corr("ra", "rb").alias("spearman"), corr("a", "b").alias("pearson"))
    return both.crossJoin(kendall)


def source_difficulty(rates: DataFrame, reference: DataFrame) -> DataFrame:
    """Mean gap of a source over models, how many got worse, and the gap of a reference compressor there."""
    got = rates.groupBy("source").agg(F.round(F.avg("gap"), 6).alias("mean_gap"), F.sum(F.when(F.col("gap") > 0, 1).otherwise(0)).cast("long").alias("worse_models"))
    return got.join(F.broadcast(reference.select("source", F.col("gap").alias("reference_gap"))), "source", "left")


def perplexity(micro, tokens):
    return F.round(F.pow(F.lit(2.0), micro / MICRO / tokens), 4)
