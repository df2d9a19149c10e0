"""Preparation of monthly slices: snapshots, change rule, body extraction, tiles, samples, budgets, drift."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import MONTHS


def monthly_snapshot(versions: DataFrame, key: list[str], month: str = "m", item: str = "item_id", months: int = MONTHS) -> DataFrame:
    """Last version of each item per month, carried forward through months without a change: ``key``, m, item_id, carried.
    The calendar is crossed with the keys' first months, not with the versions."""
    w = Window.partitionBy(*key, month).orderBy(F.desc(item))
    last = versions.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(*key, month, item)
    span = last.groupBy(*key).agg(F.min(month).alias("_lo"))
    grid = span.select(*key, F.explode(F.sequence(F.col("_lo"), F.lit(months - 1))).alias(month))
    run = Window.partitionBy(*key).orderBy(month).rowsBetween(Window.unboundedPreceding, 0)
    joined = grid.join(last, [*key, month], "left")
    return joined.select(*key, month, F.last(item, ignorenulls=True).over(run).alias(item), F.col(item).isNull().alias("carried"))


def changed_items(versions: DataFrame, key: str, order: list[str], item: str, lines: Column, threshold: float = 0.5) -> DataFrame:
    """Change ratio against the previous version by line multisets: (added + removed) over (lines now + lines before); kept
    where there is no previous version or the ratio exceeds ``threshold``. A full outer join of counted lines."""
    w = Window.partitionBy(key).orderBy(*order)
    paired = versions.select(key, *order, item, lines.alias("_lines")).withColumn("_prev", F.lag(item).over(w))
    counted = paired.select(item, F.explode("_lines").alias("_l")).groupBy(item, "_l").agg(F.count(F.lit(1)).alias("_n"))
    now = paired.select(F.col(item).alias("_of"), "_prev").where(F.col("_prev").isNotNull())
    cur = now.join(counted, F.col("_of") == counted[item]).select("_of", "_l", F.col("_n").alias("_a"))
    old = now.join(counted, F.col("_prev") == counted[item]).select("_of", "_l", F.col("_n").alias("_b"))
    diff = cur.join(old, ["_of", "_l"], "full_outer").groupBy("_of").agg(F.sum(F.abs(F.coalesce("_a", F.lit(0)) - F.coalesce("_b", F.lit(0)))).alias("_d"), F.sum(F.coalesce("_a", F.lit(0)) + F.coalesce("_b", F.lit(0))).alias("_t"))
    ratio = F.round(F.col("_d") / F.col("_t"), 6)
    return paired.select(key, *order, item).join(diff, F.col(item) == F.col("_of"), "left").select(key, *order, item, ratio.alias("ratio"), (F.col("_d").isNull() | (F.col("_d") > threshold * F.col("_t"))).alias("kept"))


def byte_budget(df: DataFrame, by: list[str], budget: int, ident: str = "item_id", size: str = "raw_bytes") -> DataFrame:
    """A deterministic sample per group: rows in the order of their id's md5, while their running bytes fit the budget."""
    w = Window.partitionBy(*by).orderBy(F.md5(F.col(ident).cast("string").cast("binary")), ident).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn("_run", F.sum(size).over(w)).where(F.col("_run") <= budget).drop("_run")


def stratified_sample(df: DataFrame, stratum: str, n: int, ident: str) -> DataFrame:
    """The first ``n`` rows of each stratum in the order of the id's md5."""
    w = Window.partitionBy(stratum).orderBy(F.md5(F.col(ident).cast("string").cast("binary")), ident)
    return df.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= n).drop("_r")


def gray_levels(values: Column) -> Column:
    """Values of -1 … 1 as 0 … 255."""
    return F.transform(values, lambda v: F.floor((F.least(F.greatest(v.cast("double"), F.lit(-1.0)), F.lit(1.0)) + 1) * 127.5).cast("int"))


def tiles(df: DataFrame, row_no: str, pixels: Column, height: int) -> DataFrame:
    """Contiguous patches of ``height`` rows, row-major; an incomplete last patch is dropped: patch_id, pixels (array of int)."""
    rows = df.select(F.floor(F.col(row_no) / height).cast("long").alias("patch_id"), F.col(row_no).alias("_row"), pixels.alias("_px"))
    got = rows.groupBy("patch_id").agg(F.sort_array(F.collect_list(F.struct("_row", "_px"))).alias("_r")).where(F.size("_r") == height)
    return got.select("patch_id", F.flatten("_r._px").alias("pixels"))


def crop(pixels: Column, width: int, left: int, keep: int) -> Column:
    """Columns ``left`` to ``left + keep`` of a row-major patch of ``width``: larger arrays cut to the patch size."""
    return F.filter(pixels, lambda _, i: (i % width >= left) & (i % width < left + keep))


def gray_of_rgb(r: Column, g: Column, b: Column) -> Column:
    return F.floor(0.299 * r + 0.587 * g + 0.114 * b).cast("int")


def pcm_sample(value: Column, low: float, high: float) -> Column:
    """A value of the range as a signed 16-bit sample."""
    return (F.floor((value - low) / (high - low) * 65535.0) - 32768).cast("int")


def resample(df: DataFrame, key: list[str], pos: str, value: str, ratio: float) -> DataFrame:
    """Linear resampling by ``ratio`` (new over old rate): key, k, value. Each old interval makes its own new points."""
    w = Window.partitionBy(*key).orderBy(pos)
    nxt = df.withColumn("_nv", F.lead(value).over(w)).withColumn("_np", F.lead(pos).over(w))
    lo, hi = F.ceil(F.col(pos) * ratio).cast("int"), (F.ceil(F.col("_np") * ratio) - 1).cast("int")
    points = nxt.where(F.col("_np").isNotNull() & (hi >= lo)).select(*key, pos, value, "_nv", "_np", F.explode(F.sequence(lo, hi)).alias("k"))
    at = (F.col("k") / ratio - F.col(pos)) / (F.col("_np") - F.col(pos))
    return points.select(*key, "k", (F.col(value) + at * (F.col("_nv") - F.col(value))).alias("value"))


def positions(df: DataFrame, key: list[str], order: list[str], span: int = 4096) -> DataFrame:
    """``df`` with _i: the place of each row in its key's series, from 0.

    The first column of ``order`` is an integer; ranges of ``span`` of its values are numbered on their own, and start where a
    prefix sum over the ranges' counts puts them. So tasks grow with the data and not with the keys.
    """
    cut = df.withColumn("_r", F.floor(F.col(order[0]) / span))
    before = Window.partitionBy(*key).orderBy("_r").rowsBetween(Window.unboundedPreceding, -1)
    starts = cut.groupBy(*key, "_r").agg(F.count(F.lit(1)).alias("_n")).select(*key, "_r", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_at"))
    inside = F.row_number().over(Window.partitionBy(*key, "_r").orderBy(*order)) - 1
    return cut.withColumn("_k", inside).join(starts, [*key, "_r"]).withColumn("_i", F.col("_at") + F.col("_k")).drop("_r", "_k", "_at")


def with_lags(series: DataFrame, key: list[str], value: str, lags: int, block: int = 1 << 14) -> DataFrame:
    """``series`` (with _i, from ``positions``) with the ``lags`` values before each row as ``value``1, ``value``2, …

    Blocks of positions are windows of their own; the last values of a block are copied into the next one.
    """
    cut = series.withColumn("_b", F.floor(F.col("_i") / block)).withColumn("_own", F.lit(True))
    carried = cut.where(F.col("_i") % block >= block - lags).withColumn("_b", F.col("_b") + 1).withColumn("_own", F.lit(False))
    w = Window.partitionBy(*key, "_b").orderBy("_i")
    both = cut.unionByName(carried)
    for k in range(1, lags + 1):
        both = both.withColumn(f"{value}{k}", F.lag(value, k).over(w))
    return both.where("_own").drop("_b", "_own")


def byte_batches(samples: DataFrame, key: list[str], order: list[str], sample: str, per_batch: int) -> DataFrame:
    """Little-endian 16-bit bytes in batches of ``per_batch`` samples: key, batch, data. The batch bounds what is gathered."""
    cut = positions(samples, key, order).withColumn("batch", F.floor(F.col("_i") / per_batch).cast("int"))
    two = F.concat(F.lpad(F.hex(F.pmod(F.col(sample), F.lit(256))), 2, "0"), F.lpad(F.hex(F.pmod(F.shiftright(F.col(sample), 8), F.lit(256))), 2, "0"))
    got = cut.groupBy(*key, "batch").agg(F.sort_array(F.collect_list(F.struct("_i", two.alias("h")))).alias("p"))
    return got.select(*key, "batch", F.unhex(F.array_join(F.col("p.h"), "")).alias("data"))


def inject_drift(slices: DataFrame, from_month: int, months: int = MONTHS, key: str = "drift", body: str = "body", share: float = 1.0) -> DataFrame:
    """Re-map a growing share of words after a month: a ground truth for drift. A word of a month past ``from_month`` is
    reversed and marked if its keyed hash falls under the month's share."""
    level = F.greatest(F.lit(0.0), (F.col("m") - from_month) / F.lit(float(months - from_month))) * share
    words = F.transform(F.split(F.col(body), " "), lambda w: F.when(F.pmod(F.xxhash64(w, F.lit(key)), F.lit(1000)) < level * 1000, F.concat(F.reverse(w), F.lit("q"))).otherwise(w))
    return slices.withColumn(body, F.array_join(words, " "))
