"""Symbol streams, chunks and overlapping windows without shuffles wherever a row holds its own sequence."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def symbols(df: DataFrame, seq: Column, keep: list[str]) -> DataFrame:
    """Long form: ``keep``, pos (from 0), sym."""
    return df.select(*keep, F.posexplode(seq).alias("pos", "sym"))


def with_context(df: DataFrame, seq: Column, order: int, keep: list[str], chunk: int | None = None) -> DataFrame:
    """Long form with ctx: up to ``order`` symbols before, inside the chunk, joined. No shuffle: the array is zipped with
    itself, shifted. ``chunk`` None: contexts reach back to the start of the row."""
    names = ["_s"] + [f"_p{k}" for k in range(1, order + 1)]
    base = df.select(*keep, seq.alias("_s"))
    for k in range(1, order + 1):
        base = base.withColumn(f"_p{k}", F.concat(F.array_repeat(F.lit(None).cast("string"), k), F.col("_s")))
    out = base.select(*keep, F.posexplode(F.arrays_zip(*names)).alias("pos", "_z")).where(F.col("_z._s").isNotNull())
    at = F.col("pos") if chunk is None else F.col("pos") % chunk
    parts = [F.when(at >= k, F.col(f"_z._p{k}")).otherwise("") for k in range(order, 0, -1)]
    return out.select(*keep, "pos", F.col("_z._s").alias("sym"), (F.concat(*parts) if order else F.lit("")).alias("ctx"))


def chunk_arrays(df: DataFrame, seq: Column, size: int, keep: list[str]) -> DataFrame:
    """One row for each chunk of at most ``size`` symbols: ``keep``, chunk_no, syms. The last one may be short; an empty
    sequence has no chunk. The unit of parallelism."""
    base = df.select(*keep, seq.alias("_seq")).where(F.size("_seq") > 0)
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.size("_seq") - 1) / size).cast("int")), lambda i: F.slice(F.col("_seq"), i * size + 1, F.lit(size)))
    return base.select(*keep, F.posexplode(cut).alias("chunk_no", "syms"))


def stream_chunks(sizes: DataFrame, by: list[str], order: str, length: str, span: int = 1024) -> DataFrame:
    """Places of rows in streams that join them end to end, in the order of an integer id: the columns of ``sizes``, start, stop.

    Offsets come from a prefix sum in two levels: totals of ranges of ``span`` ids, then inside the range. Ranges grow with the
    data; no window spans a stream's rows.
    """
    placed = sizes.withColumn("_b", F.floor(F.col(order) / span))
    totals = placed.groupBy(*by, "_b").agg(F.sum(length).alias("_t"))
    before = Window.partitionBy(*by).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select(*by, "_b", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_off"))
    inside = Window.partitionBy(*by, "_b").orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    end = F.col("_off") + F.sum(length).over(inside)
    return placed.join(offsets, [*by, "_b"]).withColumn("stop", end).withColumn("start", F.col("stop") - F.col(length)).drop("_b", "_off")


def stream_pieces(rows: DataFrame, size: int, by: list[str], order: str, data: str) -> DataFrame:
    """The chunks of ``size`` bytes of streams that join the binary ``data`` of rows end to end: ``by``, chunk_no, data.

    Each row is cut where the stream's chunks end and its pieces meet the neighbours' again; a group is one chunk."""
    sized = rows.select(*by, order, F.octet_length(data).cast("long").alias("_n")).where("_n > 0")
    placed = stream_chunks(sized, by, order, "_n").select(*by, order, "start", "stop")
    first, last = F.floor(F.col("start") / size), F.floor((F.col("stop") - 1) / size)
    cut = rows.select(*by, order, F.col(data).alias("_d")).join(placed, [*by, order]).withColumn("chunk_no", F.explode(F.sequence(first, last)))
    lo, hi = F.greatest(F.lit(0), F.col("chunk_no") * size - F.col("start")), F.least(F.col("stop"), (F.col("chunk_no") + 1) * size) - F.col("start")
    pieces = cut.select(*by, "chunk_no", "start", F.hex(F.substring(F.col("_d"), (lo + 1).cast("int"), (hi - lo).cast("int"))).alias("_h"))
    joined = pieces.groupBy(*by, "chunk_no").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("start", "_h"))), lambda x: x["_h"]), "").alias("_h"))
    return joined.select(*by, "chunk_no", F.unhex("_h").alias("data"))


def sliding_plan(lengths: DataFrame, size: int, step: int, keep: list[str], length: str = "n") -> DataFrame:
    """Overlapping windows: block b scores ``step`` symbols with the ``size`` - ``step`` before them as context.
    Columns ``keep``, blocks, forward_tokens, scored_tokens."""
    n, blocks = F.col(length), F.ceil(F.col(length) / step).cast("int")
    each = F.transform(F.sequence(F.lit(0), blocks - 1), lambda b: F.least(n, (b + 1) * step) - F.greatest(F.lit(0), b * step - (size - step)))
    forward = F.when(n > 0, F.aggregate(each, F.lit(0).cast("long"), lambda a, x: a + x)).otherwise(0)
    return lengths.select(*keep, blocks.alias("blocks"), forward.cast("long").alias("forward_tokens"), n.cast("long").alias("scored_tokens"))


def chunk_counts(tokens: DataFrame, chunk: int, unit: list[str]) -> DataFrame:
    """Per token: n_w (earlier occurrences of its symbol in its chunk) and m (symbols before it in the chunk)."""
    w = Window.partitionBy(*unit, "chunk", "sym").orderBy("pos")
    return tokens.withColumn("chunk", F.floor(F.col("pos") / chunk).cast("int")).withColumn("n_w", F.row_number().over(w) - 1).withColumn("m", F.col("pos") % chunk)


def sliding_counts(tokens: DataFrame, size: int, step: int, unit: list[str]) -> DataFrame:
    """Per token: n_w and m for overlapping windows, from block counts: earlier ones in its own block plus those of the
    ``size`` / ``step`` - 1 blocks before. No token is copied into the windows that hold it."""
    if size % step:
        raise ValueError("the window is a whole number of steps")
    t = tokens.withColumn("block", F.floor(F.col("pos") / step).cast("int"))
    own = Window.partitionBy(*unit, "sym", "block").orderBy("pos")
    ranked = t.withColumn("r", F.row_number().over(own) - 1)
    if size == step:
        return ranked.withColumn("n_w", F.col("r")).withColumn("m", F.col("pos") - F.col("block") * step).drop("r")
    before = Window.partitionBy(*unit, "sym").orderBy("block").rangeBetween(-(size // step - 1), -1)
    counts = t.groupBy(*unit, "sym", "block").agg(F.count(F.lit(1)).alias("c")).withColumn("prior", F.coalesce(F.sum("c").over(before), F.lit(0))).drop("c")
    joined = ranked.join(counts, [*unit, "sym", "block"])
    start = F.greatest(F.lit(0), F.col("block") * step - (size - step))
    return joined.withColumn("n_w", F.col("r") + F.col("prior")).withColumn("m", F.col("pos") - start).drop("r", "prior")
