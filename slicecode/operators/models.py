"""Count-based predictors: strictly positive, exactly normalised laws.

Counts are kept per month and gram, so a cutoff is a filter and a sum, not another scan. Contexts are strings of
two-digit hexadecimals (bytes) of growing length: the context at depth j is the last 2j characters.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import byte_symbols, micro_bits
from slicecode.operators.windows import with_context

ALPHABET = 256


def month_grams(slices: DataFrame, order: int, chunk: int | None = None, by: tuple[str, ...] = ("source", "m"), body: str = "body", symbols: Column | None = None) -> DataFrame:
    """``by``, ctx (longest available context), sym, n: the only thing that is shuffled is the partial count of grams.
    ``symbols``: an array column in place of the bytes of ``body``. Null bodies have no symbol; a null month or source is a group of
    its own, which no cutoff lets a model learn from."""
    tokens = with_context(slices, byte_symbols(F.col(body)) if symbols is None else symbols, order, list(by), chunk)
    return tokens.groupBy(*by, "ctx", "sym").agg(F.count(F.lit(1)).alias("n"))


def byte_grams(rows: DataFrame, order: int, chunk: int | None = None, body: str = "body", at_once: int = 1 << 21) -> DataFrame:
    """ctx, sym, n of the bytes of ``body``, as ``month_grams`` has them, for one law over all rows and up to six bytes of context: counted
    where the rows lie, so that a task sends a row for each of its distinct grams and no position becomes a row."""
    if order > 6:
        raise ValueError("contexts of up to six bytes")

    def count(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        x = np.frombuffer(b"".join(texts), np.uint8).astype(np.int64)
        pos = np.concatenate([np.arange(len(r)) for r in texts]) if texts else np.zeros(0, np.int64)
        pos = pos if chunk is None else pos % chunk
        keys = np.ones(len(x), np.int64)  # a one, the context, the symbol
        for k in range(order, 0, -1):
            before = np.concatenate((np.zeros(min(k, len(x)), np.int64), x[: max(0, len(x) - k)]))
            keys = np.where(pos >= k, keys << 8 | before, keys)
        return np.unique(keys << 8 | x, return_counts=True)

    def summed(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        keys, at = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
        out = np.zeros(len(keys), np.int64)
        np.add.at(out, at, np.concatenate([n for _, n in parts]))
        return keys, out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = [], 0
        for batch in batches:
            texts, size = [], 0
            for one in batch.column("_d"):
                texts.append(one.as_py() or b"")
                size += len(texts[-1])
                if size >= at_once:
                    found.append(count(texts))
                    texts, size = [], 0
            found.append(count(texts))
            if sum(len(k) for k, _ in found) > max(1 << 20, 2 * held):
                found = [summed(found)]
                held = len(found[0][0])
                if held > 1 << 21:  # what is sent is forgotten
                    yield pa.RecordBatch.from_arrays([*map(pa.array, found[0])], names=["key", "n"])
                    found, held = [], 0
        if found:
            yield pa.RecordBatch.from_arrays([*map(pa.array, summed(found))], names=["key", "n"])

    got = rows.select(F.encode(body, "UTF-8").alias("_d")).mapInArrow(run, "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))
    h = F.hex("key")
    return got.select(F.substring(h, F.lit(2), F.length(h) - 3).alias("ctx"), F.right(h, F.lit(2)).alias("sym"), "n")


def fit_counts(grams: DataFrame, width: int = 2, by: tuple[str, ...] = (), deepest: Column | None = None) -> DataFrame:
    """``by``, depth, ctx, sym, cnt of all depths in one pass, by the suffixes of each context; depths up to ``deepest``.

    ``by`` may name a model: then all models are counted at once, each from the rows it may see."""
    have = (F.length("ctx") / width).cast("int")
    depths = F.sequence(F.lit(0), have if deepest is None else F.least(have, deepest))
    each = grams.select(*by, F.explode(depths).alias("depth"), "ctx", "sym", "n")
    suffix = F.when(F.col("depth") == 0, "").otherwise(F.expr(f"right(ctx, depth * {width})"))
    return each.select(*by, "depth", suffix.alias("ctx"), "sym", "n").groupBy(*by, "depth", "ctx", "sym").agg(F.sum("n").alias("cnt"))


def context_totals(counts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """``by``, depth, ctx, n (occurrences), t (distinct successors)."""
    return counts.groupBy(*by, "depth", "ctx").agg(F.sum("cnt").alias("n"), F.count(F.lit(1)).alias("t"))


def fit_backoff(grams: DataFrame, until: int | None = None, month: str = "m") -> tuple[DataFrame, DataFrame]:
    """(counts, totals) from the slices up to and including month ``until``."""
    counts = fit_counts(grams if until is None else grams.where(F.col(month) <= until))
    return counts, context_totals(counts)


def seen_by(grams: DataFrame, cards: DataFrame, base_sources: tuple[str, ...]) -> DataFrame:
    """The grams once for each model that may learn from them: a range join of months with cutoffs (cards: model_id, order,
    until, extra). One row a model is broadcast."""
    may = (F.col("m") <= F.col("until")) & (F.col("source").isin(*base_sources) | F.array_contains("extra", F.col("source")))
    return grams.join(F.broadcast(cards), may).groupBy("model_id", "order", "ctx", "sym").agg(F.sum("n").alias("n"))


def score_models(grams: DataFrame, cards: DataFrame, base_sources: tuple[str, ...], order: int, smoothing: str = "wb") -> DataFrame:
    """source, model_id, m, micro, raw_bytes: all models of the cards fitted, and all grams scored, in shared passes."""
    counts = fit_counts(seen_by(grams, cards, base_sources), by=("model_id",), deepest=F.col("order"))
    totals = context_totals(counts, ("model_id",))
    short = F.when(F.length("ctx") > 2 * F.col("order"), F.expr("right(ctx, 2 * `order`)")).otherwise(F.col("ctx"))
    asked = grams.join(F.broadcast(cards.select("model_id", "order"))).select("source", "m", "model_id", F.when(F.col("order") == 0, "").otherwise(short).alias("ctx"), "sym", "n")
    asked = asked.groupBy("source", "m", "model_id", "ctx", "sym").agg(F.sum("n").alias("n"))
    law = score_grams(asked, counts, totals, order, smoothing, by=("model_id",))
    joined = asked.join(law, ["model_id", "ctx", "sym"])
    return joined.groupBy("source", "model_id", "m").agg(F.sum(F.col("n") * micro_bits(F.col("p"))).alias("micro"), F.sum("n").alias("raw_bytes"))


def save_bucketed(table: DataFrame, buckets: int, folder: str, key: str = "ctx") -> DataFrame:
    """``table`` written in ``buckets`` buckets of ``key``, sorted by it, in ``folder``; reading it again needs no exchange on the key."""
    name = f"model_{uuid.uuid4().hex}"
    table.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", f"{folder}/{name}").format("parquet").saveAsTable(name)
    return table.sparkSession.table(name)


def word_costs(grams: DataFrame, until: int, base_sources: tuple[str, ...]) -> DataFrame:
    """source, m, micro: word grams (source, m, ctx: the word before, sym, n) under a word-level law of order 1, Witten-Bell over
    order 0, of the months up to ``until``. A word that training has not seen costs the order-0 escape and eight bits for each of
    its bytes and an end. The law's two sums are one row; the rest are joins on words."""
    seen = grams.where((F.col("m") <= until) & F.col("source").isin(*base_sources)).groupBy("ctx", "sym").agg(F.sum("n").alias("c1"))
    zero = seen.groupBy("sym").agg(F.sum("c1").alias("c0"))
    total = zero.agg(F.coalesce(F.sum("c0"), F.lit(0)).cast("double").alias("n0"), F.count(F.lit(1)).cast("double").alias("t0"))
    pairs = seen.where("ctx <> ''")
    ones = pairs.groupBy("ctx").agg(F.sum("c1").alias("n1"), F.count(F.lit(1)).alias("t1"))
    j = grams.join(zero, "sym", "left").join(ones, "ctx", "left").join(pairs, ["ctx", "sym"], "left").crossJoin(F.broadcast(total))  # one row
    p0 = (F.coalesce("c0", F.lit(0)) + F.col("t0") / (F.col("t0") + 1.0)) / (F.col("n0") + F.greatest(F.col("t0"), F.lit(1.0)))
    p1 = F.when(F.col("n1").isNull(), F.col("p0")).otherwise((F.coalesce("c1", F.lit(0)) + F.col("t1") * F.col("p0")) / (F.col("n1") + F.col("t1")))
    spelled = F.when(F.col("c0").isNull(), (F.octet_length("sym").cast("long") + 1) * 8_000_000).otherwise(0)
    cost = j.withColumn("p0", p0).withColumn("p", p1).select("source", "m", (F.col("n") * (micro_bits(F.col("p")) + spelled)).alias("micro"))
    return cost.groupBy("source", "m").agg(F.sum("micro").alias("micro"))


def extend(counts: DataFrame, more: DataFrame) -> tuple[DataFrame, DataFrame]:
    """A model with further counts: a domain-tuned one."""
    both = counts.unionByName(more).groupBy("depth", "ctx", "sym").agg(F.sum("cnt").alias("cnt"))
    return both, context_totals(both)


def fold_law(steps: DataFrame, order: int, smoothing: str, alphabet: int, discount: float = 0.75, every: bool = False) -> DataFrame:
    """``steps`` (c0, n0, t0, ... of each depth) with p: every seen depth refines the one below it; the lowest law is uniform.
    Witten-Bell: (c + t p) / (n + t), which leaves p as it is for c, n, t = 0, 0, 1. Absolute discounting:
    (max(c - d, 0) + d t p) / n. One projection a depth, so no expression is copied. ``every``: the law of each order as p0, p1, … too."""
    out = steps.withColumn("p", F.lit(1.0 / alphabet))
    for k in range(order + 1):
        c, n, t = F.coalesce(f"c{k}", F.lit(0)).cast("double"), F.col(f"n{k}"), F.col(f"t{k}")
        if smoothing == "wb":
            out = out.withColumn("p", (c + F.coalesce(t, F.lit(1)) * F.col("p")) / (F.coalesce(n, F.lit(0)) + F.coalesce(t, F.lit(1))))
        else:
            out = out.withColumn("p", F.when(n.isNull(), F.col("p")).otherwise((F.greatest(c - discount, F.lit(0.0)) + discount * t * F.col("p")) / n))
        if every:
            out = out.withColumn(f"p{k}", F.col("p"))
    return out


def score_grams(grams: DataFrame, counts: DataFrame, totals: DataFrame, order: int, smoothing: str = "wb", alphabet: int = ALPHABET, width: int = 2, by: tuple[str, ...] = (), every: bool = False) -> DataFrame:
    """``by``, ctx, sym, p (``every``: also p0 … of the lower orders) for the distinct grams: score once per gram, not per position. Joins are on (depth, ctx[, sym]), so
    models larger than memory work; small ones are broadcast by the planner. ``order`` is the deepest depth."""
    distinct = grams.select(*by, "ctx", "sym").distinct()
    depths = F.sequence(F.lit(0), (F.length("ctx") / width).cast("int"))
    each = distinct.select(*by, F.col("ctx").alias("full"), "sym", F.explode(depths).alias("depth"))
    each = each.withColumn("ctx", F.when(F.col("depth") == 0, "").otherwise(F.expr(f"right(full, depth * {width})")))
    found = each.join(totals, [*by, "depth", "ctx"], "left").join(counts, [*by, "depth", "ctx", "sym"], "left")
    steps = found.groupBy(*by, "full", "sym").agg(*[F.max(F.when(F.col("depth") == k, F.col(c))).alias(f"{a}{k}") for k in range(order + 1) for a, c in (("c", "cnt"), ("n", "n"), ("t", "t"))])
    lower = [f"p{k}" for k in range(order + 1)] if every else []
    return fold_law(steps, order, smoothing, alphabet, every=every).select(*by, F.col("full").alias("ctx"), "sym", "p", *lower)


def additive(grams: DataFrame, counts: DataFrame, totals: DataFrame, order: int, alpha: float = 1.0, alphabet: int = ALPHABET) -> DataFrame:
    """ctx, sym, p of the additive law at one depth: (c + a) / (n + a V)."""
    c = counts.where(F.col("depth") == order).select("ctx", "sym", "cnt")
    t = totals.where(F.col("depth") == order).select("ctx", "n")
    distinct = grams.select("ctx", "sym").distinct()
    got = distinct.join(t, "ctx", "left").join(c, ["ctx", "sym"], "left")
    return got.select("ctx", "sym", ((F.coalesce("cnt", F.lit(0)) + alpha) / (F.coalesce("n", F.lit(0)) + alpha * alphabet)).alias("p"))


def uniform(alphabet: int = ALPHABET) -> Column:
    return F.lit(1.0 / alphabet)


def restrict(law: DataFrame, ids: DataFrame) -> DataFrame:
    """The law on a subset of symbols (columns ctx, sym, p; ``ids`` has sym), scaled to sum to one in each context."""
    kept = law.join(ids, "sym", "left_semi")
    return kept.withColumn("p", F.col("p") / F.sum("p").over(Window.partitionBy("ctx")))


def from_logprobs(external: DataFrame, stream: str = "stream_id", logprob: str = "logprob") -> DataFrame:
    """Any outside model by its natural-log probabilities per token: stream, tokens, bits."""
    micro = F.sum(F.round(-F.col(logprob) / F.log(F.lit(2.0)) * 1_000_000).cast("long"))
    return external.groupBy(stream).agg(F.count(F.lit(1)).alias("tokens"), F.round(micro / 1_000_000, 3).alias("bits"))


def cdf_table(counts: DataFrame, depth: int, bits: int = 16, alphabet: int = ALPHABET) -> DataFrame:
    """Integer slots of one depth's additive law (alpha 1) over the seen symbols and one escape slot: ctx, sym, lo, hi, total.

    A slot is floor(F(<x) (2^bits - V)) + index(x), so each has one unit at least and they are in order.
    """
    w = Window.partitionBy("ctx").orderBy("sym")
    law = counts.where(F.col("depth") == depth)
    whole = Window.partitionBy("ctx")
    span = (1 << bits) - alphabet
    run = law.withColumn("below", F.coalesce(F.sum("cnt").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("n", F.sum("cnt").over(whole)).withColumn("k", F.row_number().over(w) - 1)
    lo = F.expr(f"cast(below * {span} div n as bigint)") + F.col("k")
    hi = F.expr(f"cast((below + cnt) * {span} div n as bigint)") + F.col("k") + 1
    return run.select("ctx", "sym", lo.alias("lo"), hi.alias("hi"), F.lit(1 << bits).cast("long").alias("total"))
