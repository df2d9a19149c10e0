"""Tables, the monthly sources shaped from them, and the model cards."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slicecode.functions.exprs import month_index, month_of_date
from slicecode.operators import curate

#: Sources that the engine draws from the given tables.
TEXT_SOURCES = ("reference_articles", "news_articles", "code_files", "paper_bodies")
CARD = "model_id string, family string, size_class string, release_month date, cutoff_month date, tokenizer string, order int, max_context int, has_byte_ids boolean, smoothing string, adapt_strength double, extra_sources array<string>"


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options) -> DataFrame:
    """Other formats: json, csv, orc, text (``wholetext``), binaryFile."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def article_source(doc_source: F.Column = None):
    number = F.regexp_extract(F.col("source") if doc_source is None else doc_source, r"(\d+)$", 1).cast("int")
    return F.when(number < 10, "reference_articles").otherwise("news_articles")


def main_body(html):
    """Text of the page's article: from its opening tag to its end, tags and the common references resolved."""
    inner = F.regexp_extract(html, r"(?s)<article>(.*)</article>", 1)
    flat = F.regexp_replace(inner, r"<[^>]*>", " ")
    for name, sign in (("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        flat = F.replace(flat, F.lit(name), F.lit(sign))
    return F.trim(F.regexp_replace(flat, r"[ \t\n]+", " "))


def documents_slices(spark: SparkSession, sf_dir: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """source, item_id, m (month index), body; and a struct ``kept`` of the columns in ``keep``, as where a document came from."""
    d = load_table(spark, sf_dir, "documents")
    kept = [F.struct(*keep).alias("kept")] if keep else []
    return d.select(article_source().alias("source"), F.col("doc_id").alias("item_id"), month_index(F.col("doc_id")).alias("m"), F.col("text").alias("body"), *kept)


def page_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load_table(spark, sf_dir, "pages").select(F.col("page_id").alias("item_id"), month_index(F.col("page_id")).alias("m"), "html")
    code = p.select(F.lit("code_files").alias("source"), "item_id", "m", F.col("html").alias("body"))
    return code.unionByName(p.select(F.lit("paper_bodies").alias("source"), "item_id", "m", main_body(F.col("html")).alias("body")))


def text_slices(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = TEXT_SOURCES) -> DataFrame:
    """The text sources in one frame; only the tables that are asked for are read."""
    parts = []
    if {"reference_articles", "news_articles"} & set(sources):
        parts.append(documents_slices(spark, sf_dir))
    if {"code_files", "paper_bodies"} & set(sources):
        parts.append(page_slices(spark, sf_dir))
    out = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    return out.where(F.col("source").isin(*sources))


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Natively timed text: an order as one delimited line."""
    o = load_table(spark, sf_dir, "orders")
    return o.select(F.lit("order_log").alias("source"), F.col("o_orderkey").alias("item_id"), month_of_date(F.col("o_orderdate")).alias("m"), F.concat_ws("|", F.col("o_orderkey").cast("string"), F.col("o_custkey").cast("string"), "o_orderstatus", "o_orderpriority").alias("body"))


def dialogue_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = load_table(spark, sf_dir, "conversations")
    return c.select(F.lit("dialogues").alias("source"), F.col("conv_id").alias("item_id"), month_index(F.col("conv_id")).alias("m"), F.col("text").alias("body"))


def price_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """m, l_orderkey, l_linenumber, l_partkey, x: extended prices as signed 16-bit samples, in the order of their keys."""
    t = load_table(spark, sf_dir, "lineitem")
    return t.select(month_of_date(F.col("l_shipdate")).alias("m"), "l_orderkey", "l_linenumber", "l_partkey", curate.pcm_sample(F.col("l_extendedprice"), 0.0, 200000.0).alias("x"))


SAMPLE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey"]


def byte_slices(spark: SparkSession, sf_dir: str, height: int = 4, per_batch: int = 4096) -> DataFrame:
    """source, item_id, m, data of all six sources: texts as UTF-8, tiles of ``height`` rows and batches of samples as bytes."""
    texts = text_slices(spark, sf_dir).select("source", "item_id", "m", F.encode("body", "UTF-8").alias("data"))
    t = curate.tiles(load_table(spark, sf_dir, "embeddings"), "vec_id", curate.gray_levels(F.col("embedding")), height)
    hexed = F.array_join(F.transform("pixels", lambda x: F.lpad(F.hex(x), 2, "0")), "")
    tiles = t.select(F.lit("gray_patches").alias("source"), F.col("patch_id").alias("item_id"), month_index(F.col("patch_id")).alias("m"), F.unhex(hexed).alias("data"))
    pcm = curate.byte_batches(price_samples(spark, sf_dir), ["m"], SAMPLE_ORDER, "x", per_batch)
    series = pcm.select(F.lit("sample_series").alias("source"), (F.col("m").cast("long") * (1 << 32) + F.col("batch")).alias("item_id"), "m", "data")
    return texts.unionByName(tiles).unionByName(series)


def slice_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """source, item_id, m, raw_bytes of every source, bytes of tiles and samples included."""
    texts = text_slices(spark, sf_dir).unionByName(order_lines(spark, sf_dir)).unionByName(dialogue_lines(spark, sf_dir))
    sized = texts.select("source", "item_id", "m", F.octet_length("body").cast("long").alias("raw_bytes"))
    tiles = load_table(spark, sf_dir, "embeddings").select(F.lit("gray_patches").alias("source"), F.col("vec_id").alias("item_id"), month_index(F.col("vec_id")).alias("m"), F.size("embedding").cast("long").alias("raw_bytes"))
    pcm = load_table(spark, sf_dir, "lineitem").select(F.lit("sample_series").alias("source"), F.col("l_orderkey").alias("item_id"), month_of_date(F.col("l_shipdate")).alias("m"), F.lit(2).cast("long").alias("raw_bytes"))
    return sized.unionByName(tiles).unionByName(pcm)


def model_cards(spark: SparkSession) -> DataFrame:
    """Fourteen cards in two size classes; some cutoffs are unknown, one model has no byte ids. Driver-sized."""
    from datetime import date

    early, late = date(2020, 12, 1), date(2022, 9, 1)
    rows = [("early", o, "small" if o < 3 else "large", early, 2048, "wb") for o in (2, 3, 5)] + [("late", o, "small" if o < 3 else "large", late, 4096, "wb") for o in (2, 3, 5)]
    cards = [(f"{f}_o{o}", f, size, date(2023, 2 if f == "early" else 7, 1), cut, "byte", o, ctx, True, s, 64.0, []) for f, o, size, cut, ctx, s in rows]
    cards += [
        ("late_o2_code", "late", "small", date(2023, 8, 1), late, "byte", 2, 16384, True, "wb", 64.0, ["code_files"]),
        ("wide_vocab", "wide", "small", date(2023, 9, 1), None, "word", 1, 32768, False, "wb", 64.0, []),
        ("multi_a", "multi", "small", date(2023, 9, 1), None, "byte", 2, 4096, True, "discount", 64.0, []),
        ("multi_b", "multi", "small", date(2023, 10, 1), None, "byte", 1, 32768, True, "wb", 64.0, []),
        ("multi_c", "multi", "large", date(2023, 11, 1), None, "byte", 3, 4096, True, "discount", 64.0, []),
        ("long_ctx", "long", "small", date(2023, 9, 1), None, "byte", 2, 32768, True, "wb", 16.0, []),
        ("mid_o4", "mid", "large", date(2023, 6, 1), None, "byte", 4, 2048, True, "wb", 64.0, []),
        ("mid_o4_small", "mid", "small", date(2023, 6, 1), None, "byte", 1, 2048, True, "discount", 64.0, []),
    ]
    return spark.createDataFrame(cards, CARD)
