"""Real codes and baseline compressors: round trips, overhead, rates; filter and residual costs with SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from slicecode.functions.exprs import MICRO, byte_symbols, micro_bits, month_label, word_symbols
from slicecode.operators import baselines, bpe, coder, curate, metrics, models, pyops, windows
from slicecode.plans.base import query
from slicecode.plans.shared import rates
from slicecode.sources.tables import SAMPLE_ORDER, byte_slices, documents_slices, load_table, price_samples


def _chunks(spark, sf_dir, size=2048):
    """Byte chunks of the reference articles of the testing period: item_id, chunk_no, data."""
    s = documents_slices(spark, sf_dir).where("source = 'reference_articles' and m >= 72")
    d = s.select("item_id", F.encode("body", "UTF-8").alias("d")).where(F.octet_length("d") > 0)
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.octet_length("d") - 1) / size).cast("int")), lambda k: F.substring(F.col("d"), k * size + 1, F.lit(size)))
    return d.select("item_id", F.posexplode(cut).alias("chunk_no", "data"))


def _packed(spark, sf_dir, order=2):
    seen = documents_slices(spark, sf_dir).where("source = 'reference_articles' and m <= 68")
    return coder.pack(models.fit_counts(models.byte_grams(seen, order, 2048)), order)


@query(None)
def arith_roundtrip(spark, sf_dir):
    """Encode and decode every chunk of the testing period: ok if the bytes come back."""
    chunks, model = _chunks(spark, sf_dir), _packed(spark, sf_dir)
    codes = coder.encode_chunks(chunks, model, ["item_id", "chunk_no"])
    back = coder.decode_chunks(codes, model, ["item_id", "chunk_no"]).withColumnRenamed("data", "decoded")
    j = chunks.join(back, ["item_id", "chunk_no"], "left")
    return j.select("item_id", "chunk_no", F.octet_length("data").cast("long").alias("n"), F.col("data").eqNullSafe(F.col("decoded")).alias("ok"))


@query(None)
def arith_overhead(spark, sf_dir):
    """Bits over the ideal by the coder's precision: of quantising the law, and of finite precision with the end."""
    precisions = (18, 20, 24, 32)  # totals of 2**16 slots need 18 bits at least
    c = coder.code_lengths(_chunks(spark, sf_dir, 512), _packed(spark, sf_dir, 1), ["item_id", "chunk_no"], precisions)
    bits = [F.get("bit_lens", F.lit(k)) for k in range(len(precisions))]
    each = [F.struct(F.sum(b).alias("bits"), F.round(F.sum(b - F.col("slot_bits")), 3).alias("finite_precision"), F.lit(p).alias("precision")) for b, p in zip(bits, precisions, strict=True)]
    got = c.agg(F.count(F.lit(1)).alias("chunks"), F.sum("n").alias("symbols"), F.round(F.sum("ideal_bits"), 3).alias("ideal_bits"), F.round(F.sum(F.col("slot_bits") - F.col("ideal_bits")), 3).alias("quantisation"), F.array(*each).alias("each"))
    return got.select("chunks", "symbols", "ideal_bits", "quantisation", F.explode("each").alias("z")).select("chunks", "symbols", "z.bits", "ideal_bits", "quantisation", "z.finite_precision", "z.precision")


@query(None)
def arith_slot_codes(spark, sf_dir):
    """The model-free encoder: symbols bring their slots from a join with an order-1 slot table; ok if the length is within two
    bits of the slots' own cost."""
    counts = models.fit_counts(models.byte_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), 1, 512)).persist()
    slots = models.cdf_table(counts, 1).unionByName(models.cdf_table(counts, 0))
    t = windows.with_context(documents_slices(spark, sf_dir).where("source = 'reference_articles' and m >= 72"), byte_symbols(F.col("body")), 1, ["item_id"], 512)
    # at most 257 x 256 slots
    t = t.withColumn("chunk_no", F.floor(F.col("pos") / 512).cast("int")).join(F.broadcast(slots), ["ctx", "sym"])
    codes = coder.encode_slots(t, ["item_id", "chunk_no"])
    return codes.select("item_id", "chunk_no", "n", "bit_len", (F.abs(F.col("bit_len") - F.col("slot_bits")) <= 2.5).alias("ok"))


@query(None)
def concat_codes(spark, sf_dir):
    """Chunk codes joined in segments and cut again: as many chunks, the same bytes."""
    codes = coder.encode_chunks(_chunks(spark, sf_dir, 512), _packed(spark, sf_dir, 1), ["item_id", "chunk_no"]).persist()
    segments = coder.concat_codes(codes, ["item_id"], per_segment=4)
    again = coder.split_codes(segments, ["item_id"], 4).select("item_id", "chunk_no", F.col("code").alias("again"))
    j = codes.join(again, ["item_id", "chunk_no"], "left")
    return j.groupBy("item_id").agg(F.count(F.lit(1)).alias("chunks"), F.sum("bit_len").alias("bit_len"), F.min(F.col("code").eqNullSafe(F.col("again"))).alias("ok"))


# --- baselines -----------------------------------------------------------------------------------------------------


def _rates(rows, coded):
    s = rows.withColumn("coded", coded).groupBy("source", "m").agg(F.sum("raw").alias("raw"), F.sum("coded").alias("coded"))
    return s.select("source", month_label(F.col("m")).alias("month"), "raw", "coded", F.round(100.0 * F.col("coded") / F.col("raw"), 4).alias("rate"))


def _bodies(spark, sf_dir):
    """source, m, data, raw of all six sources."""
    return byte_slices(spark, sf_dir).select("source", "m", "data", F.octet_length("data").cast("long").alias("raw"))


def _sized(spark, sf_dir):
    return _bodies(spark, sf_dir).withColumn("sizes", baselines.source_sizes(F.col("data"), F.col("source"))).select("source", "m", "raw", "sizes.*")


@query(None)
def gzip_rate(spark, sf_dir):
    """Level 9, headers counted, a document, tile or batch at a time; all six sources."""
    return _rates(_bodies(spark, sf_dir), baselines.gzip_size(F.col("data")))


@query(None)
def gzip_scopes(spark, sf_dir):
    """gzip by document, by chunk of 2048 bytes, and by month: a month's documents in the order of their ids are cut into bounded
    segments, each coded as raw deflate that starts from the last 32 KB of the document stream before it."""
    b = byte_slices(spark, sf_dir)
    raw = F.octet_length("data").cast("long")
    whole = b.select("source", F.lit("document").alias("scope"), raw.alias("raw"), baselines.gzip_size(F.col("data")).alias("coded"))
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.octet_length("data") - 1) / 2048).cast("int")), lambda k: F.substring(F.col("data"), k * 2048 + 1, F.lit(2048)))
    chunk = b.where(raw > 0).select("source", F.explode(cut).alias("data")).select("source", F.lit("chunk").alias("scope"), raw.alias("raw"), baselines.gzip_size(F.col("data")).alias("coded"))
    month = pyops.month_segments(b, 1 << 22).select("source", F.lit("month").alias("scope"), "raw", "coded")
    s = whole.unionByName(chunk).unionByName(month).groupBy("source", "scope").agg(F.sum("raw").alias("raw"), F.sum("coded").alias("coded"))
    return s.withColumn("rate", F.round(100.0 * F.col("coded") / F.col("raw"), 4))


@query(None)
def png_rate(spark, sf_dir):
    """Rows of 64 bytes for tiles, 128 for the rest, filters chosen per row; all six sources."""
    return _rates(_sized(spark, sf_dir), F.col("png"))


@query(None)
def flac_rate(spark, sf_dir):
    """16-bit samples for the sampled source, 8-bit ones for bytes; all six sources."""
    return _rates(_sized(spark, sf_dir), F.col("flac"))


@query(None)
def compressor_report(spark, sf_dir):
    """The three compressors on all six sources beside the models' report: periods, gap, projection."""
    long = _sized(spark, sf_dir).unpivot(["source", "m", "raw"], ["gzip", "png", "flac"], "model_id", "coded")
    totals = long.groupBy("source", "model_id", "m").agg((F.sum("coded") * 8 * MICRO).alias("micro"), F.sum("raw").alias("raw_bytes"))
    r = metrics.robustness(metrics.period_rates(metrics.monthly_rate(totals)))
    return r.withColumn("projected", F.round(F.col("r_test") + F.col("gap"), 8))


@query(None)
def source_difficulty_gzip(spark, sf_dir):
    """Mean gap of the rate models by source, beside the gap of gzip on the same slices."""
    r = rates(spark, sf_dir).where("model_id <> 'uniform'")
    return metrics.source_difficulty(r, compressor_report(spark, sf_dir).where("model_id = 'gzip'"))


_PX = "px AS (SELECT vec_id, unnest(p) AS v, generate_subscripts(p, 1) - 1 AS x FROM (SELECT vec_id, list_transform(embedding, lambda v: CAST(floor((least(greatest(CAST(v AS DOUBLE), -1.0), 1.0) + 1) * 127.5) AS INTEGER)) AS p FROM embeddings))"
_SIGNED = "abs(CASE WHEN ((v - {g}) % 256 + 256) % 256 >= 128 THEN ((v - {g}) % 256 + 256) % 256 - 256 ELSE ((v - {g}) % 256 + 256) % 256 END)"
_P = "(a + b - c)"
_PAETH = f"CASE WHEN abs({_P} - a) <= abs({_P} - b) AND abs({_P} - a) <= abs({_P} - c) THEN a WHEN abs({_P} - b) <= abs({_P} - c) THEN b ELSE c END"


@query(f"""WITH {_PX}, n AS (SELECT vec_id, x, v, coalesce(lag(v) OVER (PARTITION BY vec_id ORDER BY x), 0) AS a, coalesce(CASE WHEN vec_id % 4 <> 0 THEN lag(v) OVER (PARTITION BY x ORDER BY vec_id) END, 0) AS b FROM px),
m AS (SELECT *, coalesce(lag(b) OVER (PARTITION BY vec_id ORDER BY x), 0) AS c FROM n), s AS (SELECT vec_id, {', '.join(f"CAST(sum({_SIGNED.format(g='(' + g + ')')}) AS BIGINT) AS f{k}" for k, g in enumerate(('0', 'a', 'b', '(a + b) // 2', _PAETH)))} FROM m GROUP BY vec_id)
SELECT vec_id, f0, f1, f2, f3, f4, CASE least(f0, f1, f2, f3, f4) WHEN f0 THEN 0 WHEN f1 THEN 1 WHEN f2 THEN 2 WHEN f3 THEN 3 ELSE 4 END AS filter FROM s""")
def png_filter_cost(spark, sf_dir):
    """Cost of each filter on each row of the tiles (four rows a tile), and the choice: the least, the lower number at ties."""
    from slicecode.operators.curate import gray_levels

    e = load_table(spark, sf_dir, "embeddings").select("vec_id", gray_levels(F.col("embedding")).alias("p"))
    up = e.select((F.col("vec_id") + 1).alias("vec_id"), F.col("p").alias("u"))
    j = e.join(up, "vec_id", "left").withColumn("u", F.when((F.col("vec_id") % 4 != 0) & F.col("u").isNotNull(), F.col("u")).otherwise(F.transform("p", lambda x: F.lit(0))))
    n = F.size("p")
    left = lambda c: F.concat(F.array(F.lit(0)), F.slice(c, 1, n - 1))
    j = j.withColumn("a", left(F.col("p"))).withColumn("c", left(F.col("u")))
    z = F.arrays_zip("p", "a", "u", "c")

    def paeth(a, b, c):
        p = a + b - c
        return F.when((F.abs(p - a) <= F.abs(p - b)) & (F.abs(p - a) <= F.abs(p - c)), a).when(F.abs(p - b) <= F.abs(p - c), b).otherwise(c)

    def cost(guess):
        def one(acc, s):
            r = F.pmod(s["p"] - guess(s["a"], s["u"], s["c"]), F.lit(256))
            return acc + F.abs(F.when(r >= 128, r - 256).otherwise(r))

        return F.aggregate(z, F.lit(0).cast("long"), lambda acc, s: one(acc, s).cast("long"))

    kinds = [lambda a, b, c: F.lit(0), lambda a, b, c: a, lambda a, b, c: b, lambda a, b, c: F.floor((a + b) / 2).cast("int"), paeth]
    got = j.select("vec_id", *[cost(k).alias(f"f{i}") for i, k in enumerate(kinds)])
    best = F.least("f0", "f1", "f2", "f3", "f4")
    return got.withColumn("filter", F.when(F.col("f0") == best, 0).when(F.col("f1") == best, 1).when(F.col("f2") == best, 2).when(F.col("f3") == best, 3).otherwise(4))


_S = "WITH s AS (SELECT CAST((year(l_shipdate) + 22 - 2017) * 12 + month(l_shipdate) - 1 AS INTEGER) AS m, l_orderkey, l_linenumber, l_partkey, CAST(floor((l_extendedprice - 0.0) / (200000.0 - 0.0) * 65535.0) - 32768 AS INTEGER) AS x FROM lineitem), l AS (SELECT m, x, lag(x, 1) OVER w AS x1, lag(x, 2) OVER w AS x2, lag(x, 3) OVER w AS x3, lag(x, 4) OVER w AS x4 FROM s WINDOW w AS (PARTITION BY m ORDER BY l_orderkey, l_linenumber, l_partkey))"
_RES = ("x", "x - x1", "x - 2 * x1 + x2", "x - 3 * x1 + 3 * x2 - x3", "x - 4 * x1 + 6 * x2 - 4 * x3 + x4")


def _residuals(spark, sf_dir):
    """Samples with the four before them in their month."""
    return curate.with_lags(curate.positions(price_samples(spark, sf_dir), ["m"], SAMPLE_ORDER), ["m"], "x", 4)


@query(f"{_S} SELECT m AS month_no, {', '.join(f'CAST(coalesce(sum(abs({r})), 0) AS BIGINT) AS order{k}' for k, r in enumerate(_RES))} FROM l GROUP BY m")
def flac_fixed_residuals(spark, sf_dir):
    """Sum of absolute residuals of the fixed predictors of orders 0 to 4, by month."""
    s = _residuals(spark, sf_dir)
    return s.groupBy(F.col("m").alias("month_no")).agg(*[F.coalesce(F.sum(F.abs(F.expr(r))), F.lit(0)).cast("long").alias(f"order{k}") for k, r in enumerate(_RES)])


@query(f"""{_S}, u AS (SELECT m, CAST(CASE WHEN r >= 0 THEN 2 * r ELSE -2 * r - 1 END AS BIGINT) AS u FROM (SELECT m, x - x1 AS r FROM l WHERE x1 IS NOT NULL)),
c AS (SELECT m, k, sum((u >> k) + 1 + k) AS bits FROM u CROSS JOIN (SELECT CAST(unnest(range(15)) AS INTEGER) AS k) GROUP BY ALL), b AS (SELECT m, k, bits, row_number() OVER (PARTITION BY m ORDER BY bits, k) AS r FROM c)
SELECT m AS month_no, k AS rice, CAST(bits AS BIGINT) AS bits FROM b WHERE r = 1""")
def rice_choice(spark, sf_dir):
    """The cheapest Rice parameter of the first-order residuals, by month; all fifteen in one aggregate."""
    u = _residuals(spark, sf_dir).where("x1 is not null").select("m", F.when(F.col("x") - F.col("x1") >= 0, 2 * (F.col("x") - F.col("x1"))).otherwise(-2 * (F.col("x") - F.col("x1")) - 1).cast("long").alias("u"))
    sums = u.groupBy("m").agg(*[F.sum(F.shiftright("u", k) + 1 + k).alias(f"k{k}") for k in range(15)])
    best = F.array_min(F.array(*[F.struct(F.col(f"k{k}").alias("bits"), F.lit(k).alias("rice")) for k in range(15)]))
    return sums.select(F.col("m").alias("month_no"), best["rice"].alias("rice"), best["bits"].alias("bits"))


# --- merges ---------------------------------------------------------------------------------------------------------


#: Vocabularies of the study: merges learned on all languages, and on English alone.
MERGES = {"all": (256, 1024, 4096, 8192), "en": (4096,)}


@query(None)
def bpe_table(spark, sf_dir):
    """Byte-pair tokenizers of growing vocabularies, trained on all languages or on English only: tokens and bits per token
    and byte under their own order-0 law, by language, on the testing slice. ``lossless``: the ids give every text back."""
    d = documents_slices(spark, sf_dir, keep=("lang",)).where("item_id is not null").select("source", "m", "body", "kept.lang")
    ref = d.where("source = 'reference_articles' and m >= 72").select("lang", "body", word_symbols(F.col("body")).alias("w"))
    train = d.where("source = 'reference_articles' and m < 72")
    learned = {name: list(bpe.train_bpe(train if name == "all" else train.where("lang = 'en'"), "body", max(sizes)).rank) for name, sizes in MERGES.items()}
    kinds = [(name, learned[name][:n]) for name, sizes in MERGES.items() for n in sizes]
    mergers = [bpe.Merger(merges) for _, merges in kinds]
    coded = ref.select("lang", "body", *[bpe.encode(F.col("w"), m, spark).alias(f"ids{k}") for k, m in enumerate(mergers)])
    back = coded.select("lang", "body", *[f"ids{k}" for k in range(len(kinds))], *[bpe.decode(F.col(f"ids{k}"), m, spark).alias(f"text{k}") for k, m in enumerate(mergers)])
    each = F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"ids{k}").alias("ids"), F.col(f"text{k}").eqNullSafe(F.col("body")).alias("same")) for k in range(len(kinds))])
    rows = back.select("lang", F.octet_length("body").cast("long").alias("size"), F.explode(each).alias("e")).select("lang", "size", "e.k", "e.same", F.posexplode_outer("e.ids").alias("pos", "sym"))
    size = F.when(F.coalesce("pos", F.lit(0)) == 0, F.col("size"))  # once a text
    t = rows.groupBy("k", "lang", "sym").agg(F.count("sym").alias("c"), F.min("same").alias("same"), F.sum(size).alias("bytes")).persist()  # ids of five vocabularies
    back = t.groupBy("k", "lang").agg(F.min("same").alias("lossless"), F.sum("bytes").alias("bytes"))
    t = t.where("sym is not null")
    law = t.groupBy("k", "sym").agg(F.sum("c").alias("n"))
    total = F.broadcast(law.groupBy("k").agg(F.sum("n").cast("double").alias("all")))  # a row a vocabulary
    z = t.join(law, ["k", "sym"]).join(total, "k").groupBy("k", "lang").agg(F.sum("c").alias("tokens"), F.sum(F.col("c") * micro_bits(F.col("n") / F.col("all"))).cast("double").alias("micro"))
    b = F.col("micro") / MICRO
    named = F.broadcast(spark.createDataFrame([(k, name, 256 + len(merges)) for k, (name, merges) in enumerate(kinds)], "k int, trained_on string, vocabulary int"))
    return z.join(back, ["k", "lang"]).join(named, "k").select("trained_on", "vocabulary", "lang", "tokens", F.round(b / F.col("tokens"), 6).alias("bpt"), F.round(b / F.col("bytes"), 6).alias("bpb"), "lossless")


# --- other ways to the same numbers --------------------------------------------------------------------------------

_ORDER1 = "((coalesce(c.c, 0) + CAST(1.0 AS DOUBLE)) / (coalesce(n.n, 0) + CAST(256.0 AS DOUBLE)))"
_SAME = f"""WITH r AS (SELECT doc_id, CAST(doc_id % 83 AS INTEGER) AS m, text FROM documents WHERE CAST(substr(source, 4) AS INTEGER) < 10), t AS (SELECT doc_id, m, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT doc_id, m, regexp_extract_all(hex(encode(text)), '..') AS h FROM r)),
g AS (SELECT doc_id, m, pos // 512 AS chunk_no, CASE WHEN pos % 512 = 0 THEN '' ELSE lag(sym) OVER (PARTITION BY doc_id ORDER BY pos) END AS ctx, sym FROM t), c AS (SELECT ctx, sym, count(*) AS c FROM g WHERE m <= 71 AND ctx <> '' GROUP BY ALL), n AS (SELECT ctx, sum(c) AS n FROM c GROUP BY ctx),
q AS (SELECT g.doc_id, g.m, g.chunk_no, CAST(round(-log2({_ORDER1}) * 1000000) AS BIGINT) AS micro FROM g LEFT JOIN c ON c.ctx = g.ctx AND c.sym = g.sym LEFT JOIN n ON n.ctx = g.ctx)"""
_BY_CHUNK = f"{_SAME} SELECT doc_id, CAST(chunk_no AS INTEGER) AS chunk_no, count(*) AS n, CAST(sum(micro) AS BIGINT) AS micro FROM q WHERE m >= 72 GROUP BY ALL"


def _order1_counts(spark, sf_dir):
    g = models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), 1, 512)
    return models.fit_counts(g.where("m <= 71")).where("depth = 1"), g


@query(_BY_CHUNK)
def arrow_score(spark, sf_dir):
    """The order-1 law as a fixed matrix, chunks scored in one Arrow pass: the same integers as by joins."""
    counts, _ = _order1_counts(spark, sf_dir)
    c = np.zeros((257, 256))
    for r in counts.collect():  # at most 65,536 pairs
        c[int(r["ctx"], 16), int(r["sym"], 16)] = r["cnt"]
    law = (c + 1.0) / (c.sum(1, keepdims=True) + 256.0)
    chunks = _chunks(spark, sf_dir, 512).withColumnRenamed("item_id", "doc_id")
    return pyops.arrow_score(chunks, law, ["doc_id", "chunk_no"])


@query(f"{_SAME} SELECT 'reference_articles' AS source, CAST(sum(micro) AS BIGINT) AS micro FROM q WHERE m >= 72")
def cogroup_score(spark, sf_dir):
    """Model shards meet the grams of their contexts: for models that no executor could hold."""
    counts, g = _order1_counts(spark, sf_dir)
    totals = models.context_totals(counts)
    law = models.additive(g, counts.withColumn("depth", F.lit(1)), totals, 1)
    shards = max(16, counts.count() // pyops.PAIRS_IN_A_SHARD + 1)
    shard = F.pmod(F.xxhash64("ctx"), F.lit(shards))
    grams = g.where("m >= 72").groupBy("source", "ctx", "sym").agg(F.sum("n").alias("n")).withColumn("shard", shard)
    return pyops.cogroup_score(grams, law.withColumn("shard", shard))


@query("SELECT doc_id, CAST(k AS INTEGER) AS chunk_no, CAST(least(512, n - k * 512) AS INTEGER) AS n, substr(h, CAST(k * 1024 + 1 AS INTEGER), 2) AS first_byte FROM (SELECT doc_id, strlen(text) AS n, unnest(range((strlen(text) + 511) // 512)) AS k, hex(encode(text)) AS h FROM documents)")
def udtf_chunks(spark, sf_dir):
    """A table function in a lateral join."""
    pyops.register(spark)
    load_table(spark, sf_dir, "documents").select("doc_id", "text").createOrReplaceTempView("documents_to_cut")
    return spark.sql("SELECT d.doc_id, c.chunk_no, c.n, substr(hex(c.data), 1, 2) AS first_byte FROM documents_to_cut d, LATERAL chunk_text(d.text, 512) c")
