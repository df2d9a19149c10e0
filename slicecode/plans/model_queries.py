"""Symbols, windows, laws and likelihoods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import bits, byte_symbols, char_symbols, micro_bits, month_label, month_of_date, rate, word_symbols
from slicecode.operators import inwindow, models, score, windows
from slicecode.plans.base import DOCS, MICRO, backoff, grams, label, query, tokens
from slicecode.plans.shared import byte_tokens, reference_grams
from slicecode.sources.tables import documents_slices, load_table

_REF = "ref AS (SELECT * FROM docs WHERE source = 'reference_articles')"
_HEX = "regexp_extract_all(hex(encode(text)), '..')"


def _token_stats(spark, sf_dir, seq):
    d = load_table(spark, sf_dir, "documents")
    t = windows.symbols(d, seq(F.col("text")), ["lang"])
    return t.groupBy("lang").agg(F.count(F.lit(1)).alias("tokens"), F.count_distinct("sym").alias("vocabulary"), F.max("pos").cast("long").alias("max_pos"))


def _stats_sql(seq: str) -> str:
    return f"SELECT lang, count(*) AS tokens, count(DISTINCT sym) AS vocabulary, CAST(max(pos) AS BIGINT) AS max_pos FROM (SELECT lang, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT lang, {seq} AS h FROM documents)) GROUP BY lang"


@query(_stats_sql(_HEX))
def byte_token_stats(spark, sf_dir):
    return _token_stats(spark, sf_dir, byte_symbols)


@query(_stats_sql("string_split(text, '')"))
def char_token_stats(spark, sf_dir):
    return _token_stats(spark, sf_dir, char_symbols)


@query(_stats_sql(r"regexp_extract_all(text, '[\p{L}\p{N}]+|[^\p{L}\p{N}\s]|\s')"))
def word_token_stats(spark, sf_dir):
    return _token_stats(spark, sf_dir, word_symbols)


@query(f"WITH {DOCS}, n AS (SELECT source, m, strlen(body) AS n FROM docs) SELECT source, {label('m')} AS month, CAST(sum((n + 255) // 256) AS BIGINT) AS chunks, CAST(sum((n - 1) % 256 + 1) AS BIGINT) AS last_len FROM n WHERE n > 0 GROUP BY ALL")
def chunk_plan_document(spark, sf_dir):
    """Chunks of 256 bytes inside documents; the short last ones are kept."""
    c = windows.chunk_arrays(documents_slices(spark, sf_dir), byte_symbols(F.col("body")), 256, ["source", "m", "item_id"])
    last = F.col("chunk_no") == F.max("chunk_no").over(Window.partitionBy("source", "m", "item_id"))
    got = c.select("source", "m", "item_id", "chunk_no", F.size("syms").alias("n")).withColumn("last", last)
    return got.groupBy("source", "m").agg(F.count(F.lit(1)).alias("chunks"), F.sum(F.when(F.col("last"), F.col("n"))).alias("last_len")).select("source", month_label(F.col("m")).alias("month"), "chunks", "last_len")


@query(f"WITH {DOCS}, n AS (SELECT source, m, sum(strlen(body)) AS n FROM docs GROUP BY ALL) SELECT source, {label('m')} AS month, CAST((n + 255) // 256 AS BIGINT) AS chunks, CAST((n - 1) % 256 + 1 AS BIGINT) AS last_len FROM n")
def chunk_plan_stream(spark, sf_dir):
    """The same with documents joined end to end; each document knows its place from a two-level prefix sum."""
    sizes = documents_slices(spark, sf_dir).select("source", "m", "item_id", F.octet_length("body").cast("long").alias("n"))
    placed = windows.stream_chunks(sizes, ["source", "m"], "item_id", "n")
    end = placed.groupBy("source", "m").agg(F.max("stop").alias("n"))
    return end.select("source", month_label(F.col("m")).alias("month"), F.ceil(F.col("n") / 256).alias("chunks"), ((F.col("n") - 1) % 256 + 1).alias("last_len"))


@query(f"""WITH t AS (SELECT doc_id, lang, sym, pos, row_number() OVER (PARTITION BY doc_id, sym ORDER BY pos) - 1 AS c FROM (SELECT doc_id, lang, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT doc_id, lang, {_HEX} AS h FROM documents)))
SELECT lang, count(*) AS bytes, round(CAST(sum(CAST(round(-log2((c + 0.5) / (pos + 128.0)) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits FROM t GROUP BY lang""")
def unbroken_bits(spark, sf_dir):
    """The adaptive law over whole documents: context without a bound."""
    got = _window_sums(spark, sf_dir, inwindow.Setting("whole", 0))
    return got.select("lang", "bytes", "bits")


@query("""WITH n AS (SELECT doc_id, strlen(text) AS n FROM documents), b AS (SELECT doc_id, n, unnest(range((n + 15) // 16)) AS b FROM n)
SELECT n.doc_id, CAST((n.n + 15) // 16 AS INTEGER) AS blocks, CAST(coalesce(sum(least(n.n, (b.b + 1) * 16) - greatest(0, b.b * 16 - 48)), 0) AS BIGINT) AS forward_tokens, CAST(n.n AS BIGINT) AS scored_tokens FROM n LEFT JOIN b USING (doc_id) GROUP BY n.doc_id, n.n""")
def sliding_plan(spark, sf_dir):
    """Windows of 64 that move by 16."""
    n = load_table(spark, sf_dir, "documents").select("doc_id", F.octet_length("text").alias("n"))
    return windows.sliding_plan(n, 64, 16, ["doc_id"])


_CONFIGS = ((2048, 2048), (4096, 4096), (8192, 8192), (2048, 512))


@query("""WITH n AS (SELECT strlen(text) AS n FROM documents), c AS (SELECT * FROM (VALUES (2048, 2048), (4096, 4096), (8192, 8192), (2048, 512)) v(size, step)),
b AS (SELECT size, step, n, unnest(range((n + step - 1) // step)) AS b FROM n CROSS JOIN c)
SELECT size || '/' || step AS config, CAST(sum(least(n, (b + 1) * step) - greatest(0, b * step - (size - step))) AS BIGINT) AS forward_tokens, CAST(sum(least(n, (b + 1) * step) - b * step) AS BIGINT) AS scored_tokens,
  round(CAST(sum(least(n, (b + 1) * step) - greatest(0, b * step - (size - step))) AS DOUBLE) / sum(least(n, (b + 1) * step) - b * step), 6) AS ratio FROM b GROUP BY size, step""")
def forward_token_cost(spark, sf_dir):
    """What a network would have to read under each window setting; overlap reads up to size / step times as much."""
    n = load_table(spark, sf_dir, "documents").select(F.octet_length("text").alias("n"))
    out = None
    for size, step in _CONFIGS:
        got = windows.sliding_plan(n, size, step, []).agg(F.sum("forward_tokens").alias("forward_tokens"), F.sum("scored_tokens").alias("scored_tokens")).withColumn("config", F.lit(f"{size}/{step}"))
        out = got if out is None else out.unionByName(got)
    return out.select("config", "forward_tokens", "scored_tokens", F.round(F.col("forward_tokens") / F.col("scored_tokens"), 6).alias("ratio"))


_BASE = f"WITH {DOCS}, {_REF}, {tokens('ref')}, {grams(2048, 2)}"


@query(f"{_BASE}, d AS (SELECT unnest(range(length(ctx) // 2 + 1)) AS depth, ctx, sym, n FROM grams), s AS (SELECT depth, CASE WHEN depth = 0 THEN '' ELSE right(ctx, 2 * depth) END AS h, sym, sum(n) AS n FROM d GROUP BY ALL) SELECT CAST(depth AS INTEGER) AS depth, count(*) AS grams, CAST(sum(n) AS BIGINT) AS total FROM s GROUP BY depth")
def gram_counts(spark, sf_dir):
    counts = models.fit_counts(models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), 2, 2048))
    return counts.groupBy("depth").agg(F.count(F.lit(1)).alias("grams"), F.sum("cnt").alias("total"))


@query(f"{_BASE}, s AS (SELECT right(ctx, 2) AS ctx, sym, sum(n) AS n FROM grams WHERE length(ctx) >= 2 GROUP BY ALL) SELECT ctx, CAST(sum(n) AS BIGINT) AS n, count(*) AS t FROM s GROUP BY ctx")
def context_totals(spark, sf_dir):
    counts = models.fit_counts(models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), 1, 2048))
    return models.context_totals(counts.where("depth = 1")).select("ctx", "n", "t")


def _monthly(scored_totals):
    return scored_totals.select("source", month_label(F.col("m")).alias("month"), bits(F.col("micro")).alias("bits"), rate(F.col("micro"), F.col("raw_bytes")).alias("rate"))


_OUT = f"SELECT source, {label('m')} AS month, round(CAST(micro AS DOUBLE) / 1000000, 3) AS bits, round(100.0 * micro / 1000000 / (8.0 * raw_bytes), 4) AS rate FROM totals"
_TOTALS = f"totals AS (SELECT source, m, CAST(sum(n * {MICRO}) AS BIGINT) AS micro, CAST(sum(n) AS BIGINT) AS raw_bytes FROM grams JOIN s_x USING (ctx, sym) GROUP BY source, m)"


@query(f"WITH {DOCS}, totals AS (SELECT source, m, CAST(sum(strlen(body)) * 8000000 AS BIGINT) AS micro, CAST(sum(strlen(body)) AS BIGINT) AS raw_bytes FROM docs GROUP BY ALL) {_OUT}")
def uniform_bits(spark, sf_dir):
    """The ceiling: eight bits a byte, 100 percent."""
    s = documents_slices(spark, sf_dir).groupBy("source", "m").agg(F.sum(F.octet_length("body").cast("long")).alias("raw_bytes"))
    return _monthly(s.withColumn("micro", F.col("raw_bytes") * 8_000_000))


def _law_sql(d: int, alpha: str) -> str:
    h = "''" if d == 0 else f"right(ctx, {2 * d})"
    return f"""{_BASE}, c AS (SELECT {h} AS h, sym, sum(n) AS c FROM grams WHERE m <= 71 AND length(ctx) >= {2 * d} GROUP BY ALL), t AS (SELECT h, sum(c) AS n FROM c GROUP BY h),
s_x AS (SELECT g.ctx, g.sym, (coalesce(c.c, 0) + CAST({alpha} AS DOUBLE)) / (coalesce(t.n, 0) + CAST({alpha} AS DOUBLE) * 256) AS p FROM (SELECT DISTINCT ctx, sym FROM grams) g LEFT JOIN t ON t.h = {h} AND length(g.ctx) >= {2 * d} LEFT JOIN c ON c.h = {h} AND c.sym = g.sym AND length(g.ctx) >= {2 * d}), {_TOTALS} {_OUT}"""


def _additive(spark, sf_dir, order: int, alpha: float):
    g = reference_grams(spark, sf_dir, order, 2048)
    counts, totals = models.fit_backoff(g, 71)
    full = counts.where(F.length("ctx") == 2 * order)
    law = models.additive(g, full, totals, order, alpha)
    return _monthly(score.gram_pushdown(g, law, ["source", "m"]))


@query(_law_sql(0, "1.0").replace("'' AND length(g.ctx) >= 0", "''"))
def order0_bits(spark, sf_dir):
    return _additive(spark, sf_dir, 0, 1.0)


@query(_law_sql(1, "0.5"))
def additive_bits(spark, sf_dir):
    """Order 1, half a count added; a chunk's first byte has no context and falls to the uniform law."""
    return _additive(spark, sf_dir, 1, 0.5)


_EARLY, _LATE = backoff("early", 2, "m <= 47"), backoff("late", 2, "m <= 68")
_TWO = " UNION ALL ".join(f"SELECT '{x}' AS model_id, source, m, CAST(sum(n * {MICRO}) AS BIGINT) AS micro, CAST(sum(n) AS BIGINT) AS raw_bytes FROM grams JOIN s_{x} USING (ctx, sym) GROUP BY source, m" for x in ("early", "late"))
_BACKOFF = f"{_BASE}, {_EARLY}, {_LATE}, totals AS ({_TWO}) SELECT model_id, source, {label('m')} AS month, round(CAST(micro AS DOUBLE) / 1000000, 3) AS bits, round(100.0 * micro / 1000000 / (8.0 * raw_bytes), 4) AS rate FROM totals"


def _two_models(spark, sf_dir, smoothing="wb", pushdown=True):
    g = reference_grams(spark, sf_dir, 2, 2048)
    out = None
    for name, until in (("early", 47), ("late", 68)):
        counts, totals = models.fit_backoff(g, until)
        law = models.score_grams(g, counts, totals, 2, smoothing)
        if pushdown:
            got = score.gram_pushdown(g, law, ["source", "m"])
        else:  # position by position: the reference path
            slices = documents_slices(spark, sf_dir).where("source = 'reference_articles'")
            t = windows.with_context(slices, byte_symbols(F.col("body")), 2, ["source", "m"], 2048)
            got = t.join(law, ["ctx", "sym"]).groupBy("source", "m").agg(F.sum(micro_bits(F.col("p"))).alias("micro"), F.count(F.lit(1)).alias("raw_bytes"))
        got = got.withColumn("model_id", F.lit(name))
        out = got if out is None else out.unionByName(got)
    return out.select("model_id", "source", month_label(F.col("m")).alias("month"), bits(F.col("micro")).alias("bits"), rate(F.col("micro"), F.col("raw_bytes")).alias("rate"))


@query(_BACKOFF)
def backoff_bits(spark, sf_dir):
    return _two_models(spark, sf_dir, pushdown=False)


@query(_BACKOFF)
def backoff_pushdown(spark, sf_dir):
    """The same from grams counted before scoring; equal to the last digit."""
    return _two_models(spark, sf_dir)


@query(_BACKOFF.replace(_EARLY, backoff("early", 2, "m <= 47", "discount")).replace(_LATE, backoff("late", 2, "m <= 68", "discount")))
def discount_bits(spark, sf_dir):
    return _two_models(spark, sf_dir, "discount")


_NORM = backoff("x", 1, "m <= 71").replace("FROM (SELECT DISTINCT ctx, sym FROM grams) g", "FROM (SELECT h AS ctx, upper(lpad(to_hex(k), 2, '0')) AS sym FROM (SELECT DISTINCT right(ctx, 2) AS h FROM grams) CROSS JOIN (SELECT unnest(range(256)) AS k)) g")


@query(f"{_BASE}, {_NORM} SELECT CAST(length(ctx) // 2 AS INTEGER) AS depth, count(*) AS contexts, round(max(abs(total - 1)), 6) AS max_abs_dev FROM (SELECT ctx, sum(p) AS total FROM s_x GROUP BY ctx) GROUP BY 1")
def law_normalisation(spark, sf_dir):
    """Sum of the law over the whole alphabet for every context: one, but for rounding."""
    g = reference_grams(spark, sf_dir, 2, 2048)
    counts, totals = models.fit_backoff(g, 71)
    few = g.select(F.expr("right(ctx, 2)").alias("ctx")).distinct()
    every = few.crossJoin(spark.range(256).select(F.upper(F.lpad(F.lower(F.hex("id")), 2, "0")).alias("sym")))  # contexts of one byte times the alphabet
    law = models.score_grams(every, counts.where("depth <= 1"), totals.where("depth <= 1"), 1)
    total = law.groupBy("ctx").agg(F.sum("p").alias("s"), F.count(F.lit(1)).alias("n"))
    return total.groupBy((F.length("ctx") / 2).cast("int").alias("depth")).agg(F.count(F.lit(1)).alias("contexts"), F.round(F.max(F.abs(F.col("s") - 1)), 6).alias("max_abs_dev"))


@query(f"""{_BASE}, c AS (SELECT right(ctx, 2) AS ctx, sym, CAST(sum(n) AS BIGINT) AS c FROM grams WHERE length(ctx) >= 2 GROUP BY ALL),
r AS (SELECT ctx, sym, c, CAST(coalesce(sum(c) OVER (PARTITION BY ctx ORDER BY sym ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS below, CAST(sum(c) OVER (PARTITION BY ctx) AS BIGINT) AS n, row_number() OVER (PARTITION BY ctx ORDER BY sym) - 1 AS k FROM c)
SELECT ctx, sym, CAST(below * 65280 // n + k AS BIGINT) AS lo, CAST((below + c) * 65280 // n + k + 1 AS BIGINT) AS hi, CAST(65536 AS BIGINT) AS total FROM r""")
def cdf_slots(spark, sf_dir):
    g = models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), 1, 2048)
    return models.cdf_table(models.fit_counts(g), 1)


_TOK = f"WITH t AS (SELECT doc_id, lang, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT doc_id, lang, {_HEX} AS h FROM documents))"
_SUM = "count(*) AS bytes, round(CAST(sum(CAST(round(-log2(p) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits, round(100.0 * sum(CAST(round(-log2(p) * 1000000) AS BIGINT)) / 1000000 / (8.0 * count(*)), 4) AS rate"


def _summed(costs, by):
    """bytes, bits, rate of each group of ``inwindow.window_costs``."""
    total, n = F.sum("micro"), F.sum("n")
    return costs.groupBy(*by).agg(n.alias("bytes"), bits(total).alias("bits"), rate(total, n).alias("rate"))


def _window_sums(spark, sf_dir, setting):
    """lang, bytes, bits, rate of the documents under one window setting."""
    return _summed(inwindow.window_costs(load_table(spark, sf_dir, "documents"), ["lang"], "text", [setting]), ["lang"])


@query(f"{_TOK} SELECT lang, {_SUM} FROM (SELECT lang, (row_number() OVER (PARTITION BY doc_id, pos // 2048, sym ORDER BY pos) - 1 + 0.5) / (pos % 2048 + 128.0) AS p FROM t) GROUP BY lang")
def adaptive_chunked(spark, sf_dir):
    return _window_sums(spark, sf_dir, inwindow.Setting("2048", 2048))


_SLIDE = """b AS (SELECT *, pos // 512 AS block, row_number() OVER (PARTITION BY doc_id, sym, pos // 512 ORDER BY pos) - 1 AS r FROM t),
c AS (SELECT doc_id, sym, block, coalesce(sum(n) OVER (PARTITION BY doc_id, sym ORDER BY block RANGE BETWEEN 3 PRECEDING AND 1 PRECEDING), 0) AS prior FROM (SELECT doc_id, sym, block, count(*) AS n FROM b GROUP BY ALL)),
w AS (SELECT b.*, b.r + c.prior AS n_w, b.pos - greatest(0, b.block * 512 - 1536) AS mm FROM b JOIN c USING (doc_id, sym, block))"""


@query(f"{_TOK}, {_SLIDE} SELECT lang, {_SUM} FROM (SELECT lang, (n_w + 0.5) / (mm + 128.0) AS p FROM w) GROUP BY lang")
def adaptive_sliding(spark, sf_dir):
    """Windows of 2048 that move by 512: at least 1536 symbols of context once a document has them."""
    return _window_sums(spark, sf_dir, inwindow.Setting("2048/512", 2048, 512))


@query(f"""{_TOK}, x AS (SELECT *, pos // 2048 AS chunk, CASE WHEN pos % 2048 = 0 THEN '' ELSE lag(sym) OVER (PARTITION BY doc_id ORDER BY pos) END AS ctx FROM t)
SELECT lang, {_SUM} FROM (SELECT lang, (row_number() OVER (PARTITION BY doc_id, chunk, ctx, sym ORDER BY pos) - 1 + 0.5) / (row_number() OVER (PARTITION BY doc_id, chunk, ctx ORDER BY pos) - 1 + 128.0) AS p FROM x) GROUP BY lang""")
def adaptive_order1(spark, sf_dir):
    return _window_sums(spark, sf_dir, inwindow.Setting("2048", 2048, order=1))


@query(f"""WITH {DOCS}, {tokens('docs')}, n AS (SELECT source, m, item_id, sum(strlen(body)) OVER (PARTITION BY source, m ORDER BY item_id) - strlen(body) AS before FROM docs), g AS (SELECT source, m, sym, CAST(before + pos AS BIGINT) AS g FROM tok JOIN n USING (source, m, item_id)),
q AS (SELECT source, m, (row_number() OVER (PARTITION BY source, m, g // 2048, sym ORDER BY g) - 1 + 0.5) / (g % 2048 + 128.0) AS p FROM g) SELECT source, {label('m')} AS month, count(*) AS bytes, round(CAST(sum({MICRO}) AS DOUBLE) / 1000000, 3) AS bits, round(100.0 * sum({MICRO}) / 1000000 / (8.0 * count(*)), 4) AS rate FROM q GROUP BY source, m""")
def adaptive_stream_chunks(spark, sf_dir):
    """The adaptive law over chunks of 2048 bytes of each month's stream, documents joined end to end."""
    d = documents_slices(spark, sf_dir).withColumn("data", F.encode("body", "UTF-8"))
    chunks = windows.stream_pieces(d, 2048, ["source", "m"], "item_id", "data")
    got = _summed(inwindow.window_costs(chunks, ["source", "m"], "data", [inwindow.Setting("2048", 2048)]), ["source", "m"])
    return got.select("source", month_label(F.col("m")).alias("month"), "bytes", "bits", "rate")


# --- the context study ------------------------------------------------------------------------------------------------

#: Five models: the static order under the window's counts (none: the window alone), and the longest window each can read.
STUDY = {"adaptive_o0": (None, 8192), "cached_o0": (0, 8192), "cached_o1": (1, 8192), "cached_o2": (2, 4096), "cached_o3": (3, 2048)}
_LONGEST_ORDER = 3
_STUDY_SETTINGS = [inwindow.Setting(f"{model}:{size}/{step}", size, step, law=None if k is None else f"p{k}") for model, (k, most) in STUDY.items() for size, step in _CONFIGS if size <= most]

_STATIC = f"""WITH {DOCS}, {_REF}, {tokens('ref')}, {grams(None, _LONGEST_ORDER)}, {', '.join(backoff(f'o{k}', k, 'm <= 71') for k in range(_LONGEST_ORDER + 1))},
lagged AS (SELECT item_id AS doc_id, m, pos, sym, coalesce(lag(sym, 3) OVER w, '') || coalesce(lag(sym, 2) OVER w, '') || coalesce(lag(sym) OVER w, '') AS ctx FROM tok WINDOW w AS (PARTITION BY item_id ORDER BY pos)),
t AS (SELECT l.doc_id, l.pos, l.sym, {', '.join(f's_o{k}.p AS p{k}' for k in range(_LONGEST_ORDER + 1))} FROM lagged l {' '.join(f'JOIN s_o{k} ON s_o{k}.ctx = l.ctx AND s_o{k}.sym = l.sym' for k in range(_LONGEST_ORDER + 1))} WHERE m >= 72)"""


def _cached_sql(size: int, step: int) -> str:
    ps = ", ".join(f"p{k}" for k in range(_LONGEST_ORDER + 1))
    if size == step:
        return f"SELECT {size} AS size, '{size}/{step}' AS config, {ps}, row_number() OVER (PARTITION BY doc_id, pos // {size}, sym ORDER BY pos) - 1 AS n_w, pos % {size} AS mm FROM t"
    k = size // step
    return f"""SELECT {size} AS size, '{size}/{step}' AS config, {ps}, b.r + c.prior AS n_w, b.pos - greatest(0, b.block * {step} - {size - step}) AS mm
FROM (SELECT *, pos // {step} AS block, row_number() OVER (PARTITION BY doc_id, sym, pos // {step} ORDER BY pos) - 1 AS r FROM t) b JOIN
(SELECT doc_id, sym, block, coalesce(sum(n) OVER (PARTITION BY doc_id, sym ORDER BY block RANGE BETWEEN {k - 1} PRECEDING AND 1 PRECEDING), 0) AS prior FROM (SELECT doc_id, sym, pos // {step} AS block, count(*) AS n FROM t GROUP BY ALL)) c USING (doc_id, sym, block)"""


def _study_sql(model: str) -> str:
    k, most = STUDY[model]
    p = "(n_w + CAST(0.5 AS DOUBLE)) / (mm + CAST(128.0 AS DOUBLE))" if k is None else f"(n_w + CAST(64.0 AS DOUBLE) * p{k}) / (mm + CAST(64.0 AS DOUBLE))"
    return f"SELECT '{model}' AS model_id, config, {p} AS p FROM w WHERE size <= {most}"


_STUDY_SQL = f"{_STATIC}, w AS ({' UNION ALL '.join(_cached_sql(*c) for c in _CONFIGS)}), q AS ({' UNION ALL '.join(_study_sql(x) for x in STUDY)}), r AS (SELECT model_id, config, CAST(sum({MICRO}) AS BIGINT) AS micro, count(*) AS n FROM q GROUP BY ALL)"


def static_laws(spark, sf_dir):
    """ctx, sym, p0 … p3 of the testing grams of the reference articles: the laws of orders 0 to 3 of the training months."""
    g = models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles'"), _LONGEST_ORDER, None)
    counts, totals = models.fit_backoff(g, 71)
    return models.score_grams(g.where("m >= 72"), counts, totals, _LONGEST_ORDER, every=True)


def study_costs(spark, sf_dir):
    """config (model and window), n, micro, nanos, state_bytes of every testing document under all settings, in one pass. A law with
    more pairs than may be sent to all tasks is joined position by position instead, with the same integers."""
    slices = documents_slices(spark, sf_dir).where("source = 'reference_articles' and m >= 72")
    law = static_laws(spark, sf_dir)
    packed = inwindow.pack_law(law, _LONGEST_ORDER, [f"p{k}" for k in range(_LONGEST_ORDER + 1)])
    if packed is not None:
        return inwindow.window_costs(slices, [], "body", _STUDY_SETTINGS, packed)
    return joined_costs(slices, law, _STUDY_SETTINGS)


def joined_costs(slices, law, settings):
    """The relational form: each symbol brings its law by a join and its counts by windows."""
    t = windows.with_context(slices, byte_symbols(F.col("body")), _LONGEST_ORDER, ["item_id"]).withColumnRenamed("item_id", "doc_id").join(law, ["ctx", "sym"])
    out = None
    for s in settings:
        c = windows.chunk_counts(t, s.size, ["doc_id"]) if s.size == s.step else windows.sliding_counts(t, s.size, s.step, ["doc_id"])
        p = score.adaptive(F.col("n_w"), F.col("m")) if s.law is None else score.cached(F.col("n_w"), F.col("m"), F.col(s.law), s.strength)
        got = c.select(F.lit(s.name).alias("config"), F.lit(1).cast("long").alias("n"), micro_bits(p).alias("micro"), F.lit(None).cast("long").alias("nanos"), F.lit(None).cast("long").alias("state_bytes"))
        out = got if out is None else out.unionByName(got)
    return out


def _named():
    """model_id and config of a study setting's name."""
    return F.substring_index("config", ":", 1).alias("model_id"), F.substring_index("config", ":", -1).alias("config")


@query(f"{_STUDY_SQL} SELECT model_id, config, round(CAST(micro AS DOUBLE) / 1000000, 3) AS bits, round(100.0 * micro / 1000000 / (8.0 * n), 4) AS rate FROM r")
def cached_bits(spark, sf_dir):
    """Static laws of orders 0 to 3 refined by their windows, and the window alone, on the testing months of the reference articles."""
    return _summed(study_costs(spark, sf_dir), ["config"]).select(*_named(), "bits", "rate")


_GRID = ", ".join(f"('{x}', {most}, {size}, {step})" for x, (_, most) in STUDY.items() for size, step in _CONFIGS)


@query(f"""{_STUDY_SQL}, n AS (SELECT strlen(body) AS n FROM ref WHERE m >= 72), cfg AS (SELECT * FROM (VALUES (2048, 2048), (4096, 4096), (8192, 8192), (2048, 512)) v(size, step)),
f AS (SELECT size || '/' || step AS config, CAST(sum(least(n, (b + 1) * step) - greatest(0, b * step - (size - step))) AS BIGINT) AS forward_tokens, CAST(sum(least(n, (b + 1) * step) - b * step) AS BIGINT) AS scored_tokens FROM (SELECT size, step, n, unnest(range((n + step - 1) // step)) AS b FROM n CROSS JOIN cfg) GROUP BY size, step),
g AS (SELECT model_id, size || '/' || step AS config, size <= most AS fits FROM (VALUES {_GRID}) v(model_id, most, size, step))
SELECT model_id, config, round(100.0 * r.micro / 1000000 / (8.0 * r.n), 4) AS rate, CASE WHEN fits THEN forward_tokens END AS forward_tokens, CASE WHEN fits THEN scored_tokens END AS scored_tokens,
CASE WHEN fits THEN round(CAST(forward_tokens AS DOUBLE) / scored_tokens, 6) END AS relative_cost FROM g JOIN f USING (config) LEFT JOIN r USING (model_id, config)""")
def context_size_table(spark, sf_dir):
    """Five models at 2048, 4096, 8192 and 2048 with steps of 512: rate and what a network would read; nulls past the model's
    longest window."""
    r = _summed(study_costs(spark, sf_dir), ["config"]).select(*_named(), "rate")
    n = documents_slices(spark, sf_dir).where("source = 'reference_articles' and m >= 72").select(F.octet_length("body").alias("n"))
    f = None
    for size, step in _CONFIGS:
        got = windows.sliding_plan(n, size, step, []).agg(F.sum("forward_tokens").alias("f"), F.sum("scored_tokens").alias("s")).withColumn("config", F.lit(f"{size}/{step}"))
        f = got if f is None else f.unionByName(got)
    grid = spark.createDataFrame([(x, f"{size}/{step}", size <= most) for x, (_, most) in STUDY.items() for size, step in _CONFIGS], "model_id string, config string, fits boolean")
    j = grid.join(F.broadcast(f), "config").join(F.broadcast(r), ["model_id", "config"], "left")  # a row for each model and window
    fits = lambda c: F.when(F.col("fits"), c)
    return j.select("model_id", "config", "rate", fits(F.col("f")).alias("forward_tokens"), fits(F.col("s")).alias("scored_tokens"), fits(F.round(F.col("f") / F.col("s"), 6)).alias("relative_cost"))


@query(None)
def context_size_cost(spark, sf_dir):
    """Time and memory of the same settings: seconds of counting and scoring over all tasks, the largest state that a window's
    counts take, and the pairs and bytes of the static law. Measured, so no two runs agree to the digit."""
    law = static_laws(spark, sf_dir)
    pairs = law.agg(*[F.count_distinct(F.expr(f"right(ctx, {2 * k})"), "sym").alias(f"p{k}") for k in range(_LONGEST_ORDER + 1)])
    held = pairs.unpivot([], [f"p{k}" for k in range(_LONGEST_ORDER + 1)], "law", "law_pairs")
    names = spark.createDataFrame([(x, None if k is None else f"p{k}") for x, (k, _) in STUDY.items()], "model_id string, law string")
    c = study_costs(spark, sf_dir).groupBy("config").agg((F.sum("nanos") / 1e9).alias("seconds"), (F.max("state_bytes") / 1e6).alias("state_mb"), F.sum("n").alias("scored_tokens"))
    j = c.select(*_named(), "seconds", "state_mb", "scored_tokens").join(names, "model_id").join(held, "law", "left")
    return j.select("model_id", "config", F.round("seconds", 6).alias("seconds"), F.round("state_mb", 6).alias("state_mb"), "scored_tokens", F.coalesce("law_pairs", F.lit(0)).alias("law_pairs"), (F.coalesce("law_pairs", F.lit(0)) * 24 / 1e6).alias("law_mb"))


@query("""WITH t AS (SELECT o_orderpriority AS stream_id, o_orderkey AS pos, ln((1 + o_orderkey % 97) / CAST(100.0 AS DOUBLE)) AS logprob FROM orders)
SELECT stream_id, count(*) AS tokens, round(CAST(sum(CAST(round(-logprob / ln(CAST(2.0 AS DOUBLE)) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits FROM t GROUP BY stream_id""")
def external_logprobs(spark, sf_dir):
    """The hook for outside models: a table of log-probabilities per token."""
    o = load_table(spark, sf_dir, "orders")
    t = o.select(F.col("o_orderpriority").alias("stream_id"), F.log((1 + F.col("o_orderkey") % 97) / F.lit(100.0)).alias("logprob"))
    return models.from_logprobs(t)


@query(f"""WITH px AS (SELECT vec_id, unnest(list_transform(embedding, lambda v: CAST(floor((least(greatest(CAST(v AS DOUBLE), -1.0), 1.0) + 1) * 127.5) AS INTEGER))) AS x FROM embeddings),
{DOCS}, {tokens('docs')}, c AS (SELECT sym, count(*) AS c FROM tok WHERE m <= 68 GROUP BY sym), tot AS (SELECT sum(c) + 1.0 * 256 AS n FROM c),
s AS (SELECT CAST(sum(CAST(round(-log2((coalesce(c.c, 0) + CAST(1.0 AS DOUBLE)) / tot.n) * 1000000) AS BIGINT)) AS BIGINT) AS micro, count(*) AS n FROM px LEFT JOIN c ON c.sym = upper(lpad(to_hex(px.x), 2, '0')) CROSS JOIN tot)
SELECT 'late_o0' AS model_id, 'gray_patches' AS source, round(100.0 * micro / 1000000 / (8.0 * n), 4) AS rate FROM s UNION ALL SELECT 'wide_vocab', 'gray_patches', NULL""")
def byte_only_restricted(spark, sf_dir):
    """Tile bytes under a text model's byte law; a model without byte ids has no result."""
    from slicecode.operators.curate import gray_levels

    px = load_table(spark, sf_dir, "embeddings").select(F.explode(gray_levels(F.col("embedding"))).alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("k"))
    t = byte_tokens(documents_slices(spark, sf_dir).where("m <= 68"), [])
    c = t.groupBy("sym").agg(F.count(F.lit(1)).alias("c"))
    n = c.agg((F.sum("c") + 1.0 * 256).alias("n"))
    p = (F.coalesce("c", F.lit(0)) + 1.0) / F.col("n")
    j = px.withColumn("sym", F.lpad(F.hex("x"), 2, "0")).join(c, "sym", "left").crossJoin(F.broadcast(n))  # one row
    got = j.agg(F.sum(F.col("k") * micro_bits(p)).alias("micro"), F.sum("k").alias("n")).select(F.lit("late_o0").alias("model_id"), rate(F.col("micro"), F.col("n")).alias("rate"))
    cards = spark.createDataFrame([("late_o0", True), ("wide_vocab", False)], "model_id string, has_byte_ids boolean")
    return cards.join(got, (cards["model_id"] == got["model_id"]) & cards["has_byte_ids"], "left").select(cards["model_id"], F.lit("gray_patches").alias("source"), "rate")


@query(f"""WITH l AS (SELECT CAST((year(o_orderdate) + 22 - 2017) * 12 + month(o_orderdate) - 1 AS INTEGER) AS m, o_orderkey AS item_id, 'order_log' AS source, o_orderstatus || o_orderpriority AS body FROM orders), {tokens('l')}, c AS (SELECT sym, count(*) AS c FROM tok WHERE m <= 71 GROUP BY sym),
q AS (SELECT m, (coalesce(c.c, 0) + CAST(1.0 AS DOUBLE)) / ((SELECT sum(c) FROM c) + CAST(1.0 AS DOUBLE) * 256) AS p FROM tok LEFT JOIN c USING (sym))
SELECT {label('m')} AS month, count(*) AS bytes, round(100.0 * sum({MICRO}) / 1000000 / (8.0 * count(*)), 4) AS rate FROM q GROUP BY m""")
def order_log_rates(spark, sf_dir):
    """A natively timed source: a static order-0 law on delimited orders, month by month."""
    o = load_table(spark, sf_dir, "orders")
    lines = o.select(month_of_date(F.col("o_orderdate")).alias("m"), F.concat("o_orderstatus", "o_orderpriority").alias("body"))
    g = byte_tokens(lines, ["m"]).groupBy("m", "sym").agg(F.count(F.lit(1)).alias("n"))
    c = g.where("m <= 71").groupBy("sym").agg(F.sum("n").alias("c"))
    p = (F.coalesce("c", F.lit(0)) + 1.0) / (F.col("all") + 256.0)
    j = g.join(c, "sym", "left").crossJoin(F.broadcast(c.agg(F.sum("c").alias("all"))))  # one row
    s = j.groupBy("m").agg(F.sum(F.col("n") * micro_bits(p)).alias("micro"), F.sum("n").alias("bytes"))
    return s.select(month_label(F.col("m")).alias("month"), "bytes", rate(F.col("micro"), F.col("bytes")).alias("rate"))


@query(f"{_TOK}, c AS (SELECT sym, count(*) AS c FROM t GROUP BY sym), q AS (SELECT lang, c.c / (SELECT CAST(sum(c) AS DOUBLE) FROM c) AS p FROM t JOIN c USING (sym)), s AS (SELECT lang, count(*) AS n, CAST(sum({MICRO}) AS DOUBLE) AS micro FROM q GROUP BY lang) SELECT lang, n AS tokens, round(micro / 1000000 * ln(CAST(2.0 AS DOUBLE)), 3) AS nats, round(micro / 1000000 / n, 6) AS bits_per_token, round(pow(CAST(2.0 AS DOUBLE), micro / 1000000 / n), 4) AS perplexity FROM s")
def nll_perplexity(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents")
    g = byte_tokens(d, ["lang"], "text").groupBy("lang", "sym").agg(F.count(F.lit(1)).alias("n"))
    c = g.groupBy("sym").agg(F.sum("n").alias("c"))
    j = g.join(c, "sym").crossJoin(F.broadcast(c.agg(F.sum("c").cast("double").alias("all"))))  # one row
    s = j.groupBy("lang").agg(F.sum("n").alias("tokens"), F.sum(F.col("n") * micro_bits(F.col("c") / F.col("all"))).cast("double").alias("micro"))
    per = F.col("micro") / 1_000_000 / F.col("tokens")
    return s.select("lang", "tokens", F.round(F.col("micro") / 1_000_000 * F.log(F.lit(2.0)), 3).alias("nats"), F.round(per, 6).alias("bits_per_token"), F.round(F.pow(F.lit(2.0), per), 4).alias("perplexity"))


