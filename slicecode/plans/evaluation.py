"""Evaluation over calendar time: curves, periods, robustness, ranks, agreement, tasks, contamination."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import MICRO, byte_symbols, char_symbols, micro_bits, month_index, month_label, word_symbols
from slicecode.operators import metrics, models, sharded, windows, words
from slicecode.plans.base import CLASSES, CODE, DOCS, PAPERS, PERIODS, RATES, ROBUST, backoff, grams, label, mean_sql, query, tokens
from slicecode.plans.base import MICRO as MICRO_SQL
from slicecode.plans.shared import TEXTS, byte_tokens, classes, rate_series, rates, reference_grams
from slicecode.sources.tables import byte_slices, documents_slices, load_table, model_cards, text_slices


@query(f"WITH {RATES} SELECT source, model_id, {label('m')} AS month, rate FROM series")
def monthly_rate_curve(spark, sf_dir):
    return rate_series(spark, sf_dir).select("source", "model_id", month_label(F.col("m")).alias("month"), "rate")


@query(f"WITH {PERIODS} SELECT * FROM rates0")
def period_rates_mean(spark, sf_dir):
    return metrics.period_rates(rate_series(spark, sf_dir))


@query(f"WITH {RATES} SELECT source, model_id, round(sum(micro) * (100.0 / 8 / 1000000) / sum(raw_bytes), 4) AS r_all, round(sum(micro) FILTER (WHERE m < 72) * (100.0 / 8 / 1000000) / sum(raw_bytes) FILTER (WHERE m < 72), 4) AS r_train, round(sum(micro) FILTER (WHERE m >= 72) * (100.0 / 8 / 1000000) / sum(raw_bytes) FILTER (WHERE m >= 72), 4) AS r_test FROM series GROUP BY source, model_id")
def period_rates_pooled(spark, sf_dir):
    return metrics.period_rates(rate_series(spark, sf_dir), "pooled")


@query(f"WITH {ROBUST} SELECT * FROM rates")
def robustness_gap(spark, sf_dir):
    return rates(spark, sf_dir)


@query(f"WITH {ROBUST}, {CLASSES}, p AS (SELECT source, size_class, model_id, round(r_test + gap, 8) AS projected FROM rates JOIN classes USING (model_id) WHERE r_test IS NOT NULL), k AS (SELECT *, rank() OVER (PARTITION BY source, size_class ORDER BY projected) AS rank FROM p) SELECT *, CASE rank WHEN 1 THEN 'best' WHEN 2 THEN 'second' ELSE '' END AS mark FROM k")
def projected_rank(spark, sf_dir):
    return metrics.project_and_rank(rates(spark, sf_dir), classes(spark)).select("source", "size_class", "model_id", "projected", "rank", "mark")


@query(f"""WITH {ROBUST}, mid AS (SELECT source, median(r_test) AS a, median(gap) AS b FROM rates GROUP BY source) SELECT source, model_id, r_test, gap,
CASE WHEN r_test <= a THEN 'low_rate' ELSE 'high_rate' END || '/' || CASE WHEN gap <= b THEN 'small_gap' ELSE 'large_gap' END AS quadrant FROM rates JOIN mid USING (source)""")
def performance_plane(spark, sf_dir):
    return metrics.plane(rates(spark, sf_dir)).select("source", "model_id", "r_test", "gap", "quadrant")


@query(f"WITH {ROBUST} SELECT source, model_id, NOT EXISTS (SELECT 1 FROM rates o WHERE o.source = r.source AND o.r_test <= r.r_test AND o.gap <= r.gap AND (o.r_test < r.r_test OR o.gap < r.gap)) AS on_front FROM rates r")
def pareto_front(spark, sf_dir):
    return metrics.pareto(rates(spark, sf_dir)).select("source", "model_id", "on_front")


@query(f"""WITH {RATES}, d AS (SELECT a.source, a.m, round(a.rate - b.rate, 4) AS d FROM series a JOIN series b ON a.source = b.source AND a.m = b.m WHERE a.model_id = 'early_o2' AND b.model_id = 'late_o2'),
base AS (SELECT source, avg(d) AS mu, coalesce(stddev_samp(d), 0) AS sd FROM d WHERE m <= 47 GROUP BY source), f AS (SELECT d.* FROM d JOIN base USING (source) WHERE m > 47 AND d > mu + 3 * sd),
i AS (SELECT *, m - row_number() OVER (PARTITION BY source ORDER BY m) AS isle FROM f), r AS (SELECT source, min(m) AS first FROM i GROUP BY source, isle HAVING count(*) >= 3)
SELECT s.source, CAST(min(r.first) AS BIGINT) AS month_no FROM (SELECT DISTINCT source FROM d) s LEFT JOIN r USING (source) GROUP BY s.source""")
def divergence_month(spark, sf_dir):
    """Where the model with the earlier cutoff leaves the other for good, found from the curves alone."""
    return metrics.divergence(rate_series(spark, sf_dir, ("early_o2", "late_o2")), "early_o2", "late_o2", 47)


@query(f"WITH {RATES}, c AS (SELECT * FROM (VALUES ('early_o2', 47), ('late_o2', 68)) v(model_id, k)) SELECT source, model_id, round(regr_slope(rate, m) FILTER (WHERE m <= k), 6) AS slope_before, round(regr_slope(rate, m) FILTER (WHERE m > k), 6) AS slope_after FROM series JOIN c USING (model_id) GROUP BY source, model_id")
def trend_slopes(spark, sf_dir):
    cut = spark.createDataFrame([("early_o2", 47), ("late_o2", 68)], "model_id string, last_train int")
    return metrics.trend(rate_series(spark, sf_dir, ("early_o2", "late_o2")), cut)


@query(f"WITH {ROBUST} SELECT source, model_id, r_train, r_test, gap FROM rates WHERE model_id IN ('late_o2', 'late_o2_code')")
def domain_tuned_compare(spark, sf_dir):
    """The base model and the one that also counted code, on every source."""
    s = rate_series(spark, sf_dir, ("late_o2", "late_o2_code")).where("model_id <> 'uniform'")
    return metrics.robustness(metrics.period_rates(s)).select("source", "model_id", "r_train", "r_test", "gap")


@query(f"WITH {ROBUST} SELECT s.source, s.mean_gap, s.worse_models, r.gap AS reference_gap FROM (SELECT source, round(avg(gap), 6) AS mean_gap, CAST(count(*) FILTER (WHERE gap > 0) AS BIGINT) AS worse_models FROM rates WHERE model_id NOT IN ('uniform', 'early_o1') GROUP BY source) s JOIN rates r ON r.source = s.source AND r.model_id = 'early_o1'")
def source_difficulty(spark, sf_dir):
    """Against the order-1 law as the reference; the gzip reference is in gzip_rate."""
    r = rates(spark, sf_dir)
    return metrics.source_difficulty(r.where(~F.col("model_id").isin("uniform", "early_o1")), r.where("model_id = 'early_o1'"))


_SOURCES = ("code_files", "news_articles", "reference_articles")


@query(f"WITH {ROBUST} SELECT model_id, " + ", ".join(f"max({c}) FILTER (WHERE source = '{s}') AS {s}_{n}" for s in _SOURCES for c, n in (("r_all", "avg"), ("r_test", "test"), ("gap", "gap"))) + " FROM rates GROUP BY model_id")
def table3_wide(spark, sf_dir):
    """One row a model, a triple of columns a source."""
    got = rates(spark, sf_dir).groupBy("model_id").pivot("source", list(_SOURCES)).agg(F.max("r_all").alias("avg"), F.max("r_test").alias("test"), F.max("gap").alias("gap"))
    return got


_AGREE = f"""WITH {ROBUST}, x AS (SELECT model_id, max(r_test) FILTER (WHERE source = 'reference_articles') AS a, max(r_test) FILTER (WHERE source = 'news_articles') AS b FROM rates GROUP BY model_id),
r AS (SELECT *, CAST(rank() OVER (ORDER BY a) AS DOUBLE) AS ra, CAST(rank() OVER (ORDER BY b) AS DOUBLE) AS rb FROM x)
SELECT (SELECT round(corr(ra, rb), 6) FROM r) AS spearman, (SELECT round(corr(a, b), 6) FROM r) AS pearson, (SELECT round(avg(sign((p.a - q.a) * (p.b - q.b))), 6) FROM r p JOIN r q ON p.model_id < q.model_id) AS kendall"""


@query(_AGREE)
def rank_agreement(spark, sf_dir):
    """Do two sources rank the models alike?"""
    r = rates(spark, sf_dir).groupBy("model_id").pivot("source", ["reference_articles", "news_articles"]).agg(F.max("r_test"))
    return metrics.rank_agreement(r, "reference_articles", "news_articles")


# --- tokenizers ---------------------------------------------------------------------------------------------------

_SPLITS = {"byte": ("regexp_extract_all(hex(encode(body)), '..')", byte_symbols), "char": ("string_split(body, '')", char_symbols), "word": (r"regexp_extract_all(body, '[\p{L}\p{N}]+|[^\p{L}\p{N}\s]|\s')", word_symbols)}
_TEST_SLICE = f"WITH {DOCS}, ref AS (SELECT * FROM docs WHERE source = 'reference_articles' AND m >= 72), raw AS (SELECT sum(strlen(body)) AS bytes, sum(length(body)) AS chars FROM ref)"


@query(_TEST_SLICE + ", " + ", ".join(f"t_{k} AS (SELECT sym, count(*) AS c FROM (SELECT unnest({s}) AS sym FROM ref) GROUP BY sym), z_{k} AS (SELECT count(*) AS v, sum(c) AS n, CAST(sum(c * CAST(round(-log2(c / (SELECT CAST(sum(c) AS DOUBLE) FROM t_{k})) * 1000000) AS BIGINT)) AS DOUBLE) AS micro FROM t_{k})" for k, (s, _) in _SPLITS.items()) + " "
       + " UNION ALL ".join(f"SELECT '{k}' AS tokenizer, v AS vocabulary, CAST(n AS BIGINT) AS tokens, round(micro / 1000000 / n, 6) AS bpt, round(micro / 1000000 / bytes, 6) AS bpb, round(micro / 1000000 / chars, 6) AS bpc, round(CAST(bytes AS DOUBLE) / n, 6) AS bytes_per_token, CAST(n * ceil(log2(v)) AS BIGINT) AS packed_bits FROM z_{k} CROSS JOIN raw" for k in _SPLITS))
def tokenizer_table(spark, sf_dir):
    """Vocabulary, tokens and bits per token, byte and character on the testing slice, under each tokenizer's own order-0
    law; bytes per token and packed ids show tokenization as compression in itself."""
    ref = documents_slices(spark, sf_dir).where("source = 'reference_articles' and m >= 72").select("body")
    raw = F.broadcast(ref.agg(F.sum(F.octet_length("body").cast("long")).alias("bytes"), F.sum(F.length("body").cast("long")).alias("chars")))  # one row
    out = None
    for name, (_, seq) in _SPLITS.items():
        c = ref.select(F.explode(seq(F.col("body"))).alias("sym")).groupBy("sym").agg(F.count(F.lit(1)).alias("c"))
        every = F.broadcast(c.agg(F.sum("c").cast("double").alias("all")))  # one row
        z = c.crossJoin(every).agg(F.count(F.lit(1)).alias("v"), F.sum("c").alias("n"), F.sum(F.col("c") * micro_bits(F.col("c") / F.col("all"))).cast("double").alias("micro")).crossJoin(raw)
        b = F.col("micro") / 1_000_000
        got = z.select(F.lit(name).alias("tokenizer"), F.col("v").alias("vocabulary"), F.col("n").alias("tokens"), F.round(b / F.col("n"), 6).alias("bpt"), F.round(b / F.col("bytes"), 6).alias("bpb"), F.round(b / F.col("chars"), 6).alias("bpc"), F.round(F.col("bytes") / F.col("n"), 6).alias("bytes_per_token"), (F.col("n") * F.ceil(F.log2("v"))).cast("long").alias("packed_bits"))
        out = got if out is None else out.unionByName(got)
    return out


# --- tasks --------------------------------------------------------------------------------------------------------

_TASK = f"WITH {DOCS}, ref AS (SELECT * FROM docs WHERE source = 'reference_articles'), {tokens('ref')}, {grams(2048, 2)}"


def _top_sql(x: str, d: int, until: int) -> str:
    h = f"right(ctx, {2 * d})"
    return f"top_{x} AS (SELECT h, first(sym ORDER BY c DESC, sym) AS best FROM (SELECT {h} AS h, sym, sum(n) AS c FROM grams WHERE length(ctx) >= {2 * d} AND m <= {until} GROUP BY ALL) GROUP BY h), hit_{x} AS (SELECT '{x}' AS model_id, round(avg(CASE WHEN b.sym = best THEN 1.0 ELSE 0.0 END), 6) AS score, count(*) AS positions FROM (SELECT sym, {'p1' if d == 1 else 'p2 || p1'} AS h FROM bt WHERE pos >= {d}) b LEFT JOIN top_{x} t ON t.h = b.h)"


_TOPS = (("early_o1", 1, 47), ("early_o2", 2, 47), ("late_o1", 1, 68), ("late_o2", 2, 68))


@query(f"{_TASK}, bt0 AS (SELECT item_id, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT item_id, regexp_extract_all(hex(encode(text)), '..') AS h FROM benchmark)), bt AS (SELECT *, lag(sym, 1) OVER w AS p1, lag(sym, 2) OVER w AS p2 FROM bt0 WINDOW w AS (PARTITION BY item_id ORDER BY pos)), {', '.join(_top_sql(*t) for t in _TOPS)} " + " UNION ALL ".join(f"SELECT * FROM hit_{x}" for x, _, _ in _TOPS))
def topone_accuracy(spark, sf_dir):
    """Next-byte accuracy on the benchmark items: the most frequent successor of the context, the smaller byte at ties."""
    g = reference_grams(spark, sf_dir, 2, 2048)
    bench = load_table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("body"))
    out = None
    for name, d, until in _TOPS:
        counts = models.fit_counts(g.where(F.col("m") <= until)).where(F.col("depth") == d)
        top = counts.groupBy("ctx").agg(F.max_by("sym", F.struct("cnt", (-F.conv("sym", 16, 10).cast("int")).alias("o"))).alias("best"))
        t = windows.with_context(bench, byte_symbols(F.col("body")), d, ["item_id"]).where(F.col("pos") >= d)
        got = t.join(top, "ctx", "left").agg(F.round(F.avg(F.when(F.col("sym") == F.col("best"), 1.0).otherwise(0.0)), 6).alias("score"), F.count(F.lit(1)).alias("positions")).select(F.lit(name).alias("model_id"), "score", "positions")
        out = got if out is None else out.unionByName(got)
    return out


_LANGID = """WITH d AS (SELECT doc_id, lang, CAST(doc_id % 83 AS INTEGER) AS m, text FROM documents), t AS (SELECT doc_id, lang, m, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT doc_id, lang, m, regexp_extract_all(hex(encode(text)), '..') AS h FROM d)),
g AS (SELECT doc_id, lang, m, coalesce(lag(sym) OVER (PARTITION BY doc_id ORDER BY pos), '') AS ctx, sym FROM t), c AS (SELECT lang AS guess, ctx, sym, count(*) AS c FROM g WHERE m < 72 GROUP BY ALL), n AS (SELECT guess, ctx, sum(c) AS n FROM c GROUP BY ALL),
q AS (SELECT doc_id, lang, ctx, sym, count(*) AS k FROM g WHERE m >= 72 GROUP BY ALL), l AS (SELECT DISTINCT guess FROM c),
s AS (SELECT doc_id, lang, l.guess, sum(k * CAST(round(-log2((coalesce(c.c, 0) + CAST(1.0 AS DOUBLE)) / (coalesce(n.n, 0) + CAST(256.0 AS DOUBLE))) * 1000000) AS BIGINT)) AS micro FROM q CROSS JOIN l LEFT JOIN n ON n.guess = l.guess AND n.ctx = q.ctx LEFT JOIN c ON c.guess = l.guess AND c.ctx = q.ctx AND c.sym = q.sym GROUP BY ALL),
b AS (SELECT doc_id, lang, first(guess ORDER BY micro, guess) AS best FROM s GROUP BY ALL) SELECT lang, count(*) AS docs, round(avg(CASE WHEN best = lang THEN 1.0 ELSE 0.0 END), 6) AS score FROM b GROUP BY lang"""


@query(_LANGID)
def language_id_accuracy(spark, sf_dir):
    """Four order-1 models, one a language, fitted on the training months; a testing document goes to the least code length."""
    d = load_table(spark, sf_dir, "documents").select("doc_id", "lang", month_index(F.col("doc_id")).alias("m"), F.col("text").alias("body"))
    g = windows.with_context(d, byte_symbols(F.col("body")), 1, ["doc_id", "lang", "m"]).groupBy("doc_id", "lang", "m", "ctx", "sym").agg(F.count(F.lit(1)).alias("k")).persist()
    c = g.where("m < 72").groupBy(F.col("lang").alias("guess"), "ctx", "sym").agg(F.sum("k").alias("c"))
    n = c.groupBy("guess", "ctx").agg(F.sum("c").alias("n"))
    each = g.where("m >= 72").crossJoin(F.broadcast(c.select("guess").distinct()))  # one row a language
    j = each.join(n, ["guess", "ctx"], "left").join(c, ["guess", "ctx", "sym"], "left")
    s = j.groupBy("doc_id", "lang", "guess").agg(F.sum(F.col("k") * micro_bits((F.coalesce("c", F.lit(0)) + 1.0) / (F.coalesce("n", F.lit(0)) + 256.0))).alias("micro"))
    best = s.groupBy("doc_id", "lang").agg(F.min_by("guess", F.struct("micro", "guess")).alias("best"))
    return best.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg(F.when(F.col("best") == F.col("lang"), 1.0).otherwise(0.0)), 6).alias("score"))


_COST = "WITH t AS (SELECT doc_id, unnest(regexp_extract_all(hex(encode(text)), '..')) AS sym FROM documents), c AS (SELECT sym, count(*) AS c FROM t GROUP BY sym), n AS (SELECT CAST(sum(c) AS DOUBLE) AS n FROM c), cost AS (SELECT doc_id, CAST(sum(CAST(round(-log2(c.c / n.n) * 1000000) AS BIGINT)) AS BIGINT) AS micro, count(*) AS bytes FROM t JOIN c USING (sym) CROSS JOIN n GROUP BY doc_id), costs AS (SELECT *, round(micro / 1000000.0 / bytes, 6) AS bits_per_byte FROM cost)"


def doc_costs(spark, sf_dir):
    """doc_id, micro, bytes, bits_per_byte under the corpus's order-0 law."""
    t = byte_tokens(load_table(spark, sf_dir, "documents"), ["doc_id"], "text").groupBy("doc_id", "sym").agg(F.count(F.lit(1)).alias("k")).persist()
    c = t.groupBy("sym").agg(F.sum("k").alias("c"))
    j = t.join(F.broadcast(c), "sym").crossJoin(F.broadcast(c.agg(F.sum("c").cast("double").alias("n"))))  # 256 rows, one row
    s = j.groupBy("doc_id").agg(F.sum(F.col("k") * micro_bits(F.col("c") / F.col("n"))).alias("micro"), F.sum("k").alias("bytes"))
    return s.withColumn("bits_per_byte", F.round(F.col("micro") / 1_000_000 / F.col("bytes"), 6))


def _auc_sql(label_col: str) -> str:
    return f"SELECT '{label_col}' AS label, round((sum(r) FILTER (WHERE y = 1) - count(*) FILTER (WHERE y = 1) * (count(*) FILTER (WHERE y = 1) + 1) / 2.0) / (count(*) FILTER (WHERE y = 1) * count(*) FILTER (WHERE y = 0)), 6) AS score FROM (SELECT l.{label_col} AS y, rank() OVER (ORDER BY bits_per_byte) + (count(*) OVER (PARTITION BY bits_per_byte) - 1) / 2.0 AS r FROM costs JOIN labels l USING (doc_id))"


@query(f"{_COST} {_auc_sql('quality')} UNION ALL {_auc_sql('toxic')}")
def quality_auc(spark, sf_dir):
    """Mann-Whitney by average ranks of bits per byte against each label. Ranks come from a two-level prefix sum over counts of
    distinct values, so no window spans the rows."""
    l = load_table(spark, sf_dir, "labels")  # noqa: E741
    j = doc_costs(spark, sf_dir).select("doc_id", "bits_per_byte").join(l, "doc_id").persist()
    out = None
    for c in ("quality", "toxic"):
        v = j.groupBy("bits_per_byte").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col(c) == 1, 1).otherwise(0)).alias("p")).withColumn("b", F.floor(F.col("bits_per_byte") * 64))
        tot = v.groupBy("b").agg(F.sum("n").alias("t"))
        off = tot.select("b", F.coalesce(F.sum("t").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("off"))  # at most 512 buckets
        ranked = v.join(F.broadcast(off), "b").withColumn("below", F.col("off") + F.coalesce(F.sum("n").over(Window.partitionBy("b").orderBy("bits_per_byte").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        s = ranked.agg(F.sum(F.col("p") * (F.col("below") + (F.col("n") + 1) / 2.0)).alias("r"), F.sum("p").alias("pos"), F.sum("n").alias("all"))
        got = s.select(F.lit(c).alias("label"), F.round((F.col("r") - F.col("pos") * (F.col("pos") + 1) / 2.0) / (F.col("pos") * (F.col("all") - F.col("pos"))), 6).alias("score"))
        out = got if out is None else out.unionByName(got)
    return out


@query(f"{_COST} SELECT doc_id, bits_per_byte, rank FROM (SELECT doc_id, bits_per_byte, rank() OVER (ORDER BY bits_per_byte DESC, doc_id) AS rank FROM costs) WHERE rank <= 20")
def topk_costly_docs(spark, sf_dir):
    """The twenty documents that cost most a byte: a top-k report."""
    top = doc_costs(spark, sf_dir).select("doc_id", "bits_per_byte").orderBy(F.desc("bits_per_byte"), "doc_id").limit(20)
    return top.withColumn("rank", F.rank().over(Window.orderBy(F.desc("bits_per_byte"), "doc_id")).cast("long"))


@query(f"{_COST}, s AS (SELECT d.source, c.doc_id, bits_per_byte FROM costs c JOIN documents d USING (doc_id)), r AS (SELECT *, ntile(10) OVER w AS decile, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM s WINDOW w AS (PARTITION BY source ORDER BY bits_per_byte, doc_id)) SELECT source, CAST(decile AS INTEGER) AS decile, count(*) AS docs, round(avg(bits_per_byte), 6) AS mean_bits, round(max(pr), 6) AS percent_rank, round(max(cd), 6) AS cume_dist FROM r GROUP BY ALL")
def cost_deciles(spark, sf_dir):
    """Deciles of cost inside each source."""
    s = doc_costs(spark, sf_dir).join(load_table(spark, sf_dir, "documents").select("doc_id", "source"), "doc_id")
    w = Window.partitionBy("source").orderBy("bits_per_byte", "doc_id")
    r = s.select("source", "bits_per_byte", F.ntile(10).over(w).alias("decile"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))
    return r.groupBy("source", "decile").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg("bits_per_byte"), 6).alias("mean_bits"), F.round(F.max("pr"), 6).alias("percent_rank"), F.round(F.max("cd"), 6).alias("cume_dist"))


@query(f"WITH {RATES} SELECT source, model_id, {label('m')} AS month, rate, round(avg(rate) OVER (PARTITION BY source, model_id ORDER BY m ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving, round(rate - lag(rate) OVER (PARTITION BY source, model_id ORDER BY m), 4) AS change FROM series WHERE model_id IN ('late_o2', 'uniform')")
def moving_rate(spark, sf_dir):
    w = Window.partitionBy("source", "model_id").orderBy("m")
    s = rate_series(spark, sf_dir, ("late_o2",))
    return s.select("source", "model_id", month_label(F.col("m")).alias("month"), "rate", F.round(F.avg("rate").over(w.rowsBetween(-2, 0)), 4).alias("moving"), F.round(F.col("rate") - F.lag("rate").over(w), 4).alias("change"))


# --- contamination --------------------------------------------------------------------------------------------------

_WORDS = r"regexp_extract_all(lower({}), '[\p{{L}}\p{{N}}]+')"
_CONTAMINATION = f"""WITH ws AS (SELECT item_id, {_WORDS.format('text')} AS w FROM benchmark), bs AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT item_id, w, unnest(range(1, len(w) - 6)) AS i FROM ws)),
wd AS (SELECT doc_id, {_WORDS.format('text')} AS w FROM documents), ds AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM wd)),
carry AS (SELECT DISTINCT item_id, doc_id FROM bs JOIN ds USING (s)), t AS (SELECT doc_id, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT doc_id, regexp_extract_all(hex(encode(text)), '..') AS h FROM documents)),
g AS (SELECT doc_id, coalesce(lag(sym, 2) OVER w, '') || coalesce(lag(sym) OVER w, '') AS ctx, sym FROM t WINDOW w AS (PARTITION BY doc_id ORDER BY pos)), dg AS (SELECT doc_id, ctx, sym, count(*) AS n FROM g GROUP BY ALL), c AS (SELECT ctx, sym, sum(n) AS c FROM dg GROUP BY ALL), n AS (SELECT ctx, sum(c) AS n FROM c GROUP BY ctx),
bt AS (SELECT item_id, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT item_id, regexp_extract_all(hex(encode(text)), '..') AS h FROM benchmark)), q AS (SELECT item_id, ctx, sym, count(*) AS k FROM (SELECT item_id, coalesce(lag(sym, 2) OVER w, '') || coalesce(lag(sym) OVER w, '') AS ctx, sym FROM bt WINDOW w AS (PARTITION BY item_id ORDER BY pos)) GROUP BY ALL),
oc AS (SELECT item_id, ctx, sym, sum(n) AS c FROM carry JOIN dg USING (doc_id) GROUP BY ALL), onn AS (SELECT item_id, ctx, sum(c) AS n FROM oc GROUP BY ALL), cnt AS (SELECT item_id, count(*) AS carriers FROM carry GROUP BY item_id)
SELECT q.item_id, coalesce(max(cnt.carriers), 0) AS carriers,
round(CAST(sum(k * CAST(round(-log2((coalesce(c.c, 0) + CAST(1.0 AS DOUBLE)) / (coalesce(n.n, 0) + CAST(256.0 AS DOUBLE))) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits_with,
round(CAST(sum(k * CAST(round(-log2((coalesce(c.c, 0) - coalesce(oc.c, 0) + CAST(1.0 AS DOUBLE)) / (coalesce(n.n, 0) - coalesce(onn.n, 0) + CAST(256.0 AS DOUBLE))) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits_without
FROM q LEFT JOIN c USING (ctx, sym) LEFT JOIN n USING (ctx) LEFT JOIN oc ON oc.item_id = q.item_id AND oc.ctx = q.ctx AND oc.sym = q.sym LEFT JOIN onn ON onn.item_id = q.item_id AND onn.ctx = q.ctx LEFT JOIN cnt ON cnt.item_id = q.item_id GROUP BY q.item_id"""


@query(_CONTAMINATION)
def contamination_probe(spark, sf_dir):
    """What knowing its carriers saves on each benchmark item: its bits under an order-2 law of all documents, and with the
    counts of the documents that share eight words in a row with it taken away."""
    docs, bench = load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "benchmark")

    def shingles(df, ident):
        w = df.select(ident, F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}\p{N}]+"), F.lit(0)).alias("w")).where(F.size("w") >= 8)
        return w.select(ident, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.array_join(F.slice("w", i, F.lit(8)), " ")))).alias("s"))

    carry = shingles(docs, "doc_id").join(shingles(bench, "item_id"), "s").select("item_id", "doc_id").distinct().persist()
    dg = windows.with_context(docs, byte_symbols(F.col("text")), 2, ["doc_id"]).groupBy("doc_id", "ctx", "sym").agg(F.count(F.lit(1)).alias("n")).persist()
    c = dg.groupBy("ctx", "sym").agg(F.sum("n").alias("c"))
    n = c.groupBy("ctx").agg(F.sum("c").alias("n"))
    oc = dg.join(carry, "doc_id").groupBy("item_id", "ctx", "sym").agg(F.sum("n").alias("oc"))
    on = oc.groupBy("item_id", "ctx").agg(F.sum("oc").alias("on"))
    q = windows.with_context(bench, byte_symbols(F.col("text")), 2, ["item_id"]).groupBy("item_id", "ctx", "sym").agg(F.count(F.lit(1)).alias("k"))
    j = q.join(c, ["ctx", "sym"], "left").join(n, "ctx", "left").join(oc, ["item_id", "ctx", "sym"], "left").join(on, ["item_id", "ctx"], "left")
    z = lambda x: F.coalesce(F.col(x), F.lit(0))
    s = j.groupBy("item_id").agg(F.sum(F.col("k") * micro_bits((z("c") + 1.0) / (z("n") + 256.0))).alias("a"), F.sum(F.col("k") * micro_bits((z("c") - z("oc") + 1.0) / (z("n") - z("on") + 256.0))).alias("b"))
    cnt = carry.groupBy("item_id").agg(F.count(F.lit(1)).alias("carriers"))
    return s.join(cnt, "item_id", "left").select("item_id", z("carriers").alias("carriers"), F.round(F.col("a") / MICRO, 3).alias("bits_with"), F.round(F.col("b") / MICRO, 3).alias("bits_without"))


@query(f"""WITH {DOCS}, ref AS (SELECT * FROM docs WHERE source = 'reference_articles'), {tokens('ref')}, {grams(2048, 2)}, tr AS (SELECT DISTINCT ctx, sym FROM grams WHERE m < 72), te AS (SELECT DISTINCT ctx, sym FROM grams WHERE m >= 72)
SELECT 'seen' AS kind, count(*) AS grams FROM (SELECT * FROM te INTERSECT SELECT * FROM tr) UNION ALL SELECT 'unseen', count(*) FROM (SELECT * FROM te EXCEPT SELECT * FROM tr)""")
def seen_unseen_grams(spark, sf_dir):
    g = reference_grams(spark, sf_dir, 2, 2048)
    tr, te = g.where("m < 72").select("ctx", "sym"), g.where("m >= 72").select("ctx", "sym")
    one = lambda df, k: df.agg(F.count(F.lit(1)).alias("grams")).select(F.lit(k).alias("kind"), "grams")
    return one(te.intersect(tr), "seen").unionByName(one(te.subtract(tr), "unseen"))


@query(f"""WITH {DOCS}, ref AS (SELECT * FROM docs), tr AS (SELECT DISTINCT md5(body) AS h FROM ref WHERE m < 72) SELECT source, count(*) AS docs, CAST(sum(strlen(body)) AS BIGINT) AS bytes FROM ref r WHERE m >= 72 AND NOT EXISTS (SELECT 1 FROM tr WHERE tr.h = md5(r.body)) GROUP BY source""")
def antijoin_unseen(spark, sf_dir):
    """Testing documents without an exact copy in the training months."""
    d = documents_slices(spark, sf_dir).withColumn("h", F.md5(F.col("body").cast("binary")))
    fresh = d.where("m >= 72").join(d.where("m < 72").select("h"), "h", "left_anti")
    return fresh.groupBy("source").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.octet_length("body").cast("long")).alias("bytes"))


# --- the whole report -------------------------------------------------------------------------------------------------

SIX = ("reference_articles", "news_articles", "code_files", "paper_bodies", "gray_patches", "sample_series")


def _until(card) -> int:
    """Last training month; an unknown cutoff is the end of the common training period."""
    cut = card["cutoff_month"]
    return 71 if cut is None else (cut.year - 2017) * 12 + cut.month - 1


def report_totals(spark, sf_dir, cards, sources=SIX):
    """source, model_id, m, micro, raw_bytes of the cards: byte laws on every source, the word law on the texts alone.

    One pass counts the grams of the highest order; lower orders are suffixes, cutoffs are filters on months.
    """
    byte = [c for c in cards if c["has_byte_ids"]]
    out = None
    if byte:
        if set(sources) <= set(SIX[:4]):
            slices = text_slices(spark, sf_dir, sources).select("source", "m", F.encode("body", "UTF-8").alias("data"))
        else:
            slices = byte_slices(spark, sf_dir).where(F.col("source").isin(*sources))
        out = sharded.score_cards(slices, [(c["model_id"], c["order"], _until(c), c["extra_sources"], c["smoothing"]) for c in byte], TEXTS, 2048)
    for c in cards:
        if not c["has_byte_ids"]:
            texts = text_slices(spark, sf_dir, tuple(x for x in sources if x in SIX[:4]))
            count = words.counter(spark, words.month_bigrams, "source", "m")
            each = texts.select("source", "m", F.encode("body", "UTF-8").alias("_d")).mapInArrow(count, "source string, m int, ctx string, sym string, n long")
            grams = each.groupBy("source", "m", "ctx", "sym").agg(F.sum("n").alias("n"))
            raw = texts.groupBy("source", "m").agg(F.sum(F.octet_length("body").cast("long")).alias("raw_bytes"))
            got = models.word_costs(grams, _until(c), TEXTS).join(raw, ["source", "m"]).select("source", F.lit(c["model_id"]).alias("model_id"), "m", "micro", "raw_bytes")
            out = got if out is None else out.unionByName(got)
    return out


def monthly_units(totals):
    """With rate: a month's rate in units of 1e-4 percent is micro / (8 raw), rounded as a whole number."""
    units = F.expr("(2 * cast(micro as decimal(38,0)) + 8 * raw_bytes) div (16 * raw_bytes)")
    return totals.where("raw_bytes > 0").withColumn("rate", units.cast("double") / 10000)


def card_rates(totals):
    """Periods, gap and direction from totals."""
    return metrics.robustness(metrics.period_rates(monthly_units(totals)))


def temporal_report(spark, sf_dir, model_ids: tuple[str, ...] | None = None, sources: tuple[str, ...] = SIX):
    """The cards over the sources: periods, gap, projection, rank, mark; nulls where a model has no byte ids and a source no text."""
    cards = [c for c in model_cards(spark).collect() if model_ids is None or c["model_id"] in model_ids]  # fourteen rows
    r = card_rates(report_totals(spark, sf_dir, cards, sources))
    ranked = metrics.project_and_rank(r, spark.createDataFrame([(c["model_id"], c["size_class"]) for c in cards], "model_id string, size_class string"))
    grid = spark.createDataFrame([(s, c["model_id"]) for s in sources for c in cards], "source string, model_id string")
    return grid.join(ranked, ["source", "model_id"], "left")


#: The cards as the SQL needs them: order, last training month, trained on code too, smoothing, size class; the word model is apart.
CARDS = {
    "early_o2": (2, 47, False, "wb", "small"), "early_o3": (3, 47, False, "wb", "large"), "early_o5": (5, 47, False, "wb", "large"), "late_o2": (2, 68, False, "wb", "small"), "late_o3": (3, 68, False, "wb", "large"),
    "late_o5": (5, 68, False, "wb", "large"), "late_o2_code": (2, 68, True, "wb", "small"), "multi_a": (2, 71, False, "discount", "small"), "multi_b": (1, 71, False, "wb", "small"),
    "multi_c": (3, 71, False, "discount", "large"), "long_ctx": (2, 71, False, "wb", "small"), "mid_o4": (4, 71, False, "wb", "large"), "mid_o4_small": (1, 71, False, "discount", "small"),
}
WORD_CARD = ("wide_vocab", 71, "small")

_SIX_SQL = f"""{DOCS}, {CODE}, {PAPERS}, texts AS (SELECT * FROM docs UNION ALL SELECT * FROM code UNION ALL SELECT * FROM papers),
px AS (SELECT vec_id // 4 AS item_id, vec_id, list_transform(embedding, lambda v: lpad(to_hex(CAST(floor((least(greatest(CAST(v AS DOUBLE), -1.0), 1.0) + 1) * 127.5) AS INTEGER)), 2, '0')) AS px FROM embeddings),
patches AS (SELECT item_id, upper(array_to_string(flatten(list(px ORDER BY vec_id)), '')) AS hx FROM px GROUP BY item_id HAVING count(*) = 4),
smp AS (SELECT CAST((year(l_shipdate) + 22 - 2017) * 12 + month(l_shipdate) - 1 AS INTEGER) AS m, l_orderkey, l_linenumber, l_partkey, CAST(floor((l_extendedprice - 0.0) / (200000.0 - 0.0) * 65535.0) - 32768 AS INTEGER) AS x FROM lineitem),
smo AS (SELECT m, (x + 65536) % 65536 AS u, row_number() OVER (PARTITION BY m ORDER BY l_orderkey, l_linenumber, l_partkey) - 1 AS i FROM smp),
series0 AS (SELECT m, i // 4096 AS item_id, upper(string_agg(lpad(to_hex(u % 256), 2, '0') || lpad(to_hex(u // 256), 2, '0'), '' ORDER BY i)) AS hx FROM smo GROUP BY ALL),
raws AS (SELECT source, item_id, m, hex(encode(body)) AS hx FROM texts UNION ALL SELECT 'gray_patches', item_id, CAST(item_id % 83 AS INTEGER), hx FROM patches UNION ALL SELECT 'sample_series', m * 100000 + item_id, m, hx FROM series0)"""


def _cards_sql(names) -> str:
    """CTEs that end in totals (source, model_id, m, micro, raw_bytes) of some cards on the six sources."""
    orders = sorted({CARDS[x][0] for x in names if x in CARDS})
    out = [_SIX_SQL]
    if orders:
        out += [tokens("raws", seq="regexp_extract_all(hx, '..')"), grams(2048, orders[-1])]
        out += [f"g{k} AS (SELECT source, m, right(ctx, {2 * k}) AS ctx, sym, CAST(sum(n) AS BIGINT) AS n FROM grams GROUP BY ALL)" for k in orders]
    each = []
    for x in names:
        if x in CARDS:
            k, until, extra, smoothing, _ = CARDS[x]
            out.append(backoff(x, k, f"m <= {until} AND source IN ('reference_articles', 'news_articles'{', ' + repr('code_files') if extra else ''})", smoothing).replace("FROM grams", f"FROM g{k}"))
            each.append(f"SELECT source, '{x}' AS model_id, m, CAST(sum(n * {MICRO_SQL}) AS BIGINT) AS micro, CAST(sum(n) AS BIGINT) AS raw_bytes FROM g{k} JOIN s_{x} USING (ctx, sym) GROUP BY source, m")
    if WORD_CARD[0] in names:
        out.append(tokens("texts", "wt", r"regexp_extract_all(body, '[\p{L}\p{N}]+|[^\p{L}\p{N}\s]|\s')"))
        out.append(f"""wg AS (SELECT source, m, ctx, sym, count(*) AS n FROM (SELECT source, m, sym, coalesce(lag(sym) OVER (PARTITION BY source, item_id ORDER BY pos), '') AS ctx FROM wt) GROUP BY ALL),
w1 AS (SELECT ctx, sym, sum(n) AS c1 FROM wg WHERE m <= {WORD_CARD[1]} AND source IN ('reference_articles', 'news_articles') GROUP BY ALL), w0 AS (SELECT sym, sum(c1) AS c0 FROM w1 GROUP BY sym), wn AS (SELECT CAST(coalesce(sum(c0), 0) AS DOUBLE) AS n0, CAST(count(*) AS DOUBLE) AS t0 FROM w0),
wo AS (SELECT ctx, sum(c1) AS n1, count(*) AS t1 FROM w1 WHERE ctx <> '' GROUP BY ctx),
wp AS (SELECT wg.*, c0, n1, t1, w1.c1, (coalesce(c0, 0) + t0 / (t0 + CAST(1.0 AS DOUBLE))) / (n0 + greatest(t0, CAST(1.0 AS DOUBLE))) AS p0 FROM wg LEFT JOIN w0 USING (sym) LEFT JOIN wo ON wo.ctx = wg.ctx LEFT JOIN w1 ON w1.ctx = wg.ctx AND w1.sym = wg.sym AND w1.ctx <> '' CROSS JOIN wn),
wq AS (SELECT *, CASE WHEN n1 IS NULL THEN p0 ELSE (coalesce(c1, 0) + t1 * p0) / (n1 + t1) END AS p FROM wp),
wr AS (SELECT source, m, CAST(sum(strlen(body)) AS BIGINT) AS raw_bytes FROM texts GROUP BY ALL)""")
        each.append(f"SELECT source, '{WORD_CARD[0]}', m, micro, raw_bytes FROM (SELECT source, m, CAST(sum(n * ({MICRO_SQL} + CASE WHEN c0 IS NULL THEN (strlen(sym) + 1) * 8000000 ELSE 0 END)) AS BIGINT) AS micro FROM wq GROUP BY source, m) JOIN wr USING (source, m)")
    out.append(f"totals AS ({' UNION ALL '.join(each)})")
    return ", ".join(out)


def _rates_sql(names) -> str:
    """``_cards_sql``, then crates: periods, gap and direction of each source and model."""
    return f"""{_cards_sql(names)}, cseries AS (SELECT *, CAST((2 * CAST(micro AS HUGEINT) + 8 * raw_bytes) // (16 * raw_bytes) AS DOUBLE) / 10000 AS rate FROM totals WHERE raw_bytes > 0),
c0 AS (SELECT source, model_id, {mean_sql('true')} AS r_all, {mean_sql('m < 72')} AS r_train, {mean_sql('m >= 72')} AS r_test FROM cseries GROUP BY source, model_id), c1 AS (SELECT *, round(r_test - r_train, 8) AS gap FROM c0),
crates AS (SELECT *, round(gap / r_train, 6) AS gap_rel, CASE WHEN gap > 0 THEN 'up' WHEN gap < 0 THEN 'down' ELSE 'flat' END AS arrow FROM c1)"""


_ALL_CARDS = [*CARDS, WORD_CARD[0]]
_CLASS = ", ".join(f"('{x}', '{c}')" for x, c in [*((x, v[4]) for x, v in CARDS.items()), (WORD_CARD[0], WORD_CARD[2])])


@query(f"""WITH {_rates_sql(_ALL_CARDS)}, cls AS (SELECT * FROM (VALUES {_CLASS}) v(model_id, size_class)), grid AS (SELECT source, model_id FROM (SELECT unnest([{', '.join(map(repr, SIX))}]) AS source) CROSS JOIN cls),
p AS (SELECT *, round(r_test + gap, 8) AS projected FROM crates JOIN cls USING (model_id) WHERE r_test IS NOT NULL), k AS (SELECT *, rank() OVER (PARTITION BY source, size_class ORDER BY projected) AS rank FROM p)
SELECT grid.source, grid.model_id, r_all, r_train, r_test, gap, gap_rel, arrow, size_class, projected, rank, CASE WHEN rank = 1 THEN 'best' WHEN rank = 2 THEN 'second' WHEN rank IS NOT NULL THEN '' END AS mark FROM grid LEFT JOIN k USING (source, model_id)""")
def temporal_report_all_cards(spark, sf_dir):
    """Fourteen cards on six sources; ``compressor_report`` has the three compressors on the same slices."""
    return temporal_report(spark, sf_dir)


@query(f"WITH {_cards_sql(('early_o2', 'late_o2'))} SELECT source, model_id, {label('m')} AS month, CAST((2 * CAST(micro AS HUGEINT) + 8 * raw_bytes) // (16 * raw_bytes) AS DOUBLE) / 10000 AS rate FROM totals WHERE raw_bytes > 0")
def monthly_rate_six(spark, sf_dir):
    """The monthly curves of two cards over all six sources, tiles and samples included."""
    cards = [c for c in model_cards(spark).collect() if c["model_id"] in ("early_o2", "late_o2")]  # two rows
    return monthly_units(report_totals(spark, sf_dir, cards)).select("source", "model_id", month_label(F.col("m")).alias("month"), "rate")


# --- rates against task scores ------------------------------------------------------------------------------------------

SMALL_BYTE_CARDS = tuple(x for x, v in CARDS.items() if v[4] == "small")


def next_byte_scores(spark, sf_dir, cards):
    """model_id, topone, dialogue: accuracy of each card's deepest context on the benchmark items and on the conversations; the
    smaller byte at ties."""
    most = max(c["order"] for c in cards)
    g = models.month_grams(text_slices(spark, sf_dir, (*TEXTS, "code_files")), most, 2048).persist()
    bench = load_table(spark, sf_dir, "benchmark").select(F.lit("topone").alias("task"), F.col("text").alias("body"))
    items = bench.unionByName(load_table(spark, sf_dir, "conversations").select(F.lit("dialogue").alias("task"), F.col("text").alias("body")))
    out = None
    for c in cards:
        d = c["order"]
        seen = g.where((F.col("m") <= _until(c)) & F.col("source").isin(*TEXTS, *c["extra_sources"]) & (F.length("ctx") >= 2 * d))
        counts = seen.groupBy(F.expr(f"right(ctx, {2 * d})").alias("ctx"), "sym").agg(F.sum("n").alias("cnt"))
        top = counts.groupBy("ctx").agg(F.max_by("sym", F.struct("cnt", (-F.conv("sym", 16, 10).cast("int")).alias("o"))).alias("best"))
        t = windows.with_context(items, byte_symbols(F.col("body")), d, ["task"]).where(F.col("pos") >= d)
        asked = t.groupBy("task", "ctx", "sym").agg(F.count(F.lit(1)).alias("k")).join(top, "ctx", "left")
        hits = lambda name: F.round(F.sum(F.when((F.col("task") == name) & (F.col("sym") == F.col("best")), F.col("k")).otherwise(0)) / F.sum(F.when(F.col("task") == name, F.col("k"))), 6).alias(name)
        got = asked.agg(hits("topone"), hits("dialogue")).select(F.lit(c["model_id"]).alias("model_id"), "topone", "dialogue")
        out = got if out is None else out.unionByName(got)
    return out


def task_table(spark, sf_dir):
    """model_id, code_rate, topone, paper_rate, dialogue of the seven small byte cards."""
    cards = [c for c in model_cards(spark).collect() if c["model_id"] in SMALL_BYTE_CARDS]  # seven rows
    r = card_rates(report_totals(spark, sf_dir, cards, ("code_files", *TEXTS, "paper_bodies")))
    wide = r.groupBy("model_id").agg(F.max(F.when(F.col("source") == "code_files", F.col("r_test"))).alias("code_rate"), F.max(F.when(F.col("source") == "paper_bodies", F.col("r_test"))).alias("paper_rate"))
    return wide.join(next_byte_scores(spark, sf_dir, cards), "model_id")


def _top_card_sql(x: str) -> str:
    d, until, extra, _, _ = CARDS[x]
    where = f"m <= {until} AND source IN ('reference_articles', 'news_articles'{', ' + repr('code_files') if extra else ''}) AND length(ctx) >= {2 * d}"
    score = lambda task: f"round(sum(CASE WHEN b.sym = best THEN 1 ELSE 0 END) FILTER (WHERE task = '{task}') / CAST(count(*) FILTER (WHERE task = '{task}') AS DOUBLE), 6) AS {task}"
    return f"""top_{x} AS (SELECT ctx, first(sym ORDER BY c DESC, sym) AS best FROM (SELECT ctx, sym, sum(n) AS c FROM g{d} WHERE {where} GROUP BY ALL) GROUP BY ctx),
hit_{x} AS (SELECT '{x}' AS model_id, {score('topone')}, {score('dialogue')} FROM (SELECT task, sym, {'p1' if d == 1 else 'p2 || p1'} AS ctx FROM bt WHERE pos >= {d}) b LEFT JOIN top_{x} t USING (ctx))"""


_TASK_TABLE = f"""{_rates_sql(SMALL_BYTE_CARDS)}, items AS (SELECT 'topone' AS task, row_number() OVER () AS k, text FROM benchmark UNION ALL SELECT 'dialogue', row_number() OVER (), text FROM conversations),
bt0 AS (SELECT task, k, unnest(h) AS sym, generate_subscripts(h, 1) - 1 AS pos FROM (SELECT task, k, regexp_extract_all(hex(encode(text)), '..') AS h FROM items)), bt AS (SELECT *, lag(sym, 1) OVER w AS p1, lag(sym, 2) OVER w AS p2 FROM bt0 WINDOW w AS (PARTITION BY task, k ORDER BY pos)),
{', '.join(_top_card_sql(x) for x in SMALL_BYTE_CARDS)}, hits AS ({' UNION ALL '.join(f'SELECT * FROM hit_{x}' for x in SMALL_BYTE_CARDS)}),
tasks AS (SELECT model_id, max(r_test) FILTER (WHERE source = 'code_files') AS code_rate, max(r_test) FILTER (WHERE source = 'paper_bodies') AS paper_rate, any_value(topone) AS topone, any_value(dialogue) AS dialogue FROM crates JOIN hits USING (model_id) GROUP BY model_id)"""


@query(f"WITH {_TASK_TABLE} SELECT model_id, code_rate, rank() OVER (ORDER BY code_rate) AS code_rank, topone, rank() OVER (ORDER BY topone DESC) AS topone_rank, paper_rate, rank() OVER (ORDER BY paper_rate) AS paper_rank, dialogue, rank() OVER (ORDER BY dialogue DESC) AS dialogue_rank FROM tasks")
def table4_ranks(spark, sf_dir):
    """Seven small models: testing rates on code and paper text beside two task scores, with ranks (1 is best)."""
    t = task_table(spark, sf_dir)
    rank = lambda *by: F.rank().over(Window.orderBy(*by)).cast("long")  # noqa: E731  seven rows
    last = lambda c: F.col(c).asc_nulls_last()
    return t.select("model_id", "code_rate", rank(last("code_rate")).alias("code_rank"), "topone", rank(F.desc("topone")).alias("topone_rank"), "paper_rate", rank(last("paper_rate")).alias("paper_rank"), "dialogue", rank(F.desc("dialogue")).alias("dialogue_rank"))


def _agree_sql(task: str, score: str, rate: str) -> str:
    ranked = f"(SELECT CAST(rank() OVER (ORDER BY {score}) AS DOUBLE) AS a, CAST(rank() OVER (ORDER BY -{rate}) AS DOUBLE) AS b FROM tasks)"
    return f"SELECT '{task}' AS task, (SELECT round(nullif(corr(a, b), CAST('NaN' AS DOUBLE)), 6) FROM {ranked}) AS spearman, (SELECT round(nullif(corr({score}, -{rate}), CAST('NaN' AS DOUBLE)), 6) FROM tasks) AS pearson, (SELECT round(avg(sign((p.{score} - q.{score}) * (q.{rate} - p.{rate}))), 6) FROM tasks p JOIN tasks q ON p.model_id < q.model_id) AS kendall"


@query(f"WITH {_TASK_TABLE} {_agree_sql('next_byte_and_code', 'topone', 'code_rate')} UNION ALL {_agree_sql('dialogue_and_papers', 'dialogue', 'paper_rate')}")
def table4_agreement(spark, sf_dir):
    """Do the rates rank the models as the task scores do? Spearman, Pearson and Kendall of scores with negated rates."""
    t = task_table(spark, sf_dir).withColumn("code", -F.col("code_rate")).withColumn("paper", -F.col("paper_rate")).persist()  # seven rows
    one = lambda a, b, name: metrics.rank_agreement(t, a, b).withColumn("task", F.lit(name))
    return one("topone", "code", "next_byte_and_code").unionByName(one("dialogue", "paper", "dialogue_and_papers"))


def flagship(spark, sf_dir):
    return temporal_report(spark, sf_dir, ("early_o2", "late_o2"), ("reference_articles", "news_articles"))


# --- the report's arithmetic on flat codes -----------------------------------------------------------------------------

#: Prefix codes without a law: a flag, then so many bits for a byte of the class, eight for any other one.
FLAT = {"flat_lower": ("[a-z ]", 5), "flat_letters": ("[A-Za-z ]", 6), "flat_words": ("[A-Za-z0-9 ]", 6), "flat_ascii": ("[ -~]", 7)}


def flat_bits(name: str, text: str):
    """Bits of a text under a flat code; the classes are of one-byte characters."""
    own = F.length(F.regexp_replace(text, FLAT[name][0].replace("[", "[^", 1) + "+", ""))  # the other ones are few and go in runs
    return (9 * F.octet_length(text) - (8 - FLAT[name][1]) * own).cast("long")


def _flat_sql(name: str, text: str) -> str:
    return f"(9 * strlen({text}) - {8 - FLAT[name][1]} * (length({text}) - length(regexp_replace({text}, '{FLAT[name][0]}', '', 'g'))))"


_FLAT_TOTALS = " UNION ALL ".join(f"SELECT source, '{x}' AS model_id, m, CAST(sum({_flat_sql(x, 'body')}) * 1000000 AS BIGINT) AS micro, CAST(sum(strlen(body)) AS BIGINT) AS raw_bytes FROM docs GROUP BY source, m" for x in FLAT)


@query(f"""WITH {DOCS}, totals AS ({_FLAT_TOTALS}), s AS (SELECT *, CAST((2 * CAST(micro AS HUGEINT) + 8 * raw_bytes) // (16 * raw_bytes) AS DOUBLE) / 10000 AS rate FROM totals WHERE raw_bytes > 0),
p AS (SELECT source, model_id, {mean_sql('true')} AS r_all, {mean_sql('m < 72')} AS r_train, {mean_sql('m >= 72')} AS r_test FROM s GROUP BY source, model_id), v AS (SELECT *, round(r_test - r_train, 8) AS gap FROM p)
SELECT source, model_id, round(r_test + gap, 4) AS projected, rank() OVER (PARTITION BY source ORDER BY round(r_test + gap, 4)) AS rank, abs(round(r_test - gap * 72 / 83 - r_all, 2)) AS mean_identity FROM v""")
def printed_table_checks(spark, sf_dir):
    """The report's formulas on the flat codes' rates of the documents: projections, ranks, and the identity that ties mean, test rate
    and gap together (zero where no month is empty)."""
    d = documents_slices(spark, sf_dir)
    sums = d.groupBy("source", "m").agg(*[(F.sum(flat_bits(x, "body")) * MICRO).alias(x) for x in FLAT], F.sum(F.octet_length("body").cast("long")).alias("raw_bytes"))
    r = card_rates(sums.unpivot(["source", "m", "raw_bytes"], list(FLAT), "model_id", "micro"))
    p = F.round(F.col("r_test") + F.col("gap"), 4)
    rank = F.rank().over(Window.partitionBy("source").orderBy(p.asc_nulls_last())).cast("long")  # four rows a source
    return r.select("source", "model_id", p.alias("projected"), rank.alias("rank"), F.abs(F.round(F.col("r_test") - F.col("gap") * 72 / 83 - F.col("r_all"), 2)).alias("mean_identity"))


_UNITS = "CAST((2 * CAST({x} AS HUGEINT) * 1000000 + 8 * raw) // (16 * raw) AS DOUBLE) / 10000"


@query(f"""WITH d AS (SELECT source AS model_id, sum({_flat_sql('flat_lower', 'text')}) AS a, sum({_flat_sql('flat_letters', 'text')}) AS b, CAST(sum(strlen(text)) AS BIGINT) AS raw FROM documents GROUP BY source),
l AS (SELECT source AS model_id, avg(quality) AS quality, avg(toxic) AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY source),
tasks AS (SELECT model_id, quality, toxic, {_UNITS.format(x='a')} AS lower_rate, {_UNITS.format(x='b')} AS letters_rate FROM d JOIN l USING (model_id) WHERE raw > 0)
{_agree_sql('quality', 'quality', 'lower_rate')} UNION ALL {_agree_sql('toxic', 'toxic', 'letters_rate')}""")
def printed_rank_agreement(spark, sf_dir):
    """Agreement of the documents' origins' label shares with their (negated) rates under two flat codes."""
    d = load_table(spark, sf_dir, "documents")
    sums = d.groupBy(F.col("source").alias("model_id")).agg(F.sum(flat_bits("flat_lower", "text")).alias("a"), F.sum(flat_bits("flat_letters", "text")).alias("b"), F.sum(F.octet_length("text").cast("long")).alias("raw_bytes")).where("raw_bytes > 0")
    rate = lambda c: -(F.expr(f"(2 * cast({c} as decimal(38,0)) * {MICRO} + 8 * raw_bytes) div (16 * raw_bytes)").cast("double") / 10000)
    shares = d.select("doc_id", F.col("source").alias("model_id")).join(load_table(spark, sf_dir, "labels"), "doc_id").groupBy("model_id").agg(F.avg("quality").alias("quality"), F.avg("toxic").alias("toxic"))
    v = sums.join(shares, "model_id").select("model_id", "quality", "toxic", rate("a").alias("lower"), rate("b").alias("letters")).persist()  # a row an origin
    one = lambda a, b: metrics.rank_agreement(v, a, b).withColumn("task", F.lit(a))
    return one("quality", "lower").unionByName(one("toxic", "letters"))
