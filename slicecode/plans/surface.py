"""Surrounding operators: joins, margins, functions, streams; each in the place the method needs it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from slicecode.functions.exprs import bits, char_symbols, micro_bits, month_index, month_label, rate
from slicecode.operators import metrics, models, pyops
from slicecode.plans.base import DOCS, RATES, SIZES, label, query
from slicecode.plans.shared import rate_series
from slicecode.sources.tables import documents_slices, load_table, slice_sizes
from slicecode.streaming import streams

_YEARLY = f"WITH {SIZES}, y AS (SELECT source, CAST(2017 + m // 12 AS INTEGER) AS year, CASE WHEN m < 72 THEN 'train' ELSE 'test' END AS period, raw_bytes FROM sizes)"


def _yearly(spark, sf_dir):
    s = metrics.split_common(slice_sizes(spark, sf_dir))
    return s.select("source", (2017 + F.floor(F.col("m") / 12)).cast("int").alias("year"), "period", "raw_bytes")


_AGG = "count(*) AS docs, CAST(sum(raw_bytes) AS BIGINT) AS bytes"


def _agg(g):
    return g.agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("docs"), F.sum("raw_bytes").alias("bytes"))


@query(f"{_YEARLY} SELECT source, year, CAST(grouping(source, year) AS BIGINT) AS gid, {_AGG} FROM y GROUP BY ROLLUP (source, year)")
def rollup_sizes(spark, sf_dir):
    return _agg(_yearly(spark, sf_dir).rollup("source", "year"))


@query(f"{_YEARLY} SELECT source, period, CAST(grouping(source, period) AS BIGINT) AS gid, {_AGG} FROM y GROUP BY CUBE (source, period)")
def cube_sizes(spark, sf_dir):
    return _agg(_yearly(spark, sf_dir).cube("source", "period"))


@query(f"{_YEARLY} SELECT source, year, period, CAST(grouping(source, year, period) AS BIGINT) AS gid, {_AGG} FROM y GROUP BY GROUPING SETS ((source, period), (year), ())")
def grouping_sets_sizes(spark, sf_dir):
    y = _yearly(spark, sf_dir)
    return _agg(y.groupingSets([("source", "period"), ("year",), ()], "source", "year", "period"))


@query(f"""WITH v AS (SELECT source || '/' || lang AS k, CAST(doc_id % 83 AS INTEGER) AS m, max(doc_id) AS doc_id FROM documents GROUP BY ALL), q AS (SELECT DISTINCT k, CAST(g.m AS INTEGER) AS m FROM v CROSS JOIN (SELECT unnest([11, 23, 35, 47, 59, 71, 82]) AS m) g)
SELECT q.k AS article_key, {label('q.m')} AS month, (SELECT max_by(doc_id, v.m) FROM v WHERE v.k = q.k AND v.m <= q.m) AS doc_id FROM q""")
def asof_version(spark, sf_dir):
    """The version of each article in force at the end of each year: an as-of join as a union of both sides and one ordered window."""
    v = load_table(spark, sf_dir, "documents").groupBy(F.concat_ws("/", "source", "lang").alias("k"), month_index(F.col("doc_id")).alias("m")).agg(F.max("doc_id").alias("doc_id"))
    ends = spark.createDataFrame([(x,) for x in (11, 23, 35, 47, 59, 71, 82)], "m int")
    q = v.select("k").distinct().crossJoin(F.broadcast(ends)).select("k", "m", F.lit(None).cast("long").alias("doc_id"), F.lit(1).alias("side"))
    both = v.withColumn("side", F.lit(0)).unionByName(q)
    w = Window.partitionBy("k").orderBy("m", "side").rowsBetween(Window.unboundedPreceding, 0)
    got = both.withColumn("found", F.last("doc_id", ignorenulls=True).over(w)).where("side = 1")
    return got.select(F.col("k").alias("article_key"), month_label(F.col("m")).alias("month"), F.col("found").alias("doc_id"))


@query("""WITH s AS (SELECT CAST(k AS INTEGER) AS slice, TIMESTAMP '2024-01-01' + to_days(CAST(k * 5 AS INTEGER)) AS lo, TIMESTAMP '2024-01-01' + to_days(CAST(k * 5 + 5 AS INTEGER)) AS hi FROM (SELECT unnest(range(7)) AS k))
SELECT slice, event_type, count(*) AS events FROM events JOIN s ON ts >= lo AND ts < hi GROUP BY ALL""")
def interval_events(spark, sf_dir):
    """Events in slices of five days: an interval join with a handful of slices."""
    s = spark.range(7).select(F.col("id").cast("int").alias("slice"), F.expr("timestamp_ntz'2024-01-01' + make_dt_interval(cast(id * 5 as int))").alias("lo"), F.expr("timestamp_ntz'2024-01-01' + make_dt_interval(cast(id * 5 + 5 as int))").alias("hi"))
    e = load_table(spark, sf_dir, "events").select("ts", "event_type")
    return e.join(F.broadcast(s), (F.col("ts") >= F.col("lo")) & (F.col("ts") < F.col("hi"))).groupBy("slice", "event_type").agg(F.count(F.lit(1)).alias("events"))


@query(r"""WITH v AS (SELECT CASE WHEN doc_id % 83 < 72 THEN 'train' ELSE 'test' END AS period, unnest(string_split(text, chr(10))) AS line FROM documents), a AS (SELECT line, count(*) AS n FROM v WHERE period = 'train' GROUP BY line), b AS (SELECT line, count(*) AS n FROM v WHERE period = 'test' GROUP BY line)
SELECT CASE WHEN a.line IS NULL THEN 'test_only' WHEN b.line IS NULL THEN 'train_only' ELSE 'both' END AS side, count(*) AS lines, CAST(sum(coalesce(a.n, 0)) AS BIGINT) AS train_rows, CAST(sum(coalesce(b.n, 0)) AS BIGINT) AS test_rows FROM a FULL JOIN b ON a.line = b.line GROUP BY 1""")
def fullouter_lines(spark, sf_dir):
    """Lines of the training and testing months: shared, or on one side only."""
    v = load_table(spark, sf_dir, "documents").select((month_index(F.col("doc_id")) < 72).alias("train"), F.explode(F.split("text", "\n")).alias("line"))
    a = v.where("train").groupBy("line").agg(F.count(F.lit(1)).alias("a"))
    b = v.where("not train").groupBy("line").agg(F.count(F.lit(1)).alias("b"))
    j = a.join(b, "line", "full_outer")
    side = F.when(F.col("a").isNull(), "test_only").when(F.col("b").isNull(), "train_only").otherwise("both")
    return j.groupBy(side.alias("side")).agg(F.count(F.lit(1)).alias("lines"), F.sum(F.coalesce("a", F.lit(0))).alias("train_rows"), F.sum(F.coalesce("b", F.lit(0))).alias("test_rows"))


@query("""SELECT r_name, CAST(year(o_orderdate) + 22 AS INTEGER) AS year, count(*) AS orders, CAST(sum(strlen(concat_ws('|', CAST(o_orderkey AS VARCHAR), CAST(o_custkey AS VARCHAR), o_orderstatus, o_orderpriority))) AS BIGINT) AS bytes
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL""")
def star_region_rates(spark, sf_dir):
    """Bytes of the order log by region and year: a star join, the small dimensions broadcast by the planner."""
    t = lambda n: load_table(spark, sf_dir, n)
    size = F.octet_length(F.concat_ws("|", F.col("o_orderkey").cast("string"), F.col("o_custkey").cast("string"), "o_orderstatus", "o_orderpriority"))
    o = t("orders").select("o_custkey", (F.year("o_orderdate") + 22).alias("year"), size.cast("long").alias("b"))
    j = o.join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation").select("n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region").select("r_regionkey", "r_name"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name", "year").agg(F.count(F.lit(1)).alias("orders"), F.sum("b").alias("bytes"))


@query("SELECT event_type, CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS events, round(sum(value), 2) AS total FROM events GROUP BY ALL")
def json_props(spark, sf_dir):
    e = load_table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int")["k"].alias("k"), "value")
    return e.groupBy("event_type", "k").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("value"), 2).alias("total"))


@query(r"SELECT regexp_extract(url, '^([a-z]+)://', 1) AS protocol, regexp_extract(url, '://([^/?#]+)', 1) AS host, count(*) AS pages, count(*) FILTER (WHERE url LIKE '%?%') AS with_query FROM pages GROUP BY ALL")
def url_keys(spark, sf_dir):
    p = load_table(spark, sf_dir, "pages").select(F.parse_url("url", F.lit("PROTOCOL")).alias("protocol"), F.parse_url("url", F.lit("HOST")).alias("host"), F.col("url").contains("?").alias("q"))
    return p.groupBy("protocol", "host").agg(F.count(F.lit(1)).alias("pages"), F.count_if("q").alias("with_query"))


@query("SELECT source, CAST(sum(bit_count(doc_id)) AS BIGINT) AS ones, CAST(bit_xor(doc_id) AS BIGINT) AS folded, CAST(sum(doc_id & 255) AS BIGINT) AS low, CAST(sum(doc_id >> 3) AS BIGINT) AS shifted FROM documents GROUP BY source")
def bit_ops(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").select("source", "doc_id")
    return d.groupBy("source").agg(F.sum(F.bit_count("doc_id")).cast("long").alias("ones"), F.bit_xor("doc_id").alias("folded"), F.sum(F.col("doc_id").bitwiseAND(F.lit(255))).alias("low"), F.sum(F.shiftright("doc_id", 3)).alias("shifted"))


@query(f"WITH {DOCS}, s AS (SELECT source, m, strlen(body) AS b FROM docs) SELECT source, count(*) AS docs, round(median(b), 4) AS median_bytes, round(quantile_cont(b, 0.9), 4) AS p90, round(stddev_samp(b), 4) AS deviation, CAST(max_by(m, b * 100 + m) AS INTEGER) AS month_of_longest FROM s GROUP BY source")
def size_statistics(spark, sf_dir):
    s = load_table(spark, sf_dir, "documents").select(F.when(F.regexp_extract("source", r"(\d+)$", 1).cast("int") < 10, "reference_articles").otherwise("news_articles").alias("source"), month_index(F.col("doc_id")).alias("m"), F.octet_length("text").cast("long").alias("b"))
    return s.groupBy("source").agg(F.count(F.lit(1)).alias("docs"), F.round(F.median("b"), 4).alias("median_bytes"), F.round(F.percentile("b", 0.9), 4).alias("p90"), F.round(F.stddev_samp("b"), 4).alias("deviation"), F.max_by("m", F.col("b") * 100 + F.col("m")).alias("month_of_longest"))


@query(None)
def vocabulary_sketches(spark, sf_dir):
    """Vocabulary size exact, by HyperLogLog, and as a mergeable sketch: what replaces the exact count at 100 TB."""
    from slicecode.functions.exprs import word_symbols

    w = load_table(spark, sf_dir, "documents").select("lang", F.explode(word_symbols(F.col("text"))).alias("w"))
    sketch = w.groupBy("lang").agg(F.count_distinct("w").alias("exact"), F.approx_count_distinct("w", 0.01).alias("approximate"), F.hll_sketch_agg("w", 14).alias("s"))
    return sketch.select("lang", "exact", "approximate", F.hll_sketch_estimate("s").alias("from_sketch"))


@query(f"WITH {DOCS}, w AS (SELECT source, avg(strlen(body)) FILTER (WHERE m < 72) AS train, avg(strlen(body)) FILTER (WHERE m >= 72) AS test FROM docs GROUP BY source) SELECT source, 'train' AS period, round(train, 4) AS mean_bytes FROM w UNION ALL SELECT source, 'test', round(test, 4) FROM w")
def unpivot_periods(spark, sf_dir):
    s = slice_sizes(spark, sf_dir).where(F.col("source").isin("reference_articles", "news_articles"))
    wide = s.groupBy("source").agg(F.round(F.avg(F.when(F.col("m") < 72, F.col("raw_bytes"))), 4).alias("train"), F.round(F.avg(F.when(F.col("m") >= 72, F.col("raw_bytes"))), 4).alias("test"))
    return wide.unpivot("source", ["train", "test"], "period", "mean_bytes")


@query("SELECT o_orderpriority AS priority, count(*) AS orders, CAST(min((year(o_orderdate) + 22 - 2017) * 12 + month(o_orderdate) - 1) AS INTEGER) AS first_month, CAST(max((year(o_orderdate) + 22 - 2017) * 12 + month(o_orderdate) - 1) AS INTEGER) AS last_month FROM orders WHERE o_orderdate >= DATE '1996-01-01' AND o_totalprice > (SELECT avg(o_totalprice) FROM orders) GROUP BY 1")
def sql_surface(spark, sf_dir):
    """The same engine through SQL: a view, a parameter, a scalar subquery, a temporary function of ours."""
    load_table(spark, sf_dir, "orders").createOrReplaceTempView("orders_view")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION slice_month(d TIMESTAMP_NTZ) RETURNS INT RETURN (year(d) + 22 - 2017) * 12 + month(d) - 1")
    return spark.sql("SELECT o_orderpriority AS priority, count(*) AS orders, min(slice_month(o_orderdate)) AS first_month, max(slice_month(o_orderdate)) AS last_month FROM orders_view WHERE o_orderdate >= :since AND o_totalprice > (SELECT avg(o_totalprice) FROM orders_view) GROUP BY o_orderpriority", args={"since": "1996-01-01"})


# --- streams -------------------------------------------------------------------------------------------------------


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS events, round(sum(value), 2) AS total FROM events GROUP BY ALL")
def stream_daily_rate(spark, sf_dir):
    out = streams.run_now(streams.daily(streams.event_stream(spark, sf_dir)), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "events", "total")


@query("SELECT strftime(date_trunc('hour', ts) - to_hours(CAST(k AS INTEGER)), '%Y-%m-%d %H') AS start, count(*) AS events FROM events CROSS JOIN (SELECT unnest(range(6)) AS k) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    out = streams.run_now(streams.sliding(streams.event_stream(spark, sf_dir)), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("start"), "events")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT user_id, ts, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events FROM n GROUP BY user_id, k""")
def stream_session(spark, sf_dir):
    out = streams.all_sessions(streams.event_stream(spark, sf_dir))
    return out.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "events")


@query("""WITH r AS (SELECT user_id, row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) - 1 AS c, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS m FROM events)
SELECT user_id, count(*) AS events, CAST(sum(CAST(round(-log2((c + 0.5) / (m + 2.5)) * 1000000) AS BIGINT)) AS BIGINT) AS micro FROM r GROUP BY user_id""")
def stream_state_bits(spark, sf_dir):
    """An adaptive law per user in keyed state, over the events as a stream."""
    return streams.keyed_totals(streams.event_stream(spark, sf_dir))


@query("""WITH a AS (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)), b AS (SELECT * FROM events WHERE event_type = (SELECT max(event_type) FROM events))
SELECT a.user_id, a.event_id AS first_id, b.event_id AS second_id FROM a JOIN b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""")
def stream_interval_join(spark, sf_dir):
    kinds = load_table(spark, sf_dir, "events").agg(F.min("event_type").alias("a"), F.max("event_type").alias("b")).first()
    return streams.run_now(streams.view_then_buy(streams.event_stream(spark, sf_dir), kinds["a"], kinds["b"]), "append")


# --- further operators in their places -----------------------------------------------------------------------------------


@query(f"WITH {RATES} SELECT source, year, CAST(grouping(source, year) AS BIGINT) AS gid, round(100.0 * sum(micro) / 1000000 / (8.0 * sum(raw_bytes)), 4) AS rate FROM (SELECT source, CAST(2017 + m // 12 AS INTEGER) AS year, micro, raw_bytes FROM series WHERE model_id = 'late_o2') GROUP BY ROLLUP (source, year)")
def rollup_rates(spark, sf_dir):
    """Pooled rates by source and year with their margins."""
    s = rate_series(spark, sf_dir, ("late_o2",)).where("model_id = 'late_o2'").select("source", (2017 + F.floor(F.col("m") / 12)).cast("int").alias("year"), "micro", "raw_bytes")
    return s.rollup("source", "year").agg(F.grouping_id().alias("gid"), rate(F.sum("micro"), F.sum("raw_bytes")).alias("rate"))


@query(f"WITH {RATES} SELECT source, model_id, CAST(grouping(source, model_id) AS BIGINT) AS gid, round(100.0 * sum(micro) / 1000000 / (8.0 * sum(raw_bytes)), 4) AS rate FROM series GROUP BY CUBE (source, model_id)")
def cube_rates(spark, sf_dir):
    return rate_series(spark, sf_dir).cube("source", "model_id").agg(F.grouping_id().alias("gid"), rate(F.sum("micro"), F.sum("raw_bytes")).alias("rate"))


_CHARS = "SELECT lang, unnest(string_split(lower(text), '')) AS c FROM documents"


@query(f"""WITH t AS (SELECT lang, c, count(*) AS n FROM ({_CHARS}) WHERE c <> '' GROUP BY ALL) SELECT lang, CAST(count(*) AS INTEGER) AS letters, CAST(sum(n) AS BIGINT) AS total, CAST(coalesce(max(n) FILTER (WHERE c = 'e'), 0) AS BIGINT) AS e,
CAST(count(*) FILTER (WHERE n >= 1000) AS INTEGER) AS often, CAST(max(ascii(c)) AS INTEGER) AS highest FROM t GROUP BY lang""")
def vocabulary_maps(spark, sf_dir):
    """Each language's characters as a map from character to count: an alphabet is small enough to be one value."""
    t = load_table(spark, sf_dir, "documents").select("lang", F.explode(char_symbols(F.lower("text"))).alias("c")).groupBy("lang", "c").agg(F.count(F.lit(1)).alias("n"))
    m = t.groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("c", "n"))).alias("m"))
    often = F.map_filter("m", lambda _, n: n >= 1000)
    codes = F.map_values(F.transform_values("m", lambda c, _: F.ascii(c)))
    return m.select("lang", F.size("m").alias("letters"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, n: a + n).alias("total"), F.coalesce(F.element_at("m", F.lit("e")), F.lit(0)).alias("e"), F.size(F.map_keys(often)).alias("often"), F.array_max(codes).alias("highest"))


@query(f"""WITH {DOCS}, w AS (SELECT m, unnest(regexp_extract_all(lower(body), '[a-z]+')) AS w FROM docs), te AS (SELECT w FROM w WHERE m >= 72), tr AS (SELECT w FROM w WHERE m < 72)
SELECT 'intersect_all' AS kind, count(*) AS words FROM (SELECT w FROM te INTERSECT ALL SELECT w FROM tr) UNION ALL SELECT 'except_all', count(*) FROM (SELECT w FROM te EXCEPT ALL SELECT w FROM tr)""")
def multiset_words(spark, sf_dir):
    """Testing words that the training months hold as often, and those beyond."""
    w = documents_slices(spark, sf_dir).select("m", F.explode(F.regexp_extract_all(F.lower("body"), F.lit("[a-z]+"), F.lit(0))).alias("w"))
    te, tr = w.where("m >= 72").select("w"), w.where("m < 72").select("w")
    one = lambda df, k: df.agg(F.count(F.lit(1)).alias("words")).select(F.lit(k).alias("kind"), "words")
    return one(te.intersectAll(tr), "intersect_all").unionByName(one(te.exceptAll(tr), "except_all"))


@query(f"""WITH l AS (SELECT source, lang, doc_id, row_number() OVER (PARTITION BY source, lang ORDER BY strlen(text) DESC, doc_id DESC) AS r FROM documents WHERE text IS NOT NULL AND doc_id IN (SELECT doc_id FROM labels)),
c AS (SELECT k.source || '/' || k.lang AS model_id, {label('doc_id % 83')} AS cutoff FROM (SELECT DISTINCT source, lang FROM documents) k LEFT JOIN l ON l.source = k.source AND l.lang = k.lang AND r = 1)
SELECT a.model_id, b.model_id AS other, a.cutoff FROM c a JOIN c b ON a.cutoff IS NOT DISTINCT FROM b.cutoff AND a.model_id < b.model_id""")
def same_cutoff_pairs(spark, sf_dir):
    """Origins that may be compared month by month: the same cutoff, or unknown in both. An origin's (source and language) cutoff is
    the month of its longest labelled document."""
    d = load_table(spark, sf_dir, "documents").select(F.concat_ws("/", "source", "lang").alias("model_id"), "source", "lang", "doc_id", F.octet_length("text").alias("size"))
    d = d.where("source is not null and lang is not null")
    labelled = load_table(spark, sf_dir, "labels").select("doc_id").distinct()
    last = d.where("size is not null").join(labelled, "doc_id", "left_semi").groupBy("model_id").agg(F.max(F.struct("size", "doc_id"))["doc_id"].alias("doc_id"))
    c = d.select("model_id").distinct().join(last, "model_id", "left").select("model_id", month_label(month_index(F.col("doc_id"))).alias("cutoff"))
    o = c.select(F.col("model_id").alias("other"), F.col("cutoff").alias("its"))
    return c.join(o, F.col("cutoff").eqNullSafe(F.col("its")) & (F.col("model_id") < F.col("other"))).select("model_id", "other", "cutoff")


@query("""WITH t AS (SELECT c_mktsegment AS k, count(*) AS n FROM customer GROUP BY 1), j AS (SELECT count(*) AS rows, CAST(sum(n) AS BIGINT) AS total FROM customer JOIN t ON k = c_mktsegment) SELECT unnest(['broadcast', 'merge', 'shuffle_hash']) AS strategy, rows, total FROM j""")
def hinted_joins(spark, sf_dir):
    """One lookup under three strategies: the same rows."""
    c = load_table(spark, sf_dir, "customer")
    t = c.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    one = lambda h: c.join(t.hint(h), "c_mktsegment").agg(F.lit(h).alias("strategy"), F.count(F.lit(1)).alias("rows"), F.sum("n").alias("total"))
    return one("broadcast").unionByName(one("merge")).unionByName(one("shuffle_hash"))


@query(f"""WITH {DOCS}, t AS (SELECT m, unnest(string_split(body, '')) AS c FROM docs), s AS (SELECT c, count(*) AS n FROM t WHERE c <> '' AND m < 72 GROUP BY c), ids AS (SELECT c, n, sum(n) OVER () AS n_all FROM s WHERE ascii(c) < 128),
q AS (SELECT c, count(*) AS k FROM t WHERE c <> '' AND m >= 72 GROUP BY c) SELECT count(*) AS symbols, CAST(sum(k) AS BIGINT) AS scored, round(CAST(sum(k * CAST(round(-log2(CAST(n AS DOUBLE) / n_all) * 1000000) AS BIGINT)) AS DOUBLE) / 1000000, 3) AS bits FROM q JOIN ids USING (c)""")
def restricted_law(spark, sf_dir):
    """A law over all characters, kept to the one-byte ones and scaled to sum to one there, on the testing months."""
    t = documents_slices(spark, sf_dir).select("m", F.explode(char_symbols(F.col("body"))).alias("sym"))
    n = t.where("m < 72").groupBy("sym").agg(F.count(F.lit(1)).alias("p")).select(F.lit("").alias("ctx"), "sym", F.col("p").cast("double").alias("p"))
    law = models.restrict(n, n.where(F.ascii("sym") < 128).select("sym"))
    q = t.where("m >= 72").groupBy("sym").agg(F.count(F.lit(1)).alias("k"))
    return q.join(law, "sym").agg(F.count(F.lit(1)).alias("symbols"), F.sum("k").alias("scored"), bits(F.sum(F.col("k") * micro_bits(F.col("p")))).alias("bits"))


_AUC_LANG = "sum(r) FILTER (WHERE y = 1) - CAST(count(*) FILTER (WHERE y = 1) AS DOUBLE) * (count(*) FILTER (WHERE y = 1) + 1) / 2"


@query(f"""WITH j AS (SELECT d.lang, l.quality AS y, length(d.text) AS s FROM documents d JOIN labels l USING (doc_id)), k AS (SELECT *, rank() OVER (PARTITION BY lang ORDER BY s) + (count(*) OVER (PARTITION BY lang, s) - 1) / CAST(2 AS DOUBLE) AS r FROM j)
SELECT lang, round(({_AUC_LANG}) / (count(*) FILTER (WHERE y = 1) * count(*) FILTER (WHERE y = 0)), 6) AS score FROM k GROUP BY lang HAVING count(*) FILTER (WHERE y = 1) > 0 AND count(*) FILTER (WHERE y = 0) > 0""")
def length_auc(spark, sf_dir):
    """How well length alone tells quality, by language: a grouped aggregate in pandas, on the labelled documents."""
    d = load_table(spark, sf_dir, "documents").select("doc_id", "lang", F.length("text").cast("double").alias("s"))
    j = d.join(load_table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    return j.groupBy("lang").agg(F.round(pyops.auc("s", "quality"), 6).alias("score")).where(F.col("score").isNotNull() & ~F.isnan("score"))
