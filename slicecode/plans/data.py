"""Corpus, calendar, periods and preparation."""

from __future__ import annotations

from pyspark.sql import functions as F

from slicecode.functions.exprs import MONTHS, month_index, month_label, month_of_date
from slicecode.operators import curate, metrics
from slicecode.plans.base import BODY, DOCS, SIZES, label, query
from slicecode.sources.tables import SAMPLE_ORDER, article_source, load_table, main_body, model_cards, price_samples, slice_sizes


@query(f"WITH {SIZES} SELECT source, count(DISTINCT m) AS months, round(count(*) / count(DISTINCT m), 4) AS docs_per_month, round(sum(raw_bytes) / count(DISTINCT m), 4) AS bytes_per_month, CAST(sum(raw_bytes) AS BIGINT) AS total_bytes FROM sizes GROUP BY source")
def corpus_statistics(spark, sf_dir):
    months = F.count_distinct("m")
    return slice_sizes(spark, sf_dir).groupBy("source").agg(months.alias("months"), F.round(F.count(F.lit(1)) / months, 4).alias("docs_per_month"), F.round(F.sum("raw_bytes") / months, 4).alias("bytes_per_month"), F.sum("raw_bytes").alias("total_bytes"))


@query(f"WITH {DOCS} SELECT source, CAST(2017 + m // 12 AS BIGINT) AS year, round(avg(length(body)), 4) AS mean_chars FROM docs GROUP BY ALL")
def yearly_length_growth(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").select(article_source().alias("source"), (2017 + F.floor(month_index(F.col("doc_id")) / 12)).alias("year"), F.length("text").alias("n"))
    return d.groupBy("source", "year").agg(F.round(F.avg("n"), 4).alias("mean_chars"))


@query(f"WITH {SIZES}, grid AS (SELECT s.source, CAST(g.m AS INTEGER) AS m FROM (SELECT DISTINCT source FROM sizes) s CROSS JOIN (SELECT unnest(range(83)) AS m) g) SELECT g.source, {label('g.m')} AS month, count(s.item_id) AS docs, CAST(coalesce(sum(s.raw_bytes), 0) AS BIGINT) AS bytes FROM grid g LEFT JOIN sizes s ON g.source = s.source AND g.m = s.m GROUP BY ALL")
def monthly_calendar(spark, sf_dir):
    """Every source on every month, months without documents as zero: a cross join of a few sources with 83 months."""
    s = slice_sizes(spark, sf_dir).groupBy("source", "m").agg(F.count(F.lit(1)).alias("docs"), F.sum("raw_bytes").alias("bytes"))
    grid = s.select("source").distinct().crossJoin(spark.range(MONTHS).select(F.col("id").cast("int").alias("m")))
    zero = F.lit(0).cast("long")
    return grid.join(s, ["source", "m"], "left").select("source", month_label(F.col("m")).alias("month"), F.coalesce("docs", zero).alias("docs"), F.coalesce("bytes", zero).alias("bytes"))


@query(f"WITH {SIZES} SELECT source, CASE WHEN m < 72 THEN 'train' ELSE 'test' END AS period, count(DISTINCT m) AS months, count(*) AS docs, CAST(sum(raw_bytes) AS BIGINT) AS bytes FROM sizes GROUP BY ALL")
def period_split_common(spark, sf_dir):
    s = metrics.split_common(slice_sizes(spark, sf_dir))
    return s.groupBy("source", "period").agg(F.count_distinct("m").alias("months"), F.count(F.lit(1)).alias("docs"), F.sum("raw_bytes").alias("bytes"))


_CARDS = "cards AS (SELECT * FROM (VALUES ('early_o2', 47), ('early_o3', 47), ('early_o5', 47), ('late_o2', 68), ('late_o3', 68), ('late_o5', 68), ('late_o2_code', 68), ('wide_vocab', 71), ('multi_a', 71), ('multi_b', 71), ('multi_c', 71), ('long_ctx', 71), ('mid_o4', 71), ('mid_o4_small', 71)) v(model_id, last_train))"


@query(f"WITH {DOCS}, {_CARDS} SELECT model_id, CASE WHEN m <= last_train THEN 'train' ELSE 'test' END AS period, count(DISTINCT m) AS months, count(*) AS docs FROM docs CROSS JOIN cards GROUP BY ALL")
def period_split_per_cutoff(spark, sf_dir):
    """Months are counted first, so the range join meets 83 rows, not the documents."""
    per_month = load_table(spark, sf_dir, "documents").groupBy(month_index(F.col("doc_id")).alias("m")).agg(F.count(F.lit(1)).alias("n"))
    s = metrics.split_by_cutoff(per_month, model_cards(spark))
    return s.groupBy("model_id", "period").agg(F.count_distinct("m").alias("months"), F.sum("n").alias("docs"))


@query(f"""WITH v AS (SELECT source || '/' || lang AS article_key, CAST(doc_id % 83 AS INTEGER) AS m, doc_id FROM documents), last AS (SELECT article_key, m, max(doc_id) AS doc_id FROM v GROUP BY ALL),
grid AS (SELECT article_key, unnest(range(lo, 83)) AS m FROM (SELECT article_key, min(m) AS lo FROM last GROUP BY article_key)),
j AS (SELECT g.article_key, g.m, l.doc_id FROM grid g LEFT JOIN last l ON g.article_key = l.article_key AND g.m = l.m)
SELECT article_key, {label('m')} AS month, last_value(doc_id IGNORE NULLS) OVER (PARTITION BY article_key ORDER BY m ROWS UNBOUNDED PRECEDING) AS doc_id, doc_id IS NULL AS carried FROM j""")
def monthly_snapshot(spark, sf_dir):
    v = load_table(spark, sf_dir, "documents").select(F.concat_ws("/", "source", "lang").alias("article_key"), month_index(F.col("doc_id")).alias("m"), F.col("doc_id").alias("item_id"))
    s = curate.monthly_snapshot(v, ["article_key"])
    return s.select("article_key", month_label(F.col("m")).alias("month"), F.col("item_id").alias("doc_id"), "carried")


@query(r"""WITH v AS (SELECT page_id, CAST(page_id % 83 AS INTEGER) AS m, regexp_extract(url, '://([^/]+)/([a-z]+)/', 1) || '/' || regexp_extract(url, '://([^/]+)/([a-z]+)/', 2) AS file_key, string_split(regexp_replace(html, '(</?[a-z0-9]+)', chr(10) || '\1', 'g'), chr(10)) AS l FROM pages),
p AS (SELECT file_key, m, page_id, lag(page_id) OVER (PARTITION BY file_key ORDER BY m, page_id) AS prev FROM v), c AS (SELECT page_id, line, count(*) AS n FROM (SELECT page_id, unnest(l) AS line FROM v) GROUP BY ALL),
d AS (SELECT coalesce(a.pid, b.pid) AS pid, sum(abs(coalesce(a.n, 0) - coalesce(b.n, 0))) AS d, sum(coalesce(a.n, 0) + coalesce(b.n, 0)) AS t
  FROM (SELECT p.page_id AS pid, c.line, c.n FROM p JOIN c USING (page_id) WHERE prev IS NOT NULL) a FULL JOIN (SELECT p.page_id AS pid, c.line, c.n FROM p JOIN c ON c.page_id = p.prev) b ON a.pid = b.pid AND a.line = b.line GROUP BY ALL)
SELECT p.file_key, p.page_id, round(CAST(d.d AS DOUBLE) / CAST(d.t AS DOUBLE), 6) AS ratio, (d.d IS NULL OR d.d > 0.5 * d.t) AS kept FROM p LEFT JOIN d ON p.page_id = d.pid""")
def changed_files_half(spark, sf_dir):
    key = F.concat_ws("/", F.regexp_extract("url", r"://([^/]+)/([a-z]+)/", 1), F.regexp_extract("url", r"://([^/]+)/([a-z]+)/", 2))
    v = load_table(spark, sf_dir, "pages").select("page_id", month_index(F.col("page_id")).alias("m"), key.alias("file_key"), "html")
    lines = F.split(F.regexp_replace("html", r"(</?[a-z0-9]+)", "\n$1"), "\n")
    versions = v.select("file_key", "m", "page_id", F.col("page_id").alias("pid"), lines.alias("lines"))
    got = curate.changed_items(versions, "file_key", ["m", "page_id"], "pid", F.col("lines"))
    return got.select("file_key", "page_id", "ratio", "kept")


@query(f"SELECT page_id, md5({BODY}) AS body_md5, length({BODY}) AS body_chars FROM pages")
def main_body_extract(spark, sf_dir):
    p = load_table(spark, sf_dir, "pages").select("page_id", main_body(F.col("html")).alias("body"))
    return p.select("page_id", F.md5(F.col("body").cast("binary")).alias("body_md5"), F.length("body").cast("long").alias("body_chars"))


@query("SELECT source, count(*) AS docs FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND CAST(substr(source, 4) AS INTEGER) >= 10 GROUP BY source")
def front_page_semi(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").where(article_source() == "news_articles").select("doc_id", "source")
    return d.join(load_table(spark, sf_dir, "labels").where("quality = 1"), "doc_id", "left_semi").groupBy("source").agg(F.count(F.lit(1)).alias("docs"))


@query(f"""WITH {DOCS}, s AS (SELECT source, m, item_id, strlen(body) AS b FROM docs), r AS (SELECT *, sum(b) OVER (PARTITION BY source, m ORDER BY md5(CAST(item_id AS VARCHAR)), item_id ROWS UNBOUNDED PRECEDING) AS run FROM s)
SELECT source, {label('m')} AS month, count(*) AS docs, CAST(sum(b) AS BIGINT) AS bytes FROM r WHERE run <= 12000 GROUP BY ALL""")
def byte_budget_sample(spark, sf_dir):
    d = load_table(spark, sf_dir, "documents").select(article_source().alias("source"), month_index(F.col("doc_id")).alias("m"), F.col("doc_id").alias("item_id"), F.octet_length("text").cast("long").alias("raw_bytes"))
    got = curate.byte_budget(d, ["source", "m"], 12000)
    return got.groupBy("source", "m").agg(F.count(F.lit(1)).alias("docs"), F.sum("raw_bytes").alias("bytes")).select("source", month_label(F.col("m")).alias("month"), "docs", "bytes")


@query("SELECT source, doc_id FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id) AS r FROM documents) WHERE r <= 5")
def stratified_sample(spark, sf_dir):
    """Five documents a source in the order of the id's digest: the sampling operator itself."""
    return curate.stratified_sample(load_table(spark, sf_dir, "documents").select("source", "doc_id"), "source", 5, "doc_id")


@query("""WITH px AS (SELECT vec_id // 4 AS patch_id, vec_id, list_transform(embedding, lambda v: CAST(floor((least(greatest(CAST(v AS DOUBLE), -1.0), 1.0) + 1) * 127.5) AS INTEGER)) AS px FROM embeddings),
t AS (SELECT patch_id, flatten(list(px ORDER BY vec_id)) AS p FROM px GROUP BY patch_id HAVING count(*) = 4)
SELECT CAST(patch_id AS BIGINT) AS patch_id, CAST(len(p) AS BIGINT) AS bytes, CAST(list_sum(p) AS BIGINT) AS pixel_sum, md5(array_to_string(list_transform(p, lambda v: CAST(v AS VARCHAR)), ',')) AS pixel_md5 FROM t""")
def gray_tiles(spark, sf_dir):
    e = load_table(spark, sf_dir, "embeddings")
    t = curate.tiles(e, "vec_id", curate.gray_levels(F.col("embedding")), 4)
    return t.select("patch_id", F.size("pixels").cast("long").alias("bytes"), F.aggregate("pixels", F.lit(0).cast("long"), lambda a, x: a + x).alias("pixel_sum"), F.md5(F.array_join(F.transform("pixels", lambda x: x.cast("string")), ",").cast("binary")).alias("pixel_md5"))


_SAMPLE = "CAST(floor((l_extendedprice - 0.0) / (200000.0 - 0.0) * 65535.0) - 32768 AS INTEGER)"


@query(f"""WITH s AS (SELECT CAST((year(l_shipdate) + 22 - 2017) * 12 + month(l_shipdate) - 1 AS INTEGER) AS m, l_orderkey, l_linenumber, l_partkey, {_SAMPLE} AS x FROM lineitem),
d AS (SELECT m, x, x - lag(x) OVER (PARTITION BY m ORDER BY l_orderkey, l_linenumber, l_partkey) AS dx FROM s)
SELECT {label('m')} AS month, count(*) AS samples, CAST(min(x) AS BIGINT) AS lowest, CAST(max(x) AS BIGINT) AS highest, CAST(coalesce(sum(abs(dx)), 0) AS BIGINT) AS abs_delta_sum FROM d GROUP BY m""")
def pcm_series(spark, sf_dir):
    s = curate.with_lags(curate.positions(price_samples(spark, sf_dir), ["m"], SAMPLE_ORDER), ["m"], "x", 1)
    d = s.withColumn("dx", F.col("x") - F.col("x1"))
    got = d.groupBy("m").agg(F.count(F.lit(1)).alias("samples"), F.min("x").cast("long").alias("lowest"), F.max("x").cast("long").alias("highest"), F.coalesce(F.sum(F.abs("dx")), F.lit(0)).cast("long").alias("abs_delta_sum"))
    return got.select(month_label(F.col("m")).alias("month"), "samples", "lowest", "highest", "abs_delta_sum")


@query(None)
def drifted_words(spark, sf_dir):
    """Share of words that the drift generator changed, by month; zero up to the month it begins with."""
    from slicecode.sources.tables import documents_slices

    s = documents_slices(spark, sf_dir).where(F.col("source") == "reference_articles")
    drifted = curate.inject_drift(s, 47).select("item_id", "m", F.split("body", " ").alias("b"))
    both = drifted.join(s.select("item_id", F.split("body", " ").alias("a")), "item_id")
    changed = F.size(F.filter(F.arrays_zip("a", "b"), lambda z: z["a"] != z["b"]))
    return both.groupBy("m").agg(F.sum(changed).alias("changed"), F.sum(F.size("a")).alias("words"))

