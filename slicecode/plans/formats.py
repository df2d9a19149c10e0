"""Where slices and models lie: other formats, partitioned slices, bucketed count tables, provenance, a chunk source."""

from __future__ import annotations

from pyspark.sql import functions as F

from slicecode.functions.exprs import month_label
from slicecode.operators import models, pyops
from slicecode.plans.base import CODE, DOCS, grams, label, query, tokens
from slicecode.sources.tables import documents_slices, load_table, page_slices, read_any
from slicecode.streaming.streams import checkpoint_folder

_REF = "ref AS (SELECT * FROM docs WHERE source = 'reference_articles')"


@query("""SELECT unnest(['json', 'csv', 'orc', 'parquet']) AS format, (SELECT count(*) FROM customer) AS rows, (SELECT CAST(sum(c_custkey) AS BIGINT) FROM customer) AS keys, (SELECT CAST(sum(length(c_name)) AS BIGINT) FROM customer) AS letters
UNION ALL SELECT 'text', count(*), CAST(NULL AS BIGINT), CAST(sum(length(c_name)) AS BIGINT) FROM customer UNION ALL SELECT 'binaryFile', count(*), CAST(NULL AS BIGINT), CAST(sum(length(c_name) + 1) AS BIGINT) FROM customer""")
def format_round_trip(spark, sf_dir):
    """A table written in each format and read again: rows and checksums stay. Lines come back as text and as files' bytes."""
    c, folder = load_table(spark, sf_dir, "customer").select("c_custkey", "c_name"), checkpoint_folder(spark)
    schema, out = "c_custkey bigint, c_name string", None
    for kind in ("json", "csv", "orc", "parquet"):
        c.write.format(kind).save(f"{folder}/{kind}")
        back = read_any(spark, f"{folder}/{kind}", kind, schema)
        got = back.agg(F.lit(kind).alias("format"), F.count(F.lit(1)).alias("rows"), F.sum("c_custkey").alias("keys"), F.sum(F.length("c_name")).alias("letters"))
        out = got if out is None else out.unionByName(got)
    c.select("c_name").write.text(f"{folder}/text")
    lines = read_any(spark, f"{folder}/text", "text").agg(F.lit("text").alias("format"), F.count(F.lit(1)).alias("rows"), F.lit(None).cast("long").alias("keys"), F.sum(F.length("value")).alias("letters"))
    raw = read_any(spark, f"{folder}/text", "binaryFile", pathGlobFilter="*.txt")
    held = raw.agg(F.lit("binaryFile").alias("format"), F.sum(F.length(F.regexp_replace(F.decode("content", "UTF-8"), "[^\n]", "")).cast("long")).alias("rows"), F.lit(None).cast("long").alias("keys"), F.sum(F.length(F.decode("content", "UTF-8"))).cast("long").alias("letters"))
    return out.unionByName(lines).unionByName(held)


@query(f"WITH {DOCS}, {CODE}, s AS (SELECT * FROM docs UNION ALL SELECT * FROM code) SELECT source, {label('m')} AS month, count(*) AS docs, CAST(sum(strlen(body)) AS BIGINT) AS bytes FROM s WHERE m >= 72 GROUP BY ALL")
def partitioned_slices(spark, sf_dir):
    """Slices written by source and month; a query on the testing period opens its folders only."""
    folder = checkpoint_folder(spark)
    slices = documents_slices(spark, sf_dir).unionByName(page_slices(spark, sf_dir).where("source = 'code_files'"))
    # one file a folder and range of ids, so that a large month is many files and a small one is not
    dealt = slices.withColumn("part", F.floor(F.col("item_id") / 1_000_000)).repartition("source", "m", "part").drop("part")
    dealt.write.partitionBy("source", "m").parquet(f"{folder}/slices")
    back = spark.read.parquet(f"{folder}/slices").where("m >= 72")
    return back.groupBy("source", "m").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.octet_length("body").cast("long")).alias("bytes")).select("source", month_label(F.col("m")).alias("month"), "docs", "bytes")


@query(f"WITH {DOCS}, {_REF}, {tokens('ref')}, {grams(2048, 2)}, c AS (SELECT ctx, sym, sum(n) AS cnt FROM grams WHERE m <= 71 GROUP BY ALL), t AS (SELECT ctx, sum(cnt) AS n, count(*) AS t FROM c GROUP BY ctx) SELECT CAST(length(ctx) // 2 AS INTEGER) AS depth, count(*) AS pairs, CAST(sum(cnt) AS BIGINT) AS total, CAST(sum(t.t) AS BIGINT) AS successors FROM c JOIN t USING (ctx) GROUP BY 1")
def bucketed_model(spark, sf_dir):
    """Counts and totals in tables bucketed by context: the join of the two needs no exchange, whenever the model is read again."""
    g = models.month_grams(documents_slices(spark, sf_dir).where("source = 'reference_articles' and m <= 71"), 2, 2048)
    counts = g.groupBy("ctx", "sym").agg(F.sum("n").alias("cnt"))
    totals = counts.groupBy("ctx").agg(F.sum("cnt").alias("n"), F.count(F.lit(1)).alias("t"))
    a, b = models.save_bucketed(counts, 8, checkpoint_folder(spark)), models.save_bucketed(totals, 8, checkpoint_folder(spark))
    return a.join(b.hint("merge"), "ctx").groupBy((F.length("ctx") / 2).cast("int").alias("depth")).agg(F.count(F.lit(1)).alias("pairs"), F.sum("cnt").alias("total"), F.sum("t").alias("successors"))


@query(f"""WITH d AS (SELECT CASE WHEN CAST(regexp_extract(source, '(\\d+)$', 1) AS INTEGER) < 10 THEN 'reference_articles' ELSE 'news_articles' END AS source, source AS origin, lang, doc_id % 83 AS m, text FROM documents)
SELECT source, origin, lang, CASE WHEN m < 72 THEN 'train' ELSE 'test' END AS period, count(*) AS docs, CAST(sum(strlen(text)) AS BIGINT) AS bytes FROM d GROUP BY ALL""")
def provenance(spark, sf_dir):
    """Slices keep where a document came from and its language, so a period's bytes can be traced to their origins."""
    d = documents_slices(spark, sf_dir, keep=("source", "lang"))
    period = F.when(F.col("m") < 72, "train").otherwise("test")
    return d.groupBy("source", F.col("kept.source").alias("origin"), F.col("kept.lang").alias("lang"), period.alias("period")).agg(F.count(F.lit(1)).alias("docs"), F.sum(F.octet_length("body").cast("long")).alias("bytes"))


@query("SELECT doc_id, CAST(k AS INTEGER) AS chunk_no, CAST(least(512, n - k * 512) AS INTEGER) AS n, substr(h, CAST(k * 1024 + 1 AS INTEGER), 2) AS first_byte FROM (SELECT doc_id, strlen(text) AS n, unnest(range((strlen(text) + 511) // 512)) AS k, hex(encode(text)) AS h FROM documents)")
def source_chunks(spark, sf_dir):
    """The chunks of ``udtf_chunks``, cut by a Python data source while it reads."""
    pyops.register(spark)
    path = load_table(spark, sf_dir, "documents").inputFiles()
    t = None
    for p in path:
        one = spark.read.format("text_chunks").option("path", p.removeprefix("file://").removeprefix("file:")).option("size", 512).load()
        t = one if t is None else t.unionByName(one)
    return t.select("doc_id", "chunk_no", F.octet_length("data").alias("n"), F.substring(F.hex("data"), 1, 2).alias("first_byte"))


@query(f"WITH {DOCS} SELECT source, count(*) AS rows, CAST(sum(strlen(body)) AS BIGINT) AS bytes, CAST(max(strlen(body)) AS BIGINT) AS longest FROM docs GROUP BY source")
def observed_scan(spark, sf_dir):
    """Measures taken while another action passes over the rows: no scan of their own."""
    from pyspark.sql import Observation

    d, made = documents_slices(spark, sf_dir), []
    for source in ("reference_articles", "news_articles"):
        seen, mine, size = Observation(), F.col("source") == source, F.octet_length("body").cast("long")
        d = d.observe(seen, F.count(F.when(mine, 1)).alias("rows"), F.sum(F.when(mine, size)).alias("bytes"), F.max(F.when(mine, size)).alias("longest"))
        made.append((source, seen))
    d.write.format("noop").mode("overwrite").save()
    rows = [(s, o.get["rows"], o.get["bytes"], o.get["longest"]) for s, o in made]
    return spark.createDataFrame([r for r in rows if r[1]], "source string, rows long, bytes long, longest long")


