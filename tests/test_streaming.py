"""Streams over the files present give the batch answer; restarts and repeated batches change nothing."""

from pyspark.sql import functions as F

from slicecode.streaming import streams


def parts(spark, sf, folder, n=3):
    e = spark.read.parquet(f"{sf}/events.parquet")
    for k in range(n):
        e.where(F.col("event_id") % n == k).coalesce(1).write.parquet(f"{folder}/p{k}")


def test_three_files_equal_the_batch(spark, sf, tmp_path):
    parts(spark, sf, tmp_path / "in")
    s = spark.readStream.schema(streams.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/p*").withColumn("ts", F.col("ts").cast("timestamp"))
    got = streams.run_now(streams.daily(s, "60 days"), "complete").agg(F.sum("events")).first()[0]
    assert got == spark.read.parquet(f"{sf}/events.parquet").count()


def test_late_rows_are_dropped(spark, tmp_path):
    rows = lambda day, ids: spark.createDataFrame([(i, f"2024-01-{day:02d} 12:00:00") for i in ids], "event_id long, t string").select("event_id", F.col("t").cast("timestamp").alias("ts"))
    for k, (day, ids) in enumerate(((1, [1]), (20, [2]), (20, [5]), (2, [3]), (21, [4]))):  # rows are held against the watermark of the batch before
        rows(day, ids).coalesce(1).write.parquet(f"{tmp_path}/in/{k}")
    s = spark.readStream.schema("event_id long, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    out = streams.run_now(s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")), "append", str(tmp_path / "w"))
    assert F and {str(r["window"]["start"])[:10] for r in out.collect()} >= {"2024-01-01"} and "2024-01-02" not in {str(r["window"]["start"])[:10] for r in out.collect()}


def test_merge_restarts(spark, tmp_path):
    spark.createDataFrame([("a", 1, 2), ("b", 3, 4)], "key string, micro long, raw long").coalesce(1).write.parquet(f"{tmp_path}/in/0")
    read = lambda: spark.readStream.schema("key string, micro long, raw long").parquet(f"{tmp_path}/in/*")
    streams.merge_periods(read(), str(tmp_path / "out"))
    spark.createDataFrame([("a", 10, 20)], "key string, micro long, raw long").coalesce(1).write.parquet(f"{tmp_path}/in/1")
    streams.merge_periods(read(), str(tmp_path / "out"))
    streams.merge_periods(read(), str(tmp_path / "out"))
    got = {r["key"]: (r["micro"], r["raw"]) for r in streams.merged_periods(spark, str(tmp_path / "out")).collect()}
    assert got == {"a": (11, 22), "b": (3, 4)}


def test_repeats_within_the_watermark(spark, sf, tmp_path):
    parts(spark, sf, tmp_path / "in", 1)
    spark.read.parquet(f"{tmp_path}/in/p0").coalesce(1).write.parquet(f"{tmp_path}/in/p1")
    s = spark.readStream.schema(streams.EVENTS).parquet(f"{tmp_path}/in/p*").withColumn("ts", F.col("ts").cast("timestamp"))
    got = streams.run_now(streams.without_repeats(s, "60 days"), "append", str(tmp_path / "w"))
    assert got.count() == spark.read.parquet(f"{sf}/events.parquet").count()


def test_keyed_law_equals_the_batch(spark, sf):
    from slicecode.plans import registry

    out = streams.run_now(streams.keyed_law(streams.event_stream(spark, sf)), "update")
    got = {r["user_id"]: (r["events"], r["micro"]) for r in out.collect()}
    assert got == {r["user_id"]: (r["events"], r["micro"]) for r in registry.queries()["stream_state_bits"](spark, sf).collect()}


def test_interval_join_equals_the_batch(spark, sf, duck):
    from slicecode.plans import registry
    from tests.conftest import rows_match

    rows_match(registry.queries()["stream_interval_join"](spark, sf), duck.sql(registry.oracle_sql()["stream_interval_join"]))


def test_sessions_come_from_the_state_and_not_over_the_driver(spark, sf, duck, tmp_path):
    from slicecode.plans import registry
    from tests.conftest import rows_match

    held = {t.name for t in spark.catalog.listTables()}
    got = registry.queries()["stream_session"](spark, sf)
    assert {t.name for t in spark.catalog.listTables()} == held  # a memory table would hold all sessions on the driver
    rows_match(got, duck.sql(registry.oracle_sql()["stream_session"]))
    parts(spark, sf, tmp_path / "in")
    s = spark.readStream.schema(streams.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/p*").withColumn("ts", F.col("ts").cast("timestamp"))
    assert streams.all_sessions(s, late="60 days").agg(F.sum("events")).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()
