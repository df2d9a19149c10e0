"""Arrival of new slices as streams: daily rates, sliding and session windows, keyed state, incremental periods.

Batch-equivalent: run with availableNow over the files present, every stream gives the answer of the batch query on them.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int | None = None) -> DataFrame:
    """The events files as a stream; ``ts`` becomes a timestamp in UTC for the watermark."""
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet")
    reader = reader.option("maxFilesPerTrigger", per_trigger) if per_trigger else reader
    return reader.parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def daily(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("value"), 2).alias("total"))


def sliding(events: DataFrame, size: str = "6 hours", step: str = "1 hour", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("events"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("events"))


def all_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """session_window, user_id, events of every session, the open ones too. In complete mode no session leaves the state, so the state
    that the last batch wrote to the shared folder is the result: executors read it from there, and no row comes to the driver.
    The RocksDB store keeps it off the heap."""
    spark = events.sparkSession
    folder = checkpoint_folder(spark)
    with rocks_store(spark):
        run = sessions(events, gap, late).writeStream.format("noop").outputMode("complete").option("checkpointLocation", f"{folder}/state")
        run.trigger(availableNow=True).start().awaitTermination()
        held = spark.read.format("statestore").load(f"{folder}/state")
    return held.select("value.session_window", "value.user_id", F.col("value.count").alias("events"))


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def view_then_buy(events: DataFrame, first: str, second: str, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a ``second`` event of the same user within the bound after a ``first`` one."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("first_id")).withWatermark("t1", "1 hour")
    b = events.where(F.col("event_type") == second).select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("second_id")).withWatermark("t2", "1 hour")
    return a.join(b, F.expr(f"u = user_id AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("user_id", "first_id", "second_id")


class KeyedLaw(StatefulProcessor):
    """An adaptive law per key: the state is the counts of the key's symbols so far; a batch is taken in event order."""

    def __init__(self, alphabet: int = 5) -> None:
        self.alphabet = alphabet

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.counts = handle.getMapState("counts", "sym string", "n bigint")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        import math

        batch = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        counts = {k[0]: v[0] for k, v in self.counts.iterator()}
        seen, micro = sum(counts.values()), 0
        for sym in batch["event_type"]:
            c = counts.get(sym, 0)
            micro += math.floor(-math.log2((c + 0.5) / (seen + 0.5 * self.alphabet)) * 1e6 + 0.5)
            counts[sym], seen = c + 1, seen + 1
        for k, v in counts.items():
            self.counts.updateValue((k,), (v,))
        yield pd.DataFrame({"user_id": [key[0]], "events": [len(batch)], "micro": [micro]})

    def close(self) -> None:
        pass


STATE_STORE = "spark.sql.streaming.stateStore.providerClass"
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


@contextlib.contextmanager
def rocks_store(spark: SparkSession) -> Iterator[None]:
    """The RocksDB store is named for the run and set back after it."""
    before = spark.conf.get(STATE_STORE, None)
    spark.conf.set(STATE_STORE, ROCKS)
    try:
        yield
    finally:
        spark.conf.set(STATE_STORE, before) if before else spark.conf.unset(STATE_STORE)


def keyed_totals(events: DataFrame, alphabet: int = 5) -> DataFrame:
    """user_id, events, micro over all batches of ``keyed_law``. Keyed state of this kind needs the RocksDB store."""
    with rocks_store(events.sparkSession):
        out = run_now(keyed_law(events, alphabet), "update")
    return out.groupBy("user_id").agg(F.sum("events").alias("events"), F.sum("micro").alias("micro"))


def keyed_law(events: DataFrame, alphabet: int = 5) -> DataFrame:
    return events.groupBy("user_id").transformWithStateInPandas(KeyedLaw(alphabet), "user_id long, events long, micro long", outputMode="Update", timeMode="None")


def checkpoint_folder(spark: SparkSession) -> str:
    """A new folder in the shared one that the session names; only a local session without one gets a temporary folder."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and spark.sparkContext.master.split("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return f"{named or tempfile.mkdtemp(prefix='slicecode-streams-')}/{uuid.uuid4().hex}"


def run_now(stream: DataFrame, mode: str = "complete", folder: str | None = None) -> DataFrame:
    """Run a stream over what is there now and return its result table. Append results go to files in the shared folder,
    complete and update results to a memory table."""
    spark = stream.sparkSession
    folder = folder or checkpoint_folder(spark)
    if mode == "append":
        stream.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")
    name = f"t_{uuid.uuid4().hex}"
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def merge_periods(stream: DataFrame, folder: str) -> None:
    """foreachBatch: month sums arrive as rows (key, micro, raw); what is stored is algebraic, so a new month costs only itself.
    Each batch writes its partial sums under its own number, so a repeated batch overwrites itself."""

    def store(batch: DataFrame, number: int) -> None:
        batch.groupBy("key").agg(F.sum("micro").alias("micro"), F.sum("raw").alias("raw")).write.mode("overwrite").parquet(f"{folder}/partial/batch={number}")

    stream.writeStream.foreachBatch(store).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()


def merged_periods(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/partial").groupBy("key").agg(F.sum("micro").alias("micro"), F.sum("raw").alias("raw"))
