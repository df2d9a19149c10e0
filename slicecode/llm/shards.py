"""Contiguous shards of nearly equal bytes from a global prefix sum (DataFrame functions only).

The rows are range-partitioned by (id, checksum, size); each partition's bytes and rows are totalled; the
totals of the few partitions give every partition its offset; a running sum inside the partition, put on
that offset, is the row's global position. The cuts lie at equal targets of the byte total. No window spans
all rows: the only unpartitioned one runs over the partition totals.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slicecode.llm.common import durable

#: Bytes that a row costs besides its text.
ROW_OVERHEAD = 8


def byte_shards(docs: DataFrame, shards: int = 24, doc_id: str = "doc_id", text: str = "text", parts: int | None = None) -> DataFrame:
    """Columns: doc_id, size, text_crc32, law ('bytes'), shard (0 … ``shards`` - 1), slot, grown_shard (null).

    Order: doc_id ascending (null first), then checksum and size; repeated rows are neighbours and get slots of
    their own. A row goes to the shard that holds the middle of its byte range, so a shard's bytes differ from
    the target by less than the largest row. Null text: no bytes, checksum 0. An empty table gives no rows.
    Equal texts are not held together: a group may be larger than a shard, so cuts may split it.
    """
    spark = docs.sparkSession
    raw = F.coalesce(F.col(text).cast("string"), F.lit(""))
    narrow = docs.select(F.col(doc_id).alias("doc_id"), (F.octet_length(raw).cast("long") + ROW_OVERHEAD).alias("size"), F.crc32(raw.cast("binary")).cast("long").alias("text_crc32"))
    parts = parts or max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    # the partition's number is fixed in the same write as its rows, so a lost task cannot deal them anew
    placed = durable(narrow.repartitionByRange(parts, "doc_id", "text_crc32", "size").withColumn("part", F.spark_partition_id()))
    totals = placed.groupBy("part").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("rows"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("part", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("byte_offset"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("row_offset"), F.sum("bytes").over(Window.partitionBy()).alias("all_bytes"))
    inside = Window.partitionBy("part").orderBy("doc_id", "text_crc32", "size")
    located = placed.select("*", F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("upto"), F.row_number().over(inside).alias("nth")).join(F.broadcast(offsets), "part")  # one row a partition: bounded by ``parts``
    cut = located.select(
        "doc_id", "size", "text_crc32", (F.col("row_offset") + F.col("nth") - 1).alias("position"),
        F.least(F.lit(shards - 1), F.expr(f"cast((cast({shards} as decimal(4,0)) * (2 * (byte_offset + upto) - size)) div (2 * all_bytes) as int)")).cast("int").alias("shard"),
    )
    first = cut.groupBy("shard").agg(F.min("position").alias("first"))
    return cut.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("position") - F.col("first")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))  # at most ``shards`` rows are broadcast
