"""Operators that built-in functions cannot express: a chunking table function, Arrow and cogrouped scorers, a chunk source."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from slicecode.operators.baselines import zlib_segment
from slicecode.operators.windows import stream_chunks


@F.udtf(returnType="chunk_no: int, n: int, data: binary")
class ChunkText:
    """Byte chunks of a text: a lateral join away in SQL."""

    def eval(self, text: str, size: int):
        raw = (text or "").encode()
        for k in range(0, len(raw), size):
            yield k // size, len(raw[k : k + size]), raw[k : k + size]


def arrow_score(chunks: DataFrame, law: np.ndarray, keep: list[str], data: str = "data") -> DataFrame:
    """``keep``, n, micro: micro-bits of byte chunks under an order-1 law (257 x 256 matrix of probabilities; row 256 for the first
    byte). One Arrow pass; the matrix has a fixed size."""
    cost = np.floor(-np.log2(law) * 1e6 + 0.5).astype(np.int64)
    sent = chunks.sparkSession.sparkContext.broadcast(cost)
    schema = ", ".join(f"{c} {chunks.schema[c].dataType.simpleString()}" for c in keep) + ", n long, micro long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = sent.value
        for b in batches:
            ns, sums = [], []
            for raw in b.column(data).to_pylist():
                x = np.frombuffer(raw or b"", np.uint8).astype(np.int64)
                prev = np.concatenate(([256], x[:-1])) if len(x) else x
                ns.append(len(x))
                sums.append(int(table[prev, x].sum()))
            yield pa.RecordBatch.from_arrays([b.column(c) for c in keep] + [pa.array(ns, pa.int64()), pa.array(sums, pa.int64())], names=[*keep, "n", "micro"])

    return chunks.select(*keep, data).mapInArrow(run, schema)


def cogroup_score(grams: DataFrame, law: DataFrame, shard: str = "shard") -> DataFrame:
    """source, micro: counted grams (shard, source, ctx, sym, n) meet the model shard that holds their contexts (shard, ctx, sym, p).
    For models that fit no single memory; a shard's size is the caller's choice."""

    def score(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        got = left.merge(right, on=["ctx", "sym"])
        cost = np.floor(-np.log2(got["p"].to_numpy()) * 1e6 + 0.5).astype(np.int64) * got["n"].to_numpy()
        return pd.DataFrame({"source": got["source"], "micro": cost}).groupby("source", as_index=False).sum()

    grams, law = grams.toDF(*grams.columns), law.toDF(*law.columns)  # both may come from the same counts
    parts = grams.groupBy(shard).cogroup(law.groupBy(shard)).applyInPandas(score, "source string, micro long")
    return parts.groupBy("source").agg(F.sum("micro").alias("micro"))


def month_segments(rows: DataFrame, segment: int) -> DataFrame:
    """source, m, segment, raw, coded: each month's byte stream (source, item_id, m, data; by item_id) in segments of about
    ``segment`` bytes, one group each; a segment is raw deflate that knows the last 32 KB of the stream before it.

    A document belongs to the segment its first byte falls in, so a group is ``segment`` bytes and one document at most.
    """
    sized = rows.select("source", "item_id", "m", F.octet_length("data").cast("long").alias("n"))
    placed = stream_chunks(sized, ["source", "m"], "item_id", "n")
    at = placed.select("source", "m", "item_id", F.floor(F.col("start") / segment).alias("segment"), "start", "stop")
    cut = rows.join(at, ["source", "m", "item_id"])
    # the end of a segment goes to the next one as its dictionary: the documents that reach into its last 32 KB
    ends = at.groupBy("source", "m", "segment").agg(F.max("stop").alias("end"))
    tail = cut.join(ends, ["source", "m", "segment"]).where(F.col("stop") > F.col("end") - 32768)
    last = Window.partitionBy("source", "m").orderBy("segment")
    following = ends.select("source", "m", "segment", F.lead("segment").over(last).alias("next"))  # a row a segment
    carried = tail.join(following, ["source", "m", "segment"]).where("next is not null").select("source", "m", F.col("next").alias("segment"), "start", F.substring(F.col("data"), F.greatest(F.octet_length("data") - 32767, F.lit(1)), F.lit(32768)).alias("data"), F.lit(False).alias("own"))
    both = cut.select("source", "m", "segment", "start", "data", F.lit(True).alias("own")).unionByName(carried)

    def pack(group: pa.Table) -> pa.Table:
        parts = group.sort_by([("own", "ascending"), ("start", "ascending")])
        own, data = parts.column("own").to_pylist(), parts.column("data").to_pylist()
        before = b"".join(d for o, d in zip(own, data, strict=True) if not o)
        body = b"".join(d for o, d in zip(own, data, strict=True) if o)
        head = {c: [group.column(c)[0].as_py()] for c in ("source", "m", "segment")}
        return pa.table({**head, "raw": [len(body)], "coded": [len(zlib_segment(body, before))]}, schema=pa.schema([("source", pa.string()), ("m", pa.int32()), ("segment", pa.int64()), ("raw", pa.int64()), ("coded", pa.int64())]))

    return both.groupBy("source", "m", "segment").applyInArrow(pack, "source string, m int, segment long, raw long, coded long")


@F.pandas_udf(T.DoubleType())
def auc(score: pd.Series, label: pd.Series) -> float:
    """Mann-Whitney by average ranks: a grouped aggregate for cross-checks on bounded groups."""
    r = score.rank(method="average")
    pos, n = label == 1, len(label)
    p = int(pos.sum())
    return float("nan") if p in (0, n) else float((r[pos].sum() - p * (p + 1) / 2) / (p * (n - p)))


#: Pairs of a model that one cogrouped shard should hold.
PAIRS_IN_A_SHARD = 1 << 20


class _Group(InputPartition):
    def __init__(self, path: str, group: int) -> None:
        super().__init__((path, group))
        self.path, self.group = path, group


class ChunkReader(DataSourceReader):
    """A partition for each row group of a Parquet file or folder; only the two columns are read."""

    def __init__(self, options: dict) -> None:
        self.path, self.key, self.column, self.size = options["path"], options.get("key", "doc_id"), options.get("column", "text"), int(options.get("size", 2048))

    def partitions(self):
        import os

        import pyarrow.parquet as pq

        files = [self.path] if os.path.isfile(self.path) else sorted(f"{self.path}/{f}" for f in os.listdir(self.path) if f.endswith(".parquet"))
        return [_Group(f, k) for f in files for k in range(pq.ParquetFile(f).num_row_groups)]

    def read(self, part):
        import pyarrow.parquet as pq

        for batch in pq.ParquetFile(part.path).iter_batches(256, row_groups=[part.group], columns=[self.key, self.column]):
            for key, text in zip(batch.column(self.key).to_pylist(), batch.column(self.column).to_pylist(), strict=True):
                raw = (text or "").encode()
                for k in range(0, len(raw), self.size):
                    yield key, k // self.size, raw[k : k + self.size]


class TextChunks(DataSource):
    """A Python data source that cuts windows at the source (options path, key, column, size): for files that every node can
    open by path; stores that only Spark reads go through ``windows.chunk_arrays``."""

    @classmethod
    def name(cls) -> str:
        return "text_chunks"

    def schema(self) -> str:
        return "doc_id long, chunk_no int, data binary"

    def reader(self, schema) -> ChunkReader:
        return ChunkReader(self.options)


def register(spark: SparkSession) -> None:
    spark.udtf.register("chunk_text", ChunkText)
    spark.dataSource.register(TextChunks)
