"""What the corpus operators share: table access, Arrow passes, durable cuts of lineage, checksum folds.

Conventions that every operator keeps:

* Operators pick the columns they need by name and return only declared columns, so extra columns of the
  input (whatever their names) never clash. Row filters pass whole rows through untouched.
* Whole texts are processed; a null text counts as empty unless an operator says otherwise.
* Lineage is cut with ``checkpoint()`` into the folder that ``spark.checkpoint.dir`` names, which all
  executors share; nothing is kept on one executor alone.
"""

from __future__ import annotations

import gc
import tempfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: ASCII white space as the word pattern ``[^\x20\x09-\x0D]+`` sees it; ``bytes.split()`` splits on just these.
WHITE = b" \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the shared folder that the session names; only a local session without one gets a temporary folder."""
    context = spark.sparkContext
    if context.getCheckpointDir():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not context.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="slicecode-checkpoints-"))


def durable(df: DataFrame) -> DataFrame:
    """``df`` computed once and written to the shared checkpoint folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Let go of the shuffle and checkpoint files of frames that nothing refers to any more. Spark does so when the driver's
    garbage is collected, which many small rounds alone do not bring about."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def arrow_pass(df: DataFrame, rows: Callable[..., list], schema: str, keep: list[str] | None = None) -> DataFrame:
    """One Arrow pass. ``rows`` gets the Python lists of all columns of ``df`` and returns one list (or Arrow
    array) for each field of ``schema``; the columns named in ``keep`` are put before them unchanged.

    Works batch by batch, so memory is bounded by one Arrow batch.
    """
    keep = keep or []
    types = T.StructType([df.schema[c] for c in keep] + list(T.StructType.fromDDL(schema)))
    out = to_arrow_schema(types, prefers_large_types=False)
    used = [c for c in df.columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices_by_bytes(whole):
                made = rows(*[batch.column(c).to_pylist() for c in used])
                arrays = [batch.column(c) for c in keep] + list(made)
                yield pa.RecordBatch.from_arrays([a.cast(f.type) if isinstance(a, pa.Array) and a.type != f.type else a if isinstance(a, pa.Array) else pa.array(a, f.type) for a, f in zip(arrays, out, strict=True)], schema=out)

    return df.mapInArrow(run, types)


def slices_by_bytes(batch: pa.RecordBatch, most: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about ``most`` bytes, one row at least."""
    n, size = batch.num_rows, batch.nbytes
    step = n if size <= most else max(1, int(n * most / size))
    for start in range(0, n, max(1, step)):
        yield batch.slice(start, step)


def filter_pass(df: DataFrame, column: str, verdict: Callable[[list], list[bool]]) -> DataFrame:
    """The rows of ``df`` for which ``verdict`` of their ``column`` is true, whole and unchanged."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices_by_bytes(whole):
                yield batch.filter(pa.array(verdict(batch.column(column).to_pylist()), pa.bool_()))

    return df.mapInArrow(run, df.schema)


def fold_of(doc_id, folds: int = 5):
    """crc32 of the id as text, modulo ``folds``; a null id falls in fold 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % folds, F.lit(0))
