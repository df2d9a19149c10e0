"""A corpus pipeline of five stages: toxicity, near-duplicates, decontamination, secrets, piece encoding.

Each stage takes (spark, docs, sf_dir). ``run`` writes each one's rows to the shared checkpoint folder before the next
reads them; a caller may as well write them as Parquet between stages. All but the last return the columns of
``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from slicecode.llm import anchor_simhash, decontaminate, piece_tokenizer, secret_scan, toxicity
from slicecode.llm.common import durable, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The classifier is fitted on the labelled documents of ``docs`` outside fold 0; rows scored 0.5 or more go."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.without_toxic(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component the smallest id stays. Links: fingerprints of five-word shingles within three bits; or a home anchor
    shared in one of sixteen further fingerprints, and a Jaccard similarity of the five-word shingles of 0.8 or more."""
    return anchor_simhash.keep_one_of_each(docs, width=5, least=0.8)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage within its edit budget go."""
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document stays; secrets in its text are masked, and n_chars follows."""
    return secret_scan.redacted(docs)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids, parity, round_trip of every document."""
    return piece_tokenizer.encode(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", drop_near_duplicates), ("decontamination", drop_contaminated), ("secret_scan", mask_secrets), ("piece_encoding", encode_pieces)]

#: SQL cannot express these stages; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each one's result written to the shared checkpoint folder before the next."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
