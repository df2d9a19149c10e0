"""Quality rules by cross-document line frequency.

Each document's lines are normalised and hashed; for every host and line the distinct documents are counted;
lines that are on more documents of a host than its limits allow are removed (template text); a document that
loses too many of its words is rejected as depleted. Basic measures of the text are taken in the same pass.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import WHITE, arrow_pass, durable

SYMBOLS = b"#*$%&|<>"
MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def repeated_words(words: list[bytes], width: int = 3) -> int:
    """Words that lie in a window of ``width`` words which the text has twice or more, the first one included."""
    n = len(words) - width + 1
    if n < 2:
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
    keys, base = ids[:n].copy(), len(seen)
    for j in range(1, width):
        if base ** (j + 1) > 1 << 62:
            keys = np.unique(keys, return_inverse=True)[1].astype(np.int64)
        keys = keys * base + ids[j : j + n]
    order = np.argsort(keys, kind="stable")
    same = keys[order[1:]] == keys[order[:-1]]
    if not same.any():
        return 0
    often = np.zeros(n, bool)
    often[order[1:][same]] = True
    often[order[:-1][same]] = True
    covered = np.zeros(len(words), bool)
    for j in range(width):
        covered[j : j + n] |= often
    return int(covered.sum())


def normalise_line(line: bytes) -> bytes:
    """Words joined by one space, A-Z in lower case."""
    return b" ".join(line.split()).lower()


def measure(text: str | None) -> tuple[list[int], list[int], list[int]]:
    """The measures, then the distinct normalised lines' hashes and the words under each."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    dups, before, lines = 0, set(), {}
    for line in raw.split(b"\n"):
        parts = line.split()
        if not parts:
            continue
        if line in before:
            dups += 1
        else:
            before.add(line)
        key = xxhash.xxh64_intdigest(b" ".join(parts).lower())
        key -= (key >> 63) << 64
        lines[key] = lines.get(key, 0) + len(parts)
    chars = len(text or "") - (len(raw) - len(raw.translate(None, WHITE)))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    return [len(words), chars, symbols, dups, repeated_words(words)], list(lines), list(lines.values())


def measured(docs: DataFrame, doc_id: str = "doc_id", host: str = "source", text: str = "text") -> DataFrame:
    """doc_id, host, the measures, and the arrays lines (hashes) and line_words."""

    def rows(_: list, __: list, texts: list) -> list:
        found = [measure(t) for t in texts]
        return [*[[f[0][i] for f in found] for i in range(5)], [f[1] for f in found], [f[2] for f in found]]

    narrow = docs.select(F.col(doc_id).alias("doc_id"), F.col(host).alias("host"), F.col(text).cast("string").alias("text"))
    return arrow_pass(narrow, rows, MEASURES + ", lines array<long>, line_words array<int>", keep=["doc_id", "host"])


def frequent_lines(lines: DataFrame, host_docs: DataFrame, min_docs: int, share: float) -> DataFrame:
    """host, line, n_docs of the lines on at least ``min_docs`` distinct documents and over ``share`` of its host's."""
    counted = lines.groupBy("host", "line").agg(F.countDistinct("doc_id").alias("n_docs")).where(F.col("n_docs") >= min_docs)
    sized = counted.join(host_docs, counted["host"].eqNullSafe(host_docs["of_host"]))
    return sized.where(F.col("n_docs") > share * F.col("host_docs")).select("host", "line", "n_docs")


def line_frequency_rules(docs: DataFrame, doc_id: str = "doc_id", host: str = "source", text: str = "text", min_docs: int = 20, share: float = 0.01, keep_share: float = 0.5) -> DataFrame:
    """One row for each input row: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, kept, and removed_words (words in lines above the limits), words_left.

    A line is above the limits if at least ``min_docs`` distinct documents of the host have it and more than
    ``share`` of the host's distinct documents do: the count decides on small and middle hosts, and the share, which is small so
    that a template of a part of a large host is still found, keeps chance repeats on very large ones. A document is depleted, so not kept, if less than
    ``keep_share`` of its words are left. Documents that fail the base rules (fewer than 50 words, or more than
    half of the words in repeated windows) are not kept either, but their lines count.
    Null text: no words, base rules failed. A null host is a host of its own; documents with a null id are
    judged but not counted. Rows that repeat an id count once and get one verdict each. Empty table: no rows.
    """
    found = durable(measured(docs, doc_id, host, text).withColumn("row_key", F.monotonically_increasing_id()))
    lines = found.select("row_key", "doc_id", "host", F.explode(F.arrays_zip("lines", "line_words")).alias("x")).select("row_key", "doc_id", "host", F.col("x.lines").alias("line"), F.col("x.line_words").alias("words"))
    host_docs = found.groupBy("host").agg(F.countDistinct("doc_id").alias("host_docs")).withColumnRenamed("host", "of_host")
    hot = frequent_lines(lines, host_docs, min_docs, share).select(F.col("host").alias("hot_host"), F.col("line").alias("hot_line"))
    removed = lines.join(hot, (lines["line"] == hot["hot_line"]) & lines["host"].eqNullSafe(hot["hot_host"])).groupBy("row_key").agg(F.sum("words").alias("removed"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    left = F.col("n_words") - F.coalesce("removed", F.lit(0))
    return found.join(removed, "row_key", "left").select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & (left >= keep_share * F.col("n_words"))).alias("kept"),
        F.coalesce("removed", F.lit(0)).cast("long").alias("removed_words"), left.cast("long").alias("words_left"),
    )


def remove_frequent_lines(text: str | None, hot: set[int]) -> str:
    """``text`` without the lines whose normalised hash is in ``hot``; other lines keep their form."""
    out = []
    for line in (text or "").split("\n"):
        key = xxhash.xxh64_intdigest(normalise_line(line.encode("utf-8", "surrogatepass")))
        if key - ((key >> 63) << 64) not in hot or not line.split():
            out.append(line)
    return "\n".join(out)
