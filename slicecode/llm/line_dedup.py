"""Substring dedup over paragraphs, lines, or the sentences of lines: normalise, hash, keep the earliest ranked one.

Units are cut with their offsets in the original text (code points, end exclusive). Their digests are grouped
globally; of each digest the occurrence with the smallest (rank, id, start) stays, every other one is named with
its own offsets and those of the one that stays. Texts travel only where ``apply_removals`` rewrites them.

A passage that was set into another line is no unit of its own, so whole lines cannot find it. Its inner sentences are;
``passage_report`` hashes those and judges a document by its longest run of adjacent repeated ones.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, durable

#: What parts the units. A sentence ends with its mark and the white space behind it, and with its line.
BORDERS = {"line": re.compile(rb"\n"), "paragraph": re.compile(rb"\n(?:[ \t\x0b\x0c\r]*\n)+"), "sentence": re.compile(rb"(?<=[.!?])[ \t\x0b\x0c\r]+|\n")}
HEAD = re.compile(rb"\n*")


def normalise_unit(unit: bytes) -> bytes:
    """A-Z in lower case, runs of ASCII white space as one space, no space at the ends."""
    return b" ".join(unit.split()).lower()


def units_of(text: str | None, unit: str = "line", min_words: int = 1) -> list[tuple[bytes, int, int, int]]:
    """(128-bit digest, start, end, words) of every unit with at least ``min_words`` words (one at least)."""
    if not text:
        return []
    raw, out = text.encode("utf-8", "surrogatepass"), []
    at = HEAD.match(raw).end() if unit == "paragraph" else 0
    ends = [(m.start(), m.end()) for m in BORDERS[unit].finditer(raw, at)] + [(len(raw), len(raw))]
    digest, least = xxhash.xxh3_128_digest, max(1, min_words)
    for end, following in ends:
        words = raw[at:end].split()
        if len(words) >= least:
            out.append((digest(b" ".join(words).lower()), at, end, len(words)))
        at = following
    if len(raw) == len(text) or not out:
        return out
    before = np.concatenate(([0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)))  # code points before each byte
    places = before[np.array([(s, e) for _, s, e, _ in out])].tolist()
    return [(d, s, e, n) for (d, _, _, n), (s, e) in zip(out, places, strict=True)]


def unit_table(docs: DataFrame, doc_id: str, text: str, unit: str, min_words: int, rank: Column | None) -> DataFrame:
    """One row for each input row: row_key, rank, doc_id, and the arrays d1, d2 (halves of the digests), s, e, w."""

    def rows(_: list, __: list, ___: list, texts: list) -> list:
        cut = [units_of(t, unit, min_words) for t in texts]
        ends = pa.array(np.concatenate(([0], np.cumsum([len(c) for c in cut]))), pa.int32())
        halves = np.frombuffer(b"".join([u[0] for c in cut for u in c]), ">i8").reshape(-1, 2).astype(np.int64)
        places = np.array([u[1:] for c in cut for u in c], np.int32).reshape(-1, 3)
        return [pa.ListArray.from_arrays(ends, pa.array(np.ascontiguousarray(x))) for x in (*halves.T, *places.T)]

    narrow = docs.select(F.monotonically_increasing_id().alias("row_key"), (F.lit(0) if rank is None else rank).cast("long").alias("rank"), F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    return arrow_pass(narrow, rows, "d1 array<long>, d2 array<long>, s array<int>, e array<int>, w array<int>", keep=["row_key", "rank", "doc_id"])


def later_units(table: DataFrame) -> DataFrame:
    """row_key, s, kept_doc_id, kept_start of each unit of ``unit_table`` that is not the first of its digest.

    The first occurrences come from an aggregate with partial sums in each task, so a unit of a third of all documents is
    no burden there. They are written before the join, whose two sides are then exchanged for it alone: Spark splits the
    partition of such a unit, and where few units repeat it sends those to all tasks instead.
    """
    units = table.select("row_key", "rank", "doc_id", F.explode(F.arrays_zip("d1", "d2", "s")).alias("u")).select("u.d1", "u.d2", "row_key", "rank", "doc_id", "u.s")
    first = durable(units.groupBy("d1", "d2").agg(F.min(F.struct("rank", "doc_id", "s")).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("d1", "d2", "first"))
    found = units.join(first, ["d1", "d2"]).where(~F.struct("rank", "doc_id", "s").eqNullSafe(F.col("first")))
    return found.select("row_key", "s", F.col("first.doc_id").alias("kept_doc_id"), F.col("first.s").alias("kept_start"))


def repeated_units(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", unit: str = "line", min_words: int = 1, rank: Column | None = None) -> DataFrame:
    """One row for each removed occurrence: doc_id, start, end (of the unit in its text), kept_doc_id, kept_start.

    Ranked by ``rank`` (none: all equal), then doc_id, then start; the first occurrence of a digest stays, also when
    all are in one text. ``unit`` is line, paragraph or sentence; units of fewer than ``min_words`` words are left alone.
    Null or empty texts have no units; rows with a null id rank before all others; identical rows (same id and text) are
    one document, whose occurrences are named once. Empty table: no rows.
    """
    table = durable(unit_table(docs, doc_id, text, unit, min_words, rank))
    ends = table.select("row_key", "doc_id", F.explode(F.arrays_zip("s", "e")).alias("u")).select("row_key", "doc_id", "u.s", "u.e")
    return later_units(table).join(ends, ["row_key", "s"]).select("doc_id", F.col("s").alias("start"), F.col("e").alias("end"), "kept_doc_id", "kept_start").distinct()


def repeated_lines_and_paragraphs(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", min_words: int = 1, rank: Column | None = None) -> DataFrame:
    """The rows of ``repeated_units`` for lines and for paragraphs, with the column unit. Spans of the two kinds may overlap;
    ``apply_removals`` cuts what they cover together. A paragraph is compared as a whole, so one whose lines are
    broken at other places is found too."""
    each = [repeated_units(docs, doc_id, text, unit, min_words, rank).withColumn("unit", F.lit(unit)) for unit in ("line", "paragraph")]
    return each[0].unionByName(each[1])


def longest_run(hits: list[bool], words: list[int]) -> int:
    """Words of the longest run of adjacent units that are hit."""
    best = run = 0
    for hit, n in zip(hits, words, strict=True):
        run = run + n if hit else 0
        best = max(best, run)
    return best


def passage_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", unit: str = "sentence", passage_words: int = 30, rank: Column | None = None) -> DataFrame:
    """One row for each input row: doc_id, n_units, repeated_units, repeated_words, longest_words, kept, spans.

    ``spans`` names every repeated unit, of one word or more, that is not the first of its digest, as
    ``start:end:kept_doc_id:kept_start`` by start, joined by commas: what ``repeated_units`` lists. ``longest_words`` counts
    the words of the longest run of adjacent ones whose first occurrence is in another document. ``kept`` is false if that
    run has ``passage_words`` words or more, or if no unit is left: such a document repeats a passage. The limit lies
    below the passages of over 50 words that are looked for, as a passage set into another text may share its first and
    last sentence with that text. Null and empty texts have no unit and are kept; ids, ranks and repeated rows as in
    ``repeated_units`` (rows with the same id and text are one document, and each gets its row). Empty table: no rows.
    """
    table = durable(unit_table(docs, doc_id, text, unit, 1, rank))
    hits = later_units(table).groupBy("row_key").agg(F.collect_list(F.struct("s", "kept_doc_id", "kept_start")).alias("hits"))
    both = table.select("row_key", "doc_id", "s", "e", "w").join(hits, "row_key", "left")

    def rows(ids: list, starts: list, ends: list, words: list, hits: list) -> list:
        out: list[list] = [[] for _ in range(6)]
        for own, s, e, w, found in zip(ids, starts, ends, words, hits, strict=True):
            by = {h["s"]: h for h in found or ()}
            run = longest_run([x in by and by[x]["kept_doc_id"] != own for x in s], w) if by else 0
            values = (len(s), len(by), sum(n for x, n in zip(s, w, strict=True) if x in by), run, not (by and (len(by) == len(s) or run >= passage_words)), ",".join(f"{x}:{y}:{'' if by[x]['kept_doc_id'] is None else by[x]['kept_doc_id']}:{by[x]['kept_start']}" for x, y in zip(s, e, strict=True) if x in by))
            for k, v in enumerate(values):
                out[k].append(v)
        return out

    return arrow_pass(both.select("doc_id", "s", "e", "w", "hits"), rows, "n_units long, repeated_units long, repeated_words long, longest_words long, kept boolean, spans string", keep=["doc_id"])


def cut_out(text: str | None, spans: list) -> str | None:
    """``text`` without the spans and without the one line end that follows each."""
    if text is None or not spans:
        return text
    out, at = [], 0
    for s, e in sorted((x["start"], x["end"]) for x in spans):
        out.append(text[at : max(at, s)])
        at = max(at, e + 1 if text[e : e + 1] == "\n" else e)
    return "".join(out) + text[at:]


def apply_removals(docs: DataFrame, removals: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with the removed units cut out of their texts; same columns, one row for each input row."""
    found, key = "cut_spans", "cut_id"
    while found in docs.columns or key in docs.columns:  # names that the table does not have
        found, key = found + "_", key + "_"
    spans = removals.groupBy("doc_id").agg(F.collect_list(F.struct("start", "end")).alias(found)).select(F.col("doc_id").alias(key), found)
    cut = F.udf(cut_out, "string", useArrow=True)
    joined = docs.join(spans, docs[doc_id].eqNullSafe(spans[key]), "left")
    return joined.select(*[F.when(spans[found].isNull(), docs[c]).otherwise(cut(docs[c], spans[found])).alias(c) if c == text else docs[c] for c in docs.columns])
