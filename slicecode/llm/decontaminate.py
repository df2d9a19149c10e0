"""Benchmark decontamination by pigeonhole edit matching.

Each test item is cut in (error budget + 1) pieces. If a passage of a text is within the budget of an item, at
least one piece stands in it unchanged; an Aho-Corasick automaton over all pieces finds those in one scan of the
text, and Myers' bit-parallel distance verifies the passage around each hit. Items are taken in blocks of bounded
size, so that what is sent to executors does not grow with the benchmark; each block is one pass.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, slices_by_bytes

#: Characters of items that one pass takes to the executors.
BLOCK_CHARS = 4_000_000


def normalise(text: str | None) -> str:
    """Lower case, runs of white space as one space, none at the ends."""
    return " ".join((text or "").lower().split())


def budget_of(length: int, share: float) -> int:
    return int(length * share)


def pieces(item: str, budget: int) -> list[tuple[int, str]]:
    """(offset, piece): ``budget`` + 1 pieces of nearly equal length that make up ``item``."""
    m, n = len(item), min(budget, max(len(item) - 1, 0)) + 1
    cuts = [m * j // n for j in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]


@functools.lru_cache(maxsize=4096)
def _masks(pattern: str) -> dict[str, int]:
    masks: dict[str, int] = {}
    for j, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | 1 << j
    return masks


def best_match(pattern: str, text: str) -> tuple[int, int]:
    """(distance, end): the least edit distance of ``pattern`` to any substring of ``text`` and where the first such ends.

    Bit-parallel columns: vp and vn hold where the vertical difference is +1 or -1; a Python integer is as wide as
    the pattern.
    """
    m = len(pattern)
    if not m:
        return 0, 0
    masks, full, top = _masks(pattern), (1 << m) - 1, 1 << m - 1
    vp, vn, score, best, end = full, 0, m, m, 0
    get = masks.get
    for at, c in enumerate(text, 1):
        eq = get(c, 0)
        d = (((eq & vp) + vp) ^ vp) | eq | vn
        hp = vn | ~(d | vp) & full
        hn = vp & d
        if hp & top:
            score += 1
        elif hn & top:
            score -= 1
            if score < best:
                best, end = score, at
        hp = hp << 1 & full
        hn = hn << 1 & full
        vp = hn | ~(d | hp) & full
        vn = hp & d
    return best, end


def passage(pattern: str, text: str) -> tuple[int, int, int]:
    """(distance, start, end) of the best substring of ``text``; the start by matching both backwards from the end."""
    distance, end = best_match(pattern, text)
    back, length = best_match(pattern[::-1], text[:end][::-1]) if distance < len(pattern) else (distance, 0)
    return distance, end - length, end


class Matcher:
    """All items of a block: list of (item_id, normalised text)."""

    def __init__(self, items: list[tuple[int, str]], share: float) -> None:
        self.items = [(i, t, budget_of(len(t), share)) for i, t in items]
        found: dict[str, list[tuple[int, int]]] = {}
        for k, (_, t, budget) in enumerate(self.items):
            for offset, piece in pieces(t, budget):
                found.setdefault(piece, []).append((k, offset))
        self.automaton = ahocorasick.Automaton()
        for piece, where in found.items():
            self.automaton.add_word(piece, (len(piece), where))
        if found:
            self.automaton.make_automaton()
        self.empty = not found

    def matches(self, text: str | None) -> list[tuple[int, int, int, int]]:
        """(item_id, distance, start, end) of the best passage of every item that the text holds; code points of the
        original text."""
        norm = normalise(text)
        if self.empty or not norm:
            return []
        spots: dict[int, list[int]] = {}
        for last, (length, where) in self.automaton.iter(norm):
            for k, offset in where:
                spots.setdefault(k, []).append(last + 1 - length - offset)
        out = []
        for k, starts in spots.items():
            item_id, item, budget = self.items[k]
            best, window_end = (budget + 1, 0, 0), -1
            for start in sorted(starts):
                a, b = max(0, start - budget), start + len(item) + budget
                if b <= window_end:
                    continue  # the window before holds this one
                window_end = b
                d, s, e = passage(item, norm[a:b])
                if d < best[0]:
                    best = (d, a + s, a + e)
                if not d:
                    break
            if best[0] <= budget:
                out.append((item_id, best[0], *original_span(text, best[1], best[2])))
        return sorted(out)


def original_span(text: str, start: int, end: int) -> tuple[int, int]:
    """Where the span of the normalised text lies in ``text``."""
    at, to = 0, {}
    for n, m in enumerate(re.finditer(r"\S+", text)):
        at += n > 0
        low = m[0].lower()
        for x in (start, end):
            if x not in to and at <= x <= at + len(low):
                to[x] = m.start() + min(x - at, len(m[0]))
        at += len(low)
    return to.get(start, 0), to.get(end, len(text))


def item_blocks(benchmark: DataFrame, item_id: str, text: str, most: int) -> Iterator[list[tuple[int, str]]]:
    """The items in blocks of about ``most`` characters, read one block at a time. Null or blank items have nothing to find."""
    rows = benchmark.select(F.col(item_id).alias("i"), F.col(text).cast("string").alias("t")).where("i is not null and trim(coalesce(t, '')) <> ''").distinct()
    block, size = [], 0
    for r in rows.toLocalIterator():
        norm = normalise(r["t"])
        if not norm:
            continue
        block.append((r["i"], norm))
        size += len(norm)
        if size >= most:
            yield block
            block, size = [], 0
    if block:
        yield block


def contaminated_passages(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", share: float = 0.08, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """One row for each (document, item) whose best passage is within the item's budget of int(``share`` * length)
    edits on lower-cased text with single spaces: doc_id, item_id, distance, start, end, contaminated (true).

    Complete: no passage within the budget is missed. Null, empty or very long texts are searched as they are.
    Repeated items of one id count once each, repeated rows give repeated rows. An empty benchmark or table gives
    no rows. Items shorter than 1 / ``share`` characters must occur exactly.
    """
    spark = docs.sparkSession
    narrow = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    hit = "array<struct<item_id:long,distance:int,start:int,end:int>>"
    out = None
    for block in item_blocks(benchmark, item_id, item_text, block_chars):
        sent = spark.sparkContext.broadcast((block, share))  # at most block_chars characters

        def rows(_: list, texts: list, sent=sent) -> list:
            m = _matcher(sent.value)
            return [[[dict(zip(("item_id", "distance", "start", "end"), x, strict=True)) for x in m.matches(t)] for t in texts]]

        found = arrow_pass(narrow, rows, f"hits {hit}", keep=["doc_id"]).select("doc_id", F.explode("hits").alias("h")).select("doc_id", "h.*", F.lit(True).alias("contaminated"))
        out = found if out is None else out.unionByName(found)
    if out is None:
        out = narrow.where("false").select("doc_id", F.lit(0).cast("long").alias("item_id"), *[F.lit(0).alias(c) for c in ("distance", "start", "end")], F.lit(True).alias("contaminated"))
    return out


_MADE: dict[int, tuple[object, Matcher]] = {}


def _matcher(sent: tuple[list, float]) -> Matcher:
    """One automaton for each block and worker process."""
    made = _MADE.get(id(sent))
    if made is None or made[0] is not sent:
        _MADE.clear()
        made = _MADE[id(sent)] = (sent, Matcher(*sent))
    return made[1]


def without_contaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", share: float = 0.08, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows of ``docs`` that hold no passage within the budget of any item, whole and unchanged."""
    spark, out = docs.sparkSession, docs
    for block in item_blocks(benchmark, item_id, item_text, block_chars):
        sent = spark.sparkContext.broadcast((block, share))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            m = _matcher(sent.value)
            for whole in batches:
                for batch in slices_by_bytes(whole):
                    yield batch.filter(pa.array([not m.matches(t) for t in batch.column(text).to_pylist()], pa.bool_()))

        out = out.mapInArrow(run, out.schema)
    return out
