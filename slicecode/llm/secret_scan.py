"""Secret scans: fixed patterns, and a guess-cost estimate for values in a credential context.

The estimate is the cheapest way for an attacker to spell a value: a dynamic program splits it into dictionary words
(also capitalised, with digits for letters, reversed), dates, repeats, sequences, keyboard walks and brute-force
spans, and adds the log10 of the guesses of each. A value that no cheap split explains is reported as a secret; the cost
alone decides, at every length.

The dictionary is a short list of common passwords, and the words of the corpus itself: all words of all texts are
counted, values of a credential context aside, and those that make up at least a stated share of them are ranked. A share
of 1 / n admits n words at most, however large the corpus is.
"""

from __future__ import annotations

import hashlib
import math
import re
import string
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, durable, slices_by_bytes

KINDS = ("assign", "access", "hex", "guess")
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
#: A credential word, a sign that gives it a value, and the value.
CONTEXT = re.compile(
    r"(?:pass(?:word|wd|phrase|code)?|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|credentials?|auth(?:orization)?)[\"']?\x20*(?:=>|:=|[:=]|\bis\b)\x20*(?:bearer\x20+|basic\x20+)?[\"']?([^\s\"'<>,;]+)",
    re.IGNORECASE | re.ASCII,
)
ADDRESS = re.compile(r"://[^\s/:@]+:([^\s/@]+)@")
#: A text without any of these (lower case) has no match of ASSIGN, or of CONTEXT.
ASSIGN_HINTS = ("password", "passwd", "secret", "token", "apikey", "api_key")
CONTEXT_HINTS = ("pass", "pwd", "secret", "token", "key", "credential", "auth")
#: Common words of passwords, most frequent first (fixed values).
WORDS = (
    "password", "qwerty", "admin", "welcome", "letmein", "login", "secret", "master", "hello", "dragon", "monkey", "football", "baseball", "sunshine", "princess", "shadow",
    "superman", "batman", "trustno", "iloveyou", "starwars", "whatever", "freedom", "ninja", "access", "flower", "love", "test", "guest", "root", "user", "default", "change",
    "changeme", "pass", "passwd", "token", "key", "example", "sample", "demo", "temp", "null", "none", "true", "false", "undefined", "placeholder", "redacted", "required",
    "optional", "value", "string", "your", "here", "my", "the", "and", "for", "with", "this", "that", "from", "incorrect", "invalid", "missing", "expired", "unknown", "empty",
    "summer", "winter", "spring", "autumn", "monday", "friday", "january", "october", "server", "database", "system", "public", "private", "client", "github", "google",
    "computer", "internet", "service", "account", "company", "office", "house", "money", "angel", "tiger", "michael", "jordan", "charlie", "thomas", "robert", "daniel",
)
KEY_ROWS = ("1234567890", "qwertyuiop", "asdfghjkl", "zxcvbnm")
LEET = str.maketrans("430157@$!", "aeoistasi")
#: A word of the corpus is in the dictionary if one of so many words of the corpus is that word, or more.
ONE_IN = 50_000
#: Repeats are sought with periods up to this one, and with the whole value's own smallest period.
LONGEST_PERIOD = 4096


#: Where each key lies; a row is shifted by half a key against the one above.
PLACES = {c: (2 * x + y, y) for y, row in enumerate(KEY_ROWS) for x, c in enumerate(row)}
_DATES = (re.compile(r"(?:19|20)\d\d"), re.compile(r"(?:19|20)\d\d([-/.]?)(?:1[0-2]|0?[1-9])\1(?:[12]\d|3[01]|0?[1-9])"), re.compile(r"(?:[12]\d|3[01]|0?[1-9])([-/.]?)(?:1[0-2]|0?[1-9])\1(?:(?:19|20)\d\d|\d\d)"))


@dataclass(frozen=True)
class Part:
    kind: str
    start: int
    end: int
    cost: float


class Dictionary:
    """Ranked words, the common passwords first; finds all of them in a value in one pass."""

    def __init__(self, words: Iterable[str] = ()) -> None:
        self.words = list(dict.fromkeys((*WORDS, *words)))
        self._found = None

    def __getstate__(self) -> list[str]:
        return self.words

    def __setstate__(self, words: list[str]) -> None:
        self.words, self._found = words, None

    def inside(self, value: str) -> Iterator[tuple[int, int, int]]:
        """(start, end, rank) of every occurrence of every word of three characters or more."""
        if self._found is None:
            self._found = ahocorasick.Automaton()
            for rank, word in enumerate(self.words, 1):
                if len(word) > 2:
                    self._found.add_word(word, (len(word), rank))
            self._found.make_automaton()
        for last, (n, rank) in self._found.iter(value):
            yield last + 1 - n, last + 1, rank


COMMON = Dictionary()


def _lower(value: str) -> str:
    """Lower case, character by character, so that places stay."""
    low = value.lower()
    return low if len(low) == len(value) else "".join(c.lower() if len(c.lower()) == 1 else c for c in value)


def _case_cost(raw: str) -> float:
    upper = sum(c.isupper() for c in raw)
    if not upper:
        return 0.0
    if raw[0].isupper() and upper == 1 or upper == len(raw):
        return math.log10(2)
    return math.log10(sum(math.comb(len(raw), k) for k in range(1, min(upper, len(raw) - upper) + 1)) or 2)


def _word_parts(value: str, known: Dictionary) -> list[Part]:
    low, n, two = _lower(value), len(value), math.log10(2)
    plain = low.translate(LEET)
    best: dict[tuple[int, int], float] = {}
    for s, e, rank in known.inside(low):
        best[s, e] = math.log10(rank)
    if plain != low:
        for s, e, rank in known.inside(plain):
            swapped = sum(a != b for a, b in zip(low[s:e], plain[s:e], strict=True))
            best[s, e] = min(best.get((s, e), math.inf), math.log10(rank) + two * (1 + swapped))
    for s, e, rank in known.inside(low[::-1]):
        at = (n - e, n - s)
        best[at] = min(best.get(at, math.inf), math.log10(rank) + two)
    return [Part("word", s, e, max(cost + _case_cost(value[s:e]), two)) for (s, e), cost in best.items()]


def _repeats(value: str) -> list[tuple[int, int, int]]:
    """(start, end, period) of the spans that are one block twice or more, each as long as it goes, of the smallest period."""
    n, out = len(value), []
    codes = np.frombuffer(value.encode("utf-32-le", "surrogatepass"), np.uint32)
    for period in range(1, min(n // 2, LONGEST_PERIOD) + 1):
        same = codes[:-period] == codes[period:]
        if np.count_nonzero(same) < period:
            continue
        borders = np.flatnonzero(np.diff(np.concatenate(([0], same.view(np.int8), [0])))).tolist()
        for a, b in zip(borders[::2], borders[1::2], strict=True):
            if b - a >= period and not any(period % q == 0 and s <= a and b + period <= e + q for s, e, q in out):
                out.append((a, a + (b - a + period) // period * period, period))
    whole = (value + value).find(value, 1)
    if LONGEST_PERIOD < whole < n:
        out.append((0, n, whole))
    return out


def _run_parts(value: str, known: Dictionary) -> list[Part]:
    """Keyboard walks, sequences of codes, repeats of a block."""
    out, n, low = [], len(value), _lower(value)
    i = 0
    while i < n - 2:  # keyboard walks
        j, turns, last = i + 1, 0, None
        while j < n and low[j] in PLACES and low[j - 1] in PLACES:
            (x, y), (u, v) = PLACES[low[j - 1]], PLACES[low[j]]
            way = (u - x, v - y)
            if way == (0, 0) or abs(way[0]) > 2 or abs(way[1]) > 1:
                break
            turns, last, j = turns + (way != last), way, j + 1
        if j - i >= 3:
            out.append(Part("walk", i, j, math.log10(40 * (j - i)) + turns * math.log10(3)))
        i = j if j - i >= 3 else i + 1
    i = 0
    while i < n - 2:  # abc, 321, 2468
        step, j = ord(value[i + 1]) - ord(value[i]), i + 1
        while j < n and ord(value[j]) - ord(value[j - 1]) == step:
            j += 1
        if j - i >= 3 and 0 < abs(step) <= 5:
            out.append(Part("sequence", i, j, math.log10((26 if value[i].isalpha() else 10) * (j - i) * (1 if step > 0 else 2))))
        i = max(j - 1, i + 1)
    for start, end, period in _repeats(value):
        one = guess_cost(value[start : start + period], known)[0]
        out.append(Part("repeat", start, end, max(one, 0.3) + math.log10((end - start) // period)))
    return out


def guess_cost(value: str, known: Dictionary = COMMON) -> tuple[float, list[Part]]:
    """(log10 of the guesses, the cheapest split). Brute force costs a factor of ten for each character.

    Work is linear in the length, but for the search for repeats: one vector comparison for each period.
    """
    n = len(value)
    ends: dict[int, list[Part]] = {}
    for p in _word_parts(value, known) + _run_parts(value, known):
        ends.setdefault(p.end, []).append(p)
    for i in range(n):
        for date in _DATES if value[i].isdigit() else ():
            if m := date.match(value, i):
                ends.setdefault(m.end(), []).append(Part("date", i, m.end(), math.log10(119 if len(m[0]) == 4 else 119 * 365) + (math.log10(4) if m.lastindex and m[1] else 0)))
    best: list[tuple[float, Part | None]] = [(0.0, None)]
    for j in range(1, n + 1):
        cost, part = best[j - 1][0] + 1.0, None
        for p in ends.get(j, ()):
            if best[p.start][0] + p.cost < cost:
                cost, part = best[p.start][0] + p.cost, p
        best.append((cost, part))
    parts, j = [], n
    while j:
        p = best[j][1] or Part("brute", j - 1, j, 1.0)
        if parts and p.kind == parts[-1].kind == "brute":
            parts[-1] = Part("brute", p.start, parts[-1].end, p.cost + parts[-1].cost)
        else:
            parts.append(p)
        j = p.start
    return best[n][0], parts[::-1]


def running_words(texts: list[str | None]) -> Counter:
    """How often each word of three letters or more (lower case) is in the texts, credential values left out."""
    raw: Counter = Counter()
    for t in texts:
        low = (t or "").lower()
        raw.update((CONTEXT.sub(" ", low) if any(h in low for h in CONTEXT_HINTS) else low).split())
    out: Counter = Counter()
    for w, n in raw.items():
        w = w.strip(string.punctuation)
        if len(w) > 2 and w.isalpha():
            out[w] += n
    return out


def learn_words(docs: DataFrame, text: str = "text", one_in: int = ONE_IN) -> Dictionary:
    """The dictionary of a corpus: every word that makes up 1 / ``one_in`` of all words or more, the most frequent first.

    All texts are counted; partial counts leave a task, and at most ``one_in`` words reach the driver.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices_by_bytes(whole, 32 << 20):
                found = running_words(batch.column(0).to_pylist())
                yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.string()), pa.array(found.values(), pa.int64())], names=["word", "n"])

    counts = durable(docs.select(F.col(text).cast("string").alias("text")).where("text is not null").mapInArrow(run, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    often = counts.where(F.col("n") * one_in >= F.lit(total)).collect()
    return Dictionary([r["word"] for r in sorted(often, key=lambda r: (-r["n"], r["word"]))])


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind's place in KINDS, start, end) of the fixed patterns, leftmost and without overlap in each kind."""
    low, out = text.lower(), []
    if any(h in low for h in ASSIGN_HINTS):
        out += [(0, m.start(), m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
    if "AKIA" in text:
        out += [(1, m.start(), m.end()) for m in ACCESS.finditer(text)]
    return out + [(2, m.start(), m.end()) for m in HEX.finditer(text)]


def guess_spans(text: str, base: list[tuple[int, int, int]], least_cost: float, known: Dictionary = COMMON) -> list[tuple[int, int, int]]:
    """Values of a credential context that cost at least 10**``least_cost`` guesses.

    A value that one base span covers whole is named already and not named again; one that a base span covers in part is
    named whole. Values of fewer than ``least_cost`` characters cannot cost as much.
    """
    low, out = text.lower(), set()
    found = list(CONTEXT.finditer(text)) if any(h in low for h in CONTEXT_HINTS) else []
    if "://" in text:
        found += ADDRESS.finditer(text)
    for m in found:
        value = m[1].rstrip(".)]}!?")
        start, end = m.start(1), m.start(1) + len(value)
        if len(value) >= least_cost and not any(s <= start and end <= e for _, s, e in base) and guess_cost(value, known)[0] >= least_cost:
            out.add((3, start, end))
    return sorted(out)


def spans_of(text: str | None, least_cost: float = 8.0, known: Dictionary = COMMON) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base spans, all spans), each by start and then kind."""
    by = lambda x: (x[1], x[0], x[2])
    base = base_spans(text or "")
    return sorted(base, key=by), sorted(base + guess_spans(text or "", base, least_cost, known), key=by)


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for k, s, e in spans)


def scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", least_cost: float = 8.0, known: Dictionary | None = None) -> DataFrame:
    """One row for each input row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_guess.

    Spans are in code points of the text, end exclusive, ``kind:start:end`` joined by commas. Null text counts as
    empty: no spans, the checksum of the empty string. Repeated rows give repeated rows; an empty table none. ``known``:
    the dictionary; none: that of ``docs`` (``learn_words``).
    """
    sent = docs.sparkSession.sparkContext.broadcast(learn_words(docs, text) if known is None else known)  # ONE_IN words at most

    def rows(_: list, texts: list) -> list:
        out: list[list] = [[] for _ in range(6)]
        for t in texts:
            base, every = spans_of(t, least_cost, sent.value)
            for k in range(3):
                out[k].append(sum(x[0] == k for x in base))
            out[3].append(hashlib.sha256(joined(base).encode()).hexdigest())
            out[4].append(joined(every))
            out[5].append(len(every) - len(base))
        return out

    narrow = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    return arrow_pass(narrow, rows, "n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_guess long", keep=["doc_id"])


def redact(text: str | None, mask: str = "[secret]", least_cost: float = 8.0, known: Dictionary = COMMON) -> str | None:
    """``text`` with every span, overlapping ones as one, replaced by ``mask``."""
    if text is None:
        return None
    out, at = [], 0
    for _, s, e in spans_of(text, least_cost, known)[1]:
        if s >= at:
            out += [text[at:s], mask]
        at = max(at, e)
    return "".join(out) + text[at:]


def redacted(docs: DataFrame, text: str = "text", n_chars: str | None = "n_chars", least_cost: float = 8.0, known: Dictionary | None = None) -> DataFrame:
    """``docs`` with secrets masked in ``text``; ``n_chars``, where there is such a column, follows for changed rows."""
    sent = docs.sparkSession.sparkContext.broadcast(learn_words(docs, text) if known is None else known)
    masked = F.udf(lambda t: redact(t, least_cost=least_cost, known=sent.value), "string", useArrow=True)
    if n_chars not in docs.columns:
        return docs.withColumn(text, masked(F.col(text)))
    both = docs.select(*[F.struct(docs[text], masked(docs[text]).alias("masked")).alias(text) if c == text else docs[c] for c in docs.columns])
    changed = ~F.col(f"{text}.masked").eqNullSafe(F.col(f"{text}.{text}"))
    length = F.when(changed, F.length(f"{text}.masked")).otherwise(F.col(n_chars)).cast(docs.schema[n_chars].dataType)
    return both.select(*[F.col(f"{text}.masked").alias(c) if c == text else length.alias(c) if c == n_chars else F.col(c) for c in docs.columns])
