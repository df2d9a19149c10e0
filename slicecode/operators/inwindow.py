"""Laws that learn inside their window, counted where the sequence lies.

A row holds its whole sequence, so how often a symbol came before inside a window is counted in one Arrow pass with numpy;
only a total for each row and setting leaves it. Costs are the same whole micro-bits as those of the relational form
(``windows.chunk_counts``, ``windows.sliding_counts``), which shuffles every symbol and stays as the reference.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Positions that are counted at a time; windows reach back over the border.
SEGMENT = 1 << 20
#: Pairs of a static law that may be sent to all tasks (24 bytes a pair and law); a larger one is joined instead.
MOST_PAIRS = 1 << 21


@dataclass(frozen=True)
class Setting:
    """A window of ``size`` symbols that moves by ``step`` (0: no window, the whole row). ``order`` 0 or 1: the context of the
    counts. With ``law`` (a column of the packed law) they refine that static law, which weighs ``strength`` symbols."""

    name: str
    size: int
    step: int = 0
    order: int = 0
    law: str | None = None
    strength: float = 64.0

    def since(self, pos: np.ndarray) -> np.ndarray:
        """The first position of the window that scores ``pos``."""
        if not self.size:
            return np.zeros_like(pos)
        step = self.step or self.size
        return np.maximum(0, pos // step * step - (self.size - step))


class Earlier:
    """Answers how often the key at each position came before it, from a given position on."""

    def __init__(self, keys: np.ndarray) -> None:
        self.keys, self.n = keys, len(keys)
        order = np.argsort(keys, kind="stable")
        self.places = keys[order] * (self.n + 1) + order
        self.at = np.empty(self.n, np.int64)
        self.at[order] = np.arange(self.n)

    def count(self, since: np.ndarray) -> np.ndarray:
        return self.at - np.searchsorted(self.places, self.keys * (self.n + 1) + since)


@dataclass
class PackedLaw:
    """Probabilities of (context, symbol) by sorted keys: a one, the context's bytes, the symbol."""

    order: int
    keys: np.ndarray
    p: dict[str, np.ndarray]

    def find(self, x: np.ndarray, first: int) -> np.ndarray:
        """Place of each position of ``x`` from ``first`` on."""
        pos = np.arange(len(x))
        ctx = np.ones(len(x), np.int64)
        for k in range(self.order, 0, -1):
            before = np.concatenate((np.zeros(min(k, len(x)), np.int64), x[: max(0, len(x) - k)]))
            ctx = np.where(pos >= k, ctx << 8 | before, ctx)
        key = (ctx << 8 | x)[first:]
        at = np.searchsorted(self.keys, key)
        if len(key) and not (self.keys[np.minimum(at, len(self.keys) - 1)] == key).all():
            raise KeyError("a gram that the law does not have")
        return at


def pack_law(law: DataFrame, order: int, columns: list[str]) -> PackedLaw | None:
    """The law (ctx, sym in hexadecimals, and ``columns``) for the driver to send, or None if it has more than MOST_PAIRS rows."""
    rows = law.select(F.conv(F.concat(F.lit("1"), "ctx", "sym"), 16, 10).cast("long").alias("key"), *columns).limit(MOST_PAIRS + 1).toArrow()
    if rows.num_rows > MOST_PAIRS:
        return None
    keys = rows.column("key").to_numpy()
    by = np.argsort(keys)
    return PackedLaw(order, keys[by], {c: rows.column(c).to_numpy()[by] for c in columns})


def _micro(p: np.ndarray) -> int:
    return int(np.floor(-np.log2(p) * 1e6 + 0.5).astype(np.int64).sum())


def row_costs(raw: bytes, settings: list[Setting], law: PackedLaw | None = None, segment: int = SEGMENT) -> list[tuple[int, int, int]]:
    """(micro-bits, nanoseconds, bytes of counting state) of one row under each setting."""
    x = np.frombuffer(raw, np.uint8).astype(np.int64) if len(raw) <= segment else np.frombuffer(raw, np.uint8)
    widest = max((s.size for s in settings), default=0)
    totals, spent, state = [0] * len(settings), [0] * len(settings), [0] * len(settings)
    carried = {0: np.zeros(256, np.int64), 1: np.zeros(257 * 256, np.int64)} if any(not s.size for s in settings) and len(raw) > segment else None
    for a in range(0, len(raw), segment):
        lo = max(0, a - widest)
        part = x[lo : a + segment].astype(np.int64)
        pos = np.arange(lo, lo + len(part))
        first = a - lo
        if law is not None:
            back = min(a, law.order)
            places = law.find(x[a - back : a + segment].astype(np.int64), back)
        symbols = Earlier(part) if any(s.order == 0 for s in settings) else None
        pairs: dict[int, tuple[np.ndarray, Earlier, Earlier]] = {}
        for k, s in enumerate(settings):
            began = time.perf_counter_ns()
            since = np.maximum(s.since(pos) - lo, 0)
            if s.order == 0:
                n_w, m = symbols.count(since), pos - s.since(pos)
                used = symbols.n * 24
                if carried is not None and not s.size:
                    inside = Earlier(part[first:])
                    n_w = np.concatenate((np.zeros(first, np.int64), inside.count(np.zeros(inside.n, np.int64)) + carried[0][part[first:]]))
            else:
                border = s.size or (1 << 62)
                if border not in pairs:  # at a border there is no context
                    before = np.concatenate(([256 if lo == 0 else int(x[lo - 1])], part[:-1])) if len(part) else part
                    ctx = np.where(pos % border == 0, 256, before)
                    pairs[border] = ctx * 256 + part, Earlier(ctx * 256 + part), Earlier(ctx)
                keys, both, alone = pairs[border]
                n_w, m = both.count(since), alone.count(since)
                used = both.n * 48
                if carried is not None and not s.size:
                    raise ValueError("order 1 without a window takes rows of one segment")
            n_w, m = n_w[first:], m[first:]
            if s.law is None:
                p = (n_w + 0.5) / (m + 128.0)
            else:
                p = (n_w + s.strength * law.p[s.law][places]) / (m + s.strength)
            totals[k] += _micro(p)
            spent[k] += time.perf_counter_ns() - began
            state[k] = max(state[k], used if not s.size else min(used, s.size * (24 if s.order == 0 else 48)))
        if carried is not None:
            carried[0] += np.bincount(part[first:], minlength=256)
    return list(zip(totals, spent, state, strict=True))


def window_costs(rows: DataFrame, keep: list[str], body: str, settings: list[Setting], law: PackedLaw | None = None) -> DataFrame:
    """``keep``, config, n (bytes), micro, nanos, state_bytes: one row for each input row and setting, summed by the caller.

    ``body`` is a text or binary. A null or empty one has no byte, so n and micro are 0. Columns of ``rows`` other than ``keep`` and ``body`` are not read. Memory is
    bounded by one text and one segment of it.
    """
    sent = rows.sparkSession.sparkContext.broadcast(law)  # MOST_PAIRS rows at most
    raw = F.col(body) if isinstance(rows.schema[body].dataType, T.BinaryType) else F.encode(F.col(body), "UTF-8")
    narrow = rows.select(*keep, raw.alias("_raw"))
    types = T.StructType([narrow.schema[c] for c in keep] + list(T.StructType.fromDDL("config string, n long, micro long, nanos long, state_bytes long")))
    out = to_arrow_schema(types, prefers_large_types=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raws, found = batch.column("_raw"), []
            for k in range(batch.num_rows):
                raw = raws[k].as_py() or b""
                found += [(s.name, len(raw), *c) for s, c in zip(settings, row_costs(raw, settings, sent.value) if raw else [(0, 0, 0)] * len(settings), strict=True)]
            index = pa.array(np.repeat(np.arange(batch.num_rows), len(settings)))
            made = [pa.array([f[j] for f in found]) for j in range(5)]
            yield pa.RecordBatch.from_arrays([*[batch.column(c).take(index) for c in keep], *[a.cast(f.type) for a, f in zip(made, list(out)[len(keep) :], strict=True)]], schema=out)

    return narrow.mapInArrow(run, types)
