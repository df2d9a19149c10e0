"""Lossless coding of chunks: an integer arithmetic coder over quantised conditional laws, and its decoder.

A chunk is the unit of work: its context is its own, so chunks are coded in any order on any executor. Two ways:
``encode_chunks``/``decode_chunks`` carry a packed model to the executors (its size is checked first); ``encode_slots``
needs no model, as each symbol brings its slot (lo, hi, total) from a join, for models larger than memory.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a model that may travel to every executor.
MOST_PAIRS = 4_000_000


class BitWriter:
    def __init__(self) -> None:
        self.bits: list[int] = []
        self.held = 0

    def put(self, bit: int) -> None:
        """The bit, then as many of the opposite as were deferred."""
        self.bits.append(bit)
        self.bits.extend([1 - bit] * self.held)
        self.held = 0

    def packed(self) -> bytes:
        return np.packbits(np.array(self.bits, np.uint8)).tobytes()


def encode_slots_of(slots: list[tuple[int, int, int]], precision: int = 32) -> tuple[bytes, int]:
    """(code, its bits) of the slots (lo, hi, total) in order; no slot: no bit. Totals up to 2**(precision - 2)."""
    out = BitWriter()
    if not slots:
        return b"", 0
    top, half, quarter = 1 << precision, 1 << precision - 1, 1 << precision - 2
    low, width = 0, top
    for lo, hi, total in slots:
        if not 0 <= lo < hi <= total <= quarter:
            raise ValueError("slot out of range")
        low, width = low + width * lo // total, width * hi // total - width * lo // total
        while True:
            if low + width <= half:
                out.put(0)
            elif low >= half:
                out.put(1)
                low -= half
            elif low >= quarter and low + width <= half + quarter:
                out.held += 1
                low -= quarter
            else:
                break
            low, width = 2 * low, 2 * width
    out.held += 1  # one more bit names a point inside
    out.put(int(low >= quarter))
    return out.packed(), len(out.bits)


def decode_slots_of(code: bytes, bit_len: int, n: int, law, precision: int = 32) -> list[int]:
    """``n`` symbols. ``law(so_far)`` gives the cumulative integers of the next symbol; bisection finds the slot."""
    if not n:
        return []
    bits = np.unpackbits(np.frombuffer(code, np.uint8))[:bit_len].tolist()
    top, half, quarter = 1 << precision, 1 << precision - 1, 1 << precision - 2
    at = precision
    value = int("".join(map(str, (bits + [0] * precision)[:precision])), 2)
    low, width, out = 0, top, []
    for _ in range(n):
        cum = law(out)
        total = int(cum[-1])
        target = ((value - low + 1) * total - 1) // width
        k = int(np.searchsorted(cum, target, side="right")) - 1
        lo, hi = int(cum[k]), int(cum[k + 1])
        low, width = low + width * lo // total, width * hi // total - width * lo // total
        out.append(k)
        while True:
            if low + width <= half:
                shift = 0
            elif low >= half:
                shift = half
            elif low >= quarter and low + width <= half + quarter:
                shift = quarter
            else:
                break
            low, width = 2 * (low - shift), 2 * width
            value = 2 * (value - shift) + (bits[at] if at < len(bits) else 0)
            at += 1
    return out


def exact_interval(slots: list[tuple[int, int, int]]) -> tuple[Fraction, Fraction]:
    """Start and width of the interval with unbounded precision; for short chunks and tests."""
    low, width = Fraction(0), Fraction(1)
    for lo, hi, total in slots:
        low, width = low + width * Fraction(lo, total), width * Fraction(hi - lo, total)
    return low, width


@dataclass
class PackedModel:
    """Counts by context; laws are made on demand, quantised with additions, products and floors in one fixed order, so that
    encoder and decoder agree."""

    counts: dict[bytes, tuple[np.ndarray, np.ndarray]]  # context -> symbols, counts
    order: int
    alphabet: int = 256
    resolution: int = 16

    def __post_init__(self) -> None:
        self._law = functools.lru_cache(maxsize=20_000)(self._make)

    def __getstate__(self):
        return self.counts, self.order, self.alphabet, self.resolution

    def __setstate__(self, state) -> None:
        self.counts, self.order, self.alphabet, self.resolution = state
        self.__post_init__()

    def probabilities(self, context: bytes) -> np.ndarray:
        """The Witten-Bell law of a context."""
        below = np.full(self.alphabet, 1.0 / self.alphabet) if not context else None
        if context:
            below = self.probabilities(context[1:])
        found = self.counts.get(context)
        if found is None:
            return below
        t = len(found[0])
        p = t * below
        p[found[0]] += found[1]
        return p / (found[1].sum() + t)

    def _make(self, context: bytes) -> np.ndarray:
        p = self.probabilities(context)
        f = np.concatenate(([0.0], np.cumsum(p)))
        f[-1] = 1.0
        return np.floor(np.minimum(f, 1.0) * ((1 << self.resolution) - self.alphabet)).astype(np.int64) + np.arange(self.alphabet + 1)

    def cumulative(self, so_far) -> np.ndarray:
        context = bytes(so_far[-self.order :]) if self.order else b""
        return self._law(context)

    def slots(self, symbols: bytes) -> list[tuple[int, int, int]]:
        out = []
        for k, s in enumerate(symbols):
            cum = self._law(symbols[max(0, k - self.order) : k] if self.order else b"")
            out.append((int(cum[s]), int(cum[s + 1]), int(cum[-1])))
        return out

    def ideal_bits(self, symbols: bytes) -> float:
        total = 0.0
        for k, s in enumerate(symbols):
            total -= float(np.log2(self.probabilities(symbols[max(0, k - self.order) : k] if self.order else b"")[s]))
        return total


def pack(counts: DataFrame, order: int, resolution: int = 16, most: int = MOST_PAIRS) -> PackedModel:
    """The model (depth, ctx in hexadecimals, sym, cnt) as arrays; refused if it has more than ``most`` pairs: then use slots."""
    rows = counts.where(F.col("depth") <= order).select("ctx", "sym", "cnt").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} pairs: too large to carry, attach slots by a join instead")
    by: dict[bytes, list[tuple[int, int]]] = {}
    for ctx, sym, cnt in rows:
        by.setdefault(bytes.fromhex(ctx), []).append((int(sym, 16), cnt))
    return PackedModel({c: (np.array([s for s, _ in sorted(v)]), np.array([n for _, n in sorted(v)], float)) for c, v in by.items()}, order, resolution=resolution)


def encode_chunks(chunks: DataFrame, model: PackedModel, keep: list[str], data: str = "data", precision: int = 32) -> DataFrame:
    """``keep``, n, bit_len, code, ideal_bits (of the unquantised law), slot_bits (of the quantised one)."""
    sent = chunks.sparkSession.sparkContext.broadcast(model)
    schema = ", ".join(f"{c} {chunks.schema[c].dataType.simpleString()}" for c in keep) + ", n int, bit_len long, code binary, ideal_bits double, slot_bits double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            rows = [x or b"" for x in b.column(data).to_pylist()]
            slots = [m.slots(x) for x in rows]
            made = [encode_slots_of(s, precision) for s in slots]
            cols = [b.column(c) for c in keep] + [pa.array([len(x) for x in rows], pa.int32()), pa.array([k for _, k in made], pa.int64()), pa.array([c for c, _ in made], pa.binary()), pa.array([m.ideal_bits(x) for x in rows], pa.float64()), pa.array([float(-sum(np.log2((h - l) / t) for l, h, t in s)) for s in slots], pa.float64())]
            yield pa.RecordBatch.from_arrays(cols, names=[*keep, "n", "bit_len", "code", "ideal_bits", "slot_bits"])

    return chunks.select(*keep, data).mapInArrow(run, schema)


def gram_slots(model: PackedModel, rows: list[bytes]) -> tuple[np.ndarray, ...]:
    """lo, hi, total, ideal cost and slot cost of every symbol of the rows, end to end. A distinct gram is looked up once, so laws are
    made once for each context in turn."""
    x = np.frombuffer(b"".join(rows), np.uint8).astype(np.int64)
    pos = np.concatenate([np.arange(len(r)) for r in rows]) if rows else np.zeros(0, np.int64)
    grams = np.ones(len(x), np.int64)  # a one, the context's bytes, the symbol
    if model.order > 6:
        raise ValueError("contexts of up to six bytes")
    for k in range(model.order, 0, -1):
        before = np.concatenate((np.zeros(min(k, len(x)), np.int64), x[: max(0, len(x) - k)]))
        grams = np.where(pos >= k, grams << 8 | before, grams)
    keys, where = np.unique(grams << 8 | x, return_inverse=True)
    lo, hi, total, p = (np.zeros(len(keys), kind) for kind in (np.int64, np.int64, np.int64, float))
    last = None
    for k, key in enumerate(keys.tolist()):
        if key >> 8 != last:
            last = key >> 8
            context = last.to_bytes((last.bit_length() + 7) // 8, "big")[1:]
            cum, law = model.cumulative(context), model.probabilities(context)
        s = key & 255
        lo[k], hi[k], total[k], p[k] = cum[s], cum[s + 1], cum[-1], law[s]
    return lo[where], hi[where], total[where], -np.log2(p)[where], -np.log2((hi - lo) / total)[where]


def lengths_of(lo: np.ndarray, hi: np.ndarray, total: np.ndarray, ns: np.ndarray, precision: int = 32) -> np.ndarray:
    """Bits of the codes that ``encode_slots_of`` writes for chunks of ``ns`` symbols, whose slots lie end to end.

    The same integers, a position of all chunks at a time: every doubling of the interval is one bit, now or deferred, and two more
    end a code. After the leading bits that both ends share, the doublings are the bits from the second on that are one in the
    lower end and zero in the upper one."""
    if len(lo) and not ((lo >= 0) & (lo < hi) & (hi <= total) & (total <= 1 << precision - 2)).all():
        raise ValueError("slot out of range")
    by = np.argsort(-ns, kind="stable")
    starts, alive = (np.cumsum(ns) - ns)[by], ns[by]
    low, width, bits = np.zeros(len(ns), np.int64), np.full(len(ns), 1 << precision, np.int64), np.where(alive > 0, 2, 0)
    top, half = (1 << precision) - 1, (1 << precision - 1) - 1
    length = lambda v: np.frexp(v.astype(float))[1].astype(np.int64)  # noqa: E731  exact below 2**53
    for k in range(int(ns.max(initial=0))):
        n = int(np.searchsorted(-alive, -k, side="left"))  # chunks longer than k
        at = starts[:n] + k
        below = width[:n] * lo[at] // total[at]
        w, x = width[:n] * hi[at] // total[at] - below, low[:n] + below
        shared = precision - length(x ^ (x + w - 1))
        x, w = (x << shared) & top, w << shared
        middle = precision - 1 - length(~(x & ~(x + w - 1)) & half)
        low[:n], width[:n] = (x << middle) & half, w << middle
        bits[:n] += shared + middle
    out = np.empty(len(ns), np.int64)
    out[by] = bits
    return out


def code_lengths(chunks: DataFrame, model: PackedModel, keep: list[str], precisions: tuple[int, ...], data: str = "data", at_once: int = 2048) -> DataFrame:
    """``keep``, n, ideal_bits, slot_bits as ``encode_chunks`` has them, and bit_lens: a code's bits at each of the precisions. The
    slots are looked up once for all of them, ``at_once`` chunks at a time."""
    sent = chunks.sparkSession.sparkContext.broadcast(model)
    schema = ", ".join(f"{c} {chunks.schema[c].dataType.simpleString()}" for c in keep) + ", n int, ideal_bits double, slot_bits double, bit_lens array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, at_once):
                b = whole.slice(start, at_once)
                rows = [x or b"" for x in b.column(data).to_pylist()]
                ns = np.array([len(x) for x in rows], np.int64)
                lo, hi, total, ideal, slot = gram_slots(sent.value, rows)
                chunk = np.repeat(np.arange(len(rows)), ns)
                bits = np.stack([lengths_of(lo, hi, total, ns, p) for p in precisions], axis=1)
                ends = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * len(precisions))
                made = [pa.array(ns, pa.int32()), *(pa.array(np.bincount(chunk, c, len(rows))) for c in (ideal, slot)), pa.ListArray.from_arrays(ends, pa.array(bits.ravel()))]
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), *made], names=[*keep, "n", "ideal_bits", "slot_bits", "bit_lens"])

    return chunks.select(*keep, data).mapInArrow(run, schema)


def decode_chunks(codes: DataFrame, model: PackedModel, keep: list[str], precision: int = 32) -> DataFrame:
    """``keep`` and data: the chunks again."""
    sent = codes.sparkSession.sparkContext.broadcast(model)
    schema = ", ".join(f"{c} {codes.schema[c].dataType.simpleString()}" for c in keep) + ", data binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            got = [bytes(decode_slots_of(c, k, n, m.cumulative, precision)) for c, k, n in zip(b.column("code").to_pylist(), b.column("bit_len").to_pylist(), b.column("n").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(c) for c in keep] + [pa.array(got, pa.binary())], names=[*keep, "data"])

    return codes.select(*keep, "n", "bit_len", "code").mapInArrow(run, schema)


def encode_slots(tokens: DataFrame, key: list[str], precision: int = 32, at_once: int = 64) -> DataFrame:
    """``key``, n, bit_len, code, slot_bits (the slots' own cost) from tokens that bring their slots: pos, lo, hi, total. A chunk bounds
    what is gathered; a task holds the numbers of ``at_once`` chunks, four integers a symbol in an Arrow batch."""
    kind = "int" if precision <= 32 else "long"  # totals are up to 2**(precision - 2)
    slot = F.struct(F.col("pos").cast("int").alias("pos"), *[F.col(c).cast(kind).alias(c) for c in ("lo", "hi", "total")])
    rows = tokens.groupBy(*key).agg(F.sort_array(F.collect_list(slot)).alias("slots"))
    schema = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in key) + ", n int, bit_len long, code binary, slot_bits double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, at_once):
                b = whole.slice(start, at_once)
                lists = b.column("slots")
                ends = np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy())))
                lo, hi, total = (lists.flatten().field(c).to_numpy() for c in ("lo", "hi", "total"))
                cost = -np.log2((hi - lo) / total)
                made = [encode_slots_of(list(zip(lo[i:j].tolist(), hi[i:j].tolist(), total[i:j].tolist(), strict=True)), precision) for i, j in zip(ends[:-1], ends[1:], strict=True)]
                cols = [pa.array(np.diff(ends), pa.int32()), pa.array([k for _, k in made], pa.int64()), pa.array([c for c, _ in made], pa.binary()), pa.array([float(cost[i:j].sum()) for i, j in zip(ends[:-1], ends[1:], strict=True)])]
                yield pa.RecordBatch.from_arrays([b.column(c) for c in key] + cols, names=[*key, "n", "bit_len", "code", "slot_bits"])

    return rows.mapInArrow(run, schema)


def concat_codes(codes: DataFrame, stream: list[str], order: str = "chunk_no", per_segment: int = 1024) -> DataFrame:
    """Byte-aligned chunk codes joined in segments of ``per_segment`` chunks: ``stream``, segment, chunks, bit_lens, ns, code.
    Never one row for a stream: segments bound a row's size."""
    cut = codes.withColumn("segment", F.floor(F.col(order) / per_segment).cast("int"))
    parts = F.sort_array(F.collect_list(F.struct(F.col(order).alias("o"), "n", "bit_len", "code")))
    got = cut.groupBy(*stream, "segment").agg(parts.alias("p"))
    joined = F.unhex(F.array_join(F.transform("p", lambda x: F.hex(x["code"])), ""))
    return got.select(*stream, "segment", F.size("p").alias("chunks"), F.col("p.bit_len").alias("bit_lens"), F.col("p.n").alias("ns"), joined.alias("code"))


def split_codes(segments: DataFrame, stream: list[str], per_segment: int = 1024) -> DataFrame:
    """The chunk codes of ``concat_codes`` again."""
    sizes = F.transform("bit_lens", lambda b: F.ceil(b / 8).cast("int"))
    base = segments.select("*", sizes.alias("sizes"))
    each = base.select(*stream, "segment", "code", "sizes", "bit_lens", "ns", F.explode(F.sequence(F.lit(0), F.size("sizes") - 1)).alias("k"))
    start = F.aggregate(F.slice("sizes", F.lit(1), F.col("k")), F.lit(0), lambda a, x: a + x)
    return each.select(*stream, (F.col("segment") * per_segment + F.col("k")).alias("chunk_no"), F.get("ns", F.col("k")).alias("n"), F.get("bit_lens", F.col("k")).alias("bit_len"), F.substring("code", start + 1, F.get("sizes", F.col("k"))).alias("code"))
