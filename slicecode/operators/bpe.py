"""Byte-pair merges: learned from pair counts over all distinct words of a corpus, applied by rank. Lossless by construction."""

from __future__ import annotations

import functools
import itertools
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicecode.operators import words


def word_counts(df: DataFrame, col: str) -> DataFrame:
    """w, n of every distinct word; null texts have none. Counted where the rows lie: a task sends a row for each of its distinct words."""
    run = words.counter(df.sparkSession, words.counted)
    return df.select(F.encode(col, "UTF-8").alias("_d")).mapInArrow(run, "w string, n long").groupBy("w").agg(F.sum("n").alias("n"))


class Merger:
    """Vocabulary and ranks of a list of merges; splits words and joins ids."""

    def __init__(self, merges: list[tuple[bytes, bytes]]) -> None:
        self.rank = {p: k for k, p in enumerate(merges)}
        self.vocabulary = [bytes([b]) for b in range(256)] + [a + b for a, b in merges]
        self.ids = {}
        for k, piece in enumerate(self.vocabulary):
            self.ids.setdefault(piece, k)
        self.word = functools.lru_cache(maxsize=1 << 17)(self._word)

    def __getstate__(self):
        return list(self.rank)

    def __setstate__(self, merges) -> None:
        self.__init__(merges)

    def pieces(self, word: str) -> list[bytes]:
        """The word's bytes, the merge of the lowest rank applied again and again, leftmost first."""
        p, rank, none = [bytes([b]) for b in word.encode()], self.rank.get, len(self.rank)
        while len(p) > 1:
            ranks = [rank(pair, none) for pair in zip(p, p[1:], strict=False)]
            best = min(ranks)
            if best == none:
                break
            k = ranks.index(best)
            p[k : k + 2] = [p[k] + p[k + 1]]
        return p

    def _word(self, word: str) -> tuple[int, ...]:
        return tuple(self.ids[x] for x in self.pieces(word))

    def decode(self, ids) -> str:
        return b"".join(self.vocabulary[i] for i in ids).decode("utf-8", "replace")

    @functools.cached_property
    def table(self) -> Table:
        return Table(self)


class Table:
    """A ``Merger`` as arrays, for many words at once. Words are ids of pieces, each word closed by -1."""

    def __init__(self, merger: Merger) -> None:
        ids, v = merger.ids, len(merger.vocabulary)
        a = np.array([ids[x] for x, _ in merger.rank], np.int64)
        b = np.array([ids[y] for _, y in merger.rank], np.int64)
        self.made = np.array([ids[x + y] for x, y in merger.rank], np.int32)
        self.none = len(a)
        self.order = np.argsort(a << 32 | b)
        self.keys = (a << 32 | b)[self.order]
        self.twin = a == b
        self.left, self.right = np.zeros(v + 1, bool), np.zeros(v + 1, bool)  # the last one is -1, an end
        self.left[a] = self.right[b] = True
        first = np.full(v, self.none)  # the least rank that a piece takes part in
        np.minimum.at(first, a, np.arange(self.none))
        np.minimum.at(first, b, np.arange(self.none))
        self.alone = first[self.made] <= np.arange(self.none)  # such a merge may be followed by one of a lesser rank

    def ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.full(len(a), self.none)
        if self.none:
            at = np.flatnonzero(self.left[a] & self.right[b])
            key = a[at].astype(np.int64) << 32 | b[at]
            k = np.minimum(np.searchsorted(self.keys, key), self.none - 1)
            out[at] = np.where(self.keys[k] == key, self.order[k], self.none)
        return out

    def split(self, x: np.ndarray) -> np.ndarray:
        """``Merger.pieces`` of every word, in their order: a step merges the pair of each word's lowest rank, at all of its places
        if no lower rank can follow, else at the first."""
        ends = np.flatnonzero(x < 0)
        number = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=-1))
        kept_x, kept_n = [], []
        r = np.append(self.ranks(x[:-1], x[1:]), self.none)
        while len(x):
            starts = np.append(0, np.flatnonzero(x[:-1] < 0) + 1)
            sizes = np.diff(starts, append=len(x))
            best = np.minimum.reduceat(r, starts)
            going = best < self.none
            if not going.all():
                stay = np.repeat(going, sizes)
                kept_x.append(x[~stay])
                kept_n.append(number[~stay])
                x, number, r, best, sizes = x[stay], number[stay], r[stay], best[going], sizes[going]
                if not len(x):
                    break
            at = np.flatnonzero(r == np.repeat(best, sizes))
            fresh = np.append(True, number[at[1:]] != number[at[:-1]])
            run = np.maximum.accumulate(np.where(fresh | np.append(True, np.diff(at) > 1), at, 0))
            rank = r[at]
            at = at[np.where(self.alone[rank], fresh, ~self.twin[rank] | ((at - run) % 2 == 0))]
            x[at] = self.made[r[at]]
            gone = np.ones(len(x), bool)
            gone[at + 1] = False
            at = at - np.arange(len(at))
            x, number, r = x[gone], number[gone], r[gone]
            near = np.unique(np.concatenate((at, np.maximum(at - 1, 0))))  # a word's last element is its end, so there is one after each
            r[near] = self.ranks(x[near], x[near + 1])
        if not kept_x:
            return x
        x, number = np.concatenate(kept_x), np.concatenate(kept_n)
        return x[np.argsort(number, kind="stable")]


def closed(offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
    """The bytes of words as ids of pieces, each word closed by -1."""
    sizes = np.diff(offsets)
    out = np.full(int(sizes.sum()) + len(sizes), -1, np.int32)
    keep = np.ones(len(out), bool)
    keep[np.cumsum(sizes + 1) - 1] = False
    out[keep] = data[offsets[0] : offsets[-1]]
    return out


#: Words in a block, and bytes at the most if a word is not longer.
BLOCK, BLOCK_BYTES = 1 << 17, 1 << 21


def blocks(counted: DataFrame) -> DataFrame:
    """x, n: words (w, n) in blocks, as the bytes' ids and int64 counts. A word of one byte has no pair."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        xs, ns, size = [], [], 0
        for batch in batches:
            offsets, data = words.buffers(batch.column("w").cast(pa.binary()))
            n = batch.column("n").to_numpy(zero_copy_only=False)
            cuts = np.unique(np.searchsorted(offsets, np.arange(offsets[0], offsets[-1] + BLOCK_BYTES, BLOCK_BYTES)).clip(0, len(n)))
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                xs.append(closed(offsets[lo : hi + 1], data))
                ns.append(n[lo:hi])
                size += len(xs[-1])
                if size >= BLOCK_BYTES or sum(map(len, ns)) >= BLOCK:
                    yield packed(x=np.concatenate(xs), n=np.concatenate(ns))
                    xs, ns, size = [], [], 0
        if xs:
            yield packed(x=np.concatenate(xs), n=np.concatenate(ns))

    return counted.where(F.octet_length("w") > 1).select("w", "n").mapInArrow(run, "x binary, n binary")


def packed(**columns) -> pa.RecordBatch:
    """One row: arrays as bytes, numbers as they are."""
    return pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) if isinstance(v, np.ndarray) else pa.array([v], pa.int32()) for v in columns.values()], names=list(columns))


#: Rounds after which the words are written as they are split by then; the rounds between apply what has come since.
REFRESH = 6


def written(df: DataFrame) -> DataFrame:
    """``df`` computed once, in the checkpoint folder that all executors share."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(context.getConf().get("spark.checkpoint.dir") or tempfile.mkdtemp(prefix="slicecode-checkpoints-"))
    return df.checkpoint()


def merged(held: DataFrame, merges: list[tuple[bytes, bytes]], new: int) -> DataFrame:
    """The blocks of words that were split by all merges but the last ``new``, split by these too: only words with such a pair are
    looked at, as what the earlier merges left does not change without one."""
    sent = held.sparkSession.sparkContext.broadcast((Merger(merges), new))  # as many entries as there are merges

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merger, last = sent.value
        table = merger.table
        left, right = np.zeros(len(merger.vocabulary) + 1, bool), np.zeros(len(merger.vocabulary) + 1, bool)
        for a, b in list(merger.rank)[len(merger.rank) - last :]:
            left[merger.ids[a]] = right[merger.ids[b]] = True
        for batch in batches:
            for x, n in zip(batch.column("x"), batch.column("n"), strict=True):
                x, n = np.frombuffer(x.as_buffer(), np.int32), np.frombuffer(n.as_buffer(), np.int64)
                ends = np.flatnonzero(x < 0)
                hit = np.zeros(len(ends), bool)
                hit[np.searchsorted(ends, np.flatnonzero(left[x[:-1]] & right[x[1:]]))] = True
                mask = np.repeat(hit, np.diff(ends, prepend=-1))
                yield packed(x=np.concatenate((x[~mask], table.split(x[mask]))), n=np.concatenate((n[~hit], n[hit])))

    return held.mapInArrow(run, "x binary, n binary")


def summed(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, ascending, and the sums of their counts."""
    if not len(keys):
        return keys, n
    order = np.argsort(keys)
    keys, n = keys[order], n[order]
    first = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
    return keys[first], np.add.reduceat(n, first)


def top_pairs(held: DataFrame, merger: Merger, most: int) -> list[tuple[bytes, bytes, int]]:
    """(a, b, n) of the ``most`` most frequent pairs of neighbouring pieces over all words, the lesser bytes first at ties. Sums of blocks
    leave a task, dealt by pair; of each part's pairs its ``most`` first come to the driver."""
    parts = max(16, int(held.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    order = np.argsort(np.argsort(np.array([*merger.vocabulary], object), kind="stable"), kind="stable")
    sent = held.sparkSession.sparkContext.broadcast(order)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = []
        for batch in batches:
            for x, n in zip(batch.column("x"), batch.column("n"), strict=True):
                x, n = np.frombuffer(x.as_buffer(), np.int32), np.frombuffer(n.as_buffer(), np.int64)
                pair = (x[:-1] >= 0) & (x[1:] >= 0)
                each = np.repeat(n, np.diff(np.flatnonzero(x < 0), prepend=-1))
                found.append(summed((x[:-1].astype(np.int64) << 32 | x[1:])[pair], each[:-1][pair]))
                if len(found) > 1 and sum(len(k) for k, _ in found[1:]) > len(found[0][0]):
                    found = [summed(*(np.concatenate(c) for c in zip(*found, strict=True)))]
        if found:
            keys, n = summed(*(np.concatenate(c) for c in zip(*found, strict=True)))
            to = ((keys >> 32) * 1_000_003 + (keys & 0xFFFFFFFF)) % parts
            for p in range(parts):
                if (to == p).any():
                    yield packed(p=p, k=keys[to == p], n=n[to == p])

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [(np.frombuffer(k.as_buffer(), np.int64), np.frombuffer(n.as_buffer(), np.int64)) for batch in batches for k, n in zip(batch.column("k"), batch.column("n"), strict=True)]
        if got:
            yield packed(**dict(zip("kn", first(*summed(*(np.concatenate(c) for c in zip(*got, strict=True)))), strict=True)))

    def first(keys: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        place = sent.value
        if len(keys) > most:
            enough = n >= np.partition(n, len(n) - most)[len(n) - most]
            keys, n = keys[enough], n[enough]
        at = np.lexsort((place[keys & 0xFFFFFFFF], place[keys >> 32], -n))[:most]
        return keys[at], n[at]

    rows = held.mapInArrow(count, "p int, k binary, n binary").repartition("p").mapInArrow(best, "k binary, n binary").collect()
    if not rows:
        return []
    keys, n = first(*(np.concatenate([np.frombuffer(r[c], np.int64) for r in rows]) for c in ("k", "n")))
    return [(merger.vocabulary[k >> 32], merger.vocabulary[k & 0xFFFFFFFF], c) for k, c in zip(keys.tolist(), n.tolist(), strict=True)]


def learn_merges(counted: DataFrame, merges: int, growth: float = 0.5, first: int = 16) -> list[tuple[bytes, bytes]]:
    """The most frequent neighbouring pairs (the lesser bytes at ties), in rounds: each counts pairs over all words and takes up to
    ``first`` pairs, or ``growth`` times as many as there are merges by then.

    A round takes pairs in the order of their counts while they reach half of its largest one, and leaves those that would
    share a piece in a row with one that it took, as their counts would change. With ``growth`` 0 and ``first`` 1 this is one
    pair at a time. Only a round's candidates come to the driver; the words stay split in blocks from round to round.
    """
    out: list[tuple[bytes, bytes]] = []
    base, known = written(blocks(counted)), 0
    for k in itertools.count():
        most = min(merges - len(out), max(first, int(growth * len(out))))
        if not most:
            break
        if k and k % REFRESH == 0:
            base, known = written(merged(base, out, len(out) - known)), len(out)
        held = base if known == len(out) else merged(base, out, len(out) - known)
        top = top_pairs(held, Merger(out), 4 * most)
        lefts, rights, taken = set(), set(), 0
        for a, b, n in top:
            if taken == most or 2 * n < top[0][2]:
                break
            if a not in rights and b not in lefts and (a != b or taken == 0 or (a not in lefts and b not in rights)):
                lefts.add(a)
                rights.add(b)
                out.append((a, b))
                taken += 1
        if not taken:
            break
    return out


def train_bpe(df: DataFrame, col: str, merges: int) -> Merger:
    return Merger(learn_merges(word_counts(df, col), merges))


def encode(words_of: Column, merger: Merger, spark) -> Column:
    """Ids of a word-split text (an array column). Each distinct word of a batch is split once."""
    sent = spark.sparkContext.broadcast(merger)

    @F.arrow_udf("array<int>")
    def ids(values: pa.Array) -> pa.Array:
        flat = values.flatten().dictionary_encode()
        x = sent.value.table.split(closed(*words.buffers(flat.dictionary.cast(pa.binary()))))
        ends = np.flatnonzero(x < 0)
        starts = np.append(0, ends[:-1] + 1)
        at = flat.indices.to_numpy(zero_copy_only=False)
        sizes = (ends - starts)[at]
        stops = np.append(0, np.cumsum(sizes))
        out = x[np.repeat(starts[at] - stops[:-1], sizes) + np.arange(stops[-1])]
        length = np.append(0, np.cumsum(pc.fill_null(pc.list_value_length(values), 0).to_numpy(zero_copy_only=False)))
        return pa.ListArray.from_arrays(pa.array(stops[length], pa.int32()), pa.array(out, pa.int32()), mask=values.is_null())

    return ids(words_of)


def decode(ids: Column, merger: Merger, spark) -> Column:
    sent = spark.sparkContext.broadcast(merger)

    @F.arrow_udf("string")
    def text(values: pa.Array) -> pa.Array:
        pieces = pa.array(sent.value.vocabulary, pa.large_binary()).take(values.flatten())
        at, data = words.buffers(pieces)
        at = at[np.append(0, np.cumsum(pc.fill_null(pc.list_value_length(values), 0).to_numpy(zero_copy_only=False)))]
        none = values.is_null().to_pylist()
        return pa.array([None if none[k] else data[at[k] : at[k + 1]].tobytes().decode("utf-8", "replace") for k in range(len(values))], pa.string())

    return text(ids)
