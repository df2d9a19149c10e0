"""SimHash near-duplicates by anchor points of a covering code.

Fingerprints that differ in at most three of 64 bits differ in at most one bit of one 32-bit half. For each half
the anchors are the words of a covering code of radius 1: a (31, 26) Hamming code on 31 bits, the 32nd bit free.
A fingerprint's home is the one anchor within radius 1. If two halves differ in at most one bit, the home of
either lies within radius 1 + 1 of the other; so replicating every fingerprint to all anchors within covering
radius plus threshold (17 at most per half) and comparing there finds every pair, with no cap anywhere.

Only distinct fingerprints take part. First each is linked with the smallest one that shares its home, which brings large
groups of copies together; then those at home are compared with those that visit, and only links between different classes
are made, so no group is written out as all of its pairs. Crowded anchors are dealt out by salt. Links are contracted to
components by alternating large-star and small-star steps.

For texts that are similar but further apart than three bits, ``near_duplicates(views=…)`` takes several more fingerprints
of the text's distinct long words, one for each seed. Texts that share the home anchor of any half of any view are held
against each other by the exact Jaccard similarity of their shingles. In a crowded cell each text is held against the cell's
leader first. Of two texts that are then still of different classes one is far from the leader, so what it differs by from the
leader must largely be what the other differs by: such pairs are found by an exact prefix filter on these differences, and
not by pairing the cell's texts.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicecode.llm.common import arrow_pass, durable, release

BITS = 64
#: Fingerprints at home at one anchor before it is dealt out to several tasks; ids of texts to broadcast at most.
MOST_AT_HOME = 4096
MOST_NEEDED = 1 << 18
#: Links whose components the driver finds (16 bytes a link); more are contracted by star steps, with the same roots.
MOST_LINKS = 1 << 18
#: Texts of a cell that are paired as they are; those of larger cells meet by their differences from its leader.
FEW_IN_CELL = 8
#: Counters of the order in which the prefix filter takes differences. Any order is exact; a good one has rare ones first.
COUNTERS = 1 << 16


def fingerprint(text: str | None, width: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit SimHash: bit b is set if more than half of the shingles' hashes have it.

    Shingles repeat as often as they occur. Fewer words than ``width``: the whole sequence is the one shingle;
    no word: zero.
    """
    return _majority(shingle_hashes(words_of(text), width, seed))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def shingle_hashes(words: list[bytes], width: int, seed: int = 42) -> bytes:
    """Eight bytes for each shingle, in the order of the text."""
    if not words:
        return b""
    digest = xxhash.xxh64_digest
    if len(words) < width:
        return digest(b" ".join(words), seed)
    joined, ends = b" ".join(words), np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[: len(words) - width]))
    return b"".join([digest(joined[a:b], seed) for a, b in zip(starts.tolist(), (ends[width - 1 :] - 1).tolist(), strict=True)])


def _majority(hashes: bytes) -> int:
    n = len(hashes) // 8
    counts = np.zeros(BITS, np.int64)
    raw = np.frombuffer(hashes, np.uint8).reshape(n, 8)
    for at in range(0, n, 16384):  # bits of so many shingles at a time
        counts += np.unpackbits(raw[at : at + 16384], axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > n).tobytes(), "big")


def shingles(text: str | None, width: int = 5) -> frozenset[bytes]:
    """The distinct shingles themselves, as ``fingerprint`` cuts them; none without a word."""
    words = words_of(text)
    return frozenset(b" ".join(words[k : k + width]) for k in range(max(1, len(words) - width + 1))) if words else frozenset()


def similarity(a: frozenset[bytes], b: frozenset[bytes]) -> float:
    """Jaccard similarity; 0 if both are empty."""
    both = len(a & b)
    return both / (len(a) + len(b) - both) if both else 0.0


def with_fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3) -> DataFrame:
    """Columns doc_id, fp (the fingerprint's 64 bits as a signed long); null text counts as empty."""

    def rows(_: list, texts: list) -> list:
        return [np.array([fingerprint(t, width) for t in texts], np.uint64).view(np.int64).tolist()]

    return arrow_pass(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")), rows, "fp long", keep=["doc_id"])


def _halves(fps: DataFrame) -> DataFrame:
    """The columns of ``fps``, part, bits: the two halves of each fingerprint."""
    each = [F.struct(F.lit(w).cast("int").alias("part"), F.shiftrightunsigned("fp", 32 * w).bitwiseAND(F.lit((1 << 32) - 1)).alias("bits")) for w in (0, 1)]
    return fps.select("*", F.explode(F.array(*each)).alias("h")).select(*fps.columns, "h.part", "h.bits")


def _syndrome(bits: Column, size: int) -> Column:
    """XOR of the positions 1 … ``size`` - 1 of the coded bits that are set; the top bit is free."""
    parity = [F.bit_count(bits.bitwiseAND(F.lit(sum(1 << (p - 1) for p in range(1, size) if p >> j & 1)))) % 2 for j in range((size - 1).bit_length())]
    return sum((p * (1 << j) for j, p in enumerate(parity)), F.lit(0)).cast("int")


def _flip(bits: Column, position: Column) -> Column:
    """``bits`` with the bit at ``position`` (from 1; 0: none) turned over."""
    return bits.bitwiseXOR(F.when(position > 0, F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(position - 1, F.lit(0)).cast("int"))).otherwise(F.lit(0).cast("long")))


def homes(fps: DataFrame) -> DataFrame:
    """One row for each half: the anchor within radius 1. Columns part, anchor, and those of ``fps``."""
    return _halves(fps).select("part", _flip(F.col("bits"), _syndrome(F.col("bits"), 32)).alias("anchor"), *fps.columns)


def visits(fps: DataFrame) -> DataFrame:
    """One row for each half and anchor within radius 2. Columns part, anchor, and those of ``fps``.

    With syndrome s = 0 the half itself is an anchor, and so is it with the free bit turned. Else the anchors are
    one flip away (position s), two flips away (the pairs of positions i, i xor s), and one flip plus the free bit.
    """
    split = _halves(fps).withColumn("s", _syndrome(F.col("bits"), 32))
    home = _flip(F.col("bits"), F.col("s"))
    other = [F.when((F.col("s") > 0) & (F.lit(i) < F.col("s").bitwiseXOR(F.lit(i))), _flip(_flip(F.col("bits"), F.lit(i)), F.col("s").bitwiseXOR(F.lit(i)))) for i in range(1, 32)]
    anchors = F.concat(F.array(home, home.bitwiseXOR(F.lit(1 << 31))), F.array_compact(F.array(*other)))
    return split.select("part", F.explode(anchors).alias("anchor"), *fps.columns)


def _cells(placed: DataFrame) -> DataFrame:
    """``placed`` (part, anchor, …) with both in one long, ``cell``."""
    return placed.select((F.col("part").cast("long") * F.lit(1 << 32) + F.col("anchor")).alias("cell"), *[c for c in placed.columns if c not in ("part", "anchor")])


def crowded(cells: DataFrame, key: str, most: int) -> DataFrame:
    """cell, n, first (the smallest ``key``) of the cells with more than ``most`` rows, written for the joins to come."""
    return durable(cells.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.min(key).alias("first")).where(F.col("n") > most))


def leader_links(fps: DataFrame, distance: int = 3) -> DataFrame:
    """a, b: each fingerprint and the smallest one that shares its home, if it is near. Two rows a fingerprint at most."""
    at_home = _cells(homes(fps))
    led = at_home.join(crowded(at_home, "fp", 1).select("cell", F.col("first").alias("a")), "cell")
    return led.where((F.col("a") != F.col("fp")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("fp"))) <= distance)).select("a", F.col("fp").alias("b"))


def fingerprint_links(fps: DataFrame, distance: int = 3) -> DataFrame:
    """Pairs a < b of distinct fingerprints that differ in at most ``distance`` bits (up to 3), one row each. With a column
    ``root``: those of different roots only; else all."""
    if not 0 <= distance <= 3:
        raise ValueError("the anchors cover distances up to 3")
    rooted = "root" in fps.columns
    left, right = _cells(homes(fps)), _cells(visits(fps))
    dense = crowded(left, "fp", MOST_AT_HOME)
    if not dense.isEmpty():  # the same links either way
        shares = dense.select("cell", F.ceil(F.col("n") / F.lit(MOST_AT_HOME)).cast("int").alias("salts"))
        left = left.join(shares, "cell", "left").withColumn("salt", F.pmod(F.xxhash64("fp"), F.coalesce("salts", F.lit(1))).cast("int"))
        right = right.join(shares, "cell", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)))
    key = [c for c in ("cell", "salt") if c in left.columns]
    side = lambda x, name: x.select(*key, F.col("fp").alias(name), *([F.col("root").alias(f"{name}_root")] if rooted else []))
    near = (F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= distance)
    met = side(left, "a").join(side(right, "b"), key).where(near & (F.col("a_root") != F.col("b_root")) if rooted else near)
    return met.select("a", "b").distinct()


def merged_roots(rooted: DataFrame, links: DataFrame, key: str, into: DataFrame | None = None) -> DataFrame:
    """``into`` (root, …; ``rooted`` if None) after joining the classes that ``links`` (a, b: values of ``key``) connect. ``rooted``
    has the ``key`` and root of all that is linked; both are written already. Up to MOST_LINKS links the driver finds the components."""
    into = rooted if into is None else into
    if links.count() > MOST_LINKS:
        side = lambda name: rooted.select(F.col(key).alias(name), F.col("root").alias(f"{name}_root"))
        pairs = links.join(side("a"), "a").join(side("b"), "b").select(F.col("a_root").alias("a"), F.col("b_root").alias("b"))
        found = components(pairs).select(F.col("node").alias("old"), F.col("root").alias("new"))
    else:
        ends = F.broadcast(links.select(F.col("a").alias("end")).union(links.select("b")))
        known = rooted.join(ends, F.col(key) == F.col("end"), "left_semi").select(key, "root").toArrow().to_pydict()
        roots, pairs = dict(zip(known[key], known["root"], strict=True)), links.select("a", "b").toArrow().to_pydict()
        moved = _joined((roots[a], roots[b]) for a, b in zip(pairs["a"], pairs["b"], strict=True))
        if not moved:
            return into
        found = F.broadcast(links.sparkSession.createDataFrame(pa.table({"old": pa.array(moved.keys(), pa.int64()), "new": pa.array(moved.values(), pa.int64())})))
    others = [c for c in into.columns if c != "root"]
    return into.join(found, F.col("root") == F.col("old"), "left").select(*others, F.coalesce("new", "root").alias("root"))


def _joined(pairs: Iterable[tuple[int, int]]) -> dict[int, int]:
    """The smallest node of its component for each node of ``pairs`` that is not the smallest itself."""
    above: dict[int, int] = {}

    def top(x: int) -> int:
        while (y := above.get(x, x)) != x:
            above[x] = x = above.get(y, y)
        return x

    for a, b in pairs:
        x, y = top(a), top(b)
        if x != y:
            above[max(x, y)] = min(x, y)
    return {x: top(x) for x in list(above)}


def class_roots(fps: DataFrame, distance: int = 3) -> DataFrame:
    """fp, root: the smallest fingerprint that is reachable over links of at most ``distance`` bits."""
    rooted = durable(merged_roots(fps.select("fp", F.col("fp").alias("root")), durable(leader_links(fps, distance)), "fp"))
    return merged_roots(rooted, durable(fingerprint_links(rooted, distance)), "fp")


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """Columns node, root: the smallest node of its component, for every node of ``links`` (columns a, b).

    Alternating large-star and small-star steps until the edges no longer change; each step is written to the
    shared checkpoint folder. A node's neighbours are never collected: only their minimum is. The minima are dealt out anew
    before they are joined, so that Spark may split the partition of a hub, or send few minima to all tasks.
    """
    edges = durable(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    state = None
    for _ in range(most_rounds):
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("least")).select("u", F.least("u", "least").alias("m")).hint("rebalance")
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        lower = large.groupBy("u").agg(F.min("v").alias("m")).hint("rebalance")
        small = large.join(lower, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        edges = durable(small)
        now = edges.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)")).alias("h")).first()
        if state == tuple(now):
            break
        state = tuple(now)
        both = least = large = lower = small = None  # noqa: F841  the round's frames, so that their files can go
        release(links.sparkSession)
    else:
        raise RuntimeError("components did not settle")
    found = edges.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return found.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def view_fingerprints(words: list[bytes], views: int) -> np.ndarray:
    """``views`` fingerprints of the distinct words of six bytes or more, of all distinct words where there are under 16 such."""
    distinct = set(words)
    long = [w for w in distinct if len(w) >= 6]
    chosen = long if len(long) >= 16 else distinct
    if not chosen:
        return np.zeros(views, np.uint64)
    hashes, counts = np.fromiter(map(xxhash.xxh64_intdigest, chosen), np.uint64, len(chosen)), np.zeros(views * BITS, np.int64)
    seeds = np.arange(1, views + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for at in range(0, len(hashes), 4096):  # bits of so many words at a time
        # a mix of the word's hash and the view's seed, of which every bit depends on both
        h = (hashes[at : at + 4096, None] ^ seeds) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(29)
        counts += np.add.reduce(np.unpackbits(h.view(np.uint8), axis=1), axis=0, dtype=np.uint16)
    return np.packbits((counts * 2 > len(hashes)).reshape(views, BITS), axis=1).view(">u8").ravel().astype(np.uint64)


def sized_versions(docs: DataFrame, doc_id: str, text: str, width: int, views: int) -> DataFrame:
    """doc_id, fp, n (distinct shingles), version (digest of the words in order), views (fingerprints) of each row."""

    def rows(_: list, texts: list) -> list:
        fps, sizes, versions, seen = [], [], [], []
        for t in texts:
            words = words_of(t)
            hashes = shingle_hashes(words, width)
            fps.append(_majority(hashes))
            sizes.append(len(np.unique(np.frombuffer(hashes, np.uint64))))
            versions.append(xxhash.xxh3_128_digest(b" ".join(words)))
            seen.append(view_fingerprints(words, views).view(np.int64))
        ends = pa.array(np.arange(len(texts) + 1, dtype=np.int32) * views)
        return [np.array(fps, np.uint64).view(np.int64).tolist(), sizes, versions, pa.ListArray.from_arrays(ends, pa.array(np.concatenate(seen) if seen else np.zeros(0, np.int64)))]

    return arrow_pass(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")), rows, "fp long, n int, version binary, views array<long>", keep=["doc_id"])


def shared_cells(nodes: DataFrame, views: int) -> DataFrame:
    """cell, node, view, many: the home anchors of both halves of every view, where more than one node is at home; ``many`` where
    they are more than FEW_IN_CELL."""
    parts = [F.struct(F.lit(2 * k + half).cast("int").alias("part"), F.shiftrightunsigned(F.element_at("views", k + 1), 32 * half).bitwiseAND(F.lit((1 << 32) - 1)).alias("bits"), F.element_at("views", k + 1).alias("view")) for k in range(views) for half in (0, 1)]
    each = nodes.select("node", F.explode(F.array(*parts)).alias("p")).select("node", "p.part", "p.bits", "p.view")
    cells = _cells(each.select("part", _flip(F.col("bits"), _syndrome(F.col("bits"), 32)).alias("anchor"), "node", "view"))
    return durable(cells.join(crowded(cells, "node", 1).select("cell", (F.col("n") > FEW_IN_CELL).alias("many")), "cell"))


def _comparable(least: float, apart: int) -> Column:
    """Condition on sides a and b: views that are not far apart, sizes whose Jaccard can reach ``least``."""
    return (F.bit_count(F.col("a_view").bitwiseXOR(F.col("b_view"))) <= apart) & (F.col("a_n") >= least * F.col("b_n")) & (F.col("b_n") >= least * F.col("a_n"))


def _sided(cells: DataFrame, rooted: DataFrame, name: str, *more: str) -> DataFrame:
    known = rooted.select("node", F.col("root").alias(f"{name}_root"), F.col("n").alias(f"{name}_n"))
    return cells.join(known, "node").select("cell", *more, F.col("node").alias(name), F.col("view").alias(f"{name}_view"), f"{name}_root", f"{name}_n")


def led_pairs(cells: DataFrame, rooted: DataFrame, least: float, apart: int) -> DataFrame:
    """a, b: each node with the smallest node of each of its cells; in a cell of many whatever their views and sizes are."""
    first = durable(cells.groupBy("cell").agg(F.min(F.struct("node", "view")).alias("first")).select("cell", "first.*"))
    met = _sided(first, rooted, "a").join(_sided(cells, rooted, "b", "many"), "cell")
    return met.where((F.col("a_root") != F.col("b_root")) & (F.col("many") | _comparable(least, apart))).select("a", "b").distinct()


def live_cells(cells: DataFrame, rooted: DataFrame) -> DataFrame:
    """The rows of ``cells`` whose cell still has nodes of different classes, with ``leader``, the cell's smallest node."""
    live = cells.join(rooted.select("node", "root"), "node").groupBy("cell").agg(F.min("node").alias("leader"), F.min("root").alias("x"), F.max("root").alias("y")).where("x <> y")
    return durable(cells.join(live.select("cell", "leader"), "cell"))


def cell_pairs(live: DataFrame, rooted: DataFrame, least: float, apart: int) -> DataFrame:
    """a, b: all pairs of one cell of few that are still of different classes."""
    few = live.where("not many")
    met = _sided(few, rooted, "a").join(_sided(few, rooted, "b"), "cell")
    return met.where((F.col("a") < F.col("b")) & (F.col("a_root") != F.col("b_root")) & _comparable(least, apart)).select("a", "b").distinct()


def differences(live: DataFrame, docs: DataFrame, doc_id: str, text: str, width: int, least: float) -> DataFrame | None:
    """leader, node, n (the node's shingles), d (in how many it differs from the leader), head (the first of them by the order of
    their counters, as many as the prefix filter asks for) of the nodes of cells of many; None if there is no such cell."""
    led = durable(live.where("many and node <> leader").select(F.col("leader").alias("a"), F.col("node").alias("b")).distinct())
    if led.isEmpty():
        return None

    def apart_by(_: list, __: list, left: list, right: list) -> list:
        sizes, found, last, first = [], [], None, None
        for x, y in zip(left, right, strict=True):
            if x != last:
                last, first = x, np.unique(np.frombuffer(shingle_hashes(words_of(x), width), np.int64))
            own = np.unique(np.frombuffer(shingle_hashes(words_of(y), width), np.int64))
            sizes.append(len(own))
            found.append(np.setxor1d(first, own, assume_unique=True))
        return [sizes, found]

    whole = durable(arrow_pass(_with_texts(led, docs, doc_id, text), apart_by, "n int, delta array<long>", keep=["a", "b"]))
    counted = whole.select(F.explode("delta").alias("x")).groupBy(F.col("x").bitwiseAND(F.lit(COUNTERS - 1)).alias("slot")).agg(F.count(F.lit(1)).alias("c")).toArrow()  # COUNTERS rows at most
    counts = np.zeros(COUNTERS, np.int64)
    counts[counted.column("slot").to_numpy()] = counted.column("c").to_numpy()
    sent = docs.sparkSession.sparkContext.broadcast(counts)

    def heads(_: list, __: list, sizes: list, deltas: list) -> list:
        found = []
        for n, delta in zip(sizes, deltas, strict=True):
            x = np.array(delta, np.int64)
            found.append(x[np.lexsort((x, sent.value[x & (COUNTERS - 1)]))[: _most_apart(n, least) + 1]])
        return [sizes, [len(x) for x in deltas], found]

    return durable(arrow_pass(whole, heads, "n int, d int, head array<long>", keep=["a", "b"]).select(F.col("a").alias("leader"), F.col("b").alias("node"), F.col("n").alias("size"), "d", "head"))


def _most_apart(n: int, least: float) -> int:
    """In how many shingles a text of ``n`` may differ from another with a similarity of ``least``."""
    return int(n * (1 - least) / least + 1e-9)


def difference_pairs(diffs: DataFrame, rooted: DataFrame, least: float, led: bool) -> DataFrame:
    """a, b: nodes of one leader and different classes whose differences from it may be alike enough. ``led``: of the nodes that
    share a difference only those with the smallest one.

    Two sets x, y of a and b shingles that reach ``least`` differ in h = a + b - 2 ceil(least (a + b) / (1 + least)) at most. With X, Y
    their differences from the leader, X and Y share s = (|X| + |Y| - h) / 2 or more, and s > 0, as one of two texts of different
    classes was compared with the leader and lies further than that from it. The first that they share, in a common order, is at
    places i <= |X| - s and j <= |Y| - s, so i + j <= h and the lesser of the two is h / 2 at most.
    """
    known = diffs.join(rooted.select("node", "root"), "node")
    each = known.select("leader", F.struct("node", "root", "size", "d").alias("of"), F.posexplode("head").alias("pos", "x")).select("leader", "x", F.struct("of.node", "pos", "of.root", "of.size", "of.d").alias("y"))
    if led:
        left = each.groupBy("leader", "x").agg(F.min("y").alias("l"))
    else:
        left = each.where(F.col("y.pos") <= F.floor(F.col("y.size") * ((1 - least) / least) / 2 + 1e-9)).withColumnRenamed("y", "l")
    n = F.col("l.size") + F.col("y.size")
    h = n - 2 * F.ceil(n * (least / (1 + least)) - 1e-9)
    s = F.ceil((F.col("l.d") + F.col("y.d") - h) / 2)
    near = (F.col("l.pos") <= F.col("l.d") - s) & (F.col("y.pos") <= F.col("y.d") - s) & (F.col("l.pos") + F.col("y.pos") <= h)
    met = left.join(each, ["leader", "x"]).where((F.col("l.root") != F.col("y.root")) & near)
    return met.select(F.least("l.node", "y.node").alias("a"), F.greatest("l.node", "y.node").alias("b")).distinct()


def _with_texts(pairs: DataFrame, docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    """a, b, a_text, b_text of pairs of ids that are written already."""
    needed = durable(pairs.select(F.col("a").alias("need_id")).union(pairs.select("b")).distinct())
    if needed.count() <= MOST_NEEDED:  # the same rows either way: no text is shuffled to find few of them
        needed = F.broadcast(needed)
    texts = durable(docs.select(F.col(doc_id).alias("need_id"), F.col(text).cast("string").alias("text")).join(needed, "need_id", "left_semi").dropDuplicates(["need_id"]))
    side = lambda name: texts.select(F.col("need_id").alias(name), F.col("text").alias(f"{name}_text"))
    return pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "a_text", "b_text")


def verified(pairs: DataFrame, docs: DataFrame, doc_id: str, text: str, width: int, least: float) -> DataFrame:
    """The pairs a, b of ids whose texts have a Jaccard similarity of ``least`` or more over their distinct shingles."""
    pairs = durable(pairs)

    def rows(_: list, __: list, left: list, right: list) -> list:
        out, last, cut = [], None, frozenset()
        for x, y in zip(left, right, strict=True):
            if x != last:
                last, cut = x, shingles(x, width)
            out.append(similarity(cut, shingles(y, width)) >= least)
        return [out]

    return durable(arrow_pass(_with_texts(pairs, docs, doc_id, text), rows, "same boolean", keep=["a", "b"]).where("same").select("a", "b"))


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 3, distance: int = 3, views: int = 0, least: float = 0.8, apart: int = 14) -> DataFrame:
    """Columns doc_id, fp (signed long), component_id: the smallest doc_id reachable over links, itself included.

    One row for each input row. Texts without a word share fingerprint zero and link like any other. Null text
    counts as empty. Rows with a null id take part and get their component's smallest id, null if it has none.
    An empty table gives no rows. ``views``: texts that share the home anchor of a half of any of so many further
    fingerprints, of their distinct long words, and differ in at most ``apart`` bits of that fingerprint, are linked too, if
    their Jaccard similarity over distinct ``width``-word shingles is ``least`` or more; such a link needs an id on both
    sides, by which the texts are found. Texts of crowded cells of one smallest text are linked by that similarity alone.
    """
    marked = durable(sized_versions(docs, doc_id, text, width, views) if views else with_fingerprints(docs, doc_id, text, width))
    first = durable(marked.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    roots = durable(class_roots(first.select("fp"), distance))
    if views:
        texts = marked.where("n > 0 and doc_id is not null").groupBy("version").agg(F.min("doc_id").alias("node"), F.first("fp").alias("fp"), F.first("n").alias("n"), F.first("views").alias("views"))
        nodes = durable(texts.groupBy("node").agg(F.first("fp").alias("fp"), F.first("n").alias("n"), F.first("views").alias("views")))  # an id that repeats is one document
        cells = shared_cells(nodes, views)
        rooted = durable(nodes.select("node", "fp", "n").join(roots, "fp"))

        def linked(pairs: DataFrame) -> None:
            nonlocal roots, rooted
            links = verified(pairs, docs, doc_id, text, width, least)
            roots = durable(merged_roots(rooted, links, "node", roots))
            rooted = durable(nodes.select("node", "fp", "n").join(roots, "fp"))
            release(docs.sparkSession)

        linked(led_pairs(cells, rooted, least, apart))
        live = live_cells(cells, rooted)
        linked(cell_pairs(live, rooted, least, apart))
        diffs = differences(live, docs, doc_id, text, width, least)
        if diffs is not None:
            linked(difference_pairs(diffs, rooted, least, led=True))
            linked(difference_pairs(diffs, rooted, least, led=False))
    named = first.join(roots, "fp")
    classes = named.join(named.groupBy("root").agg(F.min("first_id").alias("class_id")), "root").select("fp", "class_id")
    return marked.join(classes, "fp").select("doc_id", "fp", F.col("class_id").alias("component_id"))


def keep_one_of_each(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", width: int = 5, distance: int = 3, views: int = 16, least: float = 0.8) -> DataFrame:
    """The rows of ``docs`` whose id is the smallest of its component; the rows of one id that repeat become one
    (any of them, they are the same document). Rows with a null id cannot be named and stay as they are.
    """
    known = docs.where(F.col(doc_id).isNotNull())
    found = near_duplicates(known, doc_id, text, width, distance, views, least)
    stay = found.where("doc_id = component_id").select("doc_id").distinct()
    kept = known.join(stay, known[doc_id] == stay["doc_id"], "left_semi")
    return kept.dropDuplicates([doc_id]).unionByName(docs.where(F.col(doc_id).isNull()))
