"""Invariants of laws, windows and measures; ground truth for drift; the published arithmetic."""

import math
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from slicecode.functions.exprs import byte_symbols, micro_bits
from slicecode.operators import bpe, curate, metrics, models, score, windows


def frame(spark, texts, months=None):
    return spark.createDataFrame([("s", i, (months or [0] * len(texts))[i], t) for i, t in enumerate(texts)], "source string, item_id long, m int, body string")


def brute_backoff(train, seq, order):
    """Witten-Bell with dictionaries."""
    counts = [defaultdict(Counter) for _ in range(order + 1)]
    for t in train:
        for i, c in enumerate(t):
            for d in range(min(order, i) + 1):
                counts[d][t[i - d : i]][c] += 1
    out = []
    for i, c in enumerate(seq):
        p = 1 / 256
        for d in range(min(order, i) + 1):
            found = counts[d].get(seq[i - d : i])
            if found:
                p = (found[c] + len(found) * p) / (sum(found.values()) + len(found))
        out.append(p)
    return out


def test_backoff_equals_brute_force(spark):
    train, test = ["abracadabra", "alakazam", "bar"], ["abrakadabra", "zzz", ""]
    grams = models.month_grams(frame(spark, train + test, [0, 0, 0, 1, 1, 1]), 2)
    counts, totals = models.fit_backoff(grams, 0)
    law = models.score_grams(grams, counts, totals, 2)
    got = score.gram_pushdown(grams.where("m = 1"), law, ["m"]).first()
    want = sum(round(-math.log2(p) * 1e6) for t in test for p in brute_backoff([x.encode() for x in train], t.encode(), 2))
    assert got["micro"] == want and got["raw_bytes"] == sum(map(len, test))


def test_uniform_is_the_ceiling_and_adaptive_is_positive(spark):
    s = frame(spark, ["hello", "é"]).select(byte_symbols(F.col("body")).alias("h"))
    n = s.select(F.explode("h")).count()
    assert n == 7
    assert spark.range(1).select(micro_bits(models.uniform())).first()[0] == 8_000_000
    assert spark.range(1).select(score.adaptive(F.lit(0), F.lit(0)).alias("p")).first()[0] == 1 / 256


def test_sliding_degenerates_to_chunks_and_long_windows_to_streams(spark):
    t = windows.symbols(frame(spark, ["abcabcabcabcabc" * 3, "zz"]), byte_symbols(F.col("body")), ["item_id"])
    pick = lambda d: sorted(map(tuple, d.select("item_id", "pos", "n_w", "m").collect()))
    assert pick(windows.sliding_counts(t, 8, 8, ["item_id"])) == pick(windows.chunk_counts(t, 8, ["item_id"]))
    assert pick(windows.chunk_counts(t, 4096, ["item_id"])) == pick(windows.sliding_counts(t, 4096, 4096, ["item_id"]))
    text = ("abcabcabcabcabc" * 3).encode()
    for item, pos, n_w, m in pick(windows.sliding_counts(t, 8, 2, ["item_id"])):
        if item == 0:
            start = max(0, pos // 2 * 2 - 6)
            assert m == pos - start and n_w == text[start:pos].count(text[pos : pos + 1])


def test_restricted_law_sums_to_one(spark):
    law = spark.createDataFrame([("", "00", 0.5), ("", "01", 0.3), ("", "02", 0.2)], "ctx string, sym string, p double")
    got = models.restrict(law, spark.createDataFrame([("00",), ("02",)], "sym string"))
    assert abs(sum(r["p"] for r in got.collect()) - 1) < 1e-12


def test_periods_and_projection(spark):
    series = spark.createDataFrame([("s", "a", m, 10_000_000 * (2 if m >= 72 else 1), 100, 1.25 * (2 if m >= 72 else 1)) for m in range(83)], "source string, model_id string, m int, micro long, raw_bytes long, rate double")
    r = metrics.robustness(metrics.period_rates(series)).first()
    assert (r["r_train"], r["r_test"], r["gap"], r["arrow"]) == (1.25, 2.5, 1.25, "up")
    assert abs(r["r_all"] - (72 * 1.25 + 11 * 2.5) / 83) < 1e-7
    p = metrics.project_and_rank(metrics.robustness(metrics.period_rates(series)), spark.createDataFrame([("a", "small")], "model_id string, size_class string")).first()
    assert p["projected"] == 2 * r["r_test"] - r["r_train"] and p["mark"] == "best"


def test_divergence_finds_a_planted_month(spark):
    rows = [("s", x, m, 10.0 + 0.001 * (m % 5) + (0.5 if x == "early" and m >= 60 else 0.0)) for x in ("early", "late") for m in range(83)]
    got = metrics.divergence(spark.createDataFrame(rows, "source string, model_id string, m int, rate double"), "early", "late", 47).first()
    assert got["month_no"] == 60


def test_injected_drift_raises_the_gap(spark):
    words = "the quick brown fox jumps over lazy dogs and runs away from here".split()
    texts = [" ".join(words[(i * k) % len(words)] for k in range(1, 120)) for i in range(166)]
    s = frame(spark, texts, [i % 83 for i in range(166)])

    def gap(slices):
        g = models.month_grams(slices, 1)
        counts, totals = models.fit_backoff(g, 47)
        totals_by = score.gram_pushdown(g, models.score_grams(g, counts, totals, 1), ["source", "m"]).withColumn("model_id", F.lit("x"))
        return metrics.robustness(metrics.period_rates(metrics.monthly_rate(totals_by))).first()["gap"]

    calm, drifting = gap(s), gap(curate.inject_drift(s, 47))
    assert drifting > calm + 1 and abs(calm) < 1


def test_change_rule(spark):
    base = [f"line {k}" for k in range(10)]
    rows = [("f", 0, 1, base), ("f", 1, 2, base[:4] + ["x"] * 6), ("f", 2, 3, base[:4] + ["x"] * 6), ("g", 0, 4, base), ("g", 1, 5, ["y"] * 10)]
    v = spark.createDataFrame(rows, "k string, m int, pid long, lines array<string>")
    got = {r["pid"]: (r["ratio"], r["kept"]) for r in curate.changed_items(v, "k", ["m"], "pid", F.col("lines")).collect()}
    assert got == {1: (None, True), 2: (0.6, True), 3: (0.0, False), 4: (None, True), 5: (1.0, True)}


def test_snapshot_carries_forward(spark):
    v = spark.createDataFrame([("a", 1, 10), ("a", 1, 11), ("a", 3, 12)], "k string, m int, item_id long")
    got = [(r["m"], r["item_id"], r["carried"]) for r in curate.monthly_snapshot(v, ["k"], months=5).orderBy("m").collect()]
    assert got == [(1, 11, False), (2, 11, True), (3, 12, False), (4, 12, True)]


def test_resample_and_batches(spark):
    s = spark.createDataFrame([("a", k, float(k * k)) for k in range(5)], "key string, pos int, value double")
    up = {r["k"]: r["value"] for r in curate.resample(s, ["key"], "pos", "value", 2.0).collect()}
    assert up[0] == 0 and up[1] == 0.5 and up[4] == 4 and up[5] == 6.5
    b = curate.byte_batches(spark.createDataFrame([("a", k, v) for k, v in enumerate([1, -1, 256, -32768])], "key string, k int, x int"), ["key"], ["k"], "x", 3)
    assert [bytes(r["data"]) for r in b.orderBy("batch").collect()] == [b"\x01\x00\xff\xff\x00\x01", b"\x00\x80"]


def one_by_one(words, merges):
    """Merges learned by recounting all pairs after each one."""
    parts, out = {w: [bytes([b]) for b in w.encode()] for w in words}, []
    for _ in range(merges):
        counts = Counter()
        for w, n in words.items():
            for pair in zip(parts[w], parts[w][1:], strict=False):
                counts[pair] += n
        if not counts:
            break
        best = min(counts, key=lambda p: (-counts[p], p))
        out.append(best)
        parts = {w: bpe.Merger(out).pieces(w) for w in words}
    return out


def test_merges(spark):
    df = frame(spark, ["low lower lowest newer wider low low", "größer größte 😀 newest", None, ""])
    words = bpe.word_counts(df, "body")
    counts = {r["w"]: r["n"] for r in words.collect()}
    assert bpe.learn_merges(words, 12, 0, 1) == one_by_one(counts, 12)
    every = bpe.learn_merges(words, 60)
    assert len(set(every)) == len(every) and bpe.learn_merges(words, 10**6) == bpe.learn_merges(words, 10**6)
    lengths = []
    for n in (0, 10, 60):
        m = bpe.Merger(every[:n])
        ids = [i for w in counts for i in m.word(w)]
        assert m.decode(ids) == "".join(counts)
        lengths.append(len(ids))
    assert lengths[0] > lengths[1] > lengths[2]
    assert bpe.learn_merges(words.where("false"), 5) == []


def test_grams_counted_in_place(spark):
    df = frame(spark, ["größer 😀 aaaa", "", None, "ab" * 700, "x"])
    for order, chunk in ((0, None), (1, 512), (2, 512), (3, None)):
        want = {(r["ctx"], r["sym"]): r["n"] for r in models.month_grams(df, order, chunk, by=()).collect()}
        assert {(r["ctx"], r["sym"]): r["n"] for r in models.byte_grams(df, order, chunk, at_once=40).collect()} == want


def test_phenomena(spark, sf):
    """More capacity fits the training months better and widens the gap; overlap beats chunks."""
    from slicecode.plans import registry

    q = registry.queries()
    r = {(x["source"], x["model_id"]): x for x in q["robustness_gap"](spark, sf).collect()}
    assert r["reference_articles", "late_o2"]["r_train"] < r["reference_articles", "late_o1"]["r_train"]
    assert r["reference_articles", "late_o2"]["gap"] > r["reference_articles", "late_o1"]["gap"]
    assert r["code_files", "late_o2_code"]["r_all"] < r["code_files", "late_o2"]["r_all"]
    assert r["news_articles", "uniform"]["r_all"] == 100
    c = {x["config"]: x["rate"] for x in q["cached_bits"](spark, sf).collect() if x["model_id"] == "adaptive_o0"}
    assert c["8192/8192"] <= c["4096/4096"] <= c["2048/2048"] and c["2048/512"] <= c["2048/2048"]


def test_null_and_empty_rows(spark):
    """Null and empty bodies have no symbol, null months are never trained on, clashing names do no harm."""
    s = frame(spark, [None, "", "ab", "abc"], [0, 0, 0, None]).withColumn("ctx", F.lit("x")).withColumn("sym", F.lit(1)).withColumn("n", F.lit(2)).withColumn("pos", F.lit(3))
    g = models.month_grams(s, 1)
    assert g.agg(F.sum("n")).first()[0] == 5
    counts, totals = models.fit_backoff(g, 0)
    assert counts.where("depth = 0").agg(F.sum("cnt")).first()[0] == 2 and totals.count() == 2
    assert windows.chunk_arrays(s, byte_symbols(F.col("body")), 2, ["item_id"]).count() == 3
    assert models.score_grams(g.where("false"), counts, totals, 1).collect() == []
    empty = metrics.period_rates(metrics.monthly_rate(spark.createDataFrame([], "source string, model_id string, m int, micro long, raw_bytes long")))
    assert metrics.robustness(empty).collect() == []
    nothing = spark.createDataFrame([("s", "a", 0, 0, 0)], "source string, model_id string, m int, micro long, raw_bytes long")
    assert metrics.monthly_rate(nothing).first()["rate"] is None


def test_positions_and_lags(spark):
    """Places and values before, over ranges and blocks, as one ordered window would give them."""
    from pyspark.sql import Window

    rows = [("a" if k % 3 else None, k * 7 % 1000, k, k * k % 91) for k in range(500)]
    df = spark.createDataFrame(rows, "key string, o long, o2 long, x int")
    w = Window.partitionBy("key").orderBy("o", "o2")
    want = df.withColumn("_i", F.row_number().over(w) - 1).withColumn("x1", F.lag("x", 1).over(w)).withColumn("x2", F.lag("x", 2).over(w)).where("key is not null")
    got = curate.with_lags(curate.positions(df.where("key is not null"), ["key"], ["o", "o2"], span=64), ["key"], "x", 2, block=16)
    pick = lambda d: sorted((tuple(r) for r in d.select("key", "o", "_i", "x", "x1", "x2").collect()), key=str)
    assert pick(got) == pick(want)


def test_sampling_fractions(spark):
    """Bernoulli and stratified samples: none, all, and the same rows for the same seed."""
    d = spark.range(1000).withColumn("k", F.col("id") % 2)
    assert d.sample(0.0, 1).count() == 0 and d.sample(1.0, 1).count() == 1000
    s = d.sampleBy("k", {0: 1.0, 1: 0.0}, 7)
    assert s.count() == 500 and s.where("k = 1").count() == 0
    assert d.sample(0.3, 5).collect() == d.sample(0.3, 5).collect()


def test_crops_and_gray(spark):
    got = spark.range(1).select(curate.crop(F.array(*[F.lit(k) for k in range(12)]), 4, 1, 2).alias("c"), curate.gray_of_rgb(F.lit(255), F.lit(0), F.lit(255)).alias("g")).first()
    assert got["c"] == [1, 2, 5, 6, 9, 10] and got["g"] == 105


@pytest.mark.parametrize("key", ["printed_table_checks", "printed_rank_agreement", "same_cutoff_pairs"])
def test_given_tables_are_read(spark, sf, key):
    from slicecode.plans import registry

    assert "parquet" in registry.queries()[key](spark, sf)._jdf.queryExecution().analyzed().toString()
