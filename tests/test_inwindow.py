"""Counting inside a row against counting by hand, across segments; the Arrow pass against the relational form."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from slicecode.operators import inwindow
from slicecode.plans import model_queries

SETTINGS = [inwindow.Setting("whole", 0), inwindow.Setting("8", 8), inwindow.Setting("8/2", 8, 2), inwindow.Setting("8o1", 8, order=1), inwindow.Setting("s16/4", 16, 4, law="p0", strength=3.0)]


def by_hand(raw, s, law):
    total = 0
    for i, c in enumerate(raw):
        step = s.step or s.size
        start = max(0, i // step * step - (s.size - step)) if s.size else 0
        seen = raw[start:i]
        if s.order:
            start = i // s.size * s.size
            ctx = raw[i - 1] if i > start else None
            pairs = [(raw[j - 1] if j > start else None, raw[j]) for j in range(start, i)]
            n_w, m = pairs.count((ctx, c)), sum(x == ctx for x, _ in pairs)
        else:
            n_w, m = seen.count(bytes([c])), len(seen)
        p = (n_w + 0.5) / (m + 128.0) if s.law is None else (n_w + s.strength * law[raw[max(0, i - 2) : i], c]) / (m + s.strength)
        total += math.floor(-math.log2(p) * 1e6 + 0.5)
    return total


@pytest.mark.parametrize("segment", [16, 32, 1 << 20])
def test_row_costs(segment):
    r = random.Random(segment)
    for n in (1, 2, 15, 16, 17, 40, 100):
        raw = bytes(r.choice(b"abcd") for _ in range(n))
        law = {(raw[max(0, i - 2) : i], c): r.random() for i, c in enumerate(raw)}
        key = lambda ctx, c: int("1" + ctx.hex() + f"{c:02x}", 16)
        keys = sorted((key(*k), p) for k, p in law.items())
        packed = inwindow.PackedLaw(2, np.array([k for k, _ in keys]), {"p0": np.array([p for _, p in keys])})
        some = SETTINGS if segment > 100 else [s for s in SETTINGS if not s.order or s.size]
        got = inwindow.row_costs(raw, some, packed, segment)
        for (micro, _, _), s in zip(got, some, strict=True):
            assert abs(micro - by_hand(raw, s, law)) <= 1, (n, s.name)


def test_unknown_gram_is_refused():
    with pytest.raises(KeyError):
        inwindow.row_costs(b"ab", [inwindow.Setting("8", 8, law="p")], inwindow.PackedLaw(0, np.array([0x161]), {"p": np.array([0.5])}))


def test_arrow_equals_joins(spark, sf):
    """The packed law in one pass, and the form for laws that are too large to send: the same integers."""
    slices = model_queries.documents_slices(spark, sf).where("source = 'reference_articles' and m >= 72")
    want = model_queries.joined_costs(slices, model_queries.static_laws(spark, sf), model_queries._STUDY_SETTINGS)
    most = inwindow.MOST_PAIRS
    sums = lambda d: {r["config"]: (r["n"], r["micro"]) for r in d.groupBy("config").agg(F.sum("n").alias("n"), F.sum("micro").alias("micro")).collect()}
    a, b = sums(model_queries.study_costs(spark, sf)), sums(want)
    assert a.keys() == b.keys() and all(a[k][0] == b[k][0] and abs(a[k][1] - b[k][1]) <= 2 for k in a)
    inwindow.MOST_PAIRS = 10
    try:
        assert sums(model_queries.study_costs(spark, sf)) == b
    finally:
        inwindow.MOST_PAIRS = most


def test_null_and_empty_rows_and_other_columns(spark):
    df = spark.createDataFrame([("a", None, 1), ("a", "", 2), (None, "xx", 3), ("a", "xy", 4)], "lang string, text string, micro int")
    got = {(r["lang"], r["config"]): (r["n"], r["micro"]) for r in inwindow.window_costs(df, ["lang"], "text", SETTINGS[:2]).groupBy("lang", "config").agg(F.sum("n").alias("n"), F.sum("micro").alias("micro")).collect()}
    assert got["a", "8"][0] == 2 and got["a", "whole"][0] == 2 and got[None, "8"][0] == 2
    assert inwindow.window_costs(df.where("false"), ["lang"], "text", SETTINGS[:1]).collect() == []


def test_study_grid(spark, sf):
    """The window alone gains from overlap; nothing is reported past a model's longest window; overlap reads up to four times as much."""
    rows = {(r["model_id"], r["config"]): r for r in model_queries.context_size_table(spark, sf).collect()}
    assert len(rows) == 20 and rows["adaptive_o0", "2048/512"]["rate"] <= rows["adaptive_o0", "2048/2048"]["rate"]
    for (model, config), r in rows.items():
        assert (r["rate"] is None) == (int(config.split("/")[0]) > model_queries.STUDY[model][1]) == (r["forward_tokens"] is None)
        assert r["relative_cost"] is None or r["relative_cost"] == 1 or config == "2048/512" and r["relative_cost"] <= 4
