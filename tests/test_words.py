"""Words cut and merged many at a time: the same as one by one."""

import random

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from slicecode.functions.exprs import word_symbols
from slicecode.operators import bpe, words

ODD = ["größer 😀 aaaa_b c", "", None, "x́y ²½Ⅷ 漢字かな\r\n\tz", "é", "a" * 900 + " " + "ab" * 300, "·\U0001f600\U00010400\U0001d7d8 end"]


def test_words_are_those_of_the_pattern(spark):
    df = spark.createDataFrame([(t,) for t in ODD], "body string")
    want = {(r["w"], r["n"]) for r in df.select(F.explode(word_symbols(F.col("body"))).alias("w")).groupBy("w").agg(F.count("*").alias("n")).collect()}
    got = bpe.word_counts(df, "body")
    assert {tuple(r) for r in got.collect()} == want
    assert "Generate" not in got._jdf.queryExecution().executedPlan().toString()  # no word becomes a row before it is counted


def test_split_is_that_of_single_words():
    draw = random.Random(5)
    pieces = [b"a", b"b", b"c", b"\xc3"]
    for _ in range(60):
        merges, have = [], list(pieces)
        for _ in range(draw.randrange(12)):
            pair = (draw.choice(have), draw.choice(have))
            if pair not in merges:
                merges.append(pair)
                have.append(pair[0] + pair[1])  # the same piece may be made in several ways
        m = bpe.Merger(merges)
        some = ["".join(draw.choice("abc") for _ in range(draw.randrange(1, 30))) for _ in range(20)]
        x = m.table.split(bpe.closed(*words.buffers(pa.array(some).cast(pa.binary()))))
        assert [tuple(w) for w in np.split(x, np.flatnonzero(x < 0) + 1)[:-1]] == [(*m.word(w), -1) for w in some]


def test_ids_give_texts_back(spark):
    df = spark.createDataFrame([(t,) for t in ODD], "body string").select("body", word_symbols(F.col("body")).alias("w"))
    m = bpe.train_bpe(df, "body", 40)
    got = df.select("body", "w", bpe.encode(F.col("w"), m, spark).alias("ids")).withColumn("back", bpe.decode(F.col("ids"), m, spark)).collect()
    assert all(r["back"] == r["body"] and r["ids"] == (None if r["w"] is None else [i for w in r["w"] for i in m.word(w)]) for r in got)
