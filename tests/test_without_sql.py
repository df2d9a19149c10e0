"""Queries that SQL cannot express, on the smallest tables: round trips, bounds, recounts."""

import gzip
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from slicecode.plans import registry
from slicecode.sources.tables import byte_slices

SIX = {"reference_articles", "news_articles", "code_files", "paper_bodies", "gray_patches", "sample_series"}


@pytest.fixture(scope="module")
def rows(spark, sf):
    found: dict = {}

    def of(key):
        if key not in found:
            found[key] = registry.queries()[key](spark, sf).collect()
        return found[key]

    return of


def test_codes_come_back(spark, sf, rows):
    got = rows("arith_roundtrip")
    size = spark.read.parquet(f"{sf}/documents.parquet").where("pmod(doc_id, 83) >= 72 and cast(substring(source, 4) as int) < 10").agg(F.sum(F.octet_length("text"))).first()[0]
    assert got and all(r["ok"] for r in got) and sum(r["n"] for r in got) == size
    assert all(r["ok"] for r in rows("arith_slot_codes")) and all(r["ok"] for r in rows("concat_codes"))


def test_overhead_falls_with_precision(rows):
    got = rows("arith_overhead")
    spare = [r["finite_precision"] for r in got]
    assert len(got) == 4 and len({r["symbols"] for r in got}) == 1 and spare == sorted(spare, reverse=True)
    for r in got:
        assert r["bits"] >= r["ideal_bits"] and spare[-1] <= 2.5 * r["chunks"] and r["quantisation"] >= 0


def test_compressed_sizes(spark, sf, rows):
    want = defaultdict(int)
    for r in byte_slices(spark, sf).where("data is not null").collect():
        want[r["source"]] += len(gzip.compress(bytes(r["data"]), 9, mtime=0))
    got = rows("gzip_rate")
    sums = defaultdict(int)
    for r in got:
        sums[r["source"]] += r["coded"]
    assert sums == want and set(want) == SIX
    for key in ("png_rate", "flac_rate"):
        assert {r["source"] for r in rows(key)} == SIX and all(r["coded"] > 0 for r in rows(key))
    report = {(r["source"], r["model_id"]) for r in rows("compressor_report")}
    assert report == {(s, c) for s in SIX for c in ("gzip", "png", "flac")}
    scopes = {(r["source"], r["scope"]): r for r in rows("gzip_scopes")}
    assert all(scopes[s, "chunk"]["coded"] >= scopes[s, "document"]["coded"] >= scopes[s, "month"]["coded"] for s in SIX)
    assert all(len({scopes[s, k]["raw"] for k in ("chunk", "document", "month")}) == 1 for s in SIX)


def test_byte_pairs(rows):
    got = {(r["trained_on"], r["vocabulary"], r["lang"]): r for r in rows("bpe_table")}
    assert all(r["lossless"] for r in got.values())
    for lang in {k[2] for k in got}:
        tokens = [got[k]["tokens"] for k in sorted(k for k in got if k[0] == "all" and k[2] == lang)]
        assert tokens == sorted(tokens, reverse=True)


def test_drift_and_sketches(rows):
    for r in rows("drifted_words"):
        assert r["changed"] == 0 if r["m"] <= 47 else 0 <= r["changed"] <= r["words"]
    assert any(r["changed"] for r in rows("drifted_words"))
    for r in rows("vocabulary_sketches"):
        assert abs(r["approximate"] - r["exact"]) <= 0.05 * r["exact"] and abs(r["from_sketch"] - r["exact"]) <= 0.05 * r["exact"]


def test_context_cost(rows):
    got = rows("context_size_cost")
    assert len(got) == 17 and all(r["seconds"] > 0 and r["state_mb"] > 0 for r in got)
    pairs = {r["model_id"]: r["law_pairs"] for r in got}
    assert pairs["adaptive_o0"] == 0 < pairs["cached_o0"] < pairs["cached_o1"] < pairs["cached_o2"] < pairs["cached_o3"]


def test_difficulty_has_a_reference(rows):
    assert {r["source"] for r in rows("source_difficulty_gzip")} <= SIX
