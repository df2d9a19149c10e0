"""The coder: round trips at the edges, length bounds, agreement with exact rationals."""

import random

import numpy as np
import pytest

from slicecode.operators.coder import PackedModel, decode_slots_of, encode_slots_of, exact_interval, gram_slots, lengths_of

MODEL = PackedModel({b"": (np.array([65, 66]), np.array([30.0, 2.0])), b"A": (np.array([65]), np.array([9.0]))}, 1)
CASES = [b"", b"A", bytes(range(256)) * 2, b"A" * 10_000 + b"B", bytes(random.Random(3).choices(b"AB", k=2048))]


@pytest.mark.parametrize("precision", [20, 24, 32])
@pytest.mark.parametrize("data", CASES)
def test_round_trip_and_bounds(data, precision):
    slots = MODEL.slots(data)
    code, bits = encode_slots_of(slots, precision)
    assert bytes(decode_slots_of(code, bits, len(data), MODEL.cumulative, precision)) == data
    ideal = -sum(np.log2((h - lo) / t) for lo, h, t in slots)
    assert bits >= ideal - 1e-6 or not data
    assert bits <= ideal + 2 + len(data) * 2.0 ** (18 - precision)
    assert len(code) == (bits + 7) // 8


def test_exact_interval_holds_the_code():
    data = b"ABBAAB"
    low, width = exact_interval(MODEL.slots(data))
    code, bits = encode_slots_of(MODEL.slots(data), 32)
    value = int.from_bytes(code, "big") / 2 ** (8 * len(code))
    assert float(low) <= value < float(low + width)


def test_laws_are_normalised_and_slots_ordered():
    for ctx in (b"", b"A", b"Z", b"AA"):
        assert abs(MODEL.probabilities(ctx[-1:]).sum() - 1) < 1e-12
        cum = MODEL.cumulative(list(ctx))
        assert (np.diff(cum) >= 1).all() and cum[0] == 0


def test_finite_precision_costs_less_with_more_bits():
    data = CASES[-1]
    extra = [encode_slots_of(MODEL.slots(data), b)[1] for b in (18, 32)]
    assert extra[1] <= extra[0] + 1


def test_alphabet_of_one_costs_nothing():
    assert encode_slots_of([(0, 4, 4)] * 100)[1] <= 2


def test_slot_out_of_range():
    with pytest.raises(ValueError):
        encode_slots_of([(3, 3, 4)])


@pytest.mark.parametrize("order", [0, 1])
def test_lengths_of_many_chunks_at_once(order):
    model = PackedModel(MODEL.counts, order)
    rows = [*CASES, *(bytes(random.Random(k).choices(b"ABC", [30, 2, 1], k=k % 97)) for k in range(200))]
    lo, hi, total, ideal, _ = gram_slots(model, rows)
    ns = np.array([len(x) for x in rows])
    for precision in (18, 20, 24, 32):
        assert lengths_of(lo, hi, total, ns, precision).tolist() == [encode_slots_of(model.slots(x), precision)[1] for x in rows]
    assert np.isclose(ideal.sum(), sum(map(model.ideal_bits, rows)))


def test_slots_of_a_batch_are_not_held_as_objects(spark):
    """The codes of chunks that bring their slots, and the slots' own cost; few chunks are taken apart at a time."""
    from pyspark.sql import functions as F

    from slicecode.operators.coder import encode_slots

    rows = [(k, bytes(random.Random(k).choices(b"ABC", k=k))) for k in range(1, 150)]
    slots = {k: MODEL.slots(x) for k, x in rows}
    tokens = spark.createDataFrame([(k, i, *s) for k, all_of in slots.items() for i, s in enumerate(all_of)], "k int, pos int, lo long, hi long, total long")
    got = {r["k"]: r for r in encode_slots(tokens.orderBy(F.rand(1)), ["k"], at_once=4).collect()}
    assert {k: (bytes(r["code"]), r["bit_len"], r["n"]) for k, r in got.items()} == {k: (*encode_slots_of(s), len(s)) for k, s in slots.items()}
    assert all(np.isclose(got[k]["slot_bits"], -sum(np.log2((h - l) / t) for l, h, t in s)) for k, s in slots.items())
