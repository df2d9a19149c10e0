"""gzip, PNG and FLAC decode to their input; their choices follow the rules."""

import gzip
import random

import numpy as np
import pytest

from slicecode.operators import baselines as b

R = random.Random(5)
BYTES = [b"", b"x", bytes(R.choices(range(256), k=1000)), bytes(range(200)) * 3, b"\0" * 500]


@pytest.mark.parametrize("data", BYTES)
def test_gzip_and_png(data):
    assert gzip.decompress(b.gzip_bytes(data)) == data and len(b.gzip_bytes(b"")) == 20
    for adaptive in (True, False):
        assert b.png_pixels(b.png_bytes(data, 64, adaptive))[: len(data)] == data


def test_png_ramp_prefers_a_predictor():
    ramp = bytes((x + 3 * y) % 256 for y in range(8) for x in range(64))
    assert len(b.png_bytes(ramp, 64)) < len(b.png_bytes(ramp, 64, adaptive=False))


@pytest.mark.parametrize("samples", [np.zeros(0, int), np.array([7]), np.full(5000, -3), (8000 * np.sin(np.arange(9000) / 20)).astype(int), np.random.default_rng(1).integers(-32768, 32767, 5000)])
def test_flac(samples):
    assert (b.flac_samples(b.flac_bytes(samples)) == samples).all()
    assert b.flac_length(samples) == len(b.flac_bytes(samples))
    low = np.clip(samples, -128, 127)
    assert b.flac_length(low, 8, 100) == len(b.flac_bytes(low, 8, block=100))


def test_flac_shrinks_a_sine_and_not_noise():
    sine = (8000 * np.sin(np.arange(9000) / 20)).astype(int)
    assert len(b.flac_bytes(sine)) < 0.6 * 2 * len(sine)
    assert len(b.flac_bytes(np.random.default_rng(1).integers(-32768, 32767, 5000))) > 0.95 * 10000


def test_rice_and_segments():
    assert b.rice_choice(np.zeros(100, int)) == (0, 100)
    assert len(b.zlib_segment(b"abc" * 100, b"abc" * 100)) <= len(b.zlib_segment(b"abc" * 100))
