"""Round trips, bounds and golden values of the codecs."""

from itertools import product

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fieldmr.arrange import kd_boxes
from fieldmr.codec import blockpred_decode, blockpred_encode, blockxform_decode, blockxform_encode, eb_schedule, interp_decode, interp_encode, interp_plan, pack, unpack
from fieldmr.codec.apply import Codec, decode_chunk, encode_chunk, mrinterp
from fieldmr.pad import next_value, pad_short_axes

RNG = np.random.default_rng(0)


def smooth(shape):
    g = np.meshgrid(*[np.arange(n) for n in shape], indexing="ij")
    return 100 * np.sin(g[0] / 5) * np.cos(g[1] / 7) + 0.5 * g[2] + 0.01 * RNG.normal(size=shape)


@pytest.mark.parametrize("shape", [(17, 17, 64), (8, 8, 31), (9, 9, 9), (1, 1, 1), (1, 1, 2), (5, 3, 1), (2, 2, 2)])
@pytest.mark.parametrize("eb", [10, 0.1, 1e-4, 0])
def test_interp(shape, eb):
    a = smooth(shape)
    for order, extrap, schedule in product(("linear", "cubic"), ("copy", "linear2"), ("flat", "paper", "coarse")):
        raw, made = interp_encode(a, eb, order, extrap, schedule)
        assert np.array_equal(interp_decode(raw, shape, eb, order, extrap, schedule), made)
        assert np.abs(a - made).max() <= eb


@pytest.mark.parametrize("b", [4, 6, 8])
@pytest.mark.parametrize("predictor", ["lorenzo", "regression", "auto", "dual"])
def test_blockpred(b, predictor):
    cubes = RNG.normal(size=(20, b, b, b)).cumsum(1).cumsum(2)
    for eb in (1, 0.01, 1e-6, 0):
        raw, made = blockpred_encode(cubes, eb, predictor)
        assert np.array_equal(blockpred_decode(raw, 20, b, eb, predictor), made)
        assert np.abs(cubes - made).max() <= eb


@pytest.mark.parametrize("transform", ["lift", "dct"])
def test_blockxform(transform):
    cubes = RNG.normal(size=(20, 4, 4, 4)).cumsum(1)
    cubes[3], cubes[4], cubes[5] = np.nan, 0, cubes[5] * 1e300
    for eb in (1, 0.01, 1e-6, 0):
        raw, made = blockxform_encode(cubes, eb, transform)
        assert np.array_equal(blockxform_decode(raw, 20, eb, transform), made, equal_nan=True)
        assert np.nanmax(np.abs(cubes - made)) <= eb


def test_special_values_survive():
    a = smooth((8, 8, 8))
    a[0, 0, 0], a[1, 2, 3], a[7, 7, 7], a[4, 4, 4] = np.nan, np.inf, -np.inf, 5e-324
    raw, made = interp_encode(a, 0.1)
    back = interp_decode(raw, a.shape, 0.1)
    assert np.isnan(back[0, 0, 0]) and back[1, 2, 3] == np.inf and back[7, 7, 7] == -np.inf
    assert np.array_equal(back, made, equal_nan=True)


@pytest.mark.parametrize("codec", [Codec(), mrinterp(), Codec(arrange="stack"), Codec(arrange="kd"), Codec(arrange="zline"), Codec("blockpred"), Codec("blockpred", block=6), Codec("blockxform"), Codec("lossless")])
def test_chunks_round_trip(codec):
    keys = np.array(sorted(RNG.choice(64, 23, replace=False)))
    vals = RNG.normal(size=(23, 8, 8, 8)).cumsum(1)
    c = codec.at(0.05)
    raw, made = encode_chunk(keys, vals, c, 4, 4)
    assert np.array_equal(decode_chunk(raw, keys, 8, c, 4, 4), made)
    assert np.abs(vals - made).max() <= 0.05


def test_plan_golden():
    poor = lambda n: [r[1] + 1 for r in interp_plan(n) if r[4] == "extrapolated"]
    assert [poor(n) for n in (4, 8, 16, 32)] == [[3], [5, 7], [9, 13, 15], [17, 25, 29, 31]]
    assert not any(poor(n) for n in (5, 9, 17, 33))
    for n in range(1, 40):
        assert sorted(r[1] for r in interp_plan(n)) == list(range(n))


def test_schedule_golden():
    assert np.allclose(eb_schedule(4, 1.0), [0.125, 0.125, 0.197531, 0.444444, 1], atol=1e-6)


def test_pad_golden():
    assert [float(next_value(np.array([1.0, 2.0, 4.0]), k)) for k in ("constant", "linear", "quadratic")] == [4, 6, 7]
    a = np.zeros((4, 4, 9))
    assert pad_short_axes(a, "linear") is a
    assert pad_short_axes(np.zeros((8, 8, 16)), "linear").shape == (9, 9, 16)


def test_ramp_on_nine_points_has_no_residuals():
    a = np.arange(9.0).reshape(1, 1, 9)
    raw, made = interp_encode(a, 1e-9, "linear", schedule="flat")
    codes, _ = unpack(raw)
    assert np.count_nonzero(codes) <= 2 and np.abs(a - made).max() <= 1e-9


def test_kd_boxes_cover_exactly():
    for p in (0.1, 0.5, 0.9, 1.0):
        full = RNG.random((6, 7, 5)) < p
        seen = np.zeros(full.shape, dtype=int)
        for x0, x1, y0, y1, z0, z1 in kd_boxes(full):
            seen[x0:x1, y0:y1, z0:z1] += 1
        assert np.array_equal(seen, full.astype(int))


@settings(deadline=None, max_examples=50)
@given(st.lists(st.integers(-(2**62), 2**62), max_size=50), st.binary(max_size=20))
def test_pack(codes, extra):
    a = np.array(codes, dtype=np.int64)
    got, rest = unpack(pack(a, extra))
    assert np.array_equal(got, a) and rest == extra
