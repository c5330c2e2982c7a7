"""Grids with one axis longer than all others together, beyond one process: the same curve as of the whole array."""

import math

import numpy as np
import pytest

from gridpress import workloads as W
from gridpress.operators import factors as fac
from gridpress.operators import long_axis as L
from gridpress.operators.codec import compress_array
from gridpress.operators.planes import quantise_array, scale_exponent
from gridpress.operators.transform import omt_array
from gridpress.plans.grid import GridFrame
from gridpress.plans.targets import ErrorTarget

RNG = np.random.default_rng(31)
MIXED = RNG.normal(size=(3, 1500, 5)) * np.exp(-np.arange(5.0)) + np.array([0.0, 1.0, 5.0])[:, None, None]
FLAT = RNG.normal(size=(1600, 6)) @ RNG.normal(size=(6, 6)) + 0.3
#: a column of zeros, rows of zeros, and one column twice
POOR = np.concatenate([FLAT[:, :3], np.zeros((1600, 1)), FLAT[:, :1]], axis=1) * (np.arange(1600) < 1300)[:, None]

#: slabs without a 1 in the first planes of others
UNEVEN = FLAT * np.where(np.arange(1600) < 800, 1.0, 1e-3)[:, None]


@pytest.fixture
def small(monkeypatch):
    monkeypatch.setattr(L, "SLAB_CELLS", 5000)
    monkeypatch.setattr(W, "LOCAL_CELLS", 4000)


def test_which_axis():
    assert L.long_axis((102564, 64)) == 0 and L.long_axis((10, 10300, 64)) == 1
    assert L.long_axis((500, 64)) is None and L.long_axis((1000, 1200, 64)) is None and L.long_axis((1 << 20, 1 << 12)) is None


@pytest.mark.parametrize("a", [MIXED, FLAT, POOR, UNEVEN], ids=["mixed", "flat", "poor", "uneven"])
def test_curve_of_slabs_is_that_of_the_array(spark, small, a):
    """Before, curves refused such grids as too large to be held by one process."""
    psnrs = (20.0, 45.0)
    codecs = ("plane_omt", "plane_omt_price", "rank_cut", "block_xform")
    got = {(r.codec, r.knob): r for r in W.quality_curve(spark, {"a": (GridFrame.of(spark, a), 4)}, (*codecs, "predictive", "set_part"), psnrs).collect()}
    assert len(got) == 12
    for c in codecs:
        for p in psnrs:
            size, e, _, _ = W.run_codec(a, c, p, 4)
            r = got[c, p]
            assert r.rmse == pytest.approx(e, rel=0.02) if c.startswith("plane") else r.rmse == pytest.approx(e, rel=1e-6)
            # slabs start their runs, their coders' states and their headers anew
            assert abs(r.bytes - size) <= (0.06 * size + 300 if c.startswith("plane") else 16 * 6 if c == "block_xform" else 0)
            assert r.ratio == pytest.approx(a.size * 4 / r.bytes)
    for (c, p), r in got.items():
        if c in ("plane_omt", "block_xform", "predictive", "set_part"):
            assert r.rmse <= np.ptp(a) / (2 * 10 ** (p / 20)) * math.sqrt(3) * (1 + 1e-6)
        if c == "plane_omt":
            assert r.psnr >= p - 1e-6


def test_transform_of_slabs(spark, small):
    t, want = L.long_transform(GridFrame.of(spark, MIXED)), omt_array(MIXED)
    assert t.rows.count() > 3
    assert np.allclose(np.abs(t.core), np.abs(L.multiply(want.core, np.eye(len(t.v)), 1)[:, : len(t.v)]), atol=1e-6)
    w = np.concatenate([np.frombuffer(r.block).reshape(-1, len(t.v)) for r in t.rows.orderBy("lo").collect()])
    assert np.allclose(np.abs(w), np.abs(want.factors[1][:, : len(t.v)] * t.norms[1]), atol=1e-6)
    assert t.stats.energy == pytest.approx((MIXED**2).sum()) and t.stats.span == pytest.approx(np.ptp(MIXED))


def test_price_stop_over_slabs(spark, small, monkeypatch):
    """One slab has the blocks of the array, and so its stops, however far they are below the first planes looked at."""
    monkeypatch.setattr(L, "SLAB_CELLS", 1 << 18)
    t = L.long_transform(GridFrame.of(spark, FLAT))
    w = np.frombuffer(t.rows.first().block)
    e = scale_exponent(float(np.abs(w).max()))
    q, neg, lead = quantise_array(w, e)
    prices = [10.0, 1e-2, 1e-6, 1e-12]
    assert L.price_stops(t, e, prices, 60) == [fac.stop_by_price(q, lead, neg, e, x) for x in prices]
    monkeypatch.setattr(L, "SLAB_CELLS", 5000)
    many = L.price_stops(L.long_transform(GridFrame.of(spark, FLAT)), e, prices, 60)
    assert all(abs(p - fac.stop_by_price(q, lead, neg, e, x)[0]) <= 1 for (p, _), x in zip(many, prices, strict=True))


def test_no_axis_longer_than_the_others(spark, small):
    a = RNG.normal(size=(20, 24, 18)).cumsum(axis=1)
    got = {(r.codec, r.knob): r for r in W.quality_curve(spark, {"a": (GridFrame.of(spark, a), 8)}, psnrs=(30.0,)).collect()}
    assert len(got) == 6 and got["plane_omt", 30.0].psnr >= 30 - 1e-6
    assert got["plane_omt", 30.0].bytes == pytest.approx(compress_array(a, ErrorTarget.psnr(30.0)).bytes(), rel=0.2)
