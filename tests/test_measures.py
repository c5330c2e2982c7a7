"""Measures, spectra and experiment helpers against their definitions."""

import numpy as np
import pytest

from gridpress import workloads as W
from gridpress.operators import factors as fac
from gridpress.operators import metrics as M
from gridpress.operators import spectrum as S
from gridpress.operators import transform as X
from gridpress.operators.codec import bit_rate, breakpoint_by_bytes, compress_array, decompress_array, factor_share, ratio
from gridpress.operators.entropy import ideal_bits
from gridpress.operators.planes import quantise_array, scale_exponent, split_plane
from gridpress.plans.grid import GridFrame, GridSpec
from gridpress.plans.targets import ErrorTarget
from gridpress.sources.cubes import synthetic_array

RNG = np.random.default_rng(4)


@pytest.mark.parametrize("width", [1, 4, 8])
def test_ratio_rate_and_share_follow_from_bytes(width):
    a = synthetic_array("cosines", (16, 15, 14))
    z = compress_array(a, ErrorTarget.rel(0.01), GridSpec(("x", "y", "z"), a.shape, width))
    assert np.isclose(ratio(z), a.size * width / z.bytes()) and np.isclose(bit_rate(z), 8 * z.bytes() / a.size)
    assert np.isclose(ratio(z) * bit_rate(z), 8 * width) and np.isclose(factor_share(z), z.factor_bytes() / z.bytes())
    assert z.bytes() == 64 + z.core_bytes() + z.factor_bytes()
    assert z.core_bytes() == sum(len(x) for s in z.segments for x in s[3:]) + sum(-(-m.bits // 8) for m in z.models.values())


def test_byte_breakpoint_is_the_last_plane_that_fits():
    c = RNG.normal(size=400) * np.exp(-np.arange(400) / 40)
    q, neg, lead = quantise_array(c, scale_exponent(float(np.abs(c).max())))
    size = {}
    total = 0.0
    for p in range(63, -1, -1):
        runs, raw, signs = split_plane(q, lead, neg, p)
        total += ideal_bits(runs) + len(raw) + len(signs)
        size[p] = total / 8
    for most in (20, 100, 700):
        p = breakpoint_by_bytes(c, most)
        assert size[p] <= most and (p == 0 or size[p - 1] > most)


def test_spectra():
    n = 32
    x = np.arange(n)
    low, high = np.cos(2 * np.pi * x / n), np.cos(np.pi * x)
    cube = lambda v: v[:, None, None] + np.zeros((n, n, n))
    assert M.high_freq_share(S.grid_spectrum(cube(low)) ** 2) < 1e-9 < 0.99 < M.high_freq_share(S.grid_spectrum(high[:, None, None] * high[None, :, None] * high[None, None, :]) ** 2)
    a = RNG.normal(size=(8, 9, 10))
    assert sum(S.spectrum_histogram(a).values()) == a.size
    assert np.isclose((S.grid_spectrum(a) ** 2).sum(), a.size * (a**2).sum())
    u = X.omt_array(a).factors[0]
    mag = S.factor_spectrum(u) ** 2
    both = 2 * mag.sum(axis=0) - mag[0] - (mag[-1] if len(u) % 2 == 0 else 0)
    assert np.allclose(both / len(u), 1)  # unit columns


def test_compression_moves_energy_to_low_frequencies():
    """The claim about spectra: coarser archives of the method hold less of the high frequencies."""
    a = synthetic_array("cosines", (24, 24, 24)) + 0.2 * RNG.normal(size=(24, 24, 24))
    share = [M.high_freq_share(S.grid_spectrum(decompress_array(compress_array(a, ErrorTarget.psnr(db)))) ** 2) for db in (14.0, 20.0, 60.0)]
    assert share[0] < share[1] < share[2]


def test_clock_and_asymmetry():
    c = M.StageClock()
    c.seconds = {"compress": 6.0, "decompress": 2.0}
    assert M.asymmetry(c) == 3.0
    with c.stage("x"):
        pass
    assert c.rows()[-1][0] == "x" and c.rows()[-1][1] >= 0
    stages = W.round_trip_stages(synthetic_array("bump", (12, 12, 12)), 40.0)
    assert [s[:2] for s in stages] == [("compress", "eigen"), ("compress", "projection"), ("compress", "planes"), ("decompress", "planes"), ("decompress", "factors"), ("decompress", "products")]


def test_codecs_at_a_ratio_keep_to_it():
    a = synthetic_array("bump", (16, 16, 16))
    for codec in ("plane_omt", "rank_cut", "block_xform", "predictive", "set_part"):
        got = W.at_ratio(a, codec, 20.0)
        if got is not None:
            z, back = got
            assert a.size * 8 / z.bytes() >= 20 and back(z).shape == a.shape
    assert W.at_ratio(a, "plane_omt", 1e6) is None


def test_lead_zone(spark):
    rows = [("g", "plane_omt", r, p) for r, p in ((2.0, 40.0), (8.0, 30.0), (32.0, 20.0))] + [("g", "set_part", r, p) for r, p in ((2.0, 60.0), (8.0, 20.0))] + [("g", "plane_omt_price", 9.0, 99.0)]
    got = W.lead_zone(spark.createDataFrame(rows, "cube string, codec string, ratio double, psnr double"), 33).first()
    assert 4 < got.lo < 8 and got.hi == pytest.approx(32) and 0.4 < got.share < 0.8


def test_truncation_keeps_the_corner(spark):
    a = RNG.normal(size=(5, 4, 3))
    t = X.omt_array(a)
    df = X.truncate(GridFrame.of(spark, t.core).df, t.spec, (2, 3, 1))
    got = {r.idx: r.v for r in df.collect()}
    want = {int(np.ravel_multi_index(i, a.shape)): t.core[i] for i in np.ndindex(2, 3, 1)}
    assert got.keys() == want.keys() and all(np.isclose(got[k], want[k]) for k in got)


def test_weighted_factors_cost_the_error_of_the_grid():
    """An error on a weighted factor is the same error on the grid; weighting is undone on the way back."""
    a = synthetic_array("cosines", (14, 13, 12))
    t = X.omt_array(a)
    norms = fac.array_slice_norms(t.core)
    w = fac.weighted_factor(t.factors[0], norms[0])
    f = fac.encode_factor(t.factors[0], norms[0], 0.0, most_sse=1e-4 * (w**2).sum(), stop="budget")
    u = fac.decode_factor(f, norms[0])
    grid = X.inverse_array(t.core, [u, *t.factors[1:]])
    assert np.isclose(((grid - a) ** 2).sum(), ((fac.weighted_factor(u, norms[0]) - w) ** 2).sum(), rtol=1e-6)
    assert np.isclose(f["error"], ((fac.weighted_factor(u, norms[0]) - w) ** 2).sum(), rtol=1e-6) and f["error"] <= 1e-4 * (w**2).sum() * 1.5
    assert np.allclose(fac.unweighted(w, norms[0])[:, norms[0] > 1e-9], t.factors[0][:, norms[0] > 1e-9])
    assert fac.plane_depth(f) == len(f["planes"]) > 0
