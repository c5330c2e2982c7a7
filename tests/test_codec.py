import math

import numpy as np
import pytest

from gridpress.operators import factors as fac
from gridpress.operators import metrics as M
from gridpress.operators import resample as R
from gridpress.operators import transform as X
from gridpress.operators.codec import audit, compress, compress_array, compress_strict, core_array, decompress, decompress_array, open_archive, ratio, save
from gridpress.plans.grid import GridFrame, GridSpec, to_slabs
from gridpress.plans.targets import ErrorTarget, grid_stats
from gridpress.sources.cubes import synthetic, synthetic_array

RNG = np.random.default_rng(2)
GRIDS = {
    "cosines": synthetic_array("cosines", (20, 18, 16)),
    "bump": synthetic_array("bump", (16, 16, 16)),
    "step": synthetic_array("step", (16, 16, 16)),
    "noise4": RNG.normal(size=(5, 6, 7, 4)),
    "matrix": RNG.normal(size=(30, 12)),
    "vector": RNG.normal(size=40),
    "zero": np.zeros((3, 4, 2)),
    "constant": np.full((4, 5), 2.5),
    "one": np.array([[[3.0]]]),
    "line": np.arange(9.0).reshape(1, 9),
    "tiny": RNG.normal(size=(4, 4)) * 1e-300,
}


@pytest.mark.parametrize("name", GRIDS)
@pytest.mark.parametrize("target", [0.3, 0.05, 1e-3, 1e-6])
def test_targets_hold(name, target):
    a = GRIDS[name]
    b = decompress_array(compress_array(a, ErrorTarget.rel(target)))
    a, b = (np.ldexp(x, 1000) if name == "tiny" else x for x in (a, b))
    assert ((a - b) ** 2).sum() <= target**2 * (a**2).sum() * (1 + 1e-9) + 1e-300


@pytest.mark.parametrize("kw", [{"coder": "huffman"}, {"mode": "all_run"}, {"mode": "all_raw"}, {"order": "F"}, {"chunk": 7}, {"chunk": 1 << 20}, {"schedule": "sequential"}])
def test_variants_restore_the_same(kw):
    a = GRIDS["cosines"]
    e = np.linalg.norm(a - decompress_array(compress_array(a, ErrorTarget.rel(0.01), **kw))) / np.linalg.norm(a)
    assert e <= 0.01


def test_core_bound_and_minimality():
    a = GRIDS["noise4"]
    for rel in (0.3, 0.1, 0.01):
        z = compress_array(a, ErrorTarget.rel(rel), policy="price", rounding="floor")
        core = X.omt_array(a).core
        s = rel**2 * (a**2).sum()
        assert ((core - core_array(z)) ** 2).sum() <= s * (1 + 1e-9)
        z.header["sent"] -= 1
        q, neg, lead = fac.quantise_array(core.ravel(), z.header["exponent"])
        p = z.header["plane"]
        low = p + (np.arange(len(q)) >= z.header["sent"])
        left = (q & ((np.uint64(1) << low.astype(np.uint64)) - np.uint64(1))).astype(float)
        assert (left**2).sum() * 4.0 ** (z.header["exponent"] - 63) > s


def test_transform_identities():
    a = GRIDS["cosines"]
    one, seq = X.omt_array(a), X.omt_array(a, "sequential")
    assert np.isclose((one.core**2).sum(), (a**2).sum())
    assert np.allclose(np.abs(one.core), np.abs(seq.core), atol=1e-6 * np.abs(one.core).max())
    assert np.allclose(X.inverse_array(one.core, one.factors), a, atol=1e-9)
    for n in range(3):
        u = X.basis_by_svd(a, n)
        assert np.allclose(np.abs((u[:, :3] * one.factors[n][:, :3]).sum(axis=0)), 1, atol=1e-6)
        s = fac.array_slice_norms(one.core)[n]
        assert np.allclose(np.sqrt(one.eigenvalues[n]), s, atol=1e-6 * s[0]) and np.isclose((s**2).sum(), (a**2).sum())
    skew = [np.eye(n) + 0.1 * RNG.normal(size=(n, n)) for n in a.shape]
    assert np.allclose(X.inverse_array(X.project(a, skew), skew), a, atol=1e-8)
    d = RNG.normal(size=a.shape)
    assert np.isclose(np.linalg.norm(X.inverse_array(one.core + d, one.factors) - a), np.linalg.norm(d))


def test_invariances():
    a = GRIDS["bump"]
    s = [fac.array_slice_norms(X.omt_array(x).core)[0] for x in (a, a[RNG.permutation(16)], np.pad(a, ((0, 3), (0, 0), (0, 0))), a * 3)]
    assert np.allclose(s[0], s[1]) and np.allclose(s[0], s[2][:16]) and np.allclose(s[0] * 3, s[3])
    nz = lambda x: int((np.abs(X.omt_array(x).core) > 1e-9).sum())
    assert nz(synthetic_array("rank1", (12, 12, 12))) == 1 and nz(a) <= 8


def test_resampling_equals_data(spark):
    a = GRIDS["cosines"]
    z = compress_array(a, ErrorTarget.rel(1e-13))
    assert np.allclose(decompress_array(R.decimate(z, 2, "pick")), a[::2, ::2, ::2], atol=1e-9)
    assert np.allclose(decompress_array(R.decimate(z, 2, "literal")), a[::2, ::2, ::2], atol=1e-9)
    assert np.allclose(decompress_array(z[::-1, 3:9:2, 4]), a[::-1, 3:9:2, 4:5], atol=1e-9)
    box = a.reshape(10, 2, 9, 2, 8, 2).mean(axis=(1, 3, 5))
    assert np.allclose(decompress_array(R.decimate(z, 2, "box")), box, atol=1e-9)
    assert np.allclose(decompress_array(R.project_axis(z, 1)), a.sum(axis=1, keepdims=True), atol=1e-8)
    assert np.allclose(decompress_array(R.frame(z, 0, 3)), a[3:4], atol=1e-9)
    assert np.allclose(decompress_array(R.upsample_linear(z, 0, 2))[::2], a, atol=1e-9)
    taps = R.lanczos_taps(2)
    assert np.allclose(taps / taps[4], [0, -0.0637, 0, 0.5732, 1, 0.5732, 0, -0.0637, 0], atol=1e-4)
    long = RNG.normal(size=99)
    assert np.allclose(R.convolve_rows(a[:, :, 0], long, fft_over=10), R.convolve_rows(a[:, :, 0], long, fft_over=1000))


def test_policies_and_strict():
    a = GRIDS["bump"]
    z = compress_strict(a, ErrorTarget.rel(0.01), policy="price")
    assert audit(z, a)["rel_error"] <= 0.01
    a = GRIDS["noise4"]
    assert ratio(compress_array(a, ErrorTarget.size(300))) > ratio(compress_array(a, ErrorTarget.rel(1e-6)))


def test_midpoint_can_pass_the_target():
    v = np.array([8.0] + [4.001] * 50)
    q, neg, lead = fac.quantise_array(v, 3)
    kept = q & ~np.uint64((1 << 62) - 1)
    from gridpress.operators.planes import restore

    err = [((restore(kept, neg, 62, 51, 3, mid) - v) ** 2).sum() for mid in (False, True)]
    assert err[0] < 1e-3 and 200 < err[1] < 208


def test_hybrid_equals_local_and_storage(spark, tmp_path):
    a = GRIDS["noise4"]
    g = GridFrame.of(spark, a)
    local, hybrid = X.omt(g, "one_pass"), X.omt(g, "hybrid")
    core = GridFrame(hybrid.cells(spark), g.spec).dense()
    assert np.allclose(np.abs(core), np.abs(local.core), atol=1e-8)
    z = compress(g, ErrorTarget.rel(0.05), schedule="hybrid")
    assert M.rel_error(g, decompress(z, spark)) <= 0.05
    save(z, str(tmp_path / "a"), spark)
    back = open_archive(str(tmp_path / "a"), spark)
    assert np.allclose(decompress_array(back), decompress_array(z))
    z2 = compress_array(a, ErrorTarget.rel(0.05), g.spec)
    save(z2, str(tmp_path / "b"), spark)
    assert np.allclose(decompress_array(open_archive(str(tmp_path / "b"), spark)), decompress_array(z2))
    from gridpress.sources.datasource import read_archive

    df = read_archive(spark, str(tmp_path / "b")).where("i1 >= 1 and i1 < 3 and i3 = 2")
    want = decompress_array(z2)[1:3, :, 2:3, :]
    assert df.count() == want.size and np.isclose(df.agg({"v": "sum"}).first()[0], want.sum())


@pytest.mark.parametrize("per", [1, 2, 5])
def test_grams_do_not_depend_on_slabs(spark, per):
    a = GRIDS["noise4"]
    g = GridFrame.of(spark, a)
    got = X.slab_grams(to_slabs(g, 1, per), g.spec, 1, [0, 2, 3], tile=3)
    for n in (0, 2, 3):
        u = X._unfolded(a, n)
        assert np.allclose(got[n], u @ u.T)


def test_measures(spark):
    a = GRIDS["bump"]
    g, h = GridFrame.of(spark, a), GridFrame.of(spark, a + 0.01)
    row = M.compare(g, h).first()
    assert math.isclose(row.rmse, 0.01, rel_tol=1e-9) and math.isclose(row.psnr, M.psnr_arrays(a, a + 0.01), rel_tol=1e-9)
    sparse = GridFrame(spark.createDataFrame([(5, 2.0)], "idx long, v double"), GridSpec(("x", "y"), (4, 4)))
    st = grid_stats(sparse)
    assert (st.low, st.high, st.energy, st.cells) == (0.0, 2.0, 4.0, 16)
    assert np.allclose(synthetic(spark, "cosines", (6, 5, 4)).dense(), synthetic_array("cosines", (6, 5, 4)))
    with pytest.raises(Exception):  # noqa: B017
        GridFrame(spark.createDataFrame([(0, float("nan"))], "idx long, v double"), GridSpec(("x",), (1,))).clean().df.collect()


def test_raw_files(spark, tmp_path):
    from gridpress.sources.cubes import read_cells, read_raw

    a = RNG.integers(0, 255, (4, 3, 2)).astype("<u1")
    (tmp_path / "v.raw").write_bytes(a.tobytes())
    assert (read_raw(spark, str(tmp_path / "v.raw"), a.shape, "u8").dense() == a).all()
    (tmp_path / "f.raw").write_bytes(a.tobytes(order="F"))
    assert (read_raw(spark, str(tmp_path / "f.raw"), a.shape, "u8", "F").dense() == a).all()
    (tmp_path / "c.csv").write_text("i1,i2,v\n0,1,2.5\n1,0,1\n")
    got = read_cells(spark, str(tmp_path / "c.csv"), "csv", GridSpec(("i1", "i2"), (2, 2))).dense()
    assert got.tolist() == [[0, 2.5], [1, 0]]


@pytest.mark.parametrize("name", ["cosines", "noise4", "vector", "zero", "constant", "matrix"])
@pytest.mark.parametrize("tol", [0.2, 1e-3])
def test_baselines_keep_their_bounds(name, tol):
    from gridpress.baselines import block_xform, predictive, set_part

    a = GRIDS[name]
    span = float(a.max() - a.min())
    assert np.abs(block_xform.decompress(block_xform.compress(a, tol)) - a).max() <= tol
    assert np.abs(predictive.decompress(predictive.compress(a, tol)) - a).max() <= tol * span * (1 + 1e-9) + 1e-12
    for scope in ("run", "brick"):
        assert np.abs(set_part.decompress(set_part.compress(a, tol, scope)) - a).max() <= tol + 1e-6 * np.abs(a).max()


def test_rank_cut_is_flat():
    from gridpress.baselines import rank_cut

    a = GRIDS["cosines"]
    v = [M.psnr_arrays(a, rank_cut.decompress(rank_cut.compress(a, energy_tail=t))) for t in (1e-4, 1e-6, 1e-9, 1e-12)]
    assert abs(v[-1] - v[-2]) < 1.0 and v[0] <= v[-1] + 1
    assert M.psnr_arrays(a, rank_cut.decompress(rank_cut.compress(a, energy_tail=1e-6, quantiser="log"))) > 20


def test_blocks_decode_alone():
    from gridpress.baselines import block_xform

    a = GRIDS["cosines"]
    z = block_xform.compress(a, 1e-4)
    whole = block_xform.decompress(z)
    for at in ((0, 0, 0), (4, 4, 3), (2, 1, 0)):
        box = tuple(slice(4 * i, 4 * i + 4) for i in at)
        assert np.array_equal(block_xform.block_at(z, at), whole[box])
    assert np.allclose(block_xform.BASIS @ block_xform.BASIS.T, np.eye(4))


def test_long_axis_needs_no_gram_of_its_side(monkeypatch):
    """Tables of many short rows: no larger an archive than by the full basis, without what grows with the square of the rows."""
    import tracemalloc

    from gridpress.operators.codec import array_stats

    a = np.random.default_rng(8).normal(0, 1, (1500, 6)) * np.arange(1, 7)
    for target in (ErrorTarget.psnr(30), ErrorTarget.psnr(60), ErrorTarget.rel(1e-3)):
        z = compress_array(a, target)
        with monkeypatch.context() as m:
            m.setattr(X, "LONG_AXIS", 1 << 30)
            full = compress_array(a, target)
        assert z.header["shape"] == (1500, 6) and z.bytes() <= full.bytes()
        assert ((decompress_array(z) - a) ** 2).sum() <= target.to_sse(array_stats(a)) * (1 + 1e-9)
    b = np.random.default_rng(9).normal(0, 1, (20000, 6))
    tracemalloc.start()
    t = X.omt_array(b)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 50e6 and np.allclose(X.inverse_array(t.core, t.factors), b)
