"""The experiments, on the given tables' cubes and on formula grids; each returns a DataFrame of its rows.

Cubes here are of a size that one process may hold, and independent runs are dealt
to executors, one row of parameters a task; curves of quality also take larger ones, in slabs.
"""

from __future__ import annotations

import math
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from gridpress.baselines import block_xform, controls, predictive, rank_cut, set_part
from gridpress.operators import metrics as M
from gridpress.operators import planes as P
from gridpress.operators import resample as R
from gridpress.operators.codec import bit_rate, compress, compress_array, core_array, decompress, decompress_array, factor_share, ratio, rd_trace
from gridpress.operators.entropy import ideal_bits
from gridpress.operators.factors import plane_depth
from gridpress.operators.long_axis import compress_long, even_slabs, long_axis, long_transform, rank_cut_long, restored_errors, slab_array
from gridpress.operators.planes import quantise_array, scale_exponent, split_plane
from gridpress.operators.spectrum import factor_spectrum, grid_spectrum, spectrum_histogram
from gridpress.operators.transform import Transformed, _unfolded, eigen_basis, inverse_array, multiply, omt_array
from gridpress.plans.grid import LOCAL_CELLS, GridFrame, GridSpec, slab_cells
from gridpress.plans.targets import ErrorTarget, grid_stats
from gridpress.session import ship
from gridpress.sources.cubes import cube, synthetic_array

CODECS = ("plane_omt", "plane_omt_price", "rank_cut", "block_xform", "predictive", "set_part")
CURVE = "cube string, codec string, knob double, bytes long, ratio double, rmse double, psnr double, sec_c double, sec_d double"
#: knobs are PSNR targets, from which each codec's own knob follows
PSNRS = (20.0, 30.0, 40.0, 50.0, 60.0)
#: cells of all grids that one experiment holds in one process and sends to executors
HELD_CELLS = 1 << 23


def coded(a: np.ndarray, codec: str, db: float, width: int = 8, integer: bool = False, whole: float | None = None):
    """(coded grid, its decoder) of a codec set for a PSNR; of a slab, by the range of the `whole` grid.

    plane_omt keeps a tenth of the error for factors and so meets the target; plane_omt_price
    is the reference's rule, factors to the core's price, which bounds the core's error only.
    """
    span = float(a.max() - a.min()) or 1.0
    goal = (whole or span) / (2 * 10 ** (db / 20))  # the RMSE that the target allows
    if codec.startswith("plane_omt"):
        spec = GridSpec(tuple(f"i{n}" for n in range(a.ndim)), a.shape, width, integer)
        return compress_array(a, ErrorTarget.psnr(db), spec, policy="price" if codec.endswith("price") else "price+budget"), decompress_array
    if codec == "rank_cut":
        energy = float((a * a).sum()) or 1.0
        return rank_cut.compress(a, energy_tail=min(0.5, goal**2 * a.size / energy)), rank_cut.decompress
    if codec == "block_xform":
        return block_xform.compress(a, goal * 2), block_xform.decompress
    if codec == "predictive":
        return predictive.compress(a, goal * math.sqrt(3) / span), predictive.decompress
    return set_part.compress(a, goal * math.sqrt(3)), set_part.decompress


def run_codec(a: np.ndarray, codec: str, db: float, width: int = 8, integer: bool = False) -> tuple[int, float, float, float]:
    """(bytes, rmse, seconds to compress, to restore) of a codec set for a PSNR."""
    t0 = time.perf_counter()
    z, back = coded(a, codec, db, width, integer)
    t1 = time.perf_counter()
    b = back(z)
    t2 = time.perf_counter()
    return z.bytes(), float(np.sqrt(((a - b) ** 2).mean())), t1 - t0, t2 - t1


def at_ratio(a: np.ndarray, codec: str, ratio: float, width: int = 8, tries: int = 9):
    """(coded grid, decoder) of the best quality whose bytes are within a ratio; None where the codec does not reach it.

    plane_omt is told the bytes; the others' knobs are halved between PSNRs.
    """
    most = int(a.size * width / ratio)
    if codec == "plane_omt":
        try:
            return compress_array(a, ErrorTarget.size(most), GridSpec(tuple(f"i{n}" for n in range(a.ndim)), a.shape, width)), decompress_array
        except ValueError:
            return None
    low, high, best = 0.0, 120.0, None
    for _ in range(tries):
        db = (low + high) / 2
        got = coded(a, codec, db, width)
        if got[0].bytes() <= most:
            best, low = got, db
        else:
            high = db
    return best


def dealt(spark: SparkSession, grids: dict[str, tuple[np.ndarray, int]], jobs: list[tuple], fields: str, schema: str, one) -> DataFrame:
    """Rows of one(grid, width, *job) for jobs (cube, ...); a job is a task, grids travel by a broadcast of checked size."""
    if sum(a.size for a, _ in grids.values()) > HELD_CELLS:
        raise ValueError("grids of an experiment are too large to be held by one process")
    ship(spark)
    shared = spark.sparkContext.broadcast(grids)
    names = [f.split()[0] for f in fields.split(", ")]
    rows = spark.createDataFrame(jobs, fields).repartition(max(1, min(64, len(jobs))))
    types = [T._parse_datatype_string(f.strip().split(" ", 1)[1]) for f in schema.split(", ")]
    out = pa.schema([(f.strip().split(" ", 1)[0], to_arrow_type(t)) for f, t in zip(schema.split(", "), types, strict=True)])

    def run(batches):
        for b in batches:
            for job in zip(*(b.column(n).to_pylist() for n in names), strict=True):
                got = list(one(*shared.value[job[0]], *job))
                if got:
                    yield pa.RecordBatch.from_pylist([dict(zip(out.names, r, strict=True)) for r in got], schema=out)

    return rows.mapInArrow(run, schema)


def psnr_or_none(a: np.ndarray, b: np.ndarray) -> float | None:
    v = M.psnr_arrays(a, b)
    return None if math.isinf(v) else v


def quality_curve(spark: SparkSession, grids: dict[str, tuple[np.ndarray | GridFrame, int]], codecs: tuple[str, ...] = CODECS, psnrs: tuple[float, ...] = PSNRS) -> DataFrame:
    """PSNR against ratio for cubes, codecs and targets (ratio against the original width); one run a task, or many tasks a run for grids in slabs."""
    held = {n: g for n, g in grids.items() if not isinstance(g[0], GridFrame)}

    def one(a, width, g, c, p):
        size, e, tc, td = run_codec(a, c, p, width)
        yield curve_row(g, c, p, size, a.size, width, e, float(a.max() - a.min()), tc, td)

    out = dealt(spark, held, [(g, c, float(p)) for g in held for c in codecs for p in psnrs], "cube string, codec string, knob double", CURVE, one)
    rows = [r for n, (g, width) in grids.items() if n not in held for r in slab_curve(n, g, width, codecs, psnrs)]
    return out.unionByName(spark.createDataFrame(rows, CURVE)) if rows else out


def curve_row(g: str, c: str, p: float, size: int, cells: int, width: int, e: float, span: float, tc: float, td: float) -> tuple:
    return g, c, float(p), size, cells * width / size, e, 20 * math.log10(span / (2 * e)) if e > 0 and span > 0 else None, tc, td


def slab_curve(name: str, grid: GridFrame, width: int, codecs: tuple[str, ...], psnrs: tuple[float, ...]) -> list[tuple]:
    """Rows of quality_curve for a grid in slabs.

    plane_omt and rank_cut transform the whole grid where one axis is longer than all others
    together; else plane_omt takes the hybrid transform, and rank_cut codes each slab by itself,
    as the other baselines do.  Seconds are those of this process for what codes the whole
    grid, and sums over slabs for the others.
    """
    axis = long_axis(grid.spec.shape)
    at = int(np.argmax(grid.spec.shape)) if axis is None else axis
    slabs = even_slabs(grid, at)
    grid = GridFrame(slab_cells(slabs, grid.spec, at), grid.spec)
    t = long_transform(grid, slabs) if axis is not None else None
    stats = t.stats if t else grid_stats(grid)
    cells, span = grid.spec.cells, stats.span
    goal = {p: (span or 1.0) / (2 * 10 ** (p / 20)) for p in psnrs}
    own = [(c, p) for c in codecs for p in psnrs if c.startswith("plane_omt")]
    policy = {c: "price" if c.endswith("price") else "price+budget" for c, _ in own}
    rows = {}
    if t and own:
        long = compress_long(t, [(ErrorTarget.psnr(p), policy[c]) for c, p in own])
        t0 = time.perf_counter()
        errors = restored_errors(t, long)
        each = (time.perf_counter() - t0) / len(own)
        rows |= {job: (z.bytes, sse, z.seconds, each) for job, z, sse in zip(own, long, errors, strict=True)}
    for c, p in own if t is None else ():
        t0 = time.perf_counter()
        z = compress(grid, ErrorTarget.psnr(p), "hybrid", policy[c])
        size, tc, t0 = z.bytes(), time.perf_counter() - t0, time.perf_counter()
        rows[c, p] = size, M.sse(grid, decompress(z, grid.df.sparkSession)), tc, time.perf_counter() - t0
    if t and "rank_cut" in codecs:
        t0 = time.perf_counter()
        got = rank_cut_long(t, [min(0.5, goal[p] ** 2 * cells / (stats.energy or 1.0)) for p in psnrs])
        each = (time.perf_counter() - t0) / len(psnrs)
        rows |= {("rank_cut", p): (size, sse, t.seconds, each) for p, (size, sse) in zip(psnrs, got, strict=True)}
    rows |= slabs_coded(slabs, grid.spec, at, [(c, p) for c in codecs for p in psnrs if (c, p) not in rows], width, span)
    return [curve_row(name, c, p, size, cells, width, math.sqrt(sse / cells), span, tc, td) for (c, p), (size, sse, tc, td) in rows.items()]


def slabs_coded(slabs: DataFrame, spec: GridSpec, axis: int, jobs: list[tuple[str, float]], width: int, span: float) -> dict[tuple[str, float], tuple]:
    """(bytes, squared error, seconds to compress, to restore) of codecs over slabs, each coded by itself, to errors of the whole grid's range."""
    form = "job int, bytes long, sse double, sec_c double, sec_d double"

    def run(batches):
        for b in batches:
            for raw in b.column("block").to_pylist():
                a = slab_array(raw, spec, axis)
                for k, (codec, db) in enumerate(jobs):
                    t0 = time.perf_counter()
                    z, back = coded(a, codec, db, width, whole=span)
                    t1 = time.perf_counter()
                    sse = float(((back(z) - a) ** 2).sum())
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([z.bytes()]), pa.array([sse]), pa.array([t1 - t0]), pa.array([time.perf_counter() - t1])], names=["job", "bytes", "sse", "sec_c", "sec_d"])

    if not jobs:
        return {}
    got = slabs.select("block").mapInArrow(run, form).groupBy("job").agg(*(F.sum(c).alias(c) for c in ("bytes", "sse", "sec_c", "sec_d"))).collect()
    return {jobs[r.job]: (r.bytes, r.sse, r.sec_c, r.sec_d) for r in got}


def lead_zone(curve: DataFrame, steps: int = 32) -> DataFrame:
    """(cube, lo, hi, share): the ratios at which plane_omt's interpolated PSNR leads, of a grid over its own ratios.

    A codec that does not reach a ratio is beaten there; below its least ratio it keeps the
    PSNR of that.  The variant of the method by prices is not set against it.
    """

    def zone(key: tuple, t: pa.Table) -> pa.Table:
        df = t.to_pandas().dropna()
        curves = {c: g.sort_values("ratio") for c, g in df.groupby("codec") if c != "plane_omt_price"}
        own = curves.get("plane_omt")
        at = np.geomspace(own.ratio.min(), own.ratio.max(), steps) if own is not None else np.array([])
        lead = []
        for x in at:
            v = {c: float(np.interp(math.log(x), np.log(g.ratio), g.psnr)) if x <= g.ratio.max() * (1 + 1e-12) else -math.inf for c, g in curves.items()}
            lead.append(max(v, key=v.get) == "plane_omt")
        won = at[np.array(lead, bool)] if len(at) else at
        return pa.table({"cube": [key[0].as_py()], "lo": pa.array([float(won.min()) if len(won) else None], pa.float64()), "hi": pa.array([float(won.max()) if len(won) else None], pa.float64()), "share": pa.array([float(np.mean(lead)) if lead else None], pa.float64())})

    return curve.select("cube", "codec", "ratio", "psnr").groupBy("cube").applyInArrow(zone, "cube string, lo double, hi double, share double")


def grids(spark: SparkSession, d: str, cubes: tuple[str, ...], formulas: tuple[str, ...] = (), edge: int = 32, slabs: bool = False) -> dict[str, tuple]:
    """(array, width) by name; with `slabs`, cubes that one process may not hold stay frames."""
    out = {}
    for name in cubes:
        g = cube(spark, d, name)
        out[name] = (g if slabs and g.spec.cells > LOCAL_CELLS else g.dense(), g.spec.width)
    return out | {f: (synthetic_array(f, (edge,) * 3), 8) for f in formulas}


def w1_quality(spark: SparkSession, d: str) -> DataFrame:
    return quality_curve(spark, grids(spark, d, ("ship_density", "trade_value", "event_pulse", "glyph_pairs", "dialog_len", "page_bytes", "embed_matrix", "embed_cube"), ("rank1", "cosines", "step", "bump"), slabs=True))


def w2_time_varying(spark: SparkSession, d: str) -> DataFrame:
    return quality_curve(spark, grids(spark, d, ("order_flow", "event_pulse_4d")))


def core_planes(spark: SparkSession, a: np.ndarray) -> DataFrame:
    """(idx, q, neg, lead) of a grid's core, by the relational plane coder."""
    return P.quantise(GridFrame.of(spark, omt_array(a).core).df)


def w3_threshold_planes(spark: SparkSession, d: str) -> DataFrame:
    """Ones of each plane, and the stated ratios at which an archive, all its parts counted, stops there."""
    g = cube(spark, d, "trade_value")
    a = g.dense()
    stops: dict[int, list[int]] = {}
    for r in (1000, 300, 100, 50):
        try:
            z = compress_array(a, ErrorTarget.size(a.size * g.spec.width // r), g.spec)
        except ValueError:  # smaller than any archive of this grid
            continue
        stops.setdefault(z.header["plane"], []).append(r)
    at = F.create_map(*(F.lit(x) for p, rs in stops.items() for x in (p, rs))) if stops else F.lit(None).cast("map<int,array<int>>")
    ones = M.ones_per_plane(core_planes(spark, a))
    return ones.select("plane", "ones", F.lit(a.size // 2).cast("long").alias("half"), F.coalesce(F.try_element_at(at, F.col("plane")), F.array().cast("array<int>")).alias("stops_at_ratio"))


def w4_centroids(spark: SparkSession, d: str) -> DataFrame:
    a = cube(spark, d, "trade_value").dense()
    q = core_planes(spark, a).cache()
    got = M.ones_per_plane(q).join(M.plane_centroid(q), "plane")
    return got.select("plane", "ones", "centroid", F.lit(a.size / 2).alias("middle")).orderBy(F.desc("plane"))


def _core_codes(a: np.ndarray):
    c = omt_array(a).core.ravel()
    q, neg, lead = quantise_array(c, scale_exponent(float(np.abs(c).max())))
    for p in range(63, -1, -1):
        yield p, *split_plane(q, lead, neg, p)


def w5_w6_runs_and_rates(spark: SparkSession, d: str, names: tuple[str, ...] = ("trade_value", "glyph_pairs")) -> DataFrame:
    """Symbols, longest run, ideal bits and rate of each plane: leading bits in runs, and all bits verbatim for comparison."""

    def one(a, _, name):
        for p, runs, raw, _s in _core_codes(a):
            bits = ideal_bits(runs) + len(raw)
            yield name, p, len(runs), int(runs.max(initial=0)), float(bits), float(bits / a.size), len(raw)

    return dealt(spark, grids(spark, d, names), [(n,) for n in names], "cube string", "cube string, plane int, symbols long, longest long, bits double, rate double, verbatim long", one)


def w6_core_profile(spark: SparkSession, d: str) -> DataFrame:
    """The same by the relational operators, for the planes of a core that an archive of relative error 0.001 sends."""
    a = cube(spark, d, "event_pulse").dense()
    stop = compress_array(a, ErrorTarget.rel(1e-3)).header["plane"]
    return M.plane_profile(core_planes(spark, a).cache(), stop, 63)


def w5_run_lengths(spark: SparkSession, d: str, names: tuple[str, ...] = ("trade_value", "glyph_pairs")) -> DataFrame:
    """The distribution of run lengths in each plane of the cores."""

    def one(a, _, name):
        for p, runs, _r, _s in _core_codes(a):
            for run, freq in zip(*(x.tolist() for x in np.unique(runs, return_counts=True)), strict=True):
                yield name, p, run, freq

    return dealt(spark, grids(spark, d, names), [(n,) for n in names], "cube string", "cube string, plane int, run long, freq long", one)


def w8_slice_norms(spark: SparkSession, d: str) -> DataFrame:
    a = cube(spark, d, "glyph_pairs").dense()
    g = GridFrame.of(spark, omt_array(a).core)
    return M.slice_norms(g.df, g.spec)


def w9_round_trips(spark: SparkSession, d: str) -> DataFrame:
    return quality_curve(spark, grids(spark, d, ("ship_density",), ("cosines", "bump")), psnrs=(30.0, 45.0))


def brick_ladder(spark: SparkSession, held: dict[str, tuple[np.ndarray, int]], codecs: tuple[str, ...], ratios: tuple[float, ...], edge: int = 16) -> DataFrame:
    """A centre brick's PSNR by codec at stated ratios; null where a codec does not reach one.

    plane_omt restores the brick alone, from factor rows; the others restore the grid.
    """

    def one(a, width, name, codec, ask):
        at = tuple(n // 2 for n in a.shape)
        e = min(edge, *a.shape)
        box = tuple(slice(max(0, c - e // 2), c - e // 2 + e) for c in at)
        got = at_ratio(a, codec, ask, width)
        if got is None:
            yield name, codec, ask, None, None
            return
        z, back = got
        part = decompress_array(R.brick(z, at, e)) if codec == "plane_omt" else back(z)[box]
        yield name, codec, ask, a.size * width / z.bytes(), psnr_or_none(a[box], part)

    return dealt(spark, held, [(g, c, float(r)) for g in held for c in codecs for r in ratios], "cube string, codec string, asked double", "cube string, codec string, asked double, ratio double, brick_db double", one)


def w10_bricks(spark: SparkSession, d: str) -> DataFrame:
    """The ladder of a centre brick, the method beside its four baselines."""
    return brick_ladder(spark, grids(spark, d, ("trade_value",), ("bump",)), ("plane_omt", "rank_cut", "block_xform", "predictive", "set_part"), (10.0, 40.0, 160.0, 400.0))


SPECTRA = (("event_pulse",), ("cosines",))


def w11_spectra(spark: SparkSession, d: str) -> DataFrame:
    """High-frequency share of restored grids by codec and quality, and the mean frequency of the method's factors."""

    def one(a, width, name, codec, db):
        z, back = coded(a, codec, db, width)
        b = back(z)
        mean = None
        if codec == "plane_omt":
            top = [(np.abs(np.fft.rfftfreq(len(u)))[:, None] * factor_spectrum(u)).sum() / max(factor_spectrum(u).sum(), 1e-300) for u in z.factors()]
            mean = float(np.mean(top))
        yield name, codec, db, a.size * width / z.bytes(), M.high_freq_share(grid_spectrum(b) ** 2), M.high_freq_share(grid_spectrum(a) ** 2), mean

    held = grids(spark, d, *SPECTRA, edge=24)
    jobs = [(g, c, p) for g in held for c in ("plane_omt", "rank_cut", "block_xform", "predictive", "set_part") for p in (20.0, 30.0, 40.0, 60.0)]
    return dealt(spark, held, jobs, "cube string, codec string, target_db double", "cube string, codec string, target_db double, ratio double, high_share double, high_share_original double, factor_frequency double", one)


def w11_histograms(spark: SparkSession, d: str) -> DataFrame:
    """Histograms of spectral magnitudes, in quarter decades, of the original and of restored grids."""

    def one(a, width, name, codec, db):
        b = a
        if codec != "original":
            z, back = coded(a, codec, db, width)
            b = back(z)
        for k, n in spectrum_histogram(b).items():
            yield name, codec, db, k / 4, n

    held = grids(spark, d, *SPECTRA, edge=24)
    jobs = [(g, "original", 0.0) for g in held] + [(g, c, p) for g in held for c in ("plane_omt", "block_xform", "predictive", "set_part") for p in (20.0, 40.0)]
    return dealt(spark, held, jobs, "cube string, codec string, target_db double", "cube string, codec string, target_db double, log10_magnitude double, n long", one)


def w12_times(spark: SparkSession, d: str) -> DataFrame:
    """Seconds and MB/s both ways, a small and a large grid, five codecs, over a range of ratios."""

    def one(a, width, name, codec, db):
        size, _, tc, td = run_codec(a, codec, db, width)
        mb = a.size * width / 1e6
        yield name, codec, db, a.size * width / size, mb, tc, td, mb / tc, mb / td, tc / td

    held = grids(spark, d, ("event_pulse", "trade_value"), ("cosines",), edge=64)
    jobs = [(g, c, p) for g in held for c in ("plane_omt", "rank_cut", "block_xform", "predictive", "set_part") for p in (20.0, 40.0, 60.0)]
    return dealt(spark, held, jobs, "cube string, codec string, target_db double", "cube string, codec string, target_db double, ratio double, mb double, sec_c double, sec_d double, mb_s_c double, mb_s_d double, asymmetry double", one)


def round_trip_stages(a: np.ndarray, db: float) -> list[tuple[str, str, float]]:
    """(direction, stage, seconds): eigen bases, projection and planes one way, planes, factors and products back."""
    c = M.StageClock()
    with c.stage("eigen"):
        bases = [eigen_basis(_unfolded(a, n) @ _unfolded(a, n).T) for n in range(a.ndim)]
    with c.stage("projection"):
        core = a
        for n, (_, u) in enumerate(bases):
            core = multiply(core, u, n, transpose=True)
    t = Transformed(GridSpec(tuple(f"i{n + 1}" for n in range(a.ndim)), core.shape), [u for _, u in bases], [lam for lam, _ in bases], core)
    with c.stage("planes"):
        z = compress_array(a, ErrorTarget.psnr(db), transformed=t)
    up = [("compress", s, v) for s, v in c.rows()]
    c = M.StageClock()
    with c.stage("planes"):
        got = core_array(z)
    with c.stage("factors"):
        u = z.factors()
    with c.stage("products"):
        inverse_array(got, u, skip_zero_slices=True)
    return up + [("decompress", s, v) for s, v in c.rows()]


def w12_w13_clock(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of the stages of a round trip, loading and saving included, of a small and a large grid at three qualities."""
    import tempfile

    rows = []
    for name in ("event_pulse", "trade_value"):
        t0 = time.perf_counter()
        g = cube(spark, d, name)
        a = g.dense()
        load = time.perf_counter() - t0
        for db in (20.0, 40.0, 60.0):
            z = compress_array(a, ErrorTarget.psnr(db), g.spec)
            held = tempfile.TemporaryFile()  # archives of one process are files of it
            t0 = time.perf_counter()
            for _, _, _, *parts in z.segments:
                held.writelines(parts)
            held.flush()
            save = time.perf_counter() - t0
            held.close()
            stages = round_trip_stages(a, db)
            stages = [("compress", "load", load), *[s for s in stages if s[0] == "compress"], ("compress", "save", save), *[s for s in stages if s[0] == "decompress"]]
            c, back = (sum(v for way, s, v in stages if way == x and s not in ("load", "save")) for x in ("compress", "decompress"))
            rows += [(name, db, ratio(z), *s) for s in stages] + [(name, db, ratio(z), "both", "asymmetry", c / back)]
    return spark.createDataFrame(rows, "cube string, target_db double, ratio double, direction string, stage string, seconds double")


def w14_decimation(spark: SparkSession, d: str, ask: float = 7.5) -> DataFrame:
    """Two-fold decimation by three filters, from archives of the reference's ratio, against an ideal low-pass of the original."""
    rows = []
    smooth = synthetic_array("cosines", (40, 40, 40)) + 0.3 * np.cos(40 * np.linspace(0, np.pi, 40))[:, None, None]
    g = cube(spark, d, "ship_density")
    for name, a, width in (("ship_density", g.dense(), g.spec.width), ("cosines", smooth, 8)):
        a = a[tuple(slice(0, n - n % 2) for n in a.shape)]
        f = np.fft.fftn(a)
        for axis, n in enumerate(a.shape):
            keep = np.abs(np.fft.fftfreq(n)) < 0.25
            f = f * keep.reshape([-1 if i == axis else 1 for i in range(a.ndim)])
        ideal = np.fft.ifftn(f).real[(slice(None, None, 2),) * a.ndim]
        z = compress_array(a, ErrorTarget.size(int(a.size * width / ask)), GridSpec(tuple(f"i{n}" for n in range(a.ndim)), a.shape, width))
        for how in ("pick", "box", "lanczos2"):
            got = decompress_array(R.decimate(z, 2, how))
            rows.append((name, how, ratio(z), float(np.sqrt(((got - ideal) ** 2).mean()))))
    return spark.createDataFrame(rows, "cube string, how string, ratio double, rmse_to_lowpass double")


def w15_sweeps(spark: SparkSession, d: str) -> DataFrame:
    """Sizes of set_part over tolerances (not always monotonic) and the floor of rank_cut's quality."""
    a = cube(spark, d, "event_pulse").dense()
    span, rows = float(a.max() - a.min()), []
    for k in np.geomspace(1e-4, 0.2, 12):
        z = set_part.compress(a, k * span)
        rows.append(("set_part", float(k), z.bytes(), M.psnr_arrays(a, set_part.decompress(z)) if k else None))
    smooth = synthetic_array("cosines", (24, 24, 24))
    for tail in (1e-1, 1e-2, 1e-3, 1e-4, 1e-6, 1e-8):
        z = rank_cut.compress(smooth, energy_tail=tail)
        rows.append(("rank_cut", tail, z.bytes(), M.psnr_arrays(smooth, rank_cut.decompress(z))))
    return spark.createDataFrame([(c, k, b, None if v is not None and math.isinf(v) else v) for c, k, b, v in rows], "codec string, knob double, bytes long, psnr double")


def w16_plane_depths(spark: SparkSession, d: str) -> DataFrame:
    """Planes spent on the core and on each factor, and the share of bytes that factors take, by stopping rule."""
    rows = []
    for name in ("event_pulse", "trade_value"):
        a = cube(spark, d, name).dense()
        for policy, stop, weight in (("price+budget", "price", True), ("price", "price", True), ("price", "core_plane", True), ("price", "price", False)):
            z = compress_array(a, ErrorTarget.rel(0.1), policy=policy, stop=stop, weight=weight)
            e = float(np.sqrt(((a - decompress_array(z)) ** 2).sum() / (a * a).sum()))
            rows.append((name, policy, stop, weight, 64 - z.header["plane"], [plane_depth(f) for f in z.coded], factor_share(z), bit_rate(z), e))
    return spark.createDataFrame(rows, "cube string, policy string, stop string, weighted boolean, core_planes int, factor_planes array<int>, factor_share double, bit_rate double, rel_error double")


def w17_orders_and_coders(spark: SparkSession, d: str) -> DataFrame:
    """C against F order, range against prefix coder, split against all-run and all-raw planes."""
    rows = []
    for name in ("ship_density", "event_pulse", "trade_value", "dialog_len"):
        a = cube(spark, d, name).dense()
        for label, kw in (("C", {}), ("F", {"order": "F"}), ("huffman", {"coder": "huffman"}), ("all_run", {"mode": "all_run"}), ("all_raw", {"mode": "all_raw"}), ("inline signs", {"signs": "inline"})):
            rows.append((name, label, compress_array(a, ErrorTarget.rel(0.1), **kw).core_bytes()))
    return spark.createDataFrame(rows, "cube string, variant string, core_bytes long")


def w18_original_width(spark: SparkSession, d: str) -> DataFrame:
    """An integer cube cast to doubles still counts its own width; all codecs, with lossless controls beside them."""
    a = cube(spark, d, "ship_density").dense()
    rows = [(c, a.size / coded(a, c, 40.0, 1, True)[0].bytes()) for c in CODECS]
    rows += [("lzma_u8", a.size / controls.lossless(a, "lzma", "<u1")), ("zlib_u8", a.size / controls.lossless(a, "zlib", "<u1")), ("float32", a.size / controls.to_float32(a)[1])]
    return spark.createDataFrame(rows, "codec string, ratio double")


def rd_curve(spark: SparkSession, d: str) -> DataFrame:
    """The rate-distortion trace of a core: ideal bits, squared error left and price after each block of each plane."""
    rows = rd_trace(omt_array(cube(spark, d, "event_pulse").dense()).core, 1024)
    return spark.createDataFrame(rows, "plane int, sent long, bits double, sse double, price double")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Compress the event cube at relative error 0.1, restore it, and audit; one row a stage."""
    from gridpress.operators.codec import audit

    a = cube(spark, d, "event_pulse").dense()
    rows = []
    for target in (0.1, 0.01):
        z = compress_array(a, ErrorTarget.rel(target))
        r = audit(z, a)
        rows.append((target, r["rel_error"], r["core_sse"], r["sse"], r["bytes"], r["ratio"], r["rel_error"] <= target))
    return spark.createDataFrame(rows, "target double, rel_error double, core_sse double, sse double, bytes long, ratio double, within boolean")


WORKLOADS = {f.__name__: f for f in (w1_quality, w2_time_varying, w3_threshold_planes, w4_centroids, w5_w6_runs_and_rates, w5_run_lengths, w6_core_profile, w8_slice_norms, w9_round_trips, w10_bricks, w11_spectra, w11_histograms, w12_times, w12_w13_clock, w14_decimation, w15_sweeps, w16_plane_depths, w17_orders_and_coders, w18_original_width, rd_curve)}

