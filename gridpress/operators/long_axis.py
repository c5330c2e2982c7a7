"""Grids of any size with one axis longer than all others together: transform, codec and errors, slab by slab.

The unfolding of such an axis is a tall matrix A of M columns.  Its co-Gram (M x M, a
sum over slabs) gives every basis: the eigenvectors V give A V, whose columns are the long
factor's times their slice norms, and partial traces give the Grams of the other axes.  So
the core has at most M x M cells and is held by the driver; the long factor, which has as
many cells as the grid, stays in slabs, and is coded and restored in them.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.baselines import rank_cut
from gridpress.operators import factors as fac
from gridpress.operators.codec import BUDGET_FACTORS, Archive, _budget, _crossing, _decode_chunk, _encode_core, _price, _rounding_errors, _shift_of, _Slabs, chunk_errors, core_array
from gridpress.operators.planes import CHUNK, quantise_array, scale_exponent, split_plane, sse_by_plane, stop_by_budget
from gridpress.operators.transform import LONG_AXIS, Transformed, _unfolded, eigen_basis, inverse_array, multiply
from gridpress.plans.grid import LOCAL_CELLS, GridFrame, GridSpec, to_slabs
from gridpress.plans.targets import ErrorTarget, GridStats
from gridpress.session import cut, ship

#: cells of a slab
SLAB_CELLS = 1 << 18


def long_axis(shape: tuple[int, ...]) -> int | None:
    """The axis that is longer than all others together, where a core of theirs can be held by one process."""
    n = int(np.argmax(shape))
    rest = math.prod(shape) // shape[n]
    return n if shape[n] >= LONG_AXIS and shape[n] > rest and rest * rest <= LOCAL_CELLS else None


def even_slabs(grid: GridFrame, axis: int) -> DataFrame:
    """Slabs of about SLAB_CELLS along an axis, whole blocks of four indices, one a task."""
    n = grid.spec.shape[axis]
    per = max(4, SLAB_CELLS // (grid.spec.cells // n) // 4 * 4)
    return cut(cut(to_slabs(grid, axis, per)).repartitionByRange(-(-n // per), "lo"))


def slab_array(raw: bytes, spec: GridSpec, axis: int) -> np.ndarray:
    """A slab's cells in the grid's order of axes."""
    v, shape = np.frombuffer(raw), list(spec.shape)
    shape[axis] = len(v) * spec.shape[axis] // spec.cells
    return v.reshape(shape)


@dataclass
class LongGrid:
    """A transformed grid: slabs of its cells, slabs of the long factor's weighted rows, and all else on the driver."""

    spec: GridSpec
    axis: int
    slabs: DataFrame
    rows: DataFrame
    core: np.ndarray
    factors: list[np.ndarray]  # of the long axis: the identity
    norms: list[np.ndarray]
    v: np.ndarray
    peak: float
    stats: GridStats
    seconds: float

    @property
    def row_spec(self) -> GridSpec:
        return GridSpec(("row", "col"), (self.spec.shape[self.axis], len(self.v)))


def long_transform(grid: GridFrame, slabs: DataFrame | None = None) -> LongGrid:
    t0 = time.perf_counter()
    spark, spec, n = grid.df.sparkSession, grid.spec, long_axis(grid.spec.shape)
    if n is None:
        raise ValueError("no axis is longer than all others together, or they are too long")
    ship(spark)
    slabs = even_slabs(grid, n) if slabs is None else slabs
    size = spec.cells // spec.shape[n]

    def matrices(batches):
        for b in batches:
            for raw in b.column("block").to_pylist():
                yield _unfolded(slab_array(raw, spec, n), n)

    def gram(batches):
        g, lo, hi = np.zeros((size, size)), math.inf, -math.inf
        for a in matrices(batches):
            g += a.T @ a
            lo, hi = min(lo, float(a.min())), max(hi, float(a.max()))
        if lo <= hi:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(size, dtype=np.int32)), pa.array([x.tobytes() for x in g], pa.binary()), pa.array(np.full(size, lo)), pa.array(np.full(size, hi))], names=["i", "g", "lo", "hi"])

    def total(key: tuple, t: pa.Table) -> pa.Table:
        g = sum(np.frombuffer(x) for x in t["g"].to_pylist())
        return pa.table({"i": t["i"][:1], "g": pa.array([g.tobytes()], pa.binary()), "lo": pa.array([min(t["lo"].to_pylist())]), "hi": pa.array([max(t["hi"].to_pylist())])})

    form = "i int, g binary, lo double, hi double"
    got = slabs.select("block").mapInArrow(gram, form).groupBy("i").applyInArrow(total, form).toArrow()
    g = np.empty((size, size))
    for i, raw in zip(got["i"].to_pylist(), got["g"].to_pylist(), strict=True):
        g[i] = np.frombuffer(raw)
    stats = GridStats(min(got["lo"].to_pylist()), max(got["hi"].to_pylist()), float(np.trace(g)), spec.cells)
    if _shift_of(max(abs(stats.low), abs(stats.high))):
        raise ValueError("squares of this grid would vanish or overflow")
    v = eigen_basis(g)[1]
    shared = spark.sparkContext.broadcast(v)

    def columns(batches):
        hi, lo, e = np.full(size, -math.inf), np.full(size, math.inf), np.zeros(size)
        for a in matrices(batches):
            w = a @ shared.value
            hi, lo, e = np.maximum(hi, w.max(axis=0)), np.minimum(lo, w.min(axis=0)), e + (w * w).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(size, dtype=np.int32)), pa.array(hi), pa.array(lo), pa.array(e)], names=["i", "hi", "lo", "e"])

    col = slabs.select("block").mapInArrow(columns, "i int, hi double, lo double, e double").groupBy("i").agg(F.max("hi").alias("hi"), F.min("lo").alias("lo"), F.sum("e").alias("e")).toArrow().sort_by("i")
    hi, lo, sigma = col["hi"].to_numpy(), col["lo"].to_numpy(), np.sqrt(col["e"].to_numpy())
    # the largest entry of a column is positive
    v = v * np.where(hi >= -lo, 1.0, -1.0)
    turn = spark.sparkContext.broadcast(v)

    def turned(batches):
        for b in batches:
            w = [np.ascontiguousarray(_unfolded(slab_array(raw, spec, n), n) @ turn.value).tobytes() for raw in b.column("block").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("slab"), b.column("lo"), pa.array(w, pa.binary())], names=["slab", "lo", "block"])

    rows = cut(slabs.select("slab", "lo", "block").mapInArrow(turned, "slab int, lo long, block binary"))
    rest = [m for m in spec.shape[:n] + spec.shape[n + 1 :]]
    core = np.moveaxis((sigma[:, None] * v.T).reshape([size, *rest]), 0, n)
    whole, factors, axes = g.reshape(rest + rest), [], list(range(len(rest)))
    for m in range(len(spec.shape)):
        if m == n:
            factors.append(np.eye(size))
            continue
        k = m - (m > n)
        other = [len(rest) if a == k else a for a in axes]
        factors.append(eigen_basis(np.einsum(whole, axes + other, [k, len(rest)]))[1])
        core = multiply(core, factors[m], m, transpose=True)
    norms = fac.array_slice_norms(core)
    norms[n] = sigma
    return LongGrid(spec, n, slabs, rows, core, factors, norms, v, float(max(hi.max(), -lo.min())), stats, time.perf_counter() - t0)


# ---- where the long factor stops ----


def _run_costs(t: LongGrid, e: int, floor: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Runs of each plane from `floor` on, and their ideal bits by the histogram of all slabs."""

    def histograms(batches):
        held: dict[int, list] = {}
        for b in batches:
            for raw in b.column("block").to_pylist():
                q, neg, lead = quantise_array(np.frombuffer(raw), e)
                for p in range(int(lead.max(initial=-1)), floor - 1, -1):
                    held.setdefault(p, []).append(np.unique(split_plane(q, lead, neg, p)[0], return_counts=True))
        for p, parts in held.items():
            runs, back = np.unique(np.concatenate([r for r, _ in parts]), return_inverse=True)
            n = np.bincount(back, weights=np.concatenate([c for _, c in parts])).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(runs), p, np.int32)), pa.array(runs), pa.array(n)], names=["plane", "run", "n"])

    got = t.rows.select("block").mapInArrow(histograms, "plane int, run long, n long").groupBy("plane", "run").agg(F.sum("n").alias("n")).toArrow().sort_by([("plane", "ascending"), ("run", "ascending")])
    plane, run, n = (got[c].to_numpy() for c in ("plane", "run", "n"))
    return {int(p): (run[plane == p], np.log2(n[plane == p].sum() / n[plane == p])) for p in np.unique(plane)}


def price_stops(t: LongGrid, e: int, prices: list[float], start: int) -> list[tuple[int, int]]:
    """factors.stop_by_price of the long factor for several prices; blocks of coefficients begin anew in each slab.

    Planes are looked at down to `start`, and on by eight while a price is not reached:
    slabs give the gains of their blocks, sums over slabs go before them, and each slab then
    looks at its own blocks.
    """
    if not t.peak:
        return [(64, 0)] * len(prices)
    unit, size, block = 4.0 ** (e - 63), len(t.v), fac.PRICE_BLOCK
    floor = int(np.clip(start, 0, scale_exponent(t.peak) + 63 - e))
    while True:
        costs = t.rows.sparkSession.sparkContext.broadcast(_run_costs(t, e, floor))
        planes = list(range(max(costs.value), floor - 1, -1))  # planes without runs have bits all the same

        def gains(batches, planes=planes, costs=costs):
            for b in batches:
                for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                    q, neg, lead = quantise_array(np.frombuffer(raw), e)
                    starts = np.arange(0, len(q), block)
                    out = np.empty((len(planes), 2, len(starts)))
                    for i, p in enumerate(planes):
                        bits = (lead > p).astype(np.float64)
                        at = np.flatnonzero(lead == p)
                        runs, ideal = costs.value.get(p, (np.zeros(0), np.zeros(0)))
                        # a run without a 1 at its end costs nothing here, and above a slab's first plane it is in no histogram
                        bits[at] += 1 + ideal[np.searchsorted(runs, split_plane(q, lead, neg, p)[0][: len(at)])]
                        out[i] = [np.add.reduceat(x, starts) for x in (fac.drops(q, p), bits)]
                    yield pa.RecordBatch.from_arrays([pa.array([lo]), pa.array([len(q)]), pa.array([out.tobytes()], pa.binary()), pa.array([out.sum(axis=2).tobytes()], pa.binary())], names=["lo", "n", "gains", "sums"])

        by_slab = cut(t.rows.select("lo", "block").mapInArrow(gains, "lo long, n long, gains binary, sums binary"))
        sums = by_slab.select("lo", "sums").toArrow().sort_by("lo")  # one row a slab
        each = np.array([np.frombuffer(x).reshape(len(planes), 2) for x in sums["sums"].to_pylist()])
        before = dict(zip(sums["lo"].to_pylist(), np.cumsum(each, axis=0) - each, strict=True))
        whole = each.sum(axis=0)

        def crossings(batches, planes=planes, before=before, whole=whole):
            for b in batches:
                for lo, n, raw in zip(*(b.column(c).to_pylist() for c in ("lo", "n", "gains")), strict=True):
                    new = np.frombuffer(raw).reshape(len(planes), 2, -1).cumsum(axis=2) + before[lo][:, :, None]
                    ends = np.minimum(np.arange(1, new.shape[2] + 1) * block, n)
                    found = []
                    for i, p in enumerate(planes):
                        drop, bits = new[i] + (whole[i - 1][:, None] - new[i - 1] if i else 0.0)
                        for k, price in enumerate(prices):
                            low = np.flatnonzero((bits >= 1) & (drop * unit <= price * bits))
                            if len(low):
                                found.append((k, p, lo * size + int(ends[low[0]])))
                    yield pa.RecordBatch.from_arrays([pa.array([f[j] for f in found], pa.int64()) for j in range(3)], names=["k", "p", "sent"])

        best: dict[int, tuple[int, int]] = {}
        for r in by_slab.select("lo", "n", "gains").mapInArrow(crossings, "k long, p long, sent long").groupBy("k", "p").agg(F.min("sent").alias("sent")).collect():
            best[r.k] = min(best.get(r.k, (-1, 0)), (int(r.p), int(r.sent)), key=lambda x: (-x[0], x[1]))
        if len(best) == len(prices) or floor == 0:
            return [best.get(k, (0, size * t.spec.shape[t.axis])) for k in range(len(prices))]
        floor = max(0, floor - 8)


# ---- codec ----


@dataclass
class LongArchive:
    """Core and short factors as in an archive; the long factor's segments by slab."""

    core: Archive
    bytes: int
    long: dict
    segments: DataFrame
    models: dict
    seconds: float = 0.0


def compress_long(t: LongGrid, jobs: list[tuple[ErrorTarget, str]]) -> list[LongArchive]:
    """compress_array for several (target, policy), with the default options, of a grid in slabs."""
    n, spec, rows = t.axis, t.spec, t.row_spec
    t0 = time.perf_counter()
    flat = t.core.ravel()
    e = scale_exponent(float(np.abs(flat).max(initial=0.0)))
    q, neg, lead = quantise_array(flat, e)
    unit, sse = 4.0 ** (e - 63), sse_by_plane(q)
    f = scale_exponent(t.peak)
    by_chunk = chunk_errors(t.rows, f)
    long_sse = np.zeros(65)
    for r in by_chunk.groupBy("p").agg(F.sum("sse").alias("s")).collect():
        long_sse[r.p] = r.s
    budgets = [_budget(target, t.stats, policy) for target, policy in jobs]
    stops = [stop_by_budget(q, b / unit, sse) for b in budgets]
    prices = [_price(q, neg, lead, p, sent, unit) if p < 64 else math.inf for p, sent in stops]
    least = min((p for p, _ in stops), default=64)
    by_price = price_stops(t, f, prices, least + e - f - 2)
    shared = (time.perf_counter() - t0) / max(1, len(jobs)) + t.seconds
    head = {"axes": spec.axes, "shape": spec.shape, "core": t.core.shape, "width": spec.width, "integer": spec.integer, "order": "C", "exponent": e, "coder": "range", "mode": "split", "chunk": CHUNK, "signs": "plane", "low": t.stats.low, "high": t.stats.high, "version": 1}
    coder = _Slabs(t.rows, rows, f, 4.0 ** (f - 63), long_sse, head, [], "auto", "range", True, "price", "split", "plane")
    out = []
    for (target, policy), budget, (p, sent), price, at in zip(jobs, budgets, stops, prices, by_price, strict=True):
        t0 = time.perf_counter()
        err = _rounding_errors(flat, q, neg, p, sent, e)
        segments, models = _encode_core(q, neg, lead, p, sent, CHUNK, "range")
        left = BUDGET_FACTORS * target.to_sse(t.stats) / len(spec.shape) if policy == "price+budget" else None
        norms = t.norms if p < 64 else [np.zeros(k) for k in t.core.shape]
        coded = [fac.encode_factor(u, s, price, core_plane=p, most_sse=left) for m, (u, s) in enumerate(zip(t.factors, norms, strict=True)) if m != n]
        if p >= 64:
            at = (64, 0)
        elif left is not None:
            at = min(at, _budget_stop(t, by_chunk, long_sse, left, f), key=lambda x: (x[0], -x[1]))
        header = head | {"plane": p, "sent": sent, "sse": budget, "policy": policy, "price": price if math.isfinite(price) else None, "rounding": "midpoint" if err[0] <= err[1] else "floor"}
        mine, parts = {}, None
        if at[0] < 64:
            mine = coder.models(*at)[0]
            parts = coder.segments(*at, mine)
        long = {"plane": at[0], "sent": at[1], "exponent": f, "coder": "range", "mode": "split", "signs": "plane", "rounding": coder.rule(*at) if at[0] < 64 else "floor"}
        z = Archive(header, models, norms, coded, segments)
        # what factors.factor_bytes counts of a factor, and a norm for each column that holds something
        size = 8 + sum(-(-m.bits // 8) + 1 for m in mine.values())
        if parts is not None:
            size += parts.agg(F.sum(F.length("runs") + F.length("raw") + F.length("signs"))).first()[0] or 0
        kept = [s for m, s in enumerate(norms) if m != n]
        used = sum(int(np.count_nonzero(np.any(fac.decode_factor(c, s) != 0, axis=0) & (s > 0))) for c, s in zip(coded, kept, strict=True)) + _live_columns(t, f, *at)
        total = z.core_bytes() + sum(map(fac.factor_bytes, coded)) + size + 8 * used + 64
        out.append(LongArchive(z, int(total), long, parts, mine, shared + time.perf_counter() - t0))
    return out


def _budget_stop(t: LongGrid, by_chunk: DataFrame, sse: np.ndarray, left: float, e: int) -> tuple[int, int]:
    """planes.stop_by_budget of the long factor."""
    budget = left / 4.0 ** (e - 63)
    if sse[64] <= budget:
        return 64, 0
    ok = np.flatnonzero(sse[:64] <= budget * (1 + 1e-12))
    p = int(ok.max()) if len(ok) else 0
    return p, _crossing(t.rows, by_chunk, t.row_spec, sse, p, budget, e)


def _live_columns(t: LongGrid, e: int, p: int, sent: int) -> int:
    """Columns of the long factor that hold a bit of what is sent."""
    if p >= 64:
        return 0
    size = len(t.v)

    def live(batches):
        held = np.zeros(size, bool)
        for b in batches:
            for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                lead = quantise_array(np.frombuffer(raw), e)[2]
                held |= (lead >= p + (np.arange(lo * size, lo * size + len(lead)) >= sent)).reshape(-1, size).any(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(held))], names=["i"])

    return t.rows.select("lo", "block").mapInArrow(live, "i long").distinct().count()


def _beside(t: LongGrid, rest: np.ndarray) -> np.ndarray:
    """What rows of the long factor, weighted by their norms, are multiplied by to restore rows of the unfolding."""
    s = t.norms[t.axis]
    return np.divide(_unfolded(rest, t.axis), s[:, None], out=np.zeros((len(s), len(s))), where=s[:, None] > 0)


def restored_errors(t: LongGrid, archives: list[LongArchive]) -> list[float]:
    """Squared errors of archives' grids against the cells: each slab is decoded from its segments and restored.

    Slabs of cells are shuffled once for all archives.
    """
    n, spec, size = t.axis, t.spec, len(t.v)
    held, parts = {}, None
    for k, z in enumerate(archives):
        if z.segments is None:
            continue
        norms = [s for m, s in enumerate(z.core.norms) if m != n]
        short = iter([fac.decode_factor(c, s) for c, s in zip(z.core.coded, norms, strict=True)])
        factors = [np.eye(size) if m == n else next(short) for m in range(len(spec.shape))]
        held[k] = z.long, z.models, _beside(t, inverse_array(core_array(z.core), factors))
        mine = z.segments.select(F.lit(k).alias("job"), F.col("chunk").alias("lo"), "plane", "n_raw", "runs", "raw", "signs")
        parts = mine if parts is None else parts.unionByName(mine)
    if parts is None:
        return [t.stats.energy] * len(archives)
    shared = t.rows.sparkSession.sparkContext.broadcast(held)

    def one(key: tuple, cells: pa.Table, parts: pa.Table) -> pa.Table:
        a = _unfolded(slab_array(cells["block"][0].as_py(), spec, n), n)
        at, out = key[0].as_py() * size, []
        by: dict[int, list] = {}
        for job, *plane in zip(*(parts[c].to_pylist() for c in ("job", "plane", "n_raw", "runs", "raw", "signs")), strict=True):
            by.setdefault(job, []).append(tuple(plane))
        for k, (h, models, beside) in shared.value.items():
            w = _decode_chunk(by.get(k, []), a.size, h, models, int(np.clip(h["sent"] - at, 0, a.size)), h["plane"])
            out.append(float(((w.reshape(a.shape) @ beside - a) ** 2).sum()))
        return pa.table({"job": pa.array(list(shared.value), pa.int32()), "sse": out})

    pairs = t.slabs.select("lo", "block").groupBy("lo").cogroup(parts.groupBy("lo"))
    sse = dict(pairs.applyInArrow(one, "job int, sse double").groupBy("job").agg(F.sum("sse")).collect())
    return [sse.get(k, t.stats.energy) for k in range(len(archives))]


def rank_cut_long(t: LongGrid, tails: list[float]) -> list[tuple[int, float]]:
    """(bytes, squared error) of baselines.rank_cut of the whole grid for shares of energy left out."""
    n, spec, s = t.axis, t.spec, t.norms[t.axis]
    got = [rank_cut.compress(t.core, energy_tail=x, transformed=Transformed(t.spec, t.factors, [], t.core)) for x in tails]
    # the identity stands for the long factor, whose rows are as many as the axis is long
    sizes = [c.bytes() + 4 * c.codes.shape[n] * (spec.shape[n] - len(s)) for c in got]
    beside = t.rows.sparkSession.sparkContext.broadcast([_unfolded(rank_cut.decompress(c), n)[: c.codes.shape[n]] for c in got])
    turn = t.rows.sparkSession.sparkContext.broadcast(t.v)

    def errors(batches):
        for b in batches:
            for raw in b.column("block").to_pylist():
                a = _unfolded(slab_array(raw, spec, n), n)
                w = a @ turn.value
                u = np.divide(w, s, out=np.zeros_like(w), where=s > 0).astype(np.float32).astype(float)
                sse = [float(((u[:, : len(x)] @ x - a) ** 2).sum()) for x in beside.value]
                yield pa.RecordBatch.from_arrays([pa.array(range(len(sse)), pa.int32()), pa.array(sse)], names=["k", "sse"])

    sse = dict(t.slabs.select("block").mapInArrow(errors, "k int, sse double").groupBy("k").agg(F.sum("sse")).collect())
    return [(size, sse[k]) for k, size in enumerate(sizes)]
