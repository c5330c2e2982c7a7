"""Compress grids to an error target, keep them as archives, and restore them.

The core goes chunk by chunk: one pass gives each chunk's errors by plane, the
sums choose the stop, one more pass writes each chunk's planes.  A chunk decodes
alone.  Small grids use one process and the same kernels.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridpress.operators import factors as fac
from gridpress.operators.entropy import CODERS, ESCAPE, Model, ideal_bits
from gridpress.operators.planes import CHUNK, join_plane, quantise_array, restore, scale_exponent, split_plane, sse_by_plane, stop_by_budget
from gridpress.operators.transform import Transformed, inverse_array, inverse_slabs, omt, omt_array
from gridpress.plans.grid import LOCAL_CELLS, GridFrame, GridSpec, slab_cells
from gridpress.plans.targets import ErrorTarget, GridStats, grid_stats
from gridpress.session import cut

BUDGET_CORE, BUDGET_FACTORS = 0.9, 0.1
SEGMENTS = "part string, plane int, chunk long, n_raw long, runs binary, raw binary, signs binary"


@dataclass
class Archive:
    """Header, models, norms, factors and core segments of a compressed grid."""

    header: dict
    models: dict[int, Model]
    norms: list[np.ndarray]
    coded: list[dict]
    segments: list[tuple] | DataFrame  # (plane, chunk, n_raw, runs, raw, signs), or a DataFrame of SEGMENTS
    resampled: list[np.ndarray] | None = None
    note: dict = field(default_factory=dict)

    @property
    def spec(self) -> GridSpec:
        h = self.header
        return GridSpec(tuple(h["axes"]), tuple(h["shape"]), h["width"], h["integer"])

    @property
    def core_spec(self) -> GridSpec:
        """Of the core: smaller than the grid's where weak slices were left out before coding."""
        h = self.header
        return GridSpec(tuple(h["axes"]), tuple(h.get("core", h["shape"])), h["width"], h["integer"])

    def factors(self) -> list[np.ndarray]:
        if self.resampled is not None:
            return self.resampled
        h = self.header
        return [fac.decode_factor(f, s, h["coder"]) for f, s in zip(self.coded, self.norms, strict=True)]

    def __getitem__(self, key) -> Archive:
        from gridpress.operators.resample import take

        return take(self, key if isinstance(key, tuple) else (key,))

    # ---- sizes ----

    def core_bytes(self) -> int:
        if isinstance(self.segments, DataFrame):
            n = self.segments.agg(F.sum(F.length("runs") + F.length("raw") + F.length("signs"))).first()[0] or 0
        else:
            n = sum(len(r) + len(v) + len(s) for _, _, _, r, v, s in self.segments)
        return int(n) + sum(-(-m.bits // 8) for m in self.models.values())

    def factor_bytes(self) -> int:
        return _factor_bytes(self.coded, self.norms)

    def bytes(self) -> int:
        return self.core_bytes() + self.factor_bytes() + 64


def _factor_bytes(coded: list[dict], norms: list[np.ndarray]) -> int:
    return sum(map(fac.factor_bytes, coded)) + 8 * sum(int(np.count_nonzero(s)) for s in norms)


def ratio(a: Archive) -> float:
    """Against the original type's width."""
    return a.spec.cells * a.spec.width / max(1, a.bytes())


def bit_rate(a: Archive) -> float:
    return 8 * a.bytes() / max(1, a.spec.cells)


def factor_share(a: Archive) -> float:
    return a.factor_bytes() / max(1, a.bytes())


def _chunks(flat: np.ndarray, size: int):
    for k in range(0, len(flat), size):
        yield k // size, flat[k : k + size]


def _budget(target: ErrorTarget, stats: GridStats, policy: str) -> float:
    return target.to_sse(stats) * (BUDGET_CORE if policy == "price+budget" else 1.0)


def compress(grid: GridFrame, target: ErrorTarget, schedule: str = "auto", policy: str = "price+budget", rounding: str = "auto", order: str = "C", coder: str = "range", mode: str = "split", chunk: int = CHUNK, weight: bool = True, stop: str = "price", signs: str = "plane", drop_energy: float | None = None) -> Archive:
    """Archive of a grid.

    policy "price" codes factors until their price falls to the core's; "price+budget"
    leaves a tenth of the error to factors and codes them until they are within it.
    mode "all_run" and "all_raw" are the ablations without a split by class.  signs
    "plane" keeps a plane's new signs after its bits, "inline" puts each where its
    coefficient's verbatim bit will stand from then on.  drop_energy leaves out the weakest
    slices of each axis, up to a share of the energy, before anything is projected; what they
    hold is part of the error.

    Grids of one process and of slabs follow the same options and meet the same
    targets; slabs lie in C order and are the chunks, so another order or chunk is refused.
    """
    if schedule == "auto" and grid.spec.cells <= LOCAL_CELLS:
        schedule = "one_pass"
    if schedule in ("one_pass", "sequential"):
        return compress_array(grid.dense(), target, grid.spec, schedule, policy, rounding, order, coder, mode, chunk, weight, stop, signs=signs, drop_energy=drop_energy)
    if order != "C" or chunk != CHUNK:
        raise ValueError("slabs lie in C order and are the chunks")
    stats = grid_stats(grid)
    grid, target, stats, shift = _scaled(grid, target, stats)
    z = _compress_slabs(omt(grid, "hybrid", drop_energy), grid, stats, target, policy, rounding, coder, weight, stop, mode, signs)
    z.header["shift"] = shift
    return z


def _shift_of(most: float) -> int:
    """Power of two that brings a grid whose squares would vanish or overflow near 1; else 0."""
    return -scale_exponent(most) if most and not 1e-100 < most < 1e100 else 0


def _scaled(grid: GridFrame, target: ErrorTarget, stats: GridStats) -> tuple[GridFrame, ErrorTarget, GridStats, int]:
    shift = _shift_of(max(abs(stats.low), abs(stats.high)))
    if not shift:
        return grid, target, stats, 0
    half = shift // 2
    v = F.col("v").cast("double") * F.lit(2.0**half) * F.lit(2.0 ** (shift - half))
    grid = GridFrame(grid.df.withColumn("v", v), grid.spec)
    return grid, _shifted(target, shift), grid_stats(grid), shift


def _shifted(target: ErrorTarget, shift: int) -> ErrorTarget:
    return ErrorTarget("rmse", math.ldexp(target.value, shift)) if target.kind == "rmse" else ErrorTarget("sse", math.ldexp(target.value, 2 * shift)) if target.kind == "sse" else target


def array_stats(a: np.ndarray) -> GridStats:
    return GridStats(float(a.min()), float(a.max()), float((a * a).sum()), a.size) if a.size else GridStats(0.0, 0.0, 0.0, 0)


def compress_array(a: np.ndarray, target: ErrorTarget, spec: GridSpec | None = None, schedule: str = "one_pass", policy: str = "price+budget", rounding: str = "auto", order: str = "C", coder: str = "range", mode: str = "split", chunk: int = CHUNK, weight: bool = True, stop: str = "price", transformed: Transformed | None = None, signs: str = "plane", drop_energy: float | None = None) -> Archive:
    spec = spec or GridSpec(tuple(f"i{n + 1}" for n in range(a.ndim)), a.shape)
    # squares must neither vanish nor overflow: such grids are scaled by a power of two, and back
    shift = _shift_of(float(np.abs(a).max(initial=0.0)))
    if shift:
        a, transformed, target = np.ldexp(a, shift), None, _shifted(target, shift)
    stats = array_stats(a)
    t = transformed or omt_array(a, schedule, drop_energy=drop_energy)
    flat = t.core.ravel(order="F" if order == "F" else "C")
    e = scale_exponent(float(np.abs(flat).max(initial=0.0)))
    q, neg, lead = quantise_array(flat, e)
    unit = 4.0 ** (e - 63)
    head = {"axes": spec.axes, "shape": spec.shape, "core": t.core.shape, "width": spec.width, "integer": spec.integer, "order": order, "exponent": e, "policy": policy, "coder": coder, "mode": mode, "chunk": chunk, "signs": signs, "low": stats.low, "high": stats.high, "shift": shift, "version": 1}

    slices = fac.array_slice_norms(t.core)

    def factors_at(p: int, sent: int, left: float | None) -> tuple[list[dict], list[np.ndarray]]:
        price = _price(q, neg, lead, p, sent, unit) if p < 64 else math.inf
        norms = slices if p < 64 else [np.zeros(n) for n in t.core.shape]
        coded = fac.encode_all(t.factors, norms, price, weight=weight, stop=stop, core_plane=p, most_sse=left, coder=coder)
        head["price"] = price if math.isfinite(price) else None
        return coded, _needed(norms, coded, coder)

    def archive(p: int, sent: int, budget: float, left: float | None) -> Archive:
        segments, models = _encode_core(q, neg, lead, p, sent, chunk, coder, mode, signs)
        coded, norms = factors_at(p, sent, left)
        rule = rounding
        if rule == "auto":
            err = _rounding_errors(flat, q, neg, p, sent, e)
            rule = "midpoint" if err[0] <= err[1] else "floor"
        return Archive(head | {"plane": p, "sent": sent, "sse": budget, "rounding": rule}, models, norms, coded, segments)

    if target.kind == "size":
        return _fit_bytes(q, neg, lead, int(target.value), unit, factors_at, archive, _shares(policy, a.ndim))
    budget = _budget(target, stats, policy)
    if t.core.size < a.size:  # what was left out before is spent already
        budget = max(0.0, budget - max(0.0, stats.energy - float((t.core * t.core).sum())))
    sse = sse_by_plane(q, budget / unit)
    p, sent = stop_by_budget(q, budget / unit, sse)
    left = BUDGET_FACTORS * target.to_sse(stats) / a.ndim if policy == "price+budget" else None
    return archive(p, sent, budget, left)


def _rounding_errors(flat: np.ndarray, q: np.ndarray, neg: np.ndarray, p: int, sent: int, e: int) -> tuple[float, float]:
    """Squared errors of what is sent, taken to the middle of what is unknown and to its floor."""
    low = p + (np.arange(len(q)) >= sent)
    kept = np.where(low < 64, q >> np.minimum(low, 63).astype(np.uint64) << np.minimum(low, 63).astype(np.uint64), np.uint64(0))
    return tuple(float(((restore(kept, neg, min(p, 63), sent, e, mid) - flat) ** 2).sum()) for mid in (True, False))


def _shares(policy: str, modes: int) -> tuple[float | None, ...]:
    """Errors that each factor may add where a target is in bytes, as shares of the core's; None leaves it to prices."""
    fair = BUDGET_FACTORS / BUDGET_CORE / modes
    return (fair, 1.0, 8.0, None) if policy == "price+budget" else (None,)


def _fit_bytes(q: np.ndarray, neg: np.ndarray, lead: np.ndarray, most: int, unit: float, factors_at, archive, shares) -> Archive:
    """The archive of most core bits whose bytes, all parts counted, are within `most`.

    Ideal bits of whole planes and the factors' real bytes tell which share of the error
    factors should have, and the plane to look at; positions in it are then halved between
    one that fits and one that does not, and each try is coded in full.
    """
    n, sse = len(q), sse_by_plane(q)
    top = int(lead.max(initial=-1))
    best = archive(64, 0, float(sse[64] * unit), None)
    if best.bytes() > most:
        raise ValueError(f"the least archive of this grid has {best.bytes()} bytes")
    ideal = np.cumsum([fac.gains(q, lead, neg, p)[1].sum() for p in range(top, -1, -1)])
    picks = []
    for share in shares:
        fits, tight = top + 1, -1  # sizes grow from plane to plane
        while fits - tight > 1:
            p = (fits + tight) // 2
            if ideal[top - p] <= 8 * most:
                coded, norms = factors_at(p, n, None if share is None else float(sse[p]) * unit * share)
                if 64 + ideal[top - p] / 8 + _factor_bytes(coded, norms) <= most:
                    fits = p
                    picks.append((float(sse[p]) * unit + sum(f["error"] for f in coded), p, share))
                    continue
            tight = p
    _, plane, share = min(picks, key=lambda x: x[0], default=(0.0, top + 1, shares[-1]))

    def at(bits: int) -> Archive:
        plane, sent = top - (bits - 1) // n, (bits - 1) % n + 1
        left = max(0.0, float(sse[plane + 1] - fac.drops(q, plane)[:sent].sum()) * unit)
        return archive(plane, sent, left, None if share is None else left * share)

    # the estimate leaves models out: go up until whole planes fit
    low, high = (top - plane + 1) * n, min((top + 1) * n, (top - plane + 2) * n) + 1
    while low > 0:
        got = at(low)
        if got.bytes() <= most:
            best = got
            break
        low, high = low - n, low
    while high - low > max(1, n // 4096) and not most - max(1, most // 1000) <= best.bytes() <= most:
        mid = (low + high) // 2
        got = at(mid)
        if got.bytes() <= most:
            low, best = mid, got
        else:
            high = mid
    return best


def _needed(norms: list[np.ndarray], coded: list[dict], coder: str) -> list[np.ndarray]:
    """Norms of columns that hold something once coded; the others need none to be restored."""
    return [np.where(np.any(fac.decode_factor(f, s, coder) != 0, axis=0), s, 0.0) for f, s in zip(coded, norms, strict=True)]


def _planes(q, neg, lead, p, sent, mode, signs="plane"):
    top = int(lead.max(initial=-1)) if mode == "split" else 63
    for plane in range(top, p - 1, -1):
        yield plane, *_split(q, neg, lead, plane, sent if plane == p else len(q), mode, signs)


def _split(q, neg, lead, plane, limit, mode, signs="plane"):
    if mode == "split":
        if signs == "plane":
            return split_plane(q, lead, neg, plane, limit)
        # verbatim bits and the signs of coefficients that start here, in the order of coefficients
        runs, _, _ = split_plane(q, lead, neg, plane, limit)
        seen = lead[:limit] >= plane
        mixed = np.where(lead[:limit] == plane, neg[:limit], (q[:limit] >> np.uint64(plane)) & np.uint64(1) == 1)[seen]
        return runs, mixed.astype(np.uint8), np.zeros(0, np.uint8)
    signs = neg[:limit][lead[:limit] == plane].astype(np.uint8)
    bits = ((q[:limit] >> np.uint64(plane)) & np.uint64(1)).astype(np.uint8)
    if mode == "all_raw":
        return np.zeros(0, np.int64), bits, signs
    ones = np.where(bits == 1, plane, -1).astype(np.int64)
    return split_plane(q[:limit], ones, neg[:limit], plane)[0], np.zeros(0, np.uint8), signs


def _encode_core(q, neg, lead, p, sent, chunk, coder, mode="split", how="plane"):
    if p >= 64:
        return [], {}
    parts, counts = [], {}
    for k, lo in enumerate(range(0, len(q), chunk)):
        s = slice(lo, lo + chunk)
        mine = int(np.clip(sent - lo, 0, min(chunk, len(q) - lo)))
        for plane, runs, raw, signs in _planes(q[s], neg[s], lead[s], p, mine, mode, how):
            parts.append((plane, k, runs, raw, signs))
            counts.setdefault(plane, []).append(runs)
    models = {plane: Model.of(*np.unique(np.concatenate(r), return_counts=True)) for plane, r in counts.items()}
    out = [(plane, k, len(raw), CODERS[coder].encode(runs, models[plane]) if len(runs) else b"", np.packbits(raw).tobytes(), np.packbits(signs).tobytes()) for plane, k, runs, raw, signs in parts]
    return out, models


def _price(q, neg, lead, p, sent, unit) -> float:
    """Squared error removed per bit over the last plane's worth of bits, up to where it stopped."""
    drop, bits = fac.gains(q, lead, neg, p)
    total = np.array([drop[:sent].sum(), bits[:sent].sum()])
    if p < 63 and sent < len(q):
        drop, bits = fac.gains(q, lead, neg, p + 1)
        total += drop[sent:].sum(), bits[sent:].sum()
    return float(total[0] * unit / total[1]) if total[1] > 0 else 0.0


def rd_trace(c: np.ndarray, block: int = CHUNK) -> list[tuple[int, int, float, float, float]]:
    """(plane, coefficients sent of it, ideal bits so far, squared error left, price) after each block of each plane.

    The price is the error that a block's bits remove, for each of them.  A run costs the
    ideal bits of its plane's histogram, where it ends.
    """
    e = scale_exponent(float(np.abs(c).max(initial=0.0)))
    q, neg, lead = quantise_array(c.ravel(), e)
    unit, sse = 4.0 ** (e - 63), sse_by_plane(q)
    out, spent = [], 0.0
    for plane in range(int(lead.max(initial=-1)), -1, -1):
        drop, bits = fac.gains(q, lead, neg, plane)
        for k in range(0, len(q), block):
            d, b = float(drop[k : k + block].sum()) * unit, float(bits[k : k + block].sum())
            spent += b
            left = float(sse[plane + 1] - drop[: k + block].sum()) * unit
            out.append((plane, min(len(q), k + block), spent, max(0.0, left), d / b if b > 0 else 0.0))
    return out


def _stop_by_bytes(q, neg, lead, budget: int) -> tuple[int, int]:
    """Lowest whole plane whose ideal size still fits a number of bytes."""
    used, stop = 0.0, 64
    for plane in range(int(lead.max(initial=-1)), -1, -1):
        runs, raw, signs = split_plane(q, lead, neg, plane)
        used += ideal_bits(runs) + len(raw) + len(signs)
        if used > 8 * budget:
            break
        stop = plane
    return stop, len(q)


def breakpoint_by_bytes(c: np.ndarray, budget: int) -> int:
    q, neg, lead = quantise_array(c.ravel(), scale_exponent(float(np.abs(c).max(initial=0.0))))
    return _stop_by_bytes(q, neg, lead, budget)[0]


# ---- slabs ----


def chunk_errors(slabs: DataFrame, e: int) -> DataFrame:
    """(lo, p, sse): squared errors of each slab once planes down to p are kept, scaled."""

    def stat(batches):
        for b in batches:
            rows = []
            for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                q, _, _ = quantise_array(np.frombuffer(raw), e)
                rows += [(lo, p, float(s)) for p, s in enumerate(sse_by_plane(q))]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows]) for i in range(3)], names=["lo", "p", "sse"])

    return cut(slabs.select("lo", "block").mapInArrow(stat, "lo long, p long, sse double"))


def _compress_slabs(t: Transformed, grid: GridFrame, stats: GridStats, target: ErrorTarget, policy: str, rounding: str, coder: str, weight: bool, stop: str, mode: str = "split", signs: str = "plane") -> Archive:
    """The same for a core in C-ordered slabs: a slab is a chunk."""
    slabs, spec = t.slabs, t.spec

    def largest(batches):
        for b in batches:
            m = max((float(np.abs(np.frombuffer(x)).max()) for x in b.column("block").to_pylist()), default=0.0)
            yield pa.RecordBatch.from_arrays([pa.array([m])], names=["m"])

    e = scale_exponent(float(slabs.select("block").mapInArrow(largest, "m double").agg(F.max("m")).first()[0] or 0.0))
    unit = 4.0 ** (e - 63)

    by_chunk = chunk_errors(slabs, e)
    sse = np.zeros(65)
    for r in by_chunk.groupBy("p").agg(F.sum("sse").alias("s")).collect():
        sse[r.p] = r.s
    head = {"axes": grid.spec.axes, "shape": grid.spec.shape, "core": spec.shape, "width": grid.spec.width, "integer": grid.spec.integer, "order": "C", "exponent": e, "policy": policy, "coder": coder, "mode": mode, "chunk": 0, "signs": signs, "low": stats.low, "high": stats.high, "version": 1}
    coded_to = _Slabs(slabs, spec, e, unit, sse, head, t.factors, rounding, coder, weight, stop, mode, signs)
    if target.kind == "size":
        return coded_to.within(int(target.value), _shares(policy, len(spec.shape)))
    budget = _budget(target, stats, policy)
    if spec.cells < grid.spec.cells:  # what was left out before is spent already
        budget = max(0.0, budget - max(0.0, stats.energy - float(sse[64] * unit)))
    p, sent = 64, 0
    if sse[64] * unit > budget:
        ok = np.flatnonzero(sse[:64] * unit <= budget * (1 + 1e-12))
        p = int(ok.max()) if len(ok) else 0
        sent = _crossing(slabs, by_chunk, spec, sse, p, budget / unit, e)
    left = BUDGET_FACTORS * target.to_sse(stats) / len(spec.shape) if policy == "price+budget" else None
    return coded_to.archive(p, sent, budget, left)


def _crossing(slabs: DataFrame, by_chunk: DataFrame, spec: GridSpec, sse: np.ndarray, p: int, budget: float, e: int) -> int:
    """Coefficients of plane p after which the error is within the budget (scaled units).

    Drops of the plane by chunk, at most one row for each slab, are summed in chunk order;
    the chunk where they cross is scanned alone.
    """
    rest = spec.cells // spec.shape[0]
    drops = by_chunk.where(F.col("p").isin(p, p + 1)).groupBy("lo").agg(F.sum(F.when(F.col("p") == p + 1, F.col("sse")).otherwise(-F.col("sse"))).alias("d"))
    rows = sorted((r.lo, r.d) for r in drops.collect())
    after = float(sse[p + 1]) - np.cumsum([d for _, d in rows])
    inside = np.flatnonzero(after <= budget * (1 + 1e-12))
    if not len(inside):
        return spec.cells
    lo, d = rows[int(inside[0])]
    raw = slabs.where(F.col("lo") == lo).select("block").first()[0]
    q, _, _ = quantise_array(np.frombuffer(raw), e)
    run = after[inside[0]] + d - np.cumsum(fac.drops(q, p))
    at = np.flatnonzero(run <= budget * (1 + 1e-12))
    return lo * rest + (int(at[0]) + 1 if len(at) else len(q))


@dataclass
class _Slabs:
    """A core in slabs with what its coding needs; `archive` codes it down to a bit, `within` to a number of bytes."""

    slabs: DataFrame
    spec: GridSpec
    e: int
    unit: float
    sse: np.ndarray
    head: dict
    factors: list[np.ndarray]
    rounding: str
    coder: str
    weight: bool
    stop: str
    mode: str
    signs: str
    norms: list[np.ndarray] | None = None

    def _walk(self, p: int, sent: int, top: int = 63):
        """Function over batches of slabs: (lo, plane, runs, raw, signs) of planes top..p."""
        e, rest, mode, signs = self.e, self.spec.cells // self.spec.shape[0], self.mode, self.signs

        def split(batches):
            for b in batches:
                for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                    q, neg, lead = quantise_array(np.frombuffer(raw), e)
                    mine = int(np.clip(sent - lo * rest, 0, len(q)))
                    for plane, runs, bits, sign in _planes(q, neg, lead, p, mine, mode, signs):
                        if plane <= top:
                            yield lo, plane, runs, bits, sign

        return split

    def models(self, p: int, sent: int, top: int = 63) -> tuple[dict[int, Model], dict[int, float]]:
        """Models of planes top..p, and the bits of each plane: ideal ones of runs, and the rest as it is."""
        from pyspark.sql import Window

        from gridpress.operators.entropy import ALPHABET

        walk = self._walk(p, sent, top)

        def histograms(batches):
            for _, plane, runs, bits, sign in walk(batches):
                r, c = np.unique(runs, return_counts=True)
                # one row more carries the bits that are stored as they are
                r, c = np.append(r, -1), np.append(c, len(bits) + len(sign))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), plane, np.int32)), pa.array(r), pa.array(c)], names=["plane", "run", "n"])

        hist = cut(self.slabs.select("lo", "block").mapInArrow(histograms, "plane int, run long, n long").groupBy("plane", "run").agg(F.sum("n").alias("n")))
        rank = F.row_number().over(Window.partitionBy("plane").orderBy(F.desc("n"), "run"))
        capped = hist.where("run >= 0").withColumn("k", rank).groupBy("plane", F.when(F.col("k") < ALPHABET, F.col("run")).otherwise(F.lit(ESCAPE)).alias("run")).agg(F.sum("n").alias("n"))
        got: dict[int, list] = {}
        for r in capped.collect():  # at most 64 x ALPHABET rows
            got.setdefault(r.plane, []).append((r.run, r.n))
        models, bits = {}, {r.plane: float(r.n) for r in hist.where("run < 0").collect()}
        for plane, rows in got.items():
            runs, counts = np.array([x for x, _ in rows]), np.array([n for _, n in rows])
            models[plane] = Model.of(runs, counts)
            bits[plane] = bits.get(plane, 0.0) + float((counts * np.log2(counts.sum() / counts)).sum())
        return models, bits

    def segments(self, p: int, sent: int, models: dict[int, Model]) -> DataFrame:
        walk, coder = self._walk(p, sent), self.coder

        def emit(batches):
            for lo, plane, runs, bits, sign in walk(batches):
                runs_b = CODERS[coder].encode(runs, models[plane]) if len(runs) else b""
                yield pa.RecordBatch.from_arrays([pa.array(["core"]), pa.array([plane], pa.int32()), pa.array([lo]), pa.array([len(bits)]), pa.array([runs_b], pa.binary()), pa.array([np.packbits(bits).tobytes()], pa.binary()), pa.array([np.packbits(sign).tobytes()], pa.binary())], names=["part", "plane", "chunk", "n_raw", "runs", "raw", "signs"])

        return cut(self.slabs.select("lo", "block").mapInArrow(emit, SEGMENTS))

    def rule(self, p: int, sent: int) -> str:
        """Rounding: the better of both by measure, over all slabs."""
        if self.rounding != "auto":
            return self.rounding
        e, rest = self.e, self.spec.cells // self.spec.shape[0]

        def errors(batches):
            for b in batches:
                for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                    flat = np.frombuffer(raw)
                    q, neg, _ = quantise_array(flat, e)
                    got = _rounding_errors(flat, q, neg, p, int(np.clip(sent - lo * rest, 0, len(q))), e)
                    yield pa.RecordBatch.from_arrays([pa.array([x]) for x in got], names=["mid", "low"])

        mid, low = self.slabs.select("lo", "block").mapInArrow(errors, "mid double, low double").agg(F.sum("mid"), F.sum("low")).first()
        return "midpoint" if (mid or 0.0) <= (low or 0.0) else "floor"

    def coded_factors(self, price: float, p: int, left: float | None) -> tuple[list[dict], list[np.ndarray]]:
        self.norms = self.norms or _slab_norms(self.slabs, self.spec)
        norms = self.norms if p < 64 else [np.zeros(n) for n in self.spec.shape]
        coded = fac.encode_all(self.factors, norms, price, weight=self.weight, stop=self.stop, core_plane=p, most_sse=left, coder=self.coder)
        return coded, _needed(norms, coded, self.coder)

    def archive(self, p: int, sent: int, budget: float, left: float | None) -> Archive:
        models, segments, price = {}, self.slabs.sparkSession.createDataFrame([], SEGMENTS), math.inf
        if p < 64:
            models, bits = self.models(p, sent)
            segments = self.segments(p, sent, models)
            price = (self.sse[p + 1] - self.sse[p]) * self.unit / max(1.0, bits.get(p, 0.0))
        coded, norms = self.coded_factors(price, p, left)
        header = self.head | {"plane": p, "sent": sent, "price": price if math.isfinite(price) else None, "sse": budget, "rounding": self.rule(p, sent)}
        return Archive(header, models, norms, coded, segments)

    def within(self, most: int, shares: tuple[float | None, ...]) -> Archive:
        """The archive within a number of bytes, all parts counted: whole planes, then chunks of one more.

        Planes are looked at eight at a time from the top, until their ideal bits pass the
        bytes; with the factors' real bytes they tell the plane and the factors' share of the
        error.  A chunk's part of the last plane is coded or left as a whole.
        """
        n, rest = self.spec.cells, self.spec.cells // self.spec.shape[0]
        spent, p, picks, last = 0.0, 64, [], 64
        while p > 0 and spent <= 8 * most:
            floor = max(0, p - 8)
            got = self.models(floor, n, p - 1)[1]
            for plane in range(p - 1, floor - 1, -1):
                spent += got.get(plane, 0.0)
                if got.get(plane) and spent <= 8 * most:
                    price = (self.sse[plane + 1] - self.sse[plane]) * self.unit / max(1.0, got[plane])
                    for share in shares:
                        coded, norms = self.coded_factors(price, plane, None if share is None else float(self.sse[plane]) * self.unit * share)
                        if 64 + spent / 8 + _factor_bytes(coded, norms) <= most:
                            picks.append((float(self.sse[plane]) * self.unit + sum(f["error"] for f in coded), plane, share))
            p = floor
        _, last, share = min(picks, key=lambda x: x[0], default=(0.0, 64, shares[-1]))
        for p in range(last - 1 if last < 64 else 63, 64):
            if p < 0 or self.sse[p] >= self.sse[64]:
                continue
            error = float(self.sse[p] * self.unit)
            z = self.archive(p, n, error, None if share is None else error * share)
            if z.bytes() <= most:
                return z
            # the same archive without the last plane's part of the later chunks; its models stand
            parts = z.segments.where(F.col("plane") == p).select("chunk", (F.length("runs") + F.length("raw") + F.length("signs")).alias("b")).collect()  # one row a slab
            room = most - (z.bytes() - sum(r.b for r in parts))
            ends = sorted((r.chunk, r.b) for r in parts)
            fit = int(np.searchsorted(np.cumsum([b for _, b in ends]), room, side="right"))
            if room >= 0 and fit:
                at = ends[fit][0]
                z.header |= {"sent": at * rest, "rounding": self.rule(p, at * rest)}
                z.segments = z.segments.where((F.col("plane") > p) | (F.col("chunk") < at))
                return z
        z = self.archive(64, 0, float(self.sse[64] * self.unit), None)
        if z.bytes() > most:
            raise ValueError(f"the least archive of this grid has {z.bytes()} bytes")
        return z


def _slab_norms(slabs: DataFrame, spec: GridSpec) -> list[np.ndarray]:
    shape = spec.shape

    def run(batches):
        sums = [np.zeros(n) for n in shape]
        for b in batches:
            for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                a = np.frombuffer(raw).reshape(-1, *shape[1:]) ** 2
                sums[0][lo : lo + len(a)] += a.reshape(len(a), -1).sum(axis=1)
                for n in range(1, len(shape)):
                    sums[n] += a.sum(axis=tuple(m for m in range(len(shape)) if m != n))
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(len(shape), dtype=np.int32), shape)), pa.array(np.concatenate([np.arange(n, dtype=np.int32) for n in shape])), pa.array(np.concatenate(sums))], names=["mode", "j", "e"])

    out = [np.zeros(n) for n in shape]
    for r in slabs.select("lo", "block").mapInArrow(run, "mode int, j int, e double").groupBy("mode", "j").agg(F.sum("e").alias("e")).toLocalIterator():
        out[r.mode][r.j] = math.sqrt(r.e)
    return out


# ---- back ----


def _decode_chunk(planes: list[tuple], n: int, h: dict, models: dict[int, Model], sent: int, upto: int) -> np.ndarray:
    """Coefficients of one chunk from its planes, highest first."""
    q, seen, neg = np.zeros(n, np.uint64), np.zeros(n, bool), np.zeros(n, bool)
    coder, mode = CODERS[h["coder"]], h["mode"]
    for plane, n_raw, runs, raw, signs in sorted(planes, key=lambda x: -x[0]):
        if plane < upto:
            continue
        limit = sent if plane == h["plane"] else n
        r = coder.decode(runs, models[plane]) if runs else np.zeros(0, np.int64)
        bits = np.unpackbits(np.frombuffer(raw, np.uint8))[:n_raw] if n_raw else np.zeros(0, np.uint8)
        s = np.unpackbits(np.frombuffer(signs, np.uint8)) if signs else np.zeros(0, np.uint8)
        if mode == "split":
            free = np.flatnonzero(~seen[:limit])
            ends = np.cumsum(r + 1) - 1
            ends = ends[ends < len(free)]
            if h.get("signs", "plane") == "inline":
                # bits of coefficients seen before and signs of those that start here, in one order
                fresh = np.zeros(limit, bool)
                fresh[free[ends]] = True
                new = fresh[seen[:limit] | fresh]
                bits, s = bits[~new], bits[new]
            join_plane(q, seen, neg, plane, r, bits, s[: len(ends)], limit)
            continue
        if mode == "all_run":
            ends = np.cumsum(r + 1) - 1
            at = ends[ends < limit]
        else:
            at = np.flatnonzero(bits)
        new = at[~seen[at]]
        q[at] |= np.uint64(1 << plane)
        seen[at] = True
        neg[new] = s[: len(new)] == 1
    low = max(upto, h["plane"])
    return restore(q, neg, low, sent if low == h["plane"] else n, h["exponent"], h["rounding"] == "midpoint")


def core_array(a: Archive, upto_plane: int | None = None) -> np.ndarray:
    h = a.header
    shape = a.core_spec.shape
    n = math.prod(shape)
    out = np.zeros(n)
    upto = max(h["plane"], upto_plane or 0)
    by: dict[int, list] = {}
    if isinstance(a.segments, DataFrame):
        if n > LOCAL_CELLS:
            raise ValueError("core is too large to be held by one process")
        # planes below the one asked for are left out by the scan
        rows = [(r.plane, r.chunk, r.n_raw, r.runs, r.raw, r.signs) for r in a.segments.where(F.col("plane") >= upto).collect()]
    else:
        rows = a.segments
    slab = n // shape[0] if h["chunk"] == 0 else 0
    for plane, k, n_raw, runs, raw, signs in rows:
        by.setdefault(k, []).append((plane, n_raw, bytes(runs), bytes(raw), bytes(signs)))
    starts = sorted(by)
    for i, k in enumerate(starts):
        lo = k * (slab or h["chunk"])
        hi = (starts[i + 1] * slab if i + 1 < len(starts) else n) if slab else min(n, lo + h["chunk"])
        out[lo:hi] = _decode_chunk(by[k], hi - lo, h, a.models, int(np.clip(h["sent"] - lo, 0, hi - lo)), upto)
    return out.reshape(shape, order="F" if h["order"] == "F" else "C")


def decompress_array(a: Archive, upto_plane: int | None = None, cast: bool = False) -> np.ndarray:
    out = inverse_array(core_array(a, upto_plane), a.factors(), skip_zero_slices=True)
    if a.header.get("shift"):
        out = np.ldexp(out, -a.header["shift"])
    if cast and a.header["integer"]:
        out = np.clip(np.rint(out), a.header["low"], a.header["high"])
    return out


def decompress(a: Archive, spark: SparkSession, upto_plane: int | None = None, cast: bool = False) -> GridFrame:
    """Cells of an archive; large ones decode chunk by chunk on the executors."""
    spec = a.spec
    shape = tuple(u.shape[0] for u in a.factors())
    out_spec = replace(spec, shape=shape)
    if not isinstance(a.segments, DataFrame) or max(spec.cells, out_spec.cells) <= LOCAL_CELLS:
        return GridFrame.of(spark, decompress_array(a, upto_plane, cast), out_spec)
    h, models, core_spec = a.header, a.models, a.core_spec
    rest = core_spec.cells // core_spec.shape[0]
    upto = max(h["plane"], upto_plane or 0)
    factors = a.factors()
    # slices whose factor column holds nothing are dropped before any product
    live = [np.flatnonzero(np.any(u != 0, axis=0)) for u in factors]
    live = [x if len(x) else np.zeros(1, np.int64) for x in live]
    small = replace(core_spec, shape=tuple(map(len, live)))
    los = sorted(r[0] for r in a.segments.select("chunk").distinct().collect())  # one for each slab
    nexts = dict(zip(los, [*los[1:], core_spec.shape[0]], strict=True))

    def one(key: tuple, t: pa.Table) -> pa.Table:
        lo = key[0].as_py()
        rows = live[0][(live[0] >= lo) & (live[0] < nexts[lo])]
        if not len(rows):
            return pa.table({"slab": pa.array([], pa.int32()), "lo": pa.array([], pa.int64()), "block": pa.array([], pa.binary())})
        n = (nexts[lo] - lo) * rest
        planes = [(p, r, b, v, s) for p, r, b, v, s in zip(*(t[c].to_pylist() for c in ("plane", "n_raw", "runs", "raw", "signs")), strict=True)]
        v = _decode_chunk(planes, n, h, models, int(np.clip(h["sent"] - lo * rest, 0, n)), upto)
        v = v.reshape(-1, *core_spec.shape[1:])[np.ix_(rows - lo, *live[1:])]
        at = int(np.searchsorted(live[0], rows[0]))
        return pa.table({"slab": pa.array([at], pa.int32()), "lo": pa.array([at], pa.int64()), "block": pa.array([v.tobytes()], pa.binary())})

    core = a.segments.where(F.col("plane") >= upto).groupBy("chunk").applyInArrow(one, "slab int, lo long, block binary")
    slabs, got = inverse_slabs(core, small, [u[:, x] for u, x in zip(factors, live, strict=True)])
    df = slab_cells(slabs, got, 1)
    if h.get("shift"):
        half = -h["shift"] // 2
        df = df.withColumn("v", F.col("v") * F.lit(2.0**half) * F.lit(2.0 ** (-h["shift"] - half)))
    if cast and h["integer"]:
        df = df.withColumn("v", F.least(F.greatest(F.rint("v"), F.lit(h["low"])), F.lit(h["high"])))
    return GridFrame(df, replace(got, width=spec.width, integer=spec.integer))


def audit(a: Archive, grid: np.ndarray) -> dict:
    """Measured errors of an archive held against its grid."""
    back = decompress_array(a)
    e = float(((grid - back) ** 2).sum())
    energy = float((grid**2).sum())
    exact = omt_array(grid)
    core_part = float(((exact.core - core_array(a)) ** 2).sum())
    return {"sse": e, "core_sse": core_part, "rel_error": math.sqrt(e / energy) if energy else 0.0, "bytes": a.bytes(), "ratio": ratio(a)}


def compress_strict(a: np.ndarray, target: ErrorTarget, spec: GridSpec | None = None, rounds: int = 8, **options) -> Archive:
    """Tighten until the audit meets the target."""
    stats = array_stats(a)
    goal = target.to_sse(stats)
    t, aim = omt_array(a), goal
    for _ in range(rounds):
        got = compress_array(a, ErrorTarget("sse", aim), spec, transformed=t, **options)
        if float(((a - decompress_array(got)) ** 2).sum()) <= goal:
            return got
        aim *= 0.6
    return got


# ---- storage ----


def save(a: Archive, path: str, spark: SparkSession) -> None:
    """Segments by part and plane, then the header last, which makes the archive whole."""
    seg = a.segments if isinstance(a.segments, DataFrame) else spark.createDataFrame([("core", p, k, n, bytearray(r), bytearray(v), bytearray(s)) for p, k, n, r, v, s in a.segments], SEGMENTS)
    seg.write.mode("overwrite").partitionBy("part", "plane").parquet(f"{path}/segments")
    fseg = [(m, f["plane"], f["exponent"], f["weight"], f["midpoint"], int(f["sent"]), list(map(int, f["shape"])), p, [int(x) for x in mod.symbols], [int(x) for x in mod.freq], bytearray(r), bytearray(v), bytearray(s), n) for m, f in enumerate(a.coded) for p, mod, r, v, s, n in (f["planes"] or [(-1, Model(np.array([0]), np.array([1])), b"", b"", b"", 0)])]
    spark.createDataFrame(fseg, "mode int, stop int, exponent int, weight boolean, midpoint boolean, sent long, shape array<int>, plane int, symbols array<long>, freq array<long>, runs binary, raw binary, signs binary, n_raw long").write.mode("overwrite").parquet(f"{path}/factor_segments")
    spark.createDataFrame([(p, [int(x) for x in m.symbols], [int(x) for x in m.freq]) for p, m in a.models.items()], "plane int, symbols array<long>, freq array<long>").write.mode("overwrite").parquet(f"{path}/models")
    spark.createDataFrame([(n, j, float(s)) for n, v in enumerate(a.norms) for j, s in enumerate(v)], "mode int, j int, sigma double").write.mode("overwrite").parquet(f"{path}/norms")
    spark.createDataFrame([(json.dumps(a.header),)], "header string").coalesce(1).write.mode("overwrite").parquet(f"{path}/header")


def open_archive(path: str, spark: SparkSession) -> Archive:
    h = json.loads(spark.read.parquet(f"{path}/header").first()[0])
    models = {r.plane: Model(np.array(r.symbols), np.array(r.freq)) for r in spark.read.parquet(f"{path}/models").collect()}
    norms = [np.zeros(n) for n in h["shape"]]
    for r in spark.read.parquet(f"{path}/norms").collect():
        norms[r["mode"]][r.j] = r.sigma
    coded: dict[int, dict] = {}
    for r in spark.read.parquet(f"{path}/factor_segments").collect():
        f = coded.setdefault(r["mode"], {"shape": tuple(r["shape"]), "exponent": r.exponent, "plane": r.stop, "weight": r.weight, "midpoint": r.midpoint, "sent": r.sent, "planes": []})
        if r.plane >= 0:
            f["planes"].append((r.plane, Model(np.array(r.symbols), np.array(r.freq)), bytes(r.runs), bytes(r.raw), bytes(r.signs), r.n_raw))
    for f in coded.values():
        f["planes"].sort(key=lambda x: -x[0])
    seg = spark.read.schema(SEGMENTS).parquet(f"{path}/segments")
    return Archive(h, models, norms, [coded[m] for m in range(len(h["shape"]))], seg)
