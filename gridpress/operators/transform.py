"""Orthogonal multilinear transform: Grams, bases, projections, and their inverses.

Grids that one process may hold are transformed there in one pass.  Larger ones
go as slabs along axis 2: Grams of all other axes add up over slabs without a
shuffle of cells, their projections are slab-local, and one re-slab along axis 1
finishes axis 2.  Axis order does not matter at full rank.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.plans.grid import LOCAL_CELLS, GridFrame, GridSpec, slab_cells, to_slabs
from gridpress.session import cut, ship

#: bytes of a slab that a task should hold
SLAB_BYTES = 64 << 20
#: a Gram matrix and its basis are held by the driver up to this axis length
AXIS_LIMIT = 8192
#: from this length on, an axis longer than all others together gets as many basis columns as can be other than zero
LONG_AXIS = 1024


def unfold(grid: GridFrame, axis: int) -> DataFrame:
    """Pencils (rest, fiber): the dense fibers of an axis, one shuffle; absent cells are 0."""
    s, n = grid.spec.strides[axis], grid.spec.shape[axis]
    i = F.pmod(F.floor(F.col("idx") / s), F.lit(n)).cast("int")
    rest = F.col("idx") - i * s
    got = grid.df.select(rest.alias("rest"), i.alias("i"), "v").groupBy("rest").agg(F.map_from_entries(F.collect_list(F.struct("i", "v"))).alias("m"))
    return got.select("rest", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: F.coalesce(F.try_element_at("m", k), F.lit(0.0))).alias("fiber"))


def fold(pencils: DataFrame, spec: GridSpec, axis: int) -> DataFrame:
    """Cells of pencils."""
    return pencils.select("rest", F.posexplode("fiber").alias("i", "v")).select((F.col("rest") + F.col("i") * spec.strides[axis]).alias("idx"), "v")


def gram_sql(grid: GridFrame, axis: int) -> DataFrame:
    """(row, col, g) from sparse cells: the self-join on the fiber that SQL can say too."""
    s, n = grid.spec.strides[axis], grid.spec.shape[axis]
    i = F.pmod(F.floor(F.col("idx") / s), F.lit(n)).cast("int")
    a = grid.df.select(i.alias("row"), (F.col("idx") - i * s).alias("rest"), F.col("v").alias("x"))
    b = grid.df.select(i.alias("col"), (F.col("idx") - i * s).alias("rest"), F.col("v").alias("y"))
    return a.join(b, "rest").groupBy("row", "col").agg(F.sum(F.col("x") * F.col("y")).alias("g"))


def _unfolded(a: np.ndarray, axis: int) -> np.ndarray:
    return np.moveaxis(a, axis, 0).reshape(a.shape[axis], -1)


def slab_grams(slabs: DataFrame, spec: GridSpec, slab_axis: int, modes: list[int], tile: int = 512) -> dict[int, np.ndarray]:
    """Grams of the axes a slab holds whole: tiles of partial sums, added up by tile before they meet."""

    def run(batches):
        held: dict[tuple[int, int, int], np.ndarray] = {}
        for b in batches:
            for raw in b.column("block").to_pylist():
                v = np.frombuffer(raw)
                shape = list(spec.shape)
                shape[slab_axis] = len(v) * spec.shape[slab_axis] // spec.cells
                a = v.reshape(shape)
                for m in modes:
                    u = _unfolded(a, m)
                    for r in range(0, spec.shape[m], tile):
                        for c in range(r, spec.shape[m], tile):
                            g = u[r : r + tile] @ u[c : c + tile].T
                            held[m, r, c] = held[m, r, c] + g if (m, r, c) in held else g
        for (m, r, c), g in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([m], pa.int32()), pa.array([r], pa.int32()), pa.array([c], pa.int32()), pa.array([g.tobytes()], pa.binary())], names=["mode", "br", "bc", "tile"])

    def total(key: tuple, t: pa.Table) -> pa.Table:
        s = sum(np.frombuffer(x) for x in t["tile"].to_pylist())
        return pa.table({"mode": t["mode"][:1], "br": t["br"][:1], "bc": t["bc"][:1], "tile": pa.array([s.tobytes()], pa.binary())})

    parts = slabs.select("block").mapInArrow(run, "mode int, br int, bc int, tile binary")
    salted = parts.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(32)))
    some = salted.groupBy("mode", "br", "bc", "salt").applyInArrow(total, "mode int, br int, bc int, tile binary")
    out = {m: np.zeros((spec.shape[m], spec.shape[m])) for m in modes}
    if max(spec.shape[m] for m in modes) > AXIS_LIMIT:
        raise ValueError("axis too long for a Gram on the driver")
    for r in some.groupBy("mode", "br", "bc").applyInArrow(total, "mode int, br int, bc int, tile binary").toLocalIterator():
        n = spec.shape[r.mode]
        h, w = min(tile, n - r.br), min(tile, n - r.bc)
        g = np.frombuffer(r.tile).reshape(h, w)
        out[r.mode][r.br : r.br + h, r.bc : r.bc + w] = g
        out[r.mode][r.bc : r.bc + w, r.br : r.br + h] = g.T
    return out


def eigen_basis(g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues, largest first, and eigenvectors whose largest entry is positive."""
    lam, u = np.linalg.eigh((g + g.T) / 2)
    lam, u = lam[::-1], u[:, ::-1]
    sign = np.sign(u[np.abs(u).argmax(axis=0), np.arange(u.shape[1])])
    return np.maximum(lam, 0.0), u * np.where(sign == 0, 1.0, sign)


def long_basis(u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same of an unfolding whose axis is longer than all others together, without the Gram of its side.

    The unfolding has no more singular vectors than columns; a full basis would only add columns whose slices are zero.
    """
    left, s, _ = np.linalg.svd(u, full_matrices=False)
    sign = np.sign(left[np.abs(left).argmax(axis=0), np.arange(left.shape[1])])
    return s * s, left * np.where(sign == 0, 1.0, sign)


def basis_by_svd(a: np.ndarray, axis: int) -> np.ndarray:
    """The same basis straight from the unfolding, at the price of its long side; for small grids and checks."""
    return np.linalg.svd(_unfolded(a, axis), full_matrices=True)[0]


def subspace_basis(g: np.ndarray, rank: int, iters: int = 8, seed: int = 0) -> np.ndarray:
    """Leading eigenvectors by a stated number of block power steps."""
    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(len(g), min(rank, len(g)))))[0]
    for _ in range(iters):
        q = np.linalg.qr(g @ q)[0]
    return q @ eigen_basis(q.T @ g @ q)[1]


def multiply(a: np.ndarray, u: np.ndarray, axis: int, transpose: bool = False) -> np.ndarray:
    """Contract an axis of a with u (or its transpose)."""
    m = u.T if transpose else u
    return np.moveaxis(np.tensordot(m, a, axes=(1, axis)), 0, axis)


def ttm(slabs: DataFrame, spec: GridSpec, slab_axis: int, factors: dict[int, np.ndarray], transpose: bool) -> tuple[DataFrame, GridSpec]:
    """Project axes that slabs hold whole; factors of at most AXIS_LIMIT rows travel by broadcast."""
    shared = slabs.sparkSession.sparkContext.broadcast(factors)
    shape = list(spec.shape)
    for m, u in factors.items():
        shape[m] = u.shape[1] if transpose else u.shape[0]
    old = spec.shape
    cells = spec.cells

    def run(batches):
        for b in batches:
            blocks = []
            for raw in b.column("block").to_pylist():
                v = np.frombuffer(raw)
                s = list(old)
                s[slab_axis] = len(v) * old[slab_axis] // cells
                a = v.reshape(s)
                # what shrinks most goes first
                for m, u in sorted(shared.value.items(), key=lambda x: (x[1].shape[1] / x[1].shape[0]) if transpose else (x[1].shape[0] / x[1].shape[1])):
                    a = multiply(a, u, m, transpose)
                blocks.append(np.ascontiguousarray(a).tobytes())
            yield pa.RecordBatch.from_arrays([b.column("slab"), b.column("lo"), pa.array(blocks, pa.binary())], names=["slab", "lo", "block"])

    return slabs.select("slab", "lo", "block").mapInArrow(run, "slab int, lo long, block binary"), GridSpec(spec.axes, tuple(shape), spec.width, spec.integer)


def reslab(slabs: DataFrame, spec: GridSpec, old_axis: int, new_axis: int, per_slab: int) -> DataFrame:
    """Slabs along another axis: sub-blocks are the unit of the one shuffle, not cells."""
    n = spec.shape[new_axis]
    old_shape, cells = spec.shape, spec.cells

    def split(batches):
        for b in batches:
            for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                v = np.frombuffer(raw)
                s = list(old_shape)
                s[old_axis] = len(v) * old_shape[old_axis] // cells
                a = v.reshape(s)
                for k in range(-(-n // per_slab)):
                    part = np.take(a, range(k * per_slab, min(n, (k + 1) * per_slab)), axis=new_axis)
                    yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([lo], pa.int64()), pa.array([np.ascontiguousarray(part).tobytes()], pa.binary())], names=["slab", "at", "block"])

    def join(key: tuple, t: pa.Table) -> pa.Table:
        k = key[0].as_py()
        width = min(n, (k + 1) * per_slab) - k * per_slab
        s = list(old_shape)
        s[new_axis] = width
        out = np.zeros(s)
        for at, raw in zip(t["at"].to_pylist(), t["block"].to_pylist(), strict=True):
            v = np.frombuffer(raw)
            p = list(s)
            p[old_axis] = len(v) // (math.prod(s) // s[old_axis])
            where = [slice(None)] * len(s)
            where[old_axis] = slice(at, at + p[old_axis])
            out[tuple(where)] = v.reshape(p)
        return pa.table({"slab": pa.array([k], pa.int32()), "lo": pa.array([k * per_slab], pa.int64()), "block": pa.array([out.tobytes()], pa.binary())})

    return slabs.select("lo", "block").mapInArrow(split, "slab int, at long, block binary").groupBy("slab").applyInArrow(join, "slab int, lo long, block binary")


@dataclass
class Transformed:
    """A core and its factors; the core is an array of this process, or slabs along axis 1 in C order."""

    spec: GridSpec
    factors: list[np.ndarray]
    eigenvalues: list[np.ndarray]
    core: np.ndarray | None = None
    slabs: DataFrame | None = None

    def cells(self, spark) -> DataFrame:
        return GridFrame.of(spark, self.core).df if self.core is not None else slab_cells(self.slabs, self.spec, 0)


def _strong(lam: np.ndarray, drop_energy: float | None) -> int:
    """Columns to keep so that the slices left out hold at most a share of the energy."""
    if not drop_energy:
        return len(lam)
    tail = np.cumsum(lam[::-1])[::-1]
    return max(1, int((tail > drop_energy * lam.sum()).sum()))


def omt_array(a: np.ndarray, schedule: str = "one_pass", max_rank: int | None = None, eig_iters: int | None = None, drop_energy: float | None = None) -> Transformed:
    """Transform of an array.  one_pass takes all Grams from the input, sequential each from what is projected so far.

    max_rank keeps that many columns of each basis (lossy), by eig_iters block power steps where given;
    drop_energy leaves out the weakest slices of each axis, up to a share of the energy (lossy), before projecting.
    """
    core, factors, lams = a, [], []
    for n in range(a.ndim):
        u = _unfolded(a if schedule == "one_pass" else core, n)
        long = len(u) >= LONG_AXIS and len(u) > u.shape[1]
        lam, basis = long_basis(u) if long else eigen_basis(u @ u.T)
        if max_rank:
            basis = subspace_basis(u @ u.T, max_rank, eig_iters) if eig_iters and not long else basis[:, :max_rank]
        basis = basis[:, : _strong(lam, drop_energy)]
        factors.append(basis)
        lams.append(lam)
        core = multiply(core, basis, n, transpose=True)
    return Transformed(GridSpec(tuple(f"i{n + 1}" for n in range(a.ndim)), core.shape), factors, lams, core)


def omt(grid: GridFrame, schedule: str = "auto", drop_energy: float | None = None, **options) -> Transformed:
    if schedule == "auto":
        schedule = "one_pass" if grid.spec.cells <= LOCAL_CELLS else "hybrid"
    if schedule != "hybrid" or len(grid.spec.shape) == 1:
        return omt_array(grid.dense(), "one_pass" if schedule == "hybrid" else schedule, drop_energy=drop_energy, **options)
    spark, spec = grid.df.sparkSession, grid.spec
    ship(spark)
    others = [m for m in range(len(spec.shape)) if m != 1]
    per = max(1, min(spec.shape[1], SLAB_BYTES // (8 * (spec.cells // spec.shape[1]))))
    slabs = cut(to_slabs(grid, 1, per))
    grams = slab_grams(slabs, spec, 1, others)

    def strong(g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        lam, u = eigen_basis(g)
        return lam, u[:, : _strong(lam, drop_energy)]

    bases = {m: strong(g) for m, g in grams.items()}
    half, spec = ttm(slabs, spec, 1, {m: b[1] for m, b in bases.items()}, transpose=True)
    per = max(1, min(spec.shape[0], SLAB_BYTES // (8 * (spec.cells // spec.shape[0]))))
    lead = cut(reslab(half, spec, 1, 0, per))
    bases[1] = strong(slab_grams(lead, spec, 0, [1])[1])
    core, spec = ttm(lead, spec, 0, {1: bases[1][1]}, transpose=True)
    order = range(len(spec.shape))
    return Transformed(spec, [bases[m][1] for m in order], [bases[m][0] for m in order], slabs=cut(core))


def inverse_array(core: np.ndarray, factors: list[np.ndarray], skip_zero_slices: bool = False) -> np.ndarray:
    """Grid of a core; all-zero slices and their factor columns can be left out first."""
    if skip_zero_slices and core.size:
        for n in range(core.ndim):
            live = np.flatnonzero(np.abs(_unfolded(core, n)).max(axis=1) > 0)
            if not len(live):
                return np.zeros([u.shape[0] for u in factors])
            if len(live) < core.shape[n]:
                core = np.take(core, live, axis=n)
                factors = [u[:, live] if m == n else u for m, u in enumerate(factors)]
    for n in sorted(range(core.ndim), key=lambda n: factors[n].shape[0] / factors[n].shape[1]):
        core = multiply(core, factors[n], n)
    return core


def inverse_slabs(core: DataFrame, spec: GridSpec, factors: list[np.ndarray]) -> tuple[DataFrame, GridSpec]:
    """Grid slabs (along axis 1) of core slabs along axis 1: axes 2..N first, one re-slab, then axis 1, and back."""
    rest, mid = ttm(core, spec, 0, {m: u for m, u in enumerate(factors) if m}, transpose=False)
    per = max(1, min(mid.shape[1], SLAB_BYTES // (8 * max(mid.cells // mid.shape[1], 1))))
    turned = reslab(rest, mid, 0, 1, per)
    return ttm(turned, mid, 1, {0: factors[0]}, transpose=False)


def project(a: np.ndarray, factors: list[np.ndarray]) -> np.ndarray:
    """Core under factors that are only invertible."""
    for n, u in enumerate(factors):
        a = multiply(a, np.linalg.inv(u), n)
    return a


def cell_at(core: DataFrame, spec: GridSpec, factors: list[np.ndarray], coords: list[tuple[int, ...]]) -> DataFrame:
    """Values (k, v) at stated coordinates: one axis after the other is contracted with the factor rows that are asked for.

    Each step joins on the axis' core index and on the coordinates that are fixed so far,
    and adds up, so what is left shrinks by the axis; points of equal coordinates share it.
    """
    spark = core.sparkSession
    left = core.select(*[c.alias(f"r{n}") for n, c in enumerate(spec.coords())], F.col("v").cast("double").alias("v"))
    for n, u in enumerate(factors):
        fixed = [f"x{m}" for m in range(n)]
        heads = sorted({tuple(map(int, c[: n + 1])) for c in coords})
        near = spark.createDataFrame([(*h,) for h in heads], ", ".join(f"x{m} int" for m in range(n + 1)))
        rows = sorted({h[n] for h in heads})
        f = spark.createDataFrame([(r, c, float(u[r, c])) for r in rows for c in range(u.shape[1])], f"x{n} int, r{n} int, u double")
        step = near.join(f, f"x{n}")
        rest = [f"r{m}" for m in range(n + 1, len(factors))]
        left = left.join(step, [*fixed, f"r{n}"]).groupBy(*fixed, f"x{n}", *rest).agg(F.sum(F.col("v") * F.col("u")).alias("v"))
    names = [f"x{n}" for n in range(len(factors))]
    pts = spark.createDataFrame([(k, *map(int, c)) for k, c in enumerate(coords)], "k int, " + ", ".join(f"{x} int" for x in names))
    return pts.join(left, names).select("k", "v")


def truncate(core: DataFrame, spec: GridSpec, ranks: tuple[int, ...]) -> DataFrame:
    """The leading corner of a core."""
    df = core.select("*", *spec.coords())
    for a, r in zip(spec.axes, ranks, strict=True):
        df = df.where(F.col(a) < r)
    return df.select("idx", "v")


def factor_rows(spark, factors: list[np.ndarray]) -> DataFrame:
    parts = [pa.table({"mode": pa.array(np.full(u.size, m, np.int32)), "row": pa.array(np.repeat(np.arange(u.shape[0], dtype=np.int32), u.shape[1])), "col": pa.array(np.tile(np.arange(u.shape[1], dtype=np.int32), u.shape[0])), "u": pa.array(u.ravel())}) for m, u in enumerate(factors)]
    return spark.createDataFrame(pa.concat_tables(parts))
