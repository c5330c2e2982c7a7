"""Grid specifications and the cell and slab layouts of a grid.

A grid is a DataFrame of cells (idx BIGINT, v DOUBLE) with a GridSpec; cells that
are not stored are 0.  A slab is a run of indices along one axis with all of the
others, as a block of doubles in C order: the layout that linear algebra works on.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: grids of at most so many lattice points may be held by one process
LOCAL_CELLS = 1 << 21
#: bytes of one block: what a value of an Arrow column may hold, with room
BLOCK_LIMIT = (1 << 31) - (1 << 16)


@dataclass(frozen=True)
class GridSpec:
    axes: tuple[str, ...]
    shape: tuple[int, ...]
    width: int = 8  # bytes of a value in the original type
    integer: bool = False
    labels: dict = field(default_factory=dict, compare=False)

    @property
    def cells(self) -> int:
        return math.prod(self.shape)

    @property
    def strides(self) -> tuple[int, ...]:
        out = [1]
        for n in self.shape[:0:-1]:
            out.append(out[-1] * n)
        return tuple(out[::-1])

    def flat(self, *coords: Column) -> Column:
        """C-order index of coordinate columns (the axes' own names by default)."""
        cols = coords or tuple(F.col(a) for a in self.axes)
        return sum((c.cast("long") * s for c, s in zip(cols[1:], self.strides[1:], strict=True)), cols[0].cast("long") * self.strides[0])

    def coords(self, idx: Column | None = None) -> list[Column]:
        idx = F.col("idx") if idx is None else idx
        return [F.pmod(F.floor(idx / s) if s > 1 else idx, F.lit(n)).cast("int").alias(a) for a, s, n in zip(self.axes, self.strides, self.shape, strict=True)]

    @staticmethod
    def infer(df: DataFrame, axes: list[str], value: str, width: int = 8) -> tuple[GridSpec, DataFrame]:
        """Dense axes from the distinct labels of columns: one small dictionary for each axis, joined by broadcast.

        A dictionary has one row for each index of its axis, and axes over 2^20 are refused.
        """
        out, shape, labels = df, [], {}
        # all axes' labels in one scan; the grouping id tells whose they are, nulls among them
        most, found = 1 << 20, {a: [] for a in axes}
        sets = df.groupingSets([[F.col(a)] for a in axes], *axes).agg(F.grouping_id(*axes).alias("_g"))
        for r in sets.limit(most * len(axes) + 1).toLocalIterator():
            a = axes[[x for x in range(len(axes)) if not (r["_g"] >> (len(axes) - 1 - x)) & 1][0]]
            found[a].append(r[a])
        for a in axes:
            names = sorted(found[a], key=lambda x: (x is not None, x))
            if len(names) > most:
                raise ValueError(f"axis {a} is too long for a dictionary")
            labels[a] = names
            shape.append(max(1, len(names)))
            d = df.sparkSession.createDataFrame(list(zip(names, range(len(names)), strict=True)), df.select(a).schema.add(f"_{a}", T.IntegerType())) if names else df.select(a, F.lit(0).alias(f"_{a}"))
            out = out.join(F.broadcast(d), a).drop(a).withColumnRenamed(f"_{a}", a)
        spec = GridSpec(tuple(axes), tuple(shape), width, labels=labels)
        return spec, out.groupBy(*axes).agg(F.sum(F.col(value).cast("double")).alias("v")).select(spec.flat().alias("idx"), "v")


@dataclass
class GridFrame:
    df: DataFrame
    spec: GridSpec

    def dense(self) -> np.ndarray:
        """The whole grid in this process; refused beyond LOCAL_CELLS."""
        if self.spec.cells > LOCAL_CELLS:
            raise ValueError("grid is too large to be held by one process")
        got = self.df.select("idx", F.col("v").cast("double").alias("v")).toArrow()
        out = np.zeros(self.spec.cells)
        if len(got):
            out[got["idx"].to_numpy()] = got["v"].to_numpy()
        return out.reshape(self.spec.shape)

    @staticmethod
    def of(spark, a: np.ndarray, spec: GridSpec | None = None) -> GridFrame:
        spec = spec or GridSpec(tuple(f"i{n + 1}" for n in range(a.ndim)), a.shape)
        flat = np.ascontiguousarray(a, float).ravel()
        return GridFrame(spark.createDataFrame(pa.table({"idx": np.arange(len(flat), dtype=np.int64), "v": flat})), spec)

    def clean(self, nan: str = "error") -> GridFrame:
        """Refuse, or take for 0, what is null or not finite."""
        bad = F.col("v").isNull() | F.isnan("v") | (F.abs("v") == float("inf"))
        if nan == "zero":
            return GridFrame(self.df.withColumn("v", F.when(bad, F.lit(0.0)).otherwise(F.col("v"))), self.spec)
        return GridFrame(self.df.withColumn("v", F.when(bad, F.raise_error(F.lit("a cell is null or not finite"))).otherwise(F.col("v"))), self.spec)

    def where_box(self, box: dict[str, tuple[int, int]]) -> DataFrame:
        """Cells with coordinates in ranges [lo, hi)."""
        df = self.df.select("*", *self.spec.coords())
        for a, (lo, hi) in box.items():
            df = df.where((F.col(a) >= lo) & (F.col(a) < hi))
        return df


def to_slabs(grid: GridFrame, axis: int, per_slab: int) -> DataFrame:
    """(slab, lo, block): blocks of `per_slab` indices along `axis`, all other axes whole, C order; one shuffle."""
    spec = grid.spec
    s, n = spec.strides[axis], spec.shape[axis]
    if 8 * per_slab * (spec.cells // n) > BLOCK_LIMIT:
        raise ValueError("a slab is too large for one block")
    at = F.pmod(F.floor(F.col("idx") / s), F.lit(n))
    cells = grid.df.select(F.floor(at / per_slab).cast("int").alias("slab"), "idx", F.col("v").cast("double").alias("v"))
    every = grid.df.sparkSession.range(-(-n // per_slab)).select(F.col("id").cast("int").alias("slab"), F.lit(None).cast("long").alias("idx"), F.lit(None).cast("double").alias("v"))

    def fill(key: tuple, t: pa.Table) -> pa.Table:
        k = key[0].as_py()
        lo = k * per_slab
        hi = min(n, lo + per_slab)
        shape = [*spec.shape[:axis], hi - lo, *spec.shape[axis + 1 :]]
        out = np.zeros(math.prod(shape))
        t = t.drop_null()
        if len(t):
            idx = t["idx"].to_numpy()
            c = np.unravel_index(idx, spec.shape)
            out[np.ravel_multi_index((*c[:axis], c[axis] - lo, *c[axis + 1 :]), shape)] = t["v"].to_numpy()
        return pa.table({"slab": pa.array([k], pa.int32()), "lo": pa.array([lo], pa.int64()), "block": pa.array([out.tobytes()], pa.binary())})

    return cells.unionByName(every).groupBy("slab").applyInArrow(fill, "slab int, lo long, block binary")


def slab_cells(slabs: DataFrame, spec: GridSpec, axis: int) -> DataFrame:
    """Cells (idx, v) of slabs along an axis."""

    def run(batches):
        for b in batches:
            for lo, raw in zip(b.column("lo").to_pylist(), b.column("block").to_pylist(), strict=True):
                v = np.frombuffer(raw)
                n = len(v) * spec.shape[axis] // spec.cells
                shape = [*spec.shape[:axis], n, *spec.shape[axis + 1 :]]
                for i in range(0, len(v), 1 << 18):
                    c = np.unravel_index(np.arange(i, min(len(v), i + (1 << 18))), shape)
                    idx = np.ravel_multi_index((*c[:axis], c[axis] + lo, *c[axis + 1 :]), spec.shape)
                    yield pa.RecordBatch.from_arrays([pa.array(idx.astype(np.int64)), pa.array(v[i : i + (1 << 18)])], names=["idx", "v"])

    return slabs.select("lo", "block").mapInArrow(run, "idx long, v double")


# ---- axis binning ----


def bin_month(c: Column) -> Column:
    return (F.year(c) * 12 + F.month(c)).cast("int")


def bin_hour(c: Column) -> Column:
    return F.hour(c).cast("int")


def bin_pct(c: Column) -> Column:
    return F.round(c * 100).cast("int")


def bin_width(c: Column, lo: float, hi: float, n: int) -> Column:
    return F.least(F.greatest(F.floor((c - lo) / ((hi - lo) / n)), F.lit(0)), F.lit(n - 1)).cast("int")
