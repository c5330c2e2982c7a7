"""Accuracy, size and rate measures."""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridpress.operators.planes import mask_growth, zero_runs
from gridpress.plans.grid import GridFrame, GridSpec
from gridpress.plans.targets import grid_stats


def _paired(a: DataFrame, b: DataFrame) -> DataFrame:
    """Cells of two grids side by side; a cell missing from one is 0 there."""
    return a.select("idx", F.col("v").cast("double").alias("x")).join(b.select("idx", F.col("v").cast("double").alias("y")), "idx", "full").select("idx", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))


def compare(a: GridFrame, b: GridFrame) -> DataFrame:
    """One row: sse, rel_error, rmse, psnr of b against a (peak is half of a's range)."""
    c = a.spec.cells
    d = F.col("x") - F.col("y")
    agg = _paired(a.df, b.df).agg(F.sum(d * d).alias("sse"), F.sum(F.col("x") * F.col("x")).alias("energy"), F.min("x").alias("lo"), F.max("x").alias("hi"), F.count("*").alias("n"))
    gap = F.col("n") < c
    span = F.when(gap, F.greatest("hi", F.lit(0.0)) - F.least("lo", F.lit(0.0))).otherwise(F.col("hi") - F.col("lo"))
    rmse = F.sqrt(F.col("sse") / c)
    return agg.select("sse", F.when(F.col("energy") > 0, F.sqrt(F.col("sse") / F.col("energy"))).alias("rel_error"), rmse.alias("rmse"), F.when(F.col("sse") > 0, 20 * F.log10(span / (2 * rmse))).alias("psnr"))


def sse(a: GridFrame, b: GridFrame) -> float:
    return float(compare(a, b).first().sse or 0.0)


def rel_error(a: GridFrame, b: GridFrame) -> float:
    return compare(a, b).first().rel_error or 0.0


def rmse(a: GridFrame, b: GridFrame) -> float:
    return float(compare(a, b).first().rmse or 0.0)


def psnr(a: GridFrame, b: GridFrame) -> float:
    got = compare(a, b).first().psnr
    return math.inf if got is None else float(got)


def psnr_arrays(a: np.ndarray, b: np.ndarray) -> float:
    e = float(np.sqrt(((a - b) ** 2).mean()))
    return math.inf if e == 0 else 20 * math.log10(max(float(a.max() - a.min()), 1e-300) / (2 * e))


def entropy_bits(runs: DataFrame, with_model: bool = False) -> DataFrame:
    """Ideal bits of the run symbols of each plane; a model costs 64 bits an entry where it is counted."""
    f = runs.groupBy("plane", "run").agg(F.count("*").alias("f"))
    w = Window.partitionBy("plane")
    bits = f.withColumn("n", F.sum("f").over(w)).groupBy("plane").agg(F.sum("f").alias("symbols"), F.count("*").alias("distinct_runs"), F.sum(F.col("f") * (F.log("n") - F.log("f")) / math.log(2)).alias("bits"))
    return bits.withColumn("bits", F.col("bits") + F.col("distinct_runs") * 64) if with_model else bits


def run_histogram(runs: DataFrame) -> DataFrame:
    return runs.groupBy("plane", "run").agg(F.count("*").alias("freq"))


def _bit(q: Column, p: int) -> Column:
    return F.shiftrightunsigned(q, p).bitwiseAND(F.lit(1).cast("long"))


def ones_per_plane(q: DataFrame, planes: range = range(64)) -> DataFrame:
    """(plane, ones): all planes in one aggregate of the quantised column q."""
    one = q.agg(*(F.coalesce(F.sum(_bit(F.col("q"), p)), F.lit(0)).alias(f"p{p}") for p in planes))
    return one.select(F.explode(F.array(*(F.struct(F.lit(p).alias("plane"), F.col(f"p{p}").alias("ones")) for p in planes))).alias("x")).select("x.*")


def plane_centroid(q: DataFrame, planes: range = range(64)) -> DataFrame:
    """(plane, centroid): mean index of the 1 bits of each plane; null where it has none."""
    sums = [x for p in planes for x in (F.sum(_bit(F.col("q"), p) * F.col("idx")).alias(f"s{p}"), F.sum(_bit(F.col("q"), p)).alias(f"n{p}"))]
    row = F.array(*(F.struct(F.lit(p).alias("plane"), F.when(F.col(f"n{p}") > 0, F.col(f"s{p}") / F.col(f"n{p}")).alias("centroid")) for p in planes))
    return q.agg(*sums).select(F.explode(row).alias("x")).select("x.*")


def plane_profile(q: DataFrame, lo: int, hi: int) -> DataFrame:
    """(plane, ones, centroid, symbols, longest, bits, verbatim) of planes lo..hi: what a plane holds, and what its runs cost."""
    planes = range(lo, hi + 1)
    runs = zero_runs(q, lo, hi)
    longest = runs.groupBy("plane").agg(F.max("run").alias("longest"))
    cost = entropy_bits(runs).select("plane", "symbols", "bits").join(longest, "plane")
    held = ones_per_plane(q, planes).join(plane_centroid(q, planes), "plane").join(mask_growth(q, planes).select("plane", F.col("before").alias("verbatim")), "plane")
    return held.join(cost, "plane", "left").select("plane", "ones", "centroid", "symbols", "longest", "bits", "verbatim")


def plane_dots(q: DataFrame, planes: range = range(64), sample: float | None = None) -> DataFrame:
    """(plane, idx) of every 1 bit; a sample of cells only where one is asked for."""
    q = q.sample(sample, seed=1) if sample else q
    every = F.array(*(F.lit(p) for p in planes))
    return q.select("idx", F.explode(F.filter(every, lambda p: F.call_function("shiftrightunsigned", F.col("q"), p).bitwiseAND(F.lit(1).cast("long")) == 1)).alias("plane")).select("plane", "idx")


def slice_norms(core: DataFrame, spec: GridSpec) -> DataFrame:
    """(mode, j, sigma, log10) of all slices of all modes, by grouping sets in one scan."""
    cells = core.select(*spec.coords(), (F.col("v") * F.col("v")).alias("e"))
    mode = F.coalesce(*(F.when(F.col(a).isNotNull(), F.lit(n)) for n, a in enumerate(spec.axes)))
    got = cells.groupingSets([[F.col(a)] for a in spec.axes], *spec.axes).agg(F.sqrt(F.sum("e")).alias("sigma")).select(mode.alias("mode"), F.coalesce(*spec.axes).alias("j"), "sigma")
    return got.select("mode", "j", "sigma", F.when(F.col("sigma") > 0, F.log10("sigma")).alias("log10"))


def high_freq_share(power: np.ndarray) -> float:
    """Share of spectral energy at frequencies above half of the Nyquist radius."""
    grids = np.meshgrid(*(np.abs(np.fft.fftfreq(n)) / 0.5 for n in power.shape), indexing="ij")
    radius = np.sqrt(sum(g * g for g in grids) / power.ndim)
    total = float(power.sum())
    return float(power[radius > 0.5].sum()) / total if total else 0.0


class StageClock:
    """Seconds of named stages, each timed around an action that materialises it."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    def stage(self, name: str):
        clock = self

        class _Timer:
            def __enter__(self):
                self.began = time.perf_counter()

            def __exit__(self, *_):
                clock.seconds[name] = clock.seconds.get(name, 0.0) + time.perf_counter() - self.began

        return _Timer()

    def rows(self) -> list[tuple[str, float]]:
        return list(self.seconds.items())


def asymmetry(clock: StageClock) -> float:
    back = clock.seconds.get("decompress", 0.0)
    return clock.seconds.get("compress", 0.0) / back if back else math.inf


def stats_row(grid: GridFrame) -> DataFrame:
    s = grid_stats(grid)
    return grid.df.sparkSession.createDataFrame([(s.low, s.high, s.energy, s.cells)], "low double, high double, energy double, cells long")
