"""Spectra of factors and of grids."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def factor_spectrum(u: np.ndarray) -> np.ndarray:
    """Magnitudes: frequency x column."""
    return np.abs(np.fft.rfft(u, axis=0))


def spectrum_rows(spark, factors: list[np.ndarray]) -> DataFrame:
    parts = []
    for m, u in enumerate(factors):
        s = factor_spectrum(u)
        parts.append(pa.table({"mode": pa.array(np.full(s.size, m, np.int32)), "col": pa.array(np.tile(np.arange(s.shape[1], dtype=np.int32), s.shape[0])), "freq": pa.array(np.repeat(np.arange(s.shape[0], dtype=np.int32), s.shape[1])), "mag": pa.array(s.ravel())}))
    return spark.createDataFrame(pa.concat_tables(parts))


def grid_spectrum(a: np.ndarray) -> np.ndarray:
    return np.abs(np.fft.fftn(a))


def spectrum_histogram(a: np.ndarray, per_decade: int = 4) -> dict[int, int]:
    """Counts of magnitudes by logarithmic bins; zeros fall to the lowest bin of doubles."""
    m = grid_spectrum(a).ravel()
    b = np.floor(np.log10(np.maximum(m, 1e-300)) * per_decade).astype(int)
    k, n = np.unique(b, return_counts=True)
    return dict(zip(k.tolist(), n.tolist(), strict=True))


def pencil_fft(pencils: DataFrame) -> DataFrame:
    """(rest, freq, re, im) of every fiber: one axis of a separable transform of any size."""

    def run(batches):
        for b in batches:
            fibers = [np.asarray(x, float) for x in b.column("fiber").to_pylist()]
            for r, f in zip(b.column("rest").to_pylist(), fibers, strict=True):
                z = np.fft.fft(f)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(z), r)), pa.array(np.arange(len(z), dtype=np.int32)), pa.array(z.real.copy()), pa.array(z.imag.copy())], names=["rest", "freq", "re", "im"])

    return pencils.select("rest", "fiber").mapInArrow(run, "rest long, freq int, re double, im double")


def dft_sql(series: DataFrame, n: int) -> DataFrame:
    """(freq, re, im) of a short series (i, v) by sums of cosines and sines."""
    freqs = series.sparkSession.range(n // 2 + 1).select(F.col("id").cast("int").alias("freq"))
    angle = F.lit(2 * np.pi) * F.col("freq") * F.col("i") / F.lit(float(n))
    return series.crossJoin(F.broadcast(freqs)).groupBy("freq").agg(F.sum(F.col("v") * F.cos(angle)).alias("re"), (-F.sum(F.col("v") * F.sin(angle))).alias("im"))
