"""Error-bounded predictive coder: values to multiples of twice the bound, N-fold differences, entropy coding."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridpress.operators.entropy import Model, RangeCoder
from gridpress.plans.grid import GridSpec


@dataclass
class Predicted:
    shape: tuple[int, ...]
    bound: float
    model: Model
    blob: bytes

    def bytes(self) -> int:
        return len(self.blob) + -(-self.model.bits // 8) + 24


def _fold(d: np.ndarray) -> np.ndarray:
    """Signed to unsigned, small magnitudes first."""
    return np.where(d >= 0, 2 * d, -2 * d - 1)


def differences(k: np.ndarray) -> np.ndarray:
    for axis in range(k.ndim):
        k = np.diff(k, axis=axis, prepend=0)
    return k


def compress(a: np.ndarray, rel_bound: float) -> Predicted:
    """Every value comes back within rel_bound times the range."""
    span = float(a.max() - a.min()) if a.size else 0.0
    bound = rel_bound * span
    k = np.rint(a / (2 * bound)).astype(np.int64) if bound > 0 else np.zeros(a.shape, np.int64)
    if bound == 0 and a.size:
        bound, k = -float(a.flat[0]), k  # a constant: its value stands in for the bound
    s = _fold(differences(k)).ravel()
    m = Model.of(*np.unique(s, return_counts=True))
    return Predicted(a.shape, bound, m, RangeCoder.encode(s, m))


def decompress(c: Predicted) -> np.ndarray:
    if c.bound <= 0:
        return np.full(c.shape, -c.bound)
    s = RangeCoder.decode(c.blob, c.model)
    d = np.where(s & 1, -((s + 1) >> 1), s >> 1).reshape(c.shape)
    for axis in range(d.ndim):
        d = np.cumsum(d, axis=axis)
    return d * (2 * c.bound)


def codes_sql(cells: DataFrame, spec: GridSpec, bound: float) -> DataFrame:
    """(axes, k, d) of dense cells: the same codes by one lag window for each axis."""
    df = cells.select(*spec.coords(), F.round(F.col("v") / (2 * bound)).cast("long").alias("k")).withColumn("d", F.col("k"))
    for a in spec.axes:
        w = Window.partitionBy(*(x for x in spec.axes if x != a)).orderBy(a)
        df = df.withColumn("d", F.col("d") - F.coalesce(F.lag("d").over(w), F.lit(0)))
    return df
