"""Baselines over grids of any size: each slab of the leading axis is coded by itself on an executor."""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.baselines import block_xform, predictive, rank_cut, set_part
from gridpress.plans.grid import GridFrame, to_slabs
from gridpress.session import ship

CODECS = {"rank_cut": rank_cut, "block_xform": block_xform, "predictive": predictive, "set_part": set_part}


def _knob(codec: str, knob: float) -> dict:
    return {"rank_cut": {"energy_tail": knob}, "block_xform": {"tol": knob}, "predictive": {"rel_bound": knob}, "set_part": {"tol": knob}}[codec]


def compress_slabs(grid: GridFrame, codec: str, knob: float, per_slab: int) -> DataFrame:
    """(slab, lo, bytes, sse, worst, blob) of each slab; slabs of a multiple of four keep blocks whole."""
    ship(grid.df.sparkSession)
    shape = grid.spec.shape

    def run(batches):
        c = CODECS[codec]
        for b in batches:
            rows = []
            for slab, lo, raw in zip(*(b.column(n).to_pylist() for n in ("slab", "lo", "block")), strict=True):
                a = np.frombuffer(raw).reshape(-1, *shape[1:])
                z = c.compress(a, **_knob(codec, knob))
                d = np.abs(c.decompress(z) - a)
                rows.append((slab, lo, z.bytes(), float((d * d).sum()), float(d.max()), pickle.dumps(z)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, (pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary()), strict=True)], names=["slab", "lo", "bytes", "sse", "worst", "blob"])

    return to_slabs(grid, 0, per_slab).mapInArrow(run, "slab int, lo long, bytes long, sse double, worst double, blob binary")


def code_counts(archive: DataFrame) -> DataFrame:
    """(code, n) over the core codes of all slabs of a rank_cut archive."""

    def run(batches):
        for b in batches:
            for raw in b.column("blob"):
                v, n = np.unique(pickle.loads(raw.as_py()).codes, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(v.astype(np.int32)), pa.array(n.astype(np.int64))], names=["code", "n"])

    return archive.select("blob").mapInArrow(run, "code int, n long").groupBy("code").agg(F.sum("n").alias("n"))
