"""SQL functions: scalar, aggregate and table functions over bits and runs."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udtf, pandas_udf, udtf

from gridpress.operators.entropy import CODERS, Model, ideal_bits
from gridpress.operators.planes import lead_array, split_plane
from gridpress.operators.resample import lanczos_taps


@pandas_udf(T.IntegerType())
def float_exponent(v: pd.Series) -> pd.Series:
    """Exponent e with 2^e <= |v| < 2^(e+1); null for 0 and null."""
    m, e = np.frexp(np.abs(v.to_numpy(dtype=float, na_value=np.nan)))
    return pd.Series(np.where((m > 0) & np.isfinite(m), e - 1, np.nan)).astype("Int32")


@pandas_udf(T.IntegerType())
def lead_plane_udf(q: pd.Series) -> pd.Series:
    return pd.Series(lead_array(q.to_numpy(dtype=np.int64).view(np.uint64)).astype(np.int32))


@pandas_udf(T.DoubleType())
def entropy_bits_udaf(run: pd.Series) -> float:
    """Ideal bits of a group's symbols."""
    return ideal_bits(run.to_numpy())


@pandas_udf(T.DoubleType())
def gram_entry_udaf(x: pd.Series, y: pd.Series) -> float:
    return float((x * y).sum())


@udtf(returnType=T.StructType([T.StructField("plane", T.IntegerType()), T.StructField("bit", T.IntegerType())]))
class BitPlanes:
    """(plane, bit) of the planes of a magnitude, from its highest 1 down."""

    def eval(self, q: int):
        if q is None:
            return
        q &= (1 << 64) - 1
        for p in range(q.bit_length() - 1, -1, -1):
            yield p, (q >> p) & 1


@udtf(returnType=T.StructType([T.StructField("seq", T.IntegerType()), T.StructField("run", T.IntegerType())]))
class ZeroRuns:
    """(seq, run) of the zero runs of an array of bits."""

    def eval(self, bits: list):
        run, seq = 0, 0
        for b in bits or []:
            if b:
                seq += 1
                yield seq, run
                run = 0
            else:
                run += 1
        if run:
            yield seq + 1, run


@udtf(returnType=T.StructType([T.StructField("seq", T.IntegerType()), T.StructField("run", T.LongType())]))
class DecodeSegment:
    """(seq, run) of the runs that an archive's segment holds, from its bytes, its model and the coder's name."""

    def eval(self, payload: bytes, symbols: list, freq: list, coder: str):
        if payload is None:
            return
        model = Model(np.array(symbols, np.int64), np.array(freq, np.int64))
        for k, r in enumerate(CODERS[coder].decode(bytes(payload), model)):
            yield k + 1, int(r)


@udtf(returnType=T.StructType([T.StructField("j", T.IntegerType()), T.StructField("tap", T.DoubleType())]))
class LanczosTaps:
    def eval(self, k: int):
        w = lanczos_taps(k)
        for j, t in enumerate(w):
            yield j - len(w) // 2, float(t)


@arrow_udtf(returnType=T.StructType([T.StructField("plane", T.IntegerType()), T.StructField("run", T.LongType())]))
class VectorRuns:
    """(plane, run) of whole vectors of magnitudes, in batches."""

    def eval(self, q: pa.Array):
        for v in q.to_pylist():
            x = np.array(v or [], np.int64).view(np.uint64)
            lead, neg = lead_array(x), np.zeros(len(x), bool)
            rows = [(p, int(r)) for p in range(int(lead.max(initial=-1)), -1, -1) for r in split_plane(x, lead, neg, p)[0]]
            yield pa.table({"plane": pa.array([p for p, _ in rows], pa.int32()), "run": pa.array([r for _, r in rows], pa.int64())})


def psnr_db(span: float, rmse: float) -> float | None:
    return 20 * math.log10(span / (2 * rmse)) if span and rmse else None


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL."""
    from gridpress.session import ship

    ship(spark)
    for name, f in (("float_exponent", float_exponent), ("lead_plane", lead_plane_udf), ("entropy_bits", entropy_bits_udaf), ("gram_entry", gram_entry_udaf)):
        spark.udf.register(name, f)
    for name, f in (("bit_planes", BitPlanes), ("zero_runs", ZeroRuns), ("lanczos_taps", LanczosTaps), ("vector_runs", VectorRuns), ("decode_segment", DecodeSegment)):
        spark.udtf.register(name, f)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION psnr_db(span DOUBLE, rmse DOUBLE) RETURNS DOUBLE RETURN CASE WHEN rmse > 0 AND span > 0 THEN 20 * log10(span / (2 * rmse)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION quantise_bits(v DOUBLE, e INT) RETURNS BIGINT RETURN CAST(floor(abs(v) * power(2, e)) AS BIGINT)")
