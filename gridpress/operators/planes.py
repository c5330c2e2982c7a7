"""Bit planes of coefficients, as sets of rows instead of a loop over bits.

With `lead` the highest 1 bit of a magnitude, a bit of plane p is coded in runs
where lead <= p (not significant before), verbatim where lead > p, and is the
coefficient's first 1 where lead = p.  So masks, runs, sums of errors and the
breakpoint are aggregates and ranks; nothing depends on a visiting order.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridpress.operators.relops import numbered, running_sum
from gridpress.session import ship

PLANES = 64
CHUNK = 1 << 16
TOP = 63


# ---- magnitudes as columns ----


def scale_exponent(m: float) -> int:
    """Exponent e with 2^e <= m < 2^(e+1); scaling by 2^(63 - e) puts m in plane 63."""
    return math.frexp(m)[1] - 1 if m > 0 else 0


def lead_plane(q: Column) -> Column:
    """Highest 1 bit of the 64 raw bits, -1 for 0."""
    return F.when(q == 0, F.lit(-1)).otherwise(F.length(F.bin(q)) - 1).cast("int")


def unsigned_long(v: Column) -> Column:
    """Raw 64 bits of a non-negative double under 2^64, floor taken."""
    half = F.lit(2.0**63)
    return F.when(v >= half, (v - half).cast("long").bitwiseXOR(F.lit(-(2**63)))).otherwise(F.least(v, F.lit(2.0**63 - 1024)).cast("long"))


def quantise(coef: DataFrame, exponent: int | None = None, value: str = "v") -> DataFrame:
    """(idx, q, neg, lead): truncated magnitudes scaled so that the largest fills plane 63."""
    if exponent is None:
        exponent = scale_exponent(float(coef.agg(F.max(F.abs(value))).first()[0] or 0.0))
    k = 2.0 ** ((63 - exponent) // 2), 2.0 ** ((63 - exponent) - (63 - exponent) // 2)
    q = unsigned_long(F.abs(F.col(value).cast("double")) * F.lit(k[0]) * F.lit(k[1]))
    return coef.select("idx", q.alias("q"), (F.col(value) < 0).alias("neg")).withColumn("lead", lead_plane(F.col("q")))


def integers(df: DataFrame, q: Column, order: Column | list[str]) -> DataFrame:
    """(idx, q, lead) of integer magnitudes as they are; idx numbers rows by `order`."""
    rows = numbered(df.withColumn("_q", q.cast("long")), *(order if isinstance(order, (list, tuple)) else [order]))
    return rows.select("idx", F.col("_q").alias("q")).withColumn("lead", lead_plane(F.col("q")))


def bit(q: Column, p: Column | int) -> Column:
    return F.call_function("shiftrightunsigned", q, F.lit(p) if isinstance(p, int) else p).bitwiseAND(F.lit(1).cast("long"))


def bit_class(lead: Column, p: int) -> Column:
    return F.when(lead > p, "verbatim").otherwise("run")


def kept(q: Column, p: int) -> Column:
    """q with the bits below plane p cleared."""
    return F.shiftleft(F.shiftrightunsigned(q, p), p) if p else q


def threshold_view(q: DataFrame, p: int) -> DataFrame:
    return q.where(F.col("lead") >= p)


def mask_growth(q: DataFrame, planes: range) -> DataFrame:
    """(plane, before, after): members of the significance mask around each plane."""
    one = q.agg(*(x for p in planes for x in (F.count(F.when(F.col("lead") > p, 1)).alias(f"b{p}"), F.count(F.when(F.col("lead") >= p, 1)).alias(f"a{p}"))))
    row = F.array(*(F.struct(F.lit(p).alias("plane"), F.col(f"b{p}").alias("before"), F.col(f"a{p}").alias("after")) for p in planes))
    return one.select(F.explode(row).alias("x")).select("x.*")


def zero_runs(q: DataFrame, p_lo: int, p_hi: int) -> DataFrame:
    """(plane, seq, run) of planes p_lo..p_hi, whole vector in one scope.

    Ranks are two-level: counts of each (chunk, plane) are summed up over the
    small chunk table, and only positions inside a chunk are ranked.  The same goes
    for the 1 bits: a chunk's first one looks at the last of the chunks before.
    """
    planes = q.sparkSession.range(p_lo, p_hi + 1).select(F.col("id").cast("int").alias("plane"))
    cand = q.select("idx", "lead", F.floor(F.col("idx") / CHUNK).alias("chunk")).join(F.broadcast(planes), F.col("lead") <= F.col("plane"))
    table = cand.groupBy("plane", "chunk").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("plane").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = table.select("plane", "chunk", before.alias("start"), F.sum("n").over(Window.partitionBy("plane")).alias("total"))
    inside = F.row_number().over(Window.partitionBy("plane", "chunk").orderBy("idx"))
    ones = cand.withColumn("r", inside).where("lead = plane").join(starts, ["plane", "chunk"]).select("plane", "chunk", "total", (F.col("start") + F.col("r")).alias("rank"))
    by_chunk = Window.partitionBy("plane").orderBy("chunk")
    heads = ones.groupBy("plane", "chunk").agg(F.max("rank").alias("last"), F.count("*").alias("n"))
    carry = heads.select("plane", "chunk", F.coalesce(F.lag("last").over(by_chunk), F.lit(0)).alias("from"), F.coalesce(F.sum("n").over(by_chunk.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("n"))
    w = Window.partitionBy("plane", "chunk").orderBy("rank")
    body = ones.join(carry, ["plane", "chunk"]).select("plane", (F.col("n") + F.row_number().over(w)).alias("seq"), (F.col("rank") - F.coalesce(F.lag("rank").over(w), F.col("from")) - 1).alias("run"))
    ends = starts.groupBy("plane").agg(F.max("total").alias("total")).join(ones.groupBy("plane").agg(F.max("rank").alias("last"), F.count("*").alias("ones")), "plane", "left")
    tail = ends.where("total > coalesce(last, 0)").select("plane", (F.coalesce("ones", F.lit(0)) + 1).alias("seq"), (F.col("total") - F.coalesce("last", F.lit(0))).alias("run"))
    return body.select("plane", F.col("seq").cast("long").alias("seq"), F.col("run").cast("long").alias("run")).union(tail.select("plane", F.col("seq").cast("long"), F.col("run").cast("long")))


def plane_sse(q: DataFrame, planes: range) -> DataFrame:
    """(plane, sse_after): squared error in scaled units once planes down to it are kept; one aggregate."""
    low = lambda p: F.col("q") - kept(F.col("q"), p)
    one = q.agg(*(F.sum(low(p).cast("double") * low(p)).alias(f"s{p}") for p in planes))
    row = F.array(*(F.struct(F.lit(p).alias("plane"), F.coalesce(F.col(f"s{p}"), F.lit(0.0)).alias("sse_after")) for p in planes))
    return one.select(F.explode(row).alias("x")).select("x.*")


def breakpoint_sql(q: DataFrame, budget: float, planes: range) -> DataFrame:
    """(plane, c_star, sse): the first bit, by plane and then index, after which the error is within the budget.

    Prefix sums of a plane's drops are two-level over ranges.
    """
    stats = {r.plane: r.sse_after for r in plane_sse(q, range(planes.start, planes.stop)).collect()}
    energy = q.agg(F.sum(F.col("q").cast("double") * F.col("q"))).first()[0] or 0.0
    schema = "plane int, c_star long, sse double"
    if energy <= budget or not stats:
        return q.sparkSession.createDataFrame([(planes.stop, -1, float(energy))], schema)
    hit = [p for p in stats if stats[p] <= budget * (1 + 1e-12)]
    p = max(hit) if hit else planes.start
    above = stats.get(p + 1, energy)
    rest = (F.col("q") - kept(F.col("q"), p + 1)).cast("double") if p < TOP else F.col("q").cast("double")
    drop = F.when(bit(F.col("q"), p) == 1, rest * rest - (rest - 2.0**p) * (rest - 2.0**p)).otherwise(F.lit(0.0))
    run = running_sum(q.select("idx", drop.alias("d")), "idx", "d").select("idx", (F.lit(above) - F.col("running")).alias("sse"))
    return run.where(F.col("sse") <= budget * (1 + 1e-12)).orderBy("idx").limit(1).select(F.lit(p).alias("plane"), F.col("idx").alias("c_star"), "sse")


def dequantise(q: Column, p: int, mode: str = "midpoint") -> Column:
    """Magnitude in scaled units from planes down to p; the middle of what is unknown, or its floor."""
    k = kept(q, p).cast("double")
    return F.when(kept(q, p) == 0, F.lit(0.0)).otherwise(k + (2.0 ** (p - 1) if mode == "midpoint" and p >= 1 else 0.0))


def rle_bits(bits: Column) -> Column:
    """Zero runs of a bit string: each 1 ends a run; zeros left at the end are a run of their own."""
    parts = F.split(bits, "1", -1)
    runs = F.transform(parts, lambda s: F.length(s))
    return F.when(F.length(bits) == 0, F.array().cast("array<int>")).when(bits.endswith("1"), F.slice(runs, 1, F.size(runs) - 1)).otherwise(runs)


def worked(vectors: DataFrame, key: str) -> DataFrame:
    """(key, plane, runs, verbatim, before, after) of small vectors v of (.., q, lead), for each plane from a vector's top one down.

    A plane's zero runs over what is not in the mask yet, its bits of what is, and the mask's size before and after it.
    """
    planes = vectors.withColumn("plane", F.explode(F.sequence(F.lit(0), F.array_max(F.transform("v", lambda x: F.greatest(x["lead"], F.lit(0)))))))
    planes = planes.where(F.exists("v", lambda x: x["lead"] >= 0))
    p = F.col("plane")
    fresh = F.array_join(F.transform(F.filter("v", lambda x: x["lead"] <= p), lambda x: F.when(x["lead"] == p, "1").otherwise("0")), "")
    sent = F.array_join(F.transform(F.filter("v", lambda x: x["lead"] > p), lambda x: F.call_function("shiftright", x["q"], p).bitwiseAND(F.lit(1).cast("long")).cast("string")), "")
    size = lambda f: F.size(F.filter("v", f))
    return planes.select(key, "plane", F.array_join(rle_bits(fresh).cast("array<string>"), ",").alias("runs"), sent.alias("verbatim"), size(lambda x: x["lead"] > p).alias("before"), size(lambda x: x["lead"] >= p).alias("after"))


def negabinary(v: Column) -> Column:
    """Base -2 digits of a signed long, as raw bits."""
    m = F.lit(0xAAAAAAAAAAAAAAA)
    return (v + m).bitwiseXOR(m)


def negabinary_value(q: Column) -> Column:
    m = F.lit(0xAAAAAAAAAAAAAAA)
    return q.bitwiseXOR(m) - m


# ---- the same on arrays, for blocks ----


def quantise_array(c: np.ndarray, exponent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(q, neg, lead) of doubles."""
    m = np.ldexp(np.abs(c), 63 - exponent)
    q = np.minimum(m, np.nextafter(2.0**64, 0)).astype(np.uint64)
    return q, c < 0, lead_array(q)


def lead_array(q: np.ndarray) -> np.ndarray:
    hi, lo = (q >> np.uint64(32)).astype(np.float64), (q & np.uint64(0xFFFFFFFF)).astype(np.float64)
    return np.where(hi > 0, np.frexp(hi)[1] + 31, np.frexp(lo)[1] - 1).astype(np.int64)


def low_bits(q: np.ndarray, p: int) -> np.ndarray:
    return q & np.uint64((1 << p) - 1) if p < 64 else q


def sse_by_plane(q: np.ndarray, budget: float = -1.0) -> np.ndarray:
    """65 values: squared error in scaled units when planes p.. are kept, p = 0..64.

    Planes below the first that is within the budget are not looked at, and stay 0.
    """
    lead = lead_array(q)
    v = q.astype(np.float64)
    # what lies whole under a plane keeps its energy; only the rest is cut, and at high planes that is little
    whole = np.concatenate([[0.0], np.cumsum(np.bincount(lead + 1, weights=v * v, minlength=65))])
    out = np.zeros(65)
    for p in range(64, -1, -1):
        low = low_bits(q[lead >= p], p).astype(np.float64)
        out[p] = whole[p + 1] + float((low * low).sum())
        if out[p] <= budget:
            break
    return out


def stop_by_budget(q: np.ndarray, budget: float, sse: np.ndarray | None = None) -> tuple[int, int]:
    """(plane, coefficients of it that are sent) at the first bit within the budget; (64, 0) if nothing need be sent."""
    sse = sse_by_plane(q) if sse is None else sse
    if sse[64] <= budget:
        return 64, 0
    ok = np.flatnonzero(sse[:64] <= budget * (1 + 1e-12))
    if not len(ok):
        return 0, len(q)
    p = int(ok.max())
    rest = low_bits(q, p + 1).astype(np.float64)
    one = (q >> np.uint64(p)) & np.uint64(1) == 1
    run = sse[p + 1] - np.cumsum(np.where(one, rest**2 - (rest - 2.0**p) ** 2, 0.0))
    return p, int(np.flatnonzero(run <= budget * (1 + 1e-12))[0]) + 1


def split_plane(q: np.ndarray, lead: np.ndarray, neg: np.ndarray, p: int, sent: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(zero runs, verbatim bits, signs) of plane p over the first `sent` coefficients."""
    if sent is not None:
        q, lead, neg = q[:sent], lead[:sent], neg[:sent]
    fresh = lead[lead <= p] == p
    at = np.flatnonzero(fresh)
    runs = np.diff(np.concatenate([[-1], at])) - 1
    if len(fresh) and (not len(at) or at[-1] != len(fresh) - 1):
        runs = np.append(runs, len(fresh) - 1 - (at[-1] if len(at) else -1))
    raw = ((q[lead > p] >> np.uint64(p)) & np.uint64(1)).astype(np.uint8)
    return runs.astype(np.int64), raw, neg[lead == p].astype(np.uint8)


def join_plane(q: np.ndarray, seen: np.ndarray, neg: np.ndarray, p: int, runs: np.ndarray, raw: np.ndarray, signs: np.ndarray, sent: int) -> None:
    """Undo split_plane in place: set the bits of plane p, and grow the mask."""
    old = np.flatnonzero(seen[:sent])
    q[old[raw == 1]] |= np.uint64(1 << p)
    free = np.flatnonzero(~seen[:sent])
    ends = np.cumsum(runs + 1) - 1
    ends = ends[ends < len(free)]
    new = free[ends]
    q[new] |= np.uint64(1 << p)
    seen[new] = True
    neg[new] = signs == 1


def restore(q: np.ndarray, neg: np.ndarray, p: int, sent: int, exponent: int, midpoint: bool = True) -> np.ndarray:
    """Doubles from planes down to p (the first `sent` coefficients) or p + 1 (the others)."""
    v = q.astype(np.float64)
    if midpoint:
        half = np.full(len(q), 2.0 ** (p - 1) if p >= 1 else 0.0)
        half[sent:] = 2.0**p
        v = np.where(q > 0, v + half, 0.0)
    v = np.ldexp(v, exponent - 63)
    return np.where(neg, -v, v)


def cells_runs(q: DataFrame, p_lo: int, p_hi: int) -> DataFrame:
    """Runs that end at chunk borders, as the archive stores them: (chunk, plane, run)."""
    ship(q.sparkSession)

    def one(key: tuple, t: pa.Table) -> pa.Table:
        order = np.argsort(t["idx"].to_numpy())
        v = t["q"].to_numpy()[order].view(np.uint64)
        lead, none = lead_array(v), np.zeros(len(v), bool)
        out = [(p, r) for p in range(p_hi, p_lo - 1, -1) for r in split_plane(v, lead, none, p)[0]]
        return pa.table({"chunk": pa.array([key[0].as_py()] * len(out), pa.int64()), "plane": pa.array([p for p, _ in out], pa.int32()), "run": pa.array([int(r) for _, r in out], pa.int64())})

    return q.select(F.floor(F.col("idx") / CHUNK).alias("chunk"), "idx", "q").groupBy("chunk").applyInArrow(one, "chunk long, plane int, run long")
