"""Relational operators that work on grids needs: as-of and interval joins, densified axes, top slices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridpress.session import cut


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """Each left row with the last right value at or before it: one union, one window, no join.

    Ties go to the right side's rows first and among them to the largest value;
    without an earlier row the value is null.
    """
    a = left.select(by, on, F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(by, on, F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"))
    w = Window.partitionBy(by).orderBy(on, "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select("_row.*", F.col("_last").alias(f"last_{value}"))


def interval_join(points: DataFrame, starts: DataFrame, by: str, at: str, start: str, seconds: int) -> DataFrame:
    """Points within `seconds` after a start of the same key: an equi-join on time buckets, each start in two."""
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    p = points.withColumn("_b", bucket(F.col(at).cast("timestamp")))
    s = starts.withColumn("_b", F.explode(F.array(bucket(F.col(start).cast("timestamp")), bucket(F.col(start).cast("timestamp")) + 1)))
    gap = F.unix_micros(F.col(at).cast("timestamp")) - F.unix_micros(F.col(start).cast("timestamp"))
    return p.join(s, [by, "_b"]).where((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_b")


def densify(cells: DataFrame, axes: list[str], value: str) -> DataFrame:
    """All combinations of the axes' labels, absent values 0; axes are small dictionaries."""
    grid = None
    for a in axes:
        d = cells.select(a).distinct()
        grid = d if grid is None else grid.crossJoin(F.broadcast(d))
    return grid.join(cells, axes, "left").withColumn(value, F.coalesce(value, F.lit(0)))


def top_per_group(df: DataFrame, group: str, order: str, k: int, tie: str) -> DataFrame:
    w = Window.partitionBy(group).orderBy(F.desc(order), tie)
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def ranged(df: DataFrame, *order: str | Column) -> DataFrame:
    """df with _part and _at: rows dealt by ranges of the order, and a row's place in its range.  Written down, so that both stay."""
    sorted_ = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id())
    return cut(sorted_).withColumn("_part", F.shiftright("_m", 33).cast("int")).withColumn("_at", F.col("_m").bitwiseAND(F.lit((1 << 33) - 1))).drop("_m")


def numbered(df: DataFrame, *order: str | Column, name: str = "idx") -> DataFrame:
    """Rows numbered from 0 by an order, without a window: a place in a range plus the rows of the ranges before it.

    The table of ranges has one row for each partition.  Rows that are equal in the order
    are numbered in no stated order among each other.
    """
    rows = ranged(df, *order)
    counts = sorted((r["_part"], r["n"]) for r in rows.groupBy("_part").agg(F.count("*").alias("n")).collect())
    starts, total = [], 0
    for part, n in counts:
        starts.append((part, total))
        total += n
    first = df.sparkSession.createDataFrame(starts, "_part int, _start long")
    return rows.join(F.broadcast(first), "_part").select((F.col("_start") + F.col("_at")).alias(name), *df.columns)


def running_sum(df: DataFrame, key: str, value: str, name: str = "running") -> DataFrame:
    """Running sums by a key over any number of rows: windows inside ranges, and the sums of the ranges before."""
    rows = ranged(df, key)
    sums = sorted((r["_part"], r["t"]) for r in rows.groupBy("_part").agg(F.sum(value).alias("t")).collect())
    starts, total = [], None
    for part, t in sums:
        starts.append((part, total))
        total = t if total is None else total if t is None else total + t
    kind = rows.agg(F.sum(value).alias("t")).schema["t"].dataType.simpleString()
    first = df.sparkSession.createDataFrame(starts, f"_part int, _start {kind}")
    inside = F.sum(value).over(Window.partitionBy("_part").orderBy(key))
    return rows.join(F.broadcast(first), "_part").select(*df.columns, (F.coalesce("_start", F.lit(0)) + inside).alias(name))
