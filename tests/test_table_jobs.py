"""Queries whose data used to be made up read given tables, and equal their SQL."""

import math

import duckdb

from gridpress.catalogue import ORACLES, QUERIES
from gridpress.operators import planes as P

SMALL = "/root/testdata/sf0.001"


def same(spark, name, table, d=SMALL):
    df = QUERIES[name](spark, d)
    assert table in " ".join(f.rsplit("/", 1)[-1] for f in df.inputFiles()) or name == "synth_rank1"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW {table} AS SELECT * FROM read_parquet('{d}/{table}.parquet')")
    want = con.execute(ORACLES[name])
    assert df.columns == [c[0] for c in want.description]
    key = lambda r: [str(x) for x in r]
    got, want = sorted(map(tuple, df.collect()), key=key), sorted(want.fetchall(), key=key)
    assert got == want and got
    return got


def test_rle_string_of_events(spark):
    got = same(spark, "rle_string", "events")
    assert len({r[1] for r in got}) > 100
    rows = [("01100010", [1, 0, 3, 1]), ("0000", [4]), ("111", [0, 0, 0]), ("1", [0]), ("", [])]
    df = spark.createDataFrame(rows, "bits string, want array<int>")
    assert all(r.runs == r.want for r in df.select("want", P.rle_bits(P.F.col("bits")).alias("runs")).collect())


def test_rank_one_grid_of_events(spark):
    (ones, peak), = same(spark, "synth_rank1", "events")
    assert ones == 1 and math.isfinite(peak)


def test_worked_vectors_of_orders(spark):
    assert len(same(spark, "worked_vector", "lineitem")) > 1000
    v = spark.createDataFrame([(0, i, q) for i, q in enumerate((18, 3, 0, 9, 1, 6, 2))] + [(1, 0, 0)], "k long, i int, q long").withColumn("lead", P.lead_plane(P.F.col("q")))
    got = P.worked(v.groupBy("k").agg(P.F.array_sort(P.F.collect_list(P.F.struct("i", "q", "lead"))).alias("v")), "k").collect()
    want = [(4, "0,6", "", 0, 1), (3, "2,3", "0", 1, 2), (2, "3,1", "00", 2, 3), (1, "0,2", "101", 3, 5), (0, "1", "01100", 5, 6)]
    assert sorted(tuple(r)[1:] for r in got) == sorted(want) and {r.k for r in got} == {0}
