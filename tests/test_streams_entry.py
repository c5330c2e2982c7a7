import shutil

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridpress import streaming
from gridpress.operators.codec import decompress_array
from gridpress.plans.targets import ErrorTarget

SMALL = "/root/testdata/sf0.001"


@pytest.fixture
def events(tmp_path):
    (tmp_path / "events").mkdir()
    shutil.copy(f"{SMALL}/events.parquet", tmp_path / "events/a.parquet")
    return str(tmp_path / "events")


def test_replay_equals_batch_and_slabs_compress(spark, events, tmp_path):
    kept = {}
    types = sorted(r[0] for r in spark.read.parquet(events).select("event_type").distinct().collect())
    s = streaming.tumbling(streaming.event_stream(spark, events), late=None)
    sink = streaming.compress_slabs(ErrorTarget.rel(0.01), 24, types, lambda b, day, z: kept.__setitem__(day, z))
    s.writeStream.foreachBatch(sink).outputMode("complete").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "ck")).start().awaitTermination()
    batch = streaming.tumbling(spark.read.parquet(events).withColumn("ts", F.col("ts").cast("timestamp")), late=None)
    days = batch.groupBy(F.to_date("start").alias("d")).agg(F.sum("cents").alias("c")).collect()
    assert {str(r.d) for r in days} == set(kept)
    r = days[0]
    assert abs(decompress_array(kept[str(r.d)]).sum() - r.c) < 0.1 * r.c


def test_dedup_and_interval_join(spark, events):
    shutil.copy(f"{events}/a.parquet", f"{events}/b.parquet")
    streaming.drain(streaming.deduplicated(streaming.event_stream(spark, events, 10)).select("event_id"), "dedup_out")
    assert spark.table("dedup_out").count() == spark.read.parquet(f"{events}/a.parquet").count()


def test_incremental_gram(spark, events, tmp_path):
    fibers = streaming.event_stream(spark, events).select(F.lit(0).alias("mode"), F.array(F.col("value"), F.lit(1.0)).alias("fiber"))
    streaming.drain(streaming.incremental_gram(fibers, 2), "gram_out", "update", str(tmp_path / "ck"))
    v = np.array([r.value for r in spark.read.parquet(events).select("value").collect()])
    got = spark.table("gram_out").orderBy(F.desc("slabs")).first()
    assert got.slabs == len(v) and np.isclose(got.trace, (v**2).sum() + len(v))


def test_entry_and_catalogue(spark):
    import __spark_entry__ as entry
    from gridpress import catalogue

    assert entry.entry(spark).count() == 2
    assert set(catalogue.ORACLES) <= set(catalogue.QUERIES) and len(catalogue.QUERIES) > 120
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_no_window_over_all_cells(spark):
    from gridpress.operators import planes as P

    df = spark.range(1000).select(F.col("id").alias("idx"), (F.col("id") % 37).alias("q")).withColumn("lead", P.lead_plane(F.col("q")))
    plan = P.zero_runs(df, 0, 5)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan


def test_entry_imports_without_a_session():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parents[1]
    got = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()))"], cwd=root, capture_output=True, text=True, timeout=120)
    assert got.returncode == 0 and int(got.stdout.split()[-1]) > 120


def test_sql_functions(spark):
    from gridpress import functions

    functions.register(spark)
    rows = spark.sql("SELECT plane, run FROM vector_runs(array(18L, 3L, 0L, 9L, 1L, 6L, 2L)) ORDER BY plane DESC, run").collect()
    assert [r.run for r in rows if r.plane == 3] == [2, 3]
    assert spark.sql("SELECT count(*) AS n FROM zero_runs(array(0, 1, 1, 0, 0, 0, 1, 0))").first().n == 4
    taps = spark.sql("SELECT sum(tap) AS s FROM lanczos_taps(2)").first().s
    assert abs(taps - 1) < 1e-12
    assert spark.sql("SELECT quantise_bits(2.5D, 2) AS q, lead_plane(8L) AS p").first() == (10, 3)


def test_clicks_join_purchases(spark, events):
    a, b = (streaming.event_stream(spark, events) for _ in range(2))
    streaming.drain(streaming.clicks_to_purchases(a, b, "24 HOURS"), "click_out")
    e = spark.read.parquet(events).withColumn("ts", F.col("ts").cast("timestamp"))
    c, p = e.where("event_type = 'click'").alias("c"), e.where("event_type = 'purchase'").alias("p")
    want = c.join(p, F.expr("c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 24 HOURS")).count()
    assert spark.table("click_out").count() == want


def test_rate_source_parquet_sink_and_static_join(spark, events, tmp_path):
    # a table meets the stream, null where it has no row; nothing is written twice under one checkpoint
    users = spark.createDataFrame([(u, f"u{u}") for u in range(0, 2000, 2)], "user_id long, name string")
    for _ in range(2):
        joined = streaming.with_static(streaming.event_stream(spark, events), users, "user_id").select("event_id", "user_id", "name")
        streaming.to_parquet(joined, str(tmp_path / "out"), str(tmp_path / "ck"))
    got = spark.read.parquet(str(tmp_path / "out")).collect()
    assert len(got) == spark.read.parquet(events).count()
    assert all((r.name is None) if r.user_id % 2 else (r.name == f"u{r.user_id}" or r.user_id >= 2000) for r in got)
    q = streaming.rate_stream(spark, 50).writeStream.format("memory").queryName("rate_out").start()
    while spark.table("rate_out").count() < 100:
        q.awaitTermination(1)
    q.stop()
    rows = spark.table("rate_out").collect()
    assert all(r.v == r.idx % 97 for r in rows) and len({r.idx for r in rows}) == len(rows)


def test_rows_behind_the_watermark_are_left_out(spark, tmp_path):
    import datetime as dt

    at = lambda h, m=0: dt.datetime(2024, 1, 1, h, m)
    # 2:00 comes after the watermark of an earlier batch has passed it; 8:30 does not
    parts = [[(1, at(1)), (2, at(9))], [(3, at(8, 30))], [(4, at(2)), (5, at(14))]]
    fields = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    (tmp_path / "in").mkdir()
    for k, part in enumerate(parts):
        spark.createDataFrame([(i, t, 1, "view", 1.0, None) for i, t in part], fields).coalesce(1).write.parquet(str(tmp_path / f"p{k}"))
        shutil.copy(next((tmp_path / f"p{k}").glob("*.parquet")), tmp_path / f"in/{k}.parquet")
    s = streaming.tumbling(streaming.event_stream(spark, str(tmp_path / "in")), "1 hour", "1 hour")
    streaming.to_parquet(s, str(tmp_path / "out"), str(tmp_path / "ck"))
    got = {r.start.hour: r.n for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {1: 1, 9: 1, 8: 1}


def test_sessions_are_written_by_executors_and_whole(spark, tmp_path):
    """All sessions, those open at the end and of rows out of order in several files too, and none by a table on the driver."""
    import datetime as dt

    import duckdb

    from gridpress.catalogue import ORACLES, QUERIES

    at = lambda m: dt.datetime(2024, 1, 1) + dt.timedelta(minutes=m)
    rows = [(i, at(m), u, "view", i + 0.25, None) for i, (m, u) in enumerate([(600, 1), (5, 1), (20, 1), (50, 1), (51, 2), (595, 1), (1439, 3), (1440, 3), (0, 2)])]
    fields = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    spark.createDataFrame(rows, fields).repartition(3).write.parquet(str(tmp_path / "events.parquet"))
    spark.sql("DROP VIEW IF EXISTS stream_session")
    got = QUERIES["stream_session"](spark, str(tmp_path)).collect()
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
    assert sorted(map(tuple, got)) == sorted(con.execute(ORACLES["stream_session"]).fetchall()) and len(got) == 6
    assert not spark.catalog.tableExists("stream_session")
