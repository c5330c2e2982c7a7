import time
from pathlib import Path

import numpy as np

from gridpress.llm import components as C
from gridpress.session import cut


def test_one_task_and_rounds_agree(spark, monkeypatch):
    rng = np.random.default_rng(9)
    chain = [(i, i + 1) for i in range(300, 360)]
    edges = [tuple(map(int, e)) for e in rng.integers(0, 200, (120, 2))] + chain[::-1] + [(400, 400), (7, 7)] + chain
    df = spark.createDataFrame(edges, "a long, b long")
    root = {x: x for e in edges for x in e if e[0] != e[1]}
    for _ in root:
        for a, b in edges:
            if a != b:
                root[a] = root[b] = min(root[a], root[b])
    one = C.components(df).collect()
    monkeypatch.setattr(C, "ONE_TASK", 0)
    rounds = {r.node: r.root for r in C.components(df).collect()}
    for node in root:  # rounds name a root for each node but the roots themselves
        assert rounds.get(node, node) == root[node]
    assert {r.node: r.root for r in one} == root and len(one) == len(root)
    assert C.components(df.limit(0)).count() == 0


def test_a_small_table_takes_few_tasks(spark):
    """Rounds of stars on few edges were thousands of tasks without rows where a cluster has many partitions."""
    edges = spark.range(500).selectExpr("id + 1 as a", "id as b")
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("few", "components of few edges")
    try:
        assert {r.root for r in C.components(edges).collect()} == {0}
        stages = {s for j in tracker.getJobIdsForGroup("few") for s in tracker.getJobInfo(j).stageIds}
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(stages) <= 8


def test_cut_leaves_no_shuffle_files(spark):
    local = Path(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()[0])
    files = lambda: {f.name for f in local.rglob("shuffle_*")}
    before = files()
    df = spark.range(5000).groupBy("id").count()
    got = cut(df)
    until = time.time() + 20  # executors are told, not waited for
    while not files() <= before and time.time() < until:
        time.sleep(0.1)
    assert files() <= before
    # what was cut can be run again, and the setting is as it was
    assert df.count() == got.count() == 5000
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"
