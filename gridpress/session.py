"""Session helpers: shipping the package, cutting lineage, batch sizes."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

PACKAGE = Path(__file__).resolve().parent
_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application.

    Spark serves the zip itself, so no folder has to be shared for the code.
    """
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    fd, path = tempfile.mkstemp(prefix="gridpress_", suffix=".zip")
    os.close(fd)
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(PACKAGE.rglob("*.py")):
            z.write(f, f"{PACKAGE.name}/{f.relative_to(PACKAGE)}")
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def arrow_rows(spark: SparkSession, rows: int = 1000) -> None:
    """Bound the rows of an Arrow batch, so a batch of long texts fits a worker."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def _checkpoints(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a temporary one only where that is unset, as in local tests."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        where = spark.conf.get("spark.checkpoint.dir", None)
        if where is None and not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(where or tempfile.mkdtemp(prefix="gridpress_ckpt_"))
    return sc.getCheckpointDir()


#: lets Spark delete an execution's shuffle files once it has ended
_SHUFFLES_GO = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in spark.checkpoint.dir; the shuffle files that made it go at once, not when the driver collects its garbage."""
    spark = df.sparkSession
    _checkpoints(spark)
    before = spark.conf.get(_SHUFFLES_GO, "false")
    spark.conf.set(_SHUFFLES_GO, "true")
    try:
        # a frame of its own, planned under the setting: a later action on df plans and shuffles for itself
        return df.select("*").checkpoint(eager=True)
    finally:
        spark.conf.set(_SHUFFLES_GO, before)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder for a written table, beside the checkpoints."""
    return f"{_checkpoints(spark)}/{name}_{uuid.uuid4().hex}"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; executors get the package before anything that reads one runs there."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
