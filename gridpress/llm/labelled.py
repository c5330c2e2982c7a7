"""Bounded samples of labelled and unlabelled documents for the classifiers.

A row is held out when crc32 of its id's decimals is divisible by 5; learning
sees other rows only.  Samples take the smallest hashes of the id, so they do
not depend on partitions; their sizes are the bounds that callers state.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FOLDS = 5


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(FOLDS)) == 0, F.lit(False))


def labelled_ids(labels: DataFrame, column: str, value: int, bound: int) -> DataFrame:
    """At most `bound` ids of the learning folds whose label is `value` and never another one."""
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(column).alias("y")).where("doc_id is not null and y is not null")
    one = rows.where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.min("y").alias("lo"), F.max("y").alias("hi")).where((F.col("lo") == value) & (F.col("hi") == value))
    return one.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound).select("doc_id", F.lit(value).alias("y"))


def sample_texts(docs: DataFrame, ids: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Texts of sampled ids (a bounded table), one for each id and label."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).join(F.broadcast(ids), "doc_id")


def any_ids(docs: DataFrame, bound: int, mark: int = -1, id_col: str = "doc_id") -> DataFrame:
    """At most `bound` ids of the learning folds, labelled or not."""
    d = docs.select(F.col(id_col).cast("long").alias("doc_id")).where("doc_id is not null").where(~held_out(F.col("doc_id")))
    return d.orderBy(F.xxhash64("doc_id", F.lit(7)), "doc_id").limit(bound).distinct().select("doc_id", F.lit(mark).alias("y"))
