"""From documents to encoded training text: five stages, each one operator of gridpress.llm."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridpress.llm import darts, mixing, piece_codec, pu_quality, toxicity
from gridpress.llm.queries import piece_model_path
from gridpress.session import cut, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity scorer rejects go."""
    return toxicity.drop_toxic(docs, toxicity.fit_toxicity(docs, table(spark, sf_dir, "labels")))


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go."""
    return pu_quality.keep_quality(docs, pu_quality.fit_quality(docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class stays, the one of the least id; a row without an id goes.

    Rows are told apart by a 64-bit hash of id and text: a repeated row stays once, while
    different texts under one id are compared like any others.
    """
    keyed = docs.where("doc_id is not null").withColumn("_key", F.xxhash64("doc_id", "text"))
    classes = cut(darts.near_duplicates(keyed, "_key").select(F.col("doc_id").alias("_key"), "class_id"))
    first = F.min(F.struct("doc_id", "_key"))
    kept = keyed.select("_key", "doc_id").join(classes, "_key").groupBy("class_id").agg(first.alias("first")).select("first._key")
    return keyed.join(kept, "_key", "left_semi").dropDuplicates(["_key"]).select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as the mix takes it."""
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids and decoded text of every document, as counts and digests."""
    return piece_codec.encode_documents(docs, piece_model_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("quality", keep_quality),
    ("near_dedup", drop_near_duplicates),
    ("mixing", mix_sources),
    ("encoding", encode),
]

#: Learned stages and the encoder are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = cut(docs)
    return docs
