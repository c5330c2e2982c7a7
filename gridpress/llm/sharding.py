"""Fixed virtual slots: records hash into slots, slots map to shards through a versioned table.

Only DataFrame expressions.  The law kept is `bytes`: shard sizes are near equal.
The map is a stored table with one row for each version and slot: records read their
shard from its latest version, and rebalancing adds a version in which few slots move.
A record's group (equal texts) hashes to one virtual slot, so copies stay
together; a group heavier than a stated share of a shard is dealt over all slots
by its id instead, as one shard could not hold it evenly.

Cases: null text has size 1 and the checksum of the empty text, and is dealt by
id; repeated rows are separate records; an empty table gives no rows; extra
columns are left out of the result.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridpress.session import cut, shared_folder

SLOTS = 4096
SPREAD = 16
HEAVY_SHARE = 0.9


def _size(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1


def slotted(docs: DataFrame, shards: int = 8, slots: int = SLOTS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, virtual_slot and part (the slot's ordered fraction) of each record."""
    text = F.col(text_col)
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        _size(text).alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
        F.when(text.isNotNull(), F.xxhash64(text)).alias("group"),
    )
    # groups over HEAVY_SHARE of a shard: at most shards / HEAVY_SHARE of them, whatever the input
    groups = rows.where("group is not null").groupBy("group").agg(F.sum("size").alias("group_bytes"), F.count("*").alias("n"))
    total = rows.agg(F.sum("size")).first()[0] or 0
    heavy = groups.where((F.col("n") > 1) & (F.col("group_bytes") > F.lit(total * HEAVY_SHARE / shards))).select("group", F.lit(True).alias("heavy"))
    own = F.xxhash64(F.lit("id"), "doc_id")
    key = F.when(F.col("group").isNull() | F.col("heavy").isNotNull(), own).otherwise(F.col("group"))
    return rows.join(F.broadcast(heavy), "group", "left").select(
        "doc_id", "size", "text_crc32", F.pmod(key, F.lit(slots)).cast("int").alias("virtual_slot"), F.pmod(F.xxhash64(F.lit("part"), "doc_id"), F.lit(SPREAD)).cast("int").alias("part")
    )


def slot_sizes(rows: DataFrame) -> DataFrame:
    return rows.groupBy("virtual_slot").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))


def slot_map(sizes: DataFrame, shards: int = 8, version: int = 1) -> DataFrame:
    """Version 1 of the map: largest slot first, each to the lightest shard; one row for each slot.

    The table has at most as many rows as there are slots, so one array holds it.
    """
    state = T.StructType([T.StructField("load", T.ArrayType(T.LongType())), T.StructField("at", T.ArrayType(T.IntegerType()))])
    order = F.array_sort(F.collect_list(F.struct((-F.col("bytes")).alias("minus"), F.col("virtual_slot"))))
    start = F.struct(F.array_repeat(F.lit(0).cast("long"), shards).alias("load"), F.array().cast("array<int>").alias("at")).cast(state)

    def place(s: Column, x: Column) -> Column:
        k = F.array_position(s["load"], F.array_min(s["load"])).cast("int")
        load = F.transform(s["load"], lambda v, i: F.when(i == k - 1, v - x["minus"]).otherwise(v))
        return F.struct(load.alias("load"), F.concat(s["at"], F.array(k - 1)).alias("at"))

    placed = sizes.agg(order.alias("order")).select("order", F.aggregate("order", start, place)["at"].alias("at"))
    return placed.select(F.explode(F.arrays_zip("order", "at")).alias("z")).select(
        F.lit(version).alias("version"), F.col("z.order.virtual_slot").alias("virtual_slot"), F.col("z.at").alias("shard"), (-F.col("z.order.minus")).alias("bytes")
    )


def rebalanced(current: DataFrame, sizes: DataFrame, shards: int) -> DataFrame:
    """The next version of a map for `shards` shards: only slots above each shard's fair share move, to the shards below it."""
    now = current.select("virtual_slot", "shard", "version").join(sizes.select("virtual_slot", "bytes"), "virtual_slot")
    fair = F.sum("bytes").over(Window.partitionBy(F.lit(1))) / shards
    filled = F.sum("bytes").over(Window.partitionBy("shard").orderBy(F.desc("bytes"), "virtual_slot"))
    marked = now.withColumn("moves", (filled > fair) | (F.col("shard") >= shards))
    kept = marked.where("not moves").groupBy("shard").agg(F.sum("bytes").alias("load"))
    room = F.array_sort(F.collect_list(F.struct("shard", "load")))
    have = kept.agg(F.map_from_entries(room).alias("m")).select(F.transform(F.sequence(F.lit(0), F.lit(shards - 1)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0).cast("long"))).alias("load"))
    order = F.array_sort(F.collect_list(F.struct((-F.col("bytes")).alias("minus"), F.col("virtual_slot"))))

    def place(s: Column, x: Column) -> Column:
        k = F.array_position(s["load"], F.array_min(s["load"])).cast("int")
        load = F.transform(s["load"], lambda v, i: F.when(i == k - 1, v - x["minus"]).otherwise(v))
        return F.struct(load.alias("load"), F.concat(s["at"], F.array(k - 1)).alias("at"))

    moved = marked.where("moves").agg(F.lit(1).alias("k"), order.alias("order")).join(have.withColumn("k", F.lit(1)), "k")
    at = F.aggregate("order", F.struct(F.col("load"), F.array().cast("array<int>").alias("at")), place)["at"]
    dealt = moved.select(F.explode(F.arrays_zip("order", at.alias("at"))).alias("z")).select(F.col("z.order.virtual_slot").alias("virtual_slot"), F.col("z.at").alias("new"))
    return marked.join(dealt, "virtual_slot", "left").select((F.col("version") + 1).alias("version"), "virtual_slot", F.coalesce("new", "shard").alias("shard"), "bytes")


def store_version(mapped: DataFrame, path: str, version: int) -> DataFrame:
    """Add a version of a map to the table at `path`, and give it back as read from there.

    Versions are folders of their own, so a version is there whole or not at all, and
    storing one again replaces it.
    """
    mapped.drop("version").coalesce(1).write.mode("overwrite").parquet(f"{path}/version={version}")
    return map_of(stored_map(mapped.sparkSession, path), version)


def stored_map(spark: SparkSession, path: str) -> DataFrame:
    """All versions of a stored map: version, virtual_slot, shard, bytes."""
    return spark.read.schema("virtual_slot int, shard int, bytes long, version int").parquet(path)


def map_of(table: DataFrame, version: int) -> DataFrame:
    """One version of a stored map: one row for each slot."""
    return table.where(F.col("version") == F.lit(version))


def latest(spark: SparkSession, path: str) -> int | None:
    """The last version stored at a path, or None where none is."""
    try:
        return stored_map(spark, path).agg(F.max("version")).first()[0]
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return None


def shard_documents(docs: DataFrame, shards: int = 8, slots: int = SLOTS, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """Shard, virtual slot and place of each record, with its shard in the map's next version.

    The map's versions are stored at a path, by default a new one in the shared folder: an
    empty one gets version 1 from the slots' sizes, and one that has a map keeps to its
    latest version.  The next version, for one shard more, is stored beside it, and
    `next_shard` reads it back.  What is broadcast has slots x SPREAD rows at most, whatever
    the input.

    `slot` counts a shard's records from 0 without gaps.  It is the record's rank
    in its part of a virtual slot plus the records before that part, which come
    from a table of slots x SPREAD rows at most; so no task ranks a whole shard.
    """
    rows = slotted(docs, shards, slots, id_col, text_col)
    parts = rows.groupBy("virtual_slot", "part").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))
    # at most slots x SPREAD rows, written down: the map, its next version and the starts all read them
    parts = cut(parts)
    spark = docs.sparkSession
    every = spark.range(slots).select(F.col("id").cast("int").alias("virtual_slot"))
    sizes = every.join(parts.groupBy("virtual_slot").agg(F.sum("bytes").alias("bytes")), "virtual_slot", "left").select("virtual_slot", F.coalesce("bytes", F.lit(0)).alias("bytes"))
    version = latest(spark, path) if path else None
    path = path or shared_folder(spark, "slot_map")
    mapped = map_of(stored_map(spark, path), version) if version else store_version(slot_map(sizes, shards), path, 1)
    grown = store_version(rebalanced(mapped, sizes, shards + 1), path, (version or 1) + 1)
    mapped = mapped.select("virtual_slot", "shard", "version").join(grown.select("virtual_slot", F.col("shard").alias("next_shard")), "virtual_slot")
    before = F.sum("rows").over(Window.partitionBy("shard").orderBy("virtual_slot", "part").rowsBetween(Window.unboundedPreceding, -1))
    starts = parts.join(F.broadcast(mapped), "virtual_slot").select("virtual_slot", "part", "shard", "version", "next_shard", F.coalesce(before, F.lit(0)).alias("before"))
    rank = F.row_number().over(Window.partitionBy("virtual_slot", "part").orderBy("doc_id", "text_crc32", "size"))
    return (
        rows.withColumn("rank", rank)
        .join(F.broadcast(starts), ["virtual_slot", "part"])
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("before") + F.col("rank") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "virtual_slot", F.col("version").alias("map_version"), "next_shard")
    )
