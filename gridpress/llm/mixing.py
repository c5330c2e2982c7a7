"""Mix sources to target weights by hash thresholds, without sorting records.

Each source gets a target of words.  Whole copies of every document come first;
the rest is what falls under a threshold on a hash of the id.  The threshold is
found in histograms: words by source and hash bucket, then again only inside
the boundary bucket, until a bucket is one hash value.

Cases: null text has size 0; a null source is a source of its own, the last;
an empty source or table takes nothing; records with the same id share a hash
and so share the boundary in proportion to their sizes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridpress.session import cut

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (3, 1, 2)
SHARE, CEILING = 1.5, 2.0
HASH_BITS, STEP_BITS = 60, 12
#: tables of one row a source are broadcast up to this many rows; beyond, rows meet them by shuffles
BROADCAST_SOURCES, SALTS = 1 << 16, 64


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def record_hash(key: Column) -> Column:
    """The first 60 bits of the md5 of the id's decimals, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, HASH_BITS // 4), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, ceiling: float = CEILING) -> DataFrame:
    """source, source_size, target: weights repeat over sources by code point; what is over a ceiling goes to the rest by weight.

    The level is found in closed form: sources ordered by ceiling over weight
    reach their ceilings one after the other as the common level rises.
    One row for each source, so the windows run on that small table.
    """
    one = Window.partitionBy(F.lit(1))
    order = one.orderBy(F.col("source").isNull(), F.encode("source", "UTF-8"))
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    t = sizes.withColumn("w", weight).withColumn("top", F.col("source_size") * F.lit(float(ceiling))).withColumn("goal", F.sum("source_size").over(one) * F.lit(float(share)))
    t = t.withColumn("ratio", F.col("top") / F.col("w"))
    rising = one.orderBy("ratio", F.col("source").isNull(), F.encode("source", "UTF-8"))
    full = F.coalesce(F.sum("top").over(rising.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    open_w = F.sum("w").over(rising.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    t = t.withColumn("level", (F.col("goal") - full) / open_w)
    t = t.withColumn("step", F.row_number().over(rising))
    fits = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("step", "level"))).over(one)
    level = F.coalesce(fits["level"], F.max("ratio").over(one))
    return t.select("source", "source_size", F.least(F.col("top"), F.col("w") * level).alias("target"))


def _few(table: DataFrame) -> bool:
    return table.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES


def _thresholds(rows: DataFrame, need: DataFrame) -> DataFrame:
    """source, cut, left, at: words under hash `cut` are within the need, `left` of it remain, `at` words have that hash.

    rows: source, h, size.  Each round keeps one row for each source; the
    histogram of a round has at most 2^STEP_BITS buckets for each source.
    """
    small = F.broadcast if _few(need) else (lambda df: df)
    state = need.select("source", F.lit(0).cast("long").alias("prefix"), F.col("need").alias("left"))
    for used in range(STEP_BITS, HASH_BITS + 1, STEP_BITS):
        bucket = F.shiftright("h", HASH_BITS - used)
        inside = rows if used == STEP_BITS else rows.join(small(state.select(F.col("source").alias("s"), "prefix")), F.col("source").eqNullSafe(F.col("s")) & (F.shiftright("h", HASH_BITS - used + STEP_BITS) == F.col("prefix"))).drop("s", "prefix")
        hist = inside.groupBy("source", bucket.alias("b")).agg(F.sum("size").alias("words"))
        w = Window.partitionBy("source").orderBy("b")
        run = hist.withColumn("upto", F.sum("words").over(w))
        found = run.join(small(state.select(F.col("source").alias("s"), "left")), F.col("source").eqNullSafe(F.col("s")))
        # the first bucket that the need does not cover whole
        first = found.where(F.col("upto") > F.col("left")).groupBy("source").agg(F.min_by(F.struct("b", "words", (F.col("left") - F.col("upto") + F.col("words")).alias("left")), "b").alias("x"))
        state = first.select("source", F.col("x.b").alias("prefix"), F.col("x.left").alias("left"), F.col("x.words").alias("at"))
        # one row for each source: written down, so that a round does not plan its predecessors again
        state = cut(state if used == HASH_BITS else state.select("source", "prefix", "left"))
    return state.select("source", F.col("prefix").alias("cut"), "left", "at")


def _with_source(rows: DataFrame, table: DataFrame) -> DataFrame:
    """Rows with the values of their source (column s of a table of one row for each source).

    A table of at most BROADCAST_SOURCES rows travels to the rows.  A larger one meets them
    by source and salt, so a source of any share of the rows is dealt out.
    """
    if _few(table):
        return rows.join(F.broadcast(table), F.col("source").eqNullSafe(F.col("s")))
    salted = rows.withColumn("_salt", F.pmod("h", F.lit(SALTS)).cast("int"))
    spread = table.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return salted.join(spread, F.col("source").eqNullSafe(F.col("s")) & (F.col("_salt") == F.col("_s"))).drop("_salt", "_s")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, ceiling: float = CEILING) -> DataFrame:
    """The input's columns behind those of the mix: _size, _source_size, _target, _taken, _copies.

    _taken: words taken, repeats counted; the record on the boundary gives a
    part of its words, so that sums meet the target within a few words.
    _copies: whole copies to write where parts are not wanted (the boundary record rounds).
    """
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(source_col).alias("source"), record_hash(F.col(id_col)).alias("h"), words(F.col(text_col)).alias("size"))
    slim = docs.select(F.col(source_col).alias("source"), record_hash(F.col(id_col)).alias("h"), words(F.col(text_col)).alias("size")).groupBy("source", "h").agg(F.sum("size").alias("size"))
    slim = cut(slim)
    sizes = slim.groupBy("source").agg(F.sum("size").alias("source_size"))
    goals = source_targets(sizes, weights, share, ceiling)
    goals = goals.withColumn("full", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    goals = goals.withColumn("need", F.round(F.col("target") - F.col("full") * F.col("source_size")).cast("long"))
    goals = cut(goals)
    cuts = _thresholds(slim.where("size > 0"), goals)
    table = goals.join(cuts.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s")), "left").drop("s")
    table = cut(table.select("source", "source_size", "target", "full", "need", "cut", "left", "at")).withColumnRenamed("source", "s")
    joined = _with_source(rows, table)
    under = F.when(F.col("cut").isNull(), F.when(F.col("need") > 0, F.col("size")).otherwise(F.lit(0))).when(F.col("h") < F.col("cut"), F.col("size"))
    part = under.when(F.col("h") == F.col("cut"), F.floor(F.col("size") * F.col("left") / F.col("at"))).otherwise(F.lit(0)).cast("long")
    more = F.when((part > 0) & (part * 2 >= F.col("size")), F.lit(1)).otherwise(F.lit(0))
    return joined.select("row", F.col("size").alias("_size"), F.col("source_size").alias("_source_size"), F.col("target").cast("double").alias("_target"), (F.col("full") * F.col("size") + part).alias("_taken"), (F.col("full") + more).cast("int").alias("_copies"))


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix itself, with the input's columns: each record as many times as it is taken.

    A record without words has no size to be weighed by; it stays once.
    """
    m = mix(docs, **options)
    copies = F.when(F.col("_size") == 0, F.lit(1)).otherwise(F.col("_copies"))
    return m.select("row", F.explode(F.sequence(F.lit(1), F.when(copies > 0, copies))).alias("_n")).select("row.*")
