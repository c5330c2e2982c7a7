"""Cubes of the given tables, formula grids, and raw or listed cells."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridpress.plans.grid import GridFrame, GridSpec, bin_hour, bin_month, bin_pct
from gridpress.session import arrow_rows, ship, table


def cents(c: Column) -> Column:
    return F.round(c * 100).cast("long")


def ship_density_cells(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_shipdate", "l_quantity", "l_discount")
    return li.groupBy(bin_month(F.col("l_shipdate")).alias("month"), F.col("l_quantity").cast("int").alias("quantity"), bin_pct(F.col("l_discount")).alias("discount")).agg(F.count("*").alias("v"))


def trade_value_cells(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_suppkey", "l_partkey", "l_shipdate", "l_extendedprice")
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("nation"))
    p = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_size").alias("size"))
    return li.join(s, "l_suppkey").join(p, "l_partkey").groupBy("nation", "size", bin_month(F.col("l_shipdate")).alias("month")).agg(F.sum(cents(F.col("l_extendedprice"))).alias("v"))


def order_flow_cells(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select("o_custkey", "o_orderdate", "o_orderpriority", "o_totalprice")
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey", "c_mktsegment")
    return o.join(c, "o_custkey").groupBy(bin_month(F.col("o_orderdate")).alias("month"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"), F.col("o_orderpriority").alias("priority")).agg(F.sum(cents(F.col("o_totalprice"))).alias("v"))


def event_pulse_cells(spark: SparkSession, d: str, by_user: bool = False) -> DataFrame:
    e = table(spark, d, "events")
    keys = [F.to_date("ts").alias("day"), bin_hour(F.col("ts")).alias("hour"), F.col("event_type").alias("type")]
    if by_user:
        keys.append(F.pmod("user_id", F.lit(8)).cast("int").alias("user8"))
    return e.groupBy(*keys).agg(F.sum(cents(F.col("value"))).alias("v"))


def embed_cells(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("dim", "x")).select("vec_id", "dim", F.col("x").cast("double").alias("v"))


def embed_cube_cells(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    e = table(spark, d, "embeddings").withColumn("rank", (F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1).cast("int"))
    return e.select("label", "rank", F.posexplode("embedding").alias("dim", "x")).select("label", "rank", "dim", F.col("x").cast("double").alias("v"))


GLYPHS = 256


def glyph_pairs_cells(spark: SparkSession, d: str) -> DataFrame:
    """Adjacent code points of each whole text in lower case, codes capped at 255; each task adds its pairs up by language."""
    ship(spark)
    arrow_rows(spark)
    t = table(spark, d, "documents").select("lang", F.lower("text").alias("t")).where(F.length("t") >= 2)

    def run(batches):
        held: dict = {}
        for b in batches:
            for lang, text in zip(b.column("lang"), b.column("t"), strict=True):
                code = np.minimum(np.frombuffer(text.as_py().encode("utf-32-le"), "<u4"), GLYPHS - 1).astype(np.int64)
                n = np.bincount(code[:-1] * GLYPHS + code[1:], minlength=GLYPHS * GLYPHS)
                key = lang.as_py()
                held[key] = held[key] + n if key in held else n
        for key, n in held.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([key] * len(at), pa.string()), pa.array((at // GLYPHS).astype(np.int32)), pa.array((at % GLYPHS).astype(np.int32)), pa.array(n[at])], names=["lang", "left", "right", "n"])

    return t.mapInArrow(run, "lang string, left int, right int, n long").groupBy("lang", "left", "right").agg(F.sum("n").alias("v"))


def dialog_len_cells(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "conversations")
    return c.groupBy(F.pmod("conv_id", F.lit(32)).cast("int").alias("conv"), F.col("turn").cast("int").alias("turn"), "role").agg(F.sum(F.length("text").cast("long")).alias("v"))


def page_bytes_cells(spark: SparkSession, d: str) -> DataFrame:
    """ASCII histogram of pages by 16 position buckets."""
    p = table(spark, d, "pages").select("page_id", "html", F.length("html").alias("n")).where("n > 0")
    c = p.select("page_id", "n", F.posexplode(F.split("html", "")).alias("i", "c")).where("c <> ''").select("page_id", F.floor(F.col("i") * 16 / F.col("n")).cast("int").alias("bucket"), F.ascii("c").alias("code"))
    return c.where("code < 128").groupBy(F.pmod("page_id", F.lit(16)).cast("int").alias("page"), "bucket", "code").agg(F.count("*").alias("v"))


CUBES = {
    "ship_density": (ship_density_cells, ["month", "quantity", "discount"], 1),
    "trade_value": (trade_value_cells, ["nation", "size", "month"], 8),
    "order_flow": (order_flow_cells, ["month", "nation", "segment", "priority"], 8),
    "event_pulse": (event_pulse_cells, ["day", "hour", "type"], 8),
    "event_pulse_4d": (lambda s, d: event_pulse_cells(s, d, True), ["day", "hour", "type", "user8"], 8),
    "embed_matrix": (embed_cells, ["vec_id", "dim"], 4),
    "embed_cube": (embed_cube_cells, ["label", "rank", "dim"], 4),
    "glyph_pairs": (glyph_pairs_cells, ["lang", "left", "right"], 4),
    "dialog_len": (dialog_len_cells, ["conv", "turn", "role"], 4),
    "page_bytes": (page_bytes_cells, ["page", "bucket", "code"], 4),
}


def cube(spark: SparkSession, d: str, name: str) -> GridFrame:
    make, axes, width = CUBES[name]
    spec, df = GridSpec.infer(make(spark, d), axes, "v", width)
    return GridFrame(df, GridSpec(spec.axes, spec.shape, width, name not in ("embed_matrix", "embed_cube"), spec.labels))


# ---- formula grids ----


def formula(kind: str, *x):
    """S1-S4 on [0, 1] coordinates; works on columns and on arrays."""
    lib = F if isinstance(x[0], Column) else np
    a, b, c = x
    if kind == "rank1":
        return lib.sin(3 * a + 1) * lib.exp(-b) * (1 + c * c)
    if kind == "cosines":
        return lib.cos(6 * a + 2 * b) + lib.cos(9 * b * c) / 2 + lib.cos(14 * c + a) / 4
    if kind == "step":
        one = (lambda t: t.cast("double")) if lib is F else (lambda t: t.astype(float))
        return one((a > 0.3) & (b > 0.4) & (c < 0.7)) + one((a - 0.5) * (a - 0.5) + (b - 0.5) * (b - 0.5) < 0.1)
    if kind == "bump":
        return lib.exp(-8 * ((a - 0.4) * (a - 0.4) + (b - 0.5) * (b - 0.5) + (c - 0.6) * (c - 0.6))) + 0.2
    raise ValueError(kind)


def synthetic(spark: SparkSession, kind: str, shape: tuple[int, int, int]) -> GridFrame:
    spec = GridSpec(("x", "y", "z"), shape)
    at = spark.range(spec.cells).select(F.col("id").alias("idx"))
    x = [c / F.lit(float(max(1, n - 1))) for c, n in zip(spec.coords(), shape, strict=True)]
    return GridFrame(at.select("idx", formula(kind, *x).cast("double").alias("v")), spec)


def synthetic_array(kind: str, shape: tuple[int, int, int]) -> np.ndarray:
    return formula(kind, *np.meshgrid(*[np.arange(n) / max(1, n - 1) for n in shape], indexing="ij"))


def independent(spark: SparkSession, d: str) -> GridFrame:
    """A rank-one grid of the events table: the product of its counts by day, hour and type."""
    e = table(spark, d, "events")
    axes = {"day": F.to_date("ts"), "hour": bin_hour(F.col("ts")), "type": F.col("event_type")}
    day, hour, kind = (e.groupBy(c.alias(a)).agg(F.count("*").cast("double").alias(f"n_{a}")) for a, c in axes.items())
    cells = day.crossJoin(F.broadcast(hour)).crossJoin(F.broadcast(kind)).select(*axes, (F.col("n_day") * F.col("n_hour") * F.col("n_type")).alias("v"))
    spec, df = GridSpec.infer(cells, list(axes), "v")
    return GridFrame(df, spec)


# ---- files ----

DTYPES = {"u8": ("<u1", 1, True), "f32": ("<f4", 4, False), "f64": ("<f8", 8, False)}


def read_raw(spark: SparkSession, path: str, shape: tuple[int, ...], dtype: str, order: str = "C") -> GridFrame:
    """Raw little-endian volumes, one file or several in name order of equal slabs along the first axis."""
    kind, width, integer = DTYPES[dtype]
    files = spark.read.format("binaryFile").load(path)
    names = [r[0] for r in files.select("path").orderBy("path").collect()]
    per = math.prod(shape) // max(1, len(names))

    def run(batches):
        for b in batches:
            for p, raw in zip(b.column("path").to_pylist(), b.column("content").to_pylist(), strict=True):
                v = np.frombuffer(raw, kind)
                base = names.index(p) * per
                for i in range(0, len(v), 1 << 18):
                    part = v[i : i + (1 << 18)].astype(float)
                    idx = np.arange(base + i, base + i + len(part))
                    if order == "F":
                        idx = np.ravel_multi_index(np.unravel_index(idx, shape, order="F"), shape)
                    yield pa.RecordBatch.from_arrays([pa.array(idx.astype(np.int64)), pa.array(part)], names=["idx", "v"])

    spec = GridSpec(tuple(f"i{n + 1}" for n in range(len(shape))), tuple(shape), width, integer)
    return GridFrame(files.select("path", "content").mapInArrow(run, "idx long, v double"), spec)


def read_cells(spark: SparkSession, path: str, fmt: str, spec: GridSpec) -> GridFrame:
    """CSV (with header) or JSON rows of axis indices and v."""
    schema = ", ".join(f"{a} int" for a in spec.axes) + ", v double"
    df = spark.read.schema(schema).option("header", "true").format(fmt).load(path)
    return GridFrame(df.groupBy(*spec.axes).agg(F.sum("v").alias("v")).select(spec.flat().alias("idx"), "v"), spec)
