"""Queries over the given tables, and the SQL that DuckDB checks them with."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridpress import functions as G
from gridpress import streaming, workloads
from gridpress.baselines import block_xform, predictive, set_part
from gridpress.baselines.slabs import code_counts, compress_slabs
from gridpress.operators import metrics as M
from gridpress.operators import planes as P
from gridpress.operators import relops, spectrum
from gridpress.operators import resample as R
from gridpress.operators import transform as X
from gridpress.operators.codec import audit, compress, compress_array, decompress, decompress_array, ratio
from gridpress.operators.entropy import CODERS, Model
from gridpress.plans.grid import GridFrame, bin_month, bin_pct, bin_width, to_slabs
from gridpress.plans.targets import ErrorTarget, grid_stats
from gridpress.session import table
from gridpress.sources import cubes
from gridpress.sources.cubes import CUBES, cents, cube

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
flagship = workloads.flagship


def q(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


# ---- SQL pieces ----

_EP = "(SELECT CAST(ts AS DATE) AS day, CAST(hour(ts) AS INT) AS hour, event_type AS type, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS v FROM events GROUP BY ALL)"
_SHIP = "(SELECT CAST(year(l_shipdate) * 12 + month(l_shipdate) AS INT) AS month, CAST(l_quantity AS INT) AS quantity, CAST(round(l_discount * 100) AS INT) AS discount, count(*) AS v FROM lineitem GROUP BY ALL)"
_TRADE = "(SELECT s_nationkey AS nation, p_size AS size, CAST(year(l_shipdate) * 12 + month(l_shipdate) AS INT) AS month, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS v FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN part ON p_partkey = l_partkey GROUP BY ALL)"
_FLOW = "(SELECT CAST(year(o_orderdate) * 12 + month(o_orderdate) AS INT) AS month, c_nationkey AS nation, c_mktsegment AS segment, o_orderpriority AS priority, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS v FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY ALL)"
_DENSE = f"""dense AS (
  SELECT d.i AS i1, h.i AS i2, t.i AS i3, coalesce(c.v, 0) AS v
  FROM (SELECT day, row_number() OVER (ORDER BY day) - 1 AS i FROM (SELECT DISTINCT day FROM {_EP})) d
  CROSS JOIN (SELECT hour, row_number() OVER (ORDER BY hour) - 1 AS i FROM (SELECT DISTINCT hour FROM {_EP})) h
  CROSS JOIN (SELECT type, row_number() OVER (ORDER BY type) - 1 AS i FROM (SELECT DISTINCT type FROM {_EP})) t
  LEFT JOIN {_EP} c ON c.day = d.day AND c.hour = h.hour AND c.type = t.type
), size AS (SELECT max(i1) + 1 AS n1, max(i2) + 1 AS n2, max(i3) + 1 AS n3 FROM dense)"""
_EV = "ev AS (SELECT row_number() OVER (ORDER BY event_id) - 1 AS idx, CAST(round(value * 100) AS BIGINT) AS q FROM events), lv AS (SELECT *, CASE WHEN q = 0 THEN -1 ELSE length(bin(q)) - 1 END AS lead FROM ev)"
_PRICE = "pr AS (SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) - 1 AS idx, CAST(round(l_extendedprice * 100) AS BIGINT) AS q FROM lineitem), lv AS (SELECT *, CASE WHEN q = 0 THEN -1 ELSE length(bin(q)) - 1 END AS lead FROM pr)"
_RUNS = """pl AS (SELECT CAST(unnest(range(0, 17)) AS INT) AS plane),
cand AS (SELECT plane, idx, lead, row_number() OVER (PARTITION BY plane ORDER BY idx) AS r, count(*) OVER (PARTITION BY plane) AS total FROM lv JOIN pl ON lead <= plane),
ones AS (SELECT plane, r, total FROM cand WHERE lead = plane),
body AS (SELECT plane, row_number() OVER w AS seq, r - coalesce(lag(r) OVER w, 0) - 1 AS run FROM ones WINDOW w AS (PARTITION BY plane ORDER BY r)),
ends AS (SELECT c.plane, any_value(c.total) AS total, coalesce(max(o.r), 0) AS last, count(DISTINCT o.r) AS n FROM cand c LEFT JOIN ones o USING (plane) GROUP BY c.plane),
runs AS (SELECT plane, seq, run FROM body UNION ALL SELECT plane, n + 1, total - last FROM ends WHERE total > last)"""


def events_q(spark: SparkSession, d: str) -> DataFrame:
    return P.integers(table(spark, d, "events").select("event_id", "value"), cents(F.col("value")), F.col("event_id"))


def prices_q(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    return P.integers(li, cents(F.col("l_extendedprice")), li.columns)


# ---- cubes ----

for _name, _sql in {
    "ship_density": _SHIP,
    "trade_value": _TRADE,
    "order_flow": _FLOW,
    "event_pulse": _EP,
    "event_pulse_4d": "(SELECT CAST(ts AS DATE) AS day, CAST(hour(ts) AS INT) AS hour, event_type AS type, CAST(user_id % 8 AS INT) AS user8, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS v FROM events GROUP BY ALL)",
    "glyph_pairs": "(SELECT lang, CAST(least(unicode(p[1]), 255) AS INT) AS \"left\", CAST(least(unicode(p[2]), 255) AS INT) AS \"right\", count(*) AS v FROM (SELECT lang, unnest(list_zip(c[:-2], c[2:])) AS p FROM (SELECT lang, string_split(lower(text), '') AS c FROM documents) WHERE len(c) >= 2) GROUP BY ALL)",
    "dialog_len": "(SELECT CAST(conv_id % 32 AS INT) AS conv, CAST(turn AS INT) AS turn, role, CAST(sum(length(text)) AS BIGINT) AS v FROM conversations GROUP BY ALL)",
    "embed_matrix": "(SELECT vec_id, CAST(unnest(range(0, len(embedding))) AS INT) AS dim, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings)",
    "embed_cube": "(SELECT label, rank, CAST(unnest(range(0, len(embedding))) AS INT) AS dim, CAST(unnest(embedding) AS DOUBLE) AS v FROM (SELECT label, embedding, CAST(row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS INT) AS rank FROM embeddings))",
    "page_bytes": "(SELECT CAST(page_id % 16 AS INT) AS page, CAST(floor((i - 1) * 16 / n) AS INT) AS bucket, unicode(html[i]) AS code, count(*) AS v FROM (SELECT page_id, html, length(html) AS n, unnest(range(1, length(html) + 1)) AS i FROM pages) WHERE unicode(html[i]) < 128 GROUP BY ALL)",
}.items():
    q(f"cube_{_name}", f"SELECT * FROM {_sql}")(lambda s, d, n=_name: CUBES[n][0](s, d))


# ---- statistics, targets, measures ----


@q("grid_stats_event_pulse", f"WITH {_DENSE} SELECT CAST(min(v) AS DOUBLE) AS low, CAST(max(v) AS DOUBLE) AS high, sum(CAST(v AS DOUBLE) * v) AS energy, count(*) AS cells FROM dense")
def _(s, d):
    return M.stats_row(cube(s, d, "event_pulse"))


@q("target_budgets", f"WITH {_DENSE}, st AS (SELECT sum(CAST(v AS DOUBLE) * v) AS e, count(*) AS c, max(v) - min(v) AS span FROM dense) SELECT 'rel' AS kind, round(0.01 * e, -2) AS budget FROM st UNION ALL SELECT 'rmse', round(25.0 * c, -2) FROM st UNION ALL SELECT 'psnr', round(c * pow(span / (2 * pow(10, 40.0 / 20)), 2), -2) FROM st")
def _(s, d):
    st = grid_stats(cube(s, d, "event_pulse"))
    rows = [("rel", ErrorTarget.rel(0.1).to_sse(st)), ("rmse", ErrorTarget.rmse(5.0).to_sse(st)), ("psnr", ErrorTarget.psnr(40.0).to_sse(st))]
    return s.createDataFrame(rows, "kind string, budget double").select("kind", F.round("budget", -2).alias("budget"))


@q("compare_grids", f"WITH {_DENSE}, p AS (SELECT v, round(v / 1000.0) * 1000 AS w FROM dense), a AS (SELECT sum((v - w) * (v - w)) AS sse, sum(CAST(v AS DOUBLE) * v) AS e, max(v) - min(v) AS span, count(*) AS c FROM p) SELECT round(sse, 0) AS sse, round(sqrt(sse / e), 8) AS rel_error, round(sqrt(sse / c), 6) AS rmse, round(20 * log10(span / (2 * sqrt(sse / c))), 6) AS psnr FROM a")
def _(s, d):
    g = cube(s, d, "event_pulse")
    b = GridFrame(g.df.select("idx", (F.round(F.col("v") / 1000) * 1000).alias("v")), g.spec)
    return M.compare(g, b).select(F.round("sse", 0).alias("sse"), F.round("rel_error", 8).alias("rel_error"), F.round("rmse", 6).alias("rmse"), F.round("psnr", 6).alias("psnr"))


# ---- transform ----


def _gram_sql(cells: str, axis: str, others: list[str]) -> str:
    on = " AND ".join(f"a.{o} = b.{o}" for o in others)
    return f'WITH c AS (SELECT *, dense_rank() OVER (ORDER BY {axis}) - 1 AS i FROM {cells}) SELECT CAST(a.i AS INT) AS "row", CAST(b.i AS INT) AS col, CAST(sum(CAST(a.v AS HUGEINT) * b.v) AS DOUBLE) AS g FROM c a JOIN c b ON {on} GROUP BY ALL'


@q("gram_month", _gram_sql(_SHIP, "month", ["quantity", "discount"]))
def _(s, d):
    return X.gram_sql(cube(s, d, "ship_density"), 0)


@q("gram_quantity", _gram_sql(_SHIP, "quantity", ["month", "discount"]))
def _(s, d):
    return X.gram_sql(cube(s, d, "ship_density"), 1)


@q("gram_event_type", _gram_sql(_EP, "type", ["day", "hour"]))
def _(s, d):
    return X.gram_sql(cube(s, d, "event_pulse"), 2)


@q("gram_arrow", _gram_sql(_SHIP, "discount", ["month", "quantity"]))
def _(s, d):
    g = cube(s, d, "ship_density")
    m = X.slab_grams(to_slabs(g, 1, 7), g.spec, 1, [2])[2]
    return s.createDataFrame([(i, j, float(m[i, j])) for i in range(len(m)) for j in range(len(m))], "row int, col int, g double")


@q("gram_eigenvalues", f"WITH c AS (SELECT * FROM {_SHIP}), g AS (SELECT a.month AS r, b.month AS c, sum(a.v * b.v) AS g FROM c a JOIN c b ON a.quantity = b.quantity AND a.discount = b.discount GROUP BY ALL) SELECT CAST(sum(g) FILTER (r = c) AS BIGINT) AS trace, round(sqrt(CAST(sum(CAST(g AS HUGEINT) * g) AS DOUBLE)), 3) AS frobenius FROM g")
def _(s, d):
    g = cube(s, d, "ship_density").dense()
    lam = X.eigen_basis(X._unfolded(g, 0) @ X._unfolded(g, 0).T)[0]
    return s.createDataFrame([(round(float(lam.sum())), round(float(np.sqrt((lam**2).sum())), 3))], "trace long, frobenius double")


_ENERGY = f"SELECT CAST(round(sum(CAST(v AS DOUBLE) * v) / 1e6) AS BIGINT) AS energy FROM {_EP}"


@q("core_energy", _ENERGY)
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"))
    return t.cells(s).agg(F.round(F.sum(F.col("v") * F.col("v")) / 1e6).cast("long").alias("energy"))


@q("core_energy_hybrid", _ENERGY)
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"), "hybrid")
    return t.cells(s).agg(F.round(F.sum(F.col("v") * F.col("v")) / 1e6).cast("long").alias("energy"))


@q("core_energy_sequential", _ENERGY)
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"), "sequential")
    return t.cells(s).agg(F.round(F.sum(F.col("v") * F.col("v")) / 1e6).cast("long").alias("energy"))


@q("slice_norms_total", f"SELECT CAST(m AS INT) AS mode, CAST(round(e / 1e6) AS BIGINT) AS energy FROM (SELECT unnest(range(0, 3)) AS m, sum(CAST(v AS DOUBLE) * v) AS e FROM {_EP})")
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"))
    return M.slice_norms(t.cells(s), t.spec).groupBy("mode").agg(F.round(F.sum(F.col("sigma") * F.col("sigma")) / 1e6).cast("long").alias("energy"))


@q("slice_energy_sets", f"WITH {_DENSE} SELECT CASE WHEN grouping(i1) = 0 THEN 0 WHEN grouping(i2) = 0 THEN 1 ELSE 2 END AS mode, CAST(coalesce(i1, i2, i3) AS INT) AS j, round(sqrt(sum(CAST(v AS DOUBLE) * v)), 4) AS sigma FROM dense GROUP BY GROUPING SETS ((i1), (i2), (i3))")
def _(s, d):
    g = cube(s, d, "event_pulse")
    return M.slice_norms(g.df, g.spec).select("mode", "j", F.round("sigma", 4).alias("sigma"))


@q("scaled_core", f"SELECT CAST(round(sum(CAST(v AS DOUBLE) * v) * 9 / 1e6) AS BIGINT) AS energy FROM {_EP}")
def _(s, d):
    z = R.scale(compress(cube(s, d, "event_pulse"), ErrorTarget.rel(1e-12)), 3.0)
    v = decompress_array(z)
    return s.createDataFrame([(round(float((v * v).sum()) / 1e6),)], "energy long")


@q("permuted_core", f"WITH {_DENSE} SELECT CAST(i1 AS INT) AS i1, CAST(i2 AS INT) AS i2, CAST(n3 - 1 - i3 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense CROSS JOIN size")
def _(s, d):
    z = compress(cube(s, d, "event_pulse"), ErrorTarget.rel(1e-12))
    n = z.spec.shape[2]
    return _cells(s, decompress_array(R.permute(z, 2, list(range(n - 1, -1, -1)))))


@q("cell_at", f"WITH {_DENSE} SELECT CAST(k AS INT) AS k, CAST(v AS BIGINT) AS v FROM (SELECT *, row_number() OVER (ORDER BY i1, i2, i3) - 1 AS k FROM dense WHERE i1 < 2 AND i2 < 3 AND i3 < 2)")
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"))
    at = [(a, b, c) for a in range(2) for b in range(3) for c in range(2)]
    return X.cell_at(t.cells(s), t.spec, t.factors, at).select("k", F.round("v").cast("long").alias("v"))


@q("unfold_fold", f"WITH {_DENSE} SELECT i1 * n2 * n3 + i2 * n3 + i3 AS idx, CAST(v AS BIGINT) AS v FROM dense CROSS JOIN size")
def _(s, d):
    g = cube(s, d, "event_pulse")
    return X.fold(X.unfold(g, 1), g.spec, 1).select("idx", F.col("v").cast("long").alias("v"))


@q("agg_pencil", f"WITH {_DENSE} SELECT i1 * n2 * n3 + i3 AS rest, CAST(sum(v) AS BIGINT) AS total FROM dense CROSS JOIN size GROUP BY ALL")
def _(s, d):
    return X.unfold(cube(s, d, "event_pulse"), 1).select("rest", F.aggregate("fiber", F.lit(0.0), lambda a, x: a + x).cast("long").alias("total"))


@q("truncated_energy")
def _(s, d):
    t = X.omt(cube(s, d, "event_pulse"))
    return X.truncate(t.cells(s), t.spec, tuple(max(1, n // 2) for n in t.spec.shape)).agg(F.sum(F.col("v") * F.col("v")).alias("kept"), F.count("*").alias("cells"))


# ---- codec ----


def _cells(s: SparkSession, a: np.ndarray, scale: int = 1) -> DataFrame:
    g = GridFrame.of(s, a)
    out = g.df.select(*g.spec.coords(), F.round(F.col("v") * scale).cast("long").alias("v"))
    return out


for _name, _axes, _sql in (("event_pulse", "day, hour, type", _EP), ("ship_density", "month, quantity, discount", _SHIP)):
    _i = ", ".join(f"CAST(dense_rank() OVER (ORDER BY {a}) - 1 AS INT) AS i{k + 1}" for k, a in enumerate(_axes.split(", ")))
    q(f"roundtrip_full_{_name}", f"SELECT * FROM (SELECT {_i}, CAST(v AS BIGINT) AS v FROM {_sql}) WHERE v <> 0")(lambda s, d, n=_name: _cells(s, decompress_array(compress(cube(s, d, n), ErrorTarget.rel(1e-12)), cast=True)).where("v <> 0"))


@q("roundtrip_error_ok", "SELECT * FROM (VALUES ('rel', true), ('rmse', true), ('psnr', true)) t(kind, within)")
def _(s, d):
    g = cube(s, d, "event_pulse")
    a, st, rows = g.dense(), grid_stats(g), []
    for t in (ErrorTarget.rel(0.05), ErrorTarget.rmse(500.0), ErrorTarget.psnr(40.0)):
        r = audit(compress(g, t), a)
        rows.append((t.kind, r["sse"] <= t.to_sse(st)))
    return s.createDataFrame(rows, "kind string, within boolean")


@q("roundtrip_distributed", "SELECT true AS within, true AS matches_local")
def _(s, d):
    g = cube(s, d, "event_pulse")
    z = compress(g, ErrorTarget.rel(0.05), schedule="hybrid")
    e = M.rel_error(g, decompress(z, s))
    local = audit(compress(g, ErrorTarget.rel(0.05)), g.dense())["rel_error"]
    return s.createDataFrame([(e <= 0.05, abs(e - local) < 0.01)], "within boolean, matches_local boolean")


@q("size_target_ok", "SELECT * FROM (VALUES ('event_pulse', 1500, true), ('event_pulse', 6000, true), ('dialog_len', 400, true), ('dialog_len', 900, true)) t(cube, asked, within)")
def _(s, d):
    """Archives of a size target, coded in one process and in slabs, are within its bytes."""
    rows = []
    for name, sizes in (("event_pulse", (1500, 6000)), ("dialog_len", (400, 900))):
        g = cube(s, d, name)
        for most in sizes:
            both = [compress(g, ErrorTarget.size(most), schedule=how).bytes() for how in ("one_pass", "hybrid")]
            rows.append((name, most, max(both) <= most))
    return s.createDataFrame(rows, "cube string, asked int, within boolean")


@q("slab_targets_ok", "SELECT * FROM (VALUES ('rel', 0.3, true), ('rel', 0.02, true), ('psnr', 45.0, true)) t(kind, target, within)")
def _(s, d):
    """Targets hold for grids of slabs, with rounding chosen by measure."""
    g = cube(s, d, "event_pulse")
    st, a, rows = grid_stats(g), g.dense(), []
    for target in (ErrorTarget.rel(0.3), ErrorTarget.rel(0.02), ErrorTarget.psnr(45.0)):
        back = decompress_array(compress(g, target, schedule="hybrid"))
        rows.append((target.kind, target.value, bool(((a - back) ** 2).sum() <= target.to_sse(st) * (1 + 1e-9))))
    return s.createDataFrame(rows, "kind string, target double, within boolean")


@q("progressive_planes")
def _(s, d):
    a = cube(s, d, "event_pulse").dense()
    z = compress_array(a, ErrorTarget.psnr(60.0))
    rows = [(p, float(np.sqrt(((a - decompress_array(z, p)) ** 2).mean()))) for p in range(63, z.header["plane"] - 1, -1)]
    return s.createDataFrame(rows, "plane int, rmse double")


@q("archive_listing")
def _(s, d):
    z = compress(cube(s, d, "event_pulse"), ErrorTarget.rel(0.05))
    rows = [(p, k, n, len(r), len(v), len(g)) for p, k, n, r, v, g in z.segments]
    return s.createDataFrame(rows, "plane int, chunk long, n_raw long, run_bytes int, raw_bytes int, sign_bytes int")


_TAPS = ", ".join(f"({j}, {w!r})" for j, w in zip(range(-4, 5), R.lanczos_taps(2).tolist(), strict=True))


_full = lambda s, d: compress(cube(s, d, "event_pulse"), ErrorTarget.rel(1e-13))


@q("decimate_pick", f"WITH {_DENSE} SELECT CAST(i1 // 2 AS INT) AS i1, CAST(i2 // 2 AS INT) AS i2, CAST(i3 // 2 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense WHERE i1 % 2 = 0 AND i2 % 2 = 0 AND i3 % 2 = 0")
def _(s, d):
    return _cells(s, decompress_array(R.decimate(_full(s, d), 2, "pick")))


@q("decimate_box", f"WITH {_DENSE} SELECT CAST(i1 // 2 AS INT) AS i1, CAST(i2 // 2 AS INT) AS i2, CAST(i3 // 2 AS INT) AS i3, CAST(round(avg(v) * 8) AS BIGINT) AS v FROM dense GROUP BY ALL")
def _(s, d):
    return _cells(s, decompress_array(R.decimate(_full(s, d), 2, "box")), 8)


_NORM = lambda a: f"(SELECT i{a} AS i, sum(w) AS s FROM (SELECT DISTINCT i{a} FROM dense) CROSS JOIN taps CROSS JOIN size WHERE i{a} - j BETWEEN 0 AND n{a} - 1 GROUP BY ALL)"


@q("decimate_lanczos", f"""WITH {_DENSE}, taps(j, w) AS (VALUES {_TAPS}),
a1 AS (SELECT d.i1 + j AS i1, i2, i3, sum(w * v) AS v FROM dense d CROSS JOIN taps GROUP BY ALL),
a2 AS (SELECT i1, a1.i2 + j AS i2, i3, sum(w * v) AS v FROM a1 CROSS JOIN taps GROUP BY ALL),
a3 AS (SELECT i1, i2, a2.i3 + j AS i3, sum(w * v) AS v FROM a2 CROSS JOIN taps GROUP BY ALL)
SELECT CAST(i1 // 2 AS INT) AS i1, CAST(i2 // 2 AS INT) AS i2, CAST(i3 // 2 AS INT) AS i3, CAST(round(v / x.s / y.s / z.s * 100) AS BIGINT) AS v
FROM a3 JOIN {_NORM(1)} x ON x.i = i1 JOIN {_NORM(2)} y ON y.i = i2 JOIN {_NORM(3)} z ON z.i = i3 WHERE i1 % 2 = 0 AND i2 % 2 = 0 AND i3 % 2 = 0""")
def _(s, d):
    return _cells(s, decompress_array(R.decimate(_full(s, d), 2, "lanczos2")), 100)


@q("slice_reverse", f"WITH {_DENSE} SELECT CAST((n1 - 1 - i1) // 3 AS INT) AS i1, CAST(i2 - 2 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense CROSS JOIN size WHERE (n1 - 1 - i1) % 3 = 0 AND i2 BETWEEN 2 AND 7")
def _(s, d):
    return _cells(s, decompress_array(_full(s, d)[::-3, 2:8]))


@q("frame_day", f"WITH {_DENSE} SELECT CAST(0 AS INT) AS i1, CAST(i2 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense WHERE i1 = 4")
def _(s, d):
    return _cells(s, decompress_array(R.frame(_full(s, d), 0, 4)))


@q("project_axis", f"WITH {_DENSE} SELECT CAST(i1 AS INT) AS i1, CAST(0 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(sum(v) AS BIGINT) AS v FROM dense GROUP BY ALL")
def _(s, d):
    return _cells(s, decompress_array(R.project_axis(_full(s, d), 1)))


@q("brick_cut", f"WITH {_DENSE} SELECT CAST(i1 - 8 AS INT) AS i1, CAST(i2 - 6 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense WHERE i1 BETWEEN 8 AND 11 AND i2 BETWEEN 6 AND 9 AND i3 BETWEEN 0 AND 3")
def _(s, d):
    return _cells(s, decompress_array(R.brick(_full(s, d), (10, 8, 2), 4)))


@q("padded_and_shifted", f"WITH {_DENSE} SELECT CAST(i1 + 2 AS INT) AS i1, CAST(i2 + 1 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(v AS BIGINT) AS v FROM dense CROSS JOIN size WHERE i2 < n2 - 1 AND v <> 0")
def _(s, d):
    return _cells(s, decompress_array(R.shift(R.pad(_full(s, d), 0, 2, 1), 1, 1))).where("v <> 0")


@q("filter_separable", f"WITH {_DENSE}, f AS (SELECT i1, i2, i3, v + coalesce(lag(v) OVER w, 0) + coalesce(lead(v) OVER w, 0) AS s, 1 + (lag(v) OVER w IS NOT NULL)::INT + (lead(v) OVER w IS NOT NULL)::INT AS n FROM dense WINDOW w AS (PARTITION BY i2, i3 ORDER BY i1)) SELECT CAST(i1 AS INT) AS i1, CAST(i2 AS INT) AS i2, CAST(i3 AS INT) AS i3, CAST(round(s * 6.0 / n) AS BIGINT) AS v FROM f")
def _(s, d):
    return _cells(s, decompress_array(R.filter_separable(_full(s, d), {0: np.ones(3) / 3})), 6)


# ---- plane coder ----


@q("quantise_prices", f"WITH {_PRICE} SELECT idx, q, CAST(lead AS INT) AS lead FROM lv")
def _(s, d):
    return prices_q(s, d)


@q("lead_histogram_prices", f"WITH {_PRICE} SELECT CAST(lead AS INT) AS lead, count(*) AS n FROM lv GROUP BY lead")
def _(s, d):
    return prices_q(s, d).groupBy("lead").agg(F.count("*").alias("n"))


@q("ones_per_plane_prices", f"WITH {_PRICE} SELECT CAST(p AS INT) AS plane, CAST(sum((q >> p) & 1) AS BIGINT) AS ones FROM lv CROSS JOIN (SELECT unnest(range(0, 32)) AS p) GROUP BY p")
def _(s, d):
    return M.ones_per_plane(prices_q(s, d), range(32))


@q("centroid_prices", f"WITH {_PRICE} SELECT CAST(p AS INT) AS plane, round(sum(((q >> p) & 1) * idx) / nullif(sum((q >> p) & 1), 0), 4) AS centroid FROM lv CROSS JOIN (SELECT unnest(range(0, 26)) AS p) GROUP BY p")
def _(s, d):
    return M.plane_centroid(prices_q(s, d), range(26)).select("plane", F.round("centroid", 4).alias("centroid"))


@q("plane_dots_events", f"WITH {_EV} SELECT CAST(p AS INT) AS plane, idx FROM lv CROSS JOIN (SELECT unnest(range(0, 17)) AS p) WHERE (q >> p) & 1 = 1")
def _(s, d):
    return M.plane_dots(events_q(s, d), range(17))


@q("mask_growth_events", f"WITH {_EV} SELECT CAST(p AS INT) AS plane, count(*) FILTER (lead > p) AS before, count(*) FILTER (lead >= p) AS after FROM lv CROSS JOIN (SELECT unnest(range(0, 17)) AS p) GROUP BY p")
def _(s, d):
    return P.mask_growth(events_q(s, d), range(17))


@q("mask_nested", "SELECT CAST(0 AS BIGINT) AS outside")
def _(s, d):
    e = events_q(s, d)
    return P.threshold_view(e, 10).select("idx").exceptAll(P.threshold_view(e, 6).select("idx")).agg(F.count("*").alias("outside"))


@q("bit_classes_events", f"WITH {_EV} SELECT CASE WHEN lead > 9 THEN 'verbatim' ELSE 'run' END AS class, CAST(sum((q >> 9) & 1) AS BIGINT) AS ones, count(*) AS n FROM lv GROUP BY ALL")
def _(s, d):
    e = events_q(s, d)
    return e.groupBy(P.bit_class(F.col("lead"), 9).alias("class")).agg(F.sum(P.bit(F.col("q"), 9)).alias("ones"), F.count("*").alias("n"))


@q("threshold_view", f"WITH {_PRICE} SELECT idx, q FROM lv WHERE lead >= 22")
def _(s, d):
    return P.threshold_view(prices_q(s, d), 22).select("idx", "q")


@q("zero_runs_events", f"WITH {_EV}, {_RUNS} SELECT plane, CAST(seq AS BIGINT) AS seq, CAST(run AS BIGINT) AS run FROM runs")
def _(s, d):
    return P.zero_runs(events_q(s, d), 0, 16)


@q("run_hist_events", f"WITH {_EV}, {_RUNS} SELECT plane, CAST(run AS BIGINT) AS run, count(*) AS freq FROM runs GROUP BY ALL")
def _(s, d):
    return M.run_histogram(P.zero_runs(events_q(s, d), 0, 16))


@q("entropy_events", f"WITH {_EV}, {_RUNS}, f AS (SELECT plane, run, count(*) AS f FROM runs GROUP BY ALL), n AS (SELECT *, sum(f) OVER (PARTITION BY plane) AS n FROM f) SELECT plane, CAST(sum(f) AS BIGINT) AS symbols, count(*) AS distinct_runs, round(sum(f * log2(n / f)), 3) AS bits FROM n GROUP BY plane")
def _(s, d):
    return M.entropy_bits(P.zero_runs(events_q(s, d), 0, 16)).select("plane", "symbols", "distinct_runs", F.round("bits", 3).alias("bits"))


_WORDS = "w AS (SELECT event_id, CAST(round(value * 100) AS BIGINT) AS q FROM events), b AS (SELECT event_id, CASE WHEN length(bin(q)) < 24 THEN repeat('0', 24 - length(bin(q))) ELSE '' END || bin(q) AS bits FROM w), p AS (SELECT *, list_filter(range(1, length(bits) + 1), lambda i: bits[i] = '1') AS ones FROM b)"


@q("rle_string", f"WITH {_WORDS} SELECT event_id, bits, list_transform(list_concat(list_transform(range(1, len(ones) + 1), lambda k: ones[k] - CASE WHEN k > 1 THEN ones[k - 1] ELSE 0 END - 1), CASE WHEN bits LIKE '%1' THEN CAST([] AS BIGINT[]) WHEN len(ones) > 0 THEN [length(bits) - ones[len(ones)]] ELSE [length(bits)] END), lambda x: CAST(x AS INT)) AS runs FROM p")
def _(s, d):
    """Zero runs of each event's value as a bit string of 24 digits, or of all that it has."""
    digits = F.bin(cents(F.col("value")))
    bits = table(s, d, "events").select("event_id", F.concat(F.repeat(F.lit("0"), F.greatest(F.lit(0), 24 - F.length(digits))), digits).alias("bits"))
    return bits.select("event_id", "bits", P.rle_bits(F.col("bits")).alias("runs"))


@q("plane_sse_events", f"WITH {_EV} SELECT CAST(p AS INT) AS plane, CAST(sum(CAST(q & ((1 << p) - 1) AS DOUBLE) * (q & ((1 << p) - 1))) AS DOUBLE) AS sse_after FROM lv CROSS JOIN (SELECT CAST(unnest(range(0, 18)) AS BIGINT) AS p) GROUP BY p")
def _(s, d):
    return P.plane_sse(events_q(s, d), range(18))


_BREAK = f"""WITH {_EV}, tot AS (SELECT sum(CAST(q AS DOUBLE) * q) * 0.0001 AS s FROM lv),
sse AS (SELECT p, sum(CAST(q & ((1 << p) - 1) AS DOUBLE) * (q & ((1 << p) - 1))) AS e FROM lv CROSS JOIN (SELECT CAST(unnest(range(0, 19)) AS BIGINT) AS p) GROUP BY p),
pick AS (SELECT max(p) AS p FROM sse, tot WHERE e <= s),
r AS (SELECT idx, pick.p, CAST(q & ((1 << (pick.p + 1)) - 1) AS DOUBLE) AS rest, (q >> pick.p) & 1 AS b FROM lv, pick),
c AS (SELECT idx, r.p, (SELECT e FROM sse, pick WHERE sse.p = pick.p + 1) - sum(CASE WHEN b = 1 THEN rest * rest - (rest - pow(2, r.p)) * (rest - pow(2, r.p)) ELSE 0 END) OVER (ORDER BY idx) AS sse FROM r)
SELECT CAST(p AS INT) AS plane, idx AS c_star, sse FROM c, tot WHERE c.sse <= s ORDER BY idx LIMIT 1"""


@q("breakpoint_events", _BREAK)
def _(s, d):
    e = events_q(s, d)
    budget = float(e.agg(F.sum(F.col("q").cast("double") * F.col("q"))).first()[0]) * 0.0001
    return P.breakpoint_sql(e, budget, range(18))


for _mode in ("floor", "midpoint"):
    _half = "+ 64" if _mode == "midpoint" else ""
    q(f"{_mode}_recon_events", f"WITH {_EV} SELECT idx, CASE WHEN q >> 7 = 0 THEN 0 ELSE CAST((q >> 7 << 7) {_half} AS DOUBLE) END AS v FROM lv")(lambda s, d, m=_mode: events_q(s, d).select("idx", P.dequantise(F.col("q"), 7, m).alias("v")))


@q("negabinary_digits", "SELECT event_id, CAST(round(value * 100) AS BIGINT) - 10000 AS v, true AS same FROM events")
def _(s, d):
    v = cents(F.col("value")) - 10000
    return table(s, d, "events").select("event_id", v.alias("v"), (P.negabinary_value(P.negabinary(v)) == v).alias("same"))


@q("plane_profile_events", f"""WITH {_EV}, {_RUNS}, f AS (SELECT plane, run, count(*) AS f FROM runs GROUP BY ALL), n AS (SELECT *, sum(f) OVER (PARTITION BY plane) AS n FROM f),
e AS (SELECT plane, CAST(sum(f) AS BIGINT) AS symbols, CAST(max(run) AS BIGINT) AS longest, round(sum(f * log2(n / f)), 3) AS bits FROM n GROUP BY plane),
b AS (SELECT CAST(p AS INT) AS plane, CAST(sum((q >> p) & 1) AS BIGINT) AS ones, round(sum(((q >> p) & 1) * idx) / nullif(sum((q >> p) & 1), 0), 4) AS centroid, count(*) FILTER (lead > p) AS verbatim FROM lv CROSS JOIN (SELECT unnest(range(0, 17)) AS p) GROUP BY p)
SELECT plane, ones, centroid, symbols, longest, bits, verbatim FROM b LEFT JOIN e USING (plane)""")
def _(s, d):
    return M.plane_profile(events_q(s, d), 0, 16).withColumns({"centroid": F.round("centroid", 4), "bits": F.round("bits", 3)})


@q("worked_vector", """WITH v AS (SELECT l_orderkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice, l_quantity) AS i, CAST(l_quantity AS BIGINT) AS q FROM lineitem),
c AS (SELECT *, CASE WHEN q = 0 THEN -1 ELSE length(bin(q)) - 1 END AS lead FROM v),
pl AS (SELECT l_orderkey, unnest(range(0, max(lead) + 1)) AS plane FROM c GROUP BY l_orderkey), j AS (SELECT c.*, plane FROM c JOIN pl USING (l_orderkey)),
cand AS (SELECT l_orderkey, plane, lead, row_number() OVER (PARTITION BY l_orderkey, plane ORDER BY i) AS r FROM j WHERE lead <= plane),
ones AS (SELECT *, r - coalesce(lag(r) OVER (PARTITION BY l_orderkey, plane ORDER BY r), 0) - 1 AS run FROM cand WHERE lead = plane),
body AS (SELECT l_orderkey, plane, string_agg(CAST(run AS VARCHAR), ',' ORDER BY r) AS s, max(r) AS last FROM ones GROUP BY ALL), ends AS (SELECT l_orderkey, plane, count(*) AS total FROM cand GROUP BY ALL),
runs AS (SELECT l_orderkey, plane, concat_ws(',', s, CASE WHEN total > coalesce(last, 0) THEN CAST(total - coalesce(last, 0) AS VARCHAR) END) AS runs FROM ends LEFT JOIN body USING (l_orderkey, plane)),
m AS (SELECT l_orderkey, plane, coalesce(string_agg(CAST((q >> plane) & 1 AS VARCHAR), '' ORDER BY i) FILTER (lead > plane), '') AS verbatim, CAST(count(*) FILTER (lead > plane) AS INT) AS "before", CAST(count(*) FILTER (lead >= plane) AS INT) AS "after" FROM j GROUP BY ALL)
SELECT l_orderkey, CAST(plane AS INT) AS plane, coalesce(runs, '') AS runs, verbatim, "before", "after" FROM m LEFT JOIN runs USING (l_orderkey, plane)""")
def _(s, d):
    """Each order's quantities as a small vector, plane by plane: runs, bits sent as they are, and the mask's members around it."""
    by = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_quantity"]
    li = table(s, d, "lineitem").withColumn("q", F.col("l_quantity").cast("long")).withColumn("lead", P.lead_plane(F.col("q")))
    return P.worked(li.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct(*by, "q", "lead"))).alias("v")), "l_orderkey")


@q("chunked_run_overhead", f"""WITH {_EV}, {_RUNS}, whole AS (SELECT plane, count(*) AS whole FROM runs GROUP BY plane),
c AS (SELECT plane, idx // 65536 AS chunk, lead, row_number() OVER w AS r, count(*) OVER (PARTITION BY plane, idx // 65536) AS total FROM lv JOIN pl ON lead <= plane WINDOW w AS (PARTITION BY plane, idx // 65536 ORDER BY idx)),
p AS (SELECT plane, chunk, any_value(total) AS total, count(*) FILTER (lead = plane) AS n, coalesce(max(r) FILTER (lead = plane), 0) AS last FROM c GROUP BY ALL)
SELECT plane, chunked, whole FROM (SELECT plane, CAST(sum(n + CASE WHEN total > last THEN 1 ELSE 0 END) AS BIGINT) AS chunked FROM p GROUP BY plane) JOIN whole USING (plane)""")
def _(s, d):
    e = events_q(s, d)
    return P.cells_runs(e, 0, 16).groupBy("plane").agg(F.count("*").alias("chunked")).join(P.zero_runs(e, 0, 16).groupBy("plane").agg(F.count("*").alias("whole")), "plane")


@q("prefix_two_level", "SELECT event_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) OVER (ORDER BY event_id) AS BIGINT) AS running FROM events")
def _(s, d):
    e = table(s, d, "events").select("event_id", cents(F.col("value")).alias("c"))
    return relops.running_sum(e, "event_id", "c").select("event_id", "running")


# ---- baselines, spectra ----


@q("rank_cut_codes")
def _(s, d):
    return code_counts(compress_slabs(cube(s, d, "embed_matrix"), "rank_cut", 0.05, 512))


@q("predictive_codes", f"WITH {_DENSE}, k AS (SELECT i1, i2, i3, CAST(round(v / 2000.0) AS BIGINT) AS k FROM dense), a AS (SELECT *, k - coalesce(lag(k) OVER (PARTITION BY i2, i3 ORDER BY i1), 0) AS d1 FROM k), b AS (SELECT *, d1 - coalesce(lag(d1) OVER (PARTITION BY i1, i3 ORDER BY i2), 0) AS d2 FROM a) SELECT CAST(i1 AS INT) AS day, CAST(i2 AS INT) AS hour, CAST(i3 AS INT) AS type, k, d2 - coalesce(lag(d2) OVER (PARTITION BY i1, i2 ORDER BY i3), 0) AS d FROM b")
def _(s, d):
    g = cube(s, d, "event_pulse")
    dense = s.range(g.spec.cells).select(F.col("id").alias("idx")).join(g.df, "idx", "left").select("idx", F.coalesce("v", F.lit(0.0)).alias("v"))
    return predictive.codes_sql(dense, g.spec, 1000.0)


@q("baseline_bounds_ok", "SELECT * FROM (VALUES ('block_xform', true), ('predictive', true), ('set_part', true)) t(codec, within)")
def _(s, d):
    a = cube(s, d, "event_pulse").dense()
    span = float(a.max() - a.min())
    rows = []
    for name, c, kw, tol in (("block_xform", block_xform, {"tol": 500.0}, 500.0), ("predictive", predictive, {"rel_bound": 0.01}, 0.01 * span), ("set_part", set_part, {"tol": 500.0}, 500.0 + span * 1e-6)):
        rows.append((name, bool(np.abs(c.decompress(c.compress(a, **kw)) - a).max() <= tol * (1 + 1e-9))))
    return s.createDataFrame(rows, "codec string, within boolean")


@q("baseline_slabs")
def _(s, d):
    g = cube(s, d, "event_pulse")
    parts = [compress_slabs(g, c, k, 8).select(F.lit(c).alias("codec"), "slab", "bytes", "worst") for c, k in (("block_xform", 500.0), ("predictive", 0.01), ("set_part", 500.0), ("rank_cut", 1e-3))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


@q("block_exponents", "WITH e AS (SELECT vec_id // 4 AS bv, unnest(range(0, len(embedding))) // 4 AS bd, abs(CAST(unnest(embedding) AS DOUBLE)) AS m FROM embeddings), b AS (SELECT bv, bd, max(m) AS m FROM e GROUP BY ALL) SELECT bv, CAST(bd AS INT) AS bd, CAST(CASE WHEN m >= pow(2, ceil(log2(m))) THEN ceil(log2(m)) + 1 WHEN m < pow(2, ceil(log2(m)) - 1) THEN ceil(log2(m)) - 1 ELSE ceil(log2(m)) END AS INT) AS exponent FROM b")
def _(s, d):
    e = table(s, d, "embeddings").select(F.floor(F.col("vec_id") / 4).alias("bv"), F.posexplode("embedding").alias("i", "x")).select("bv", F.floor(F.col("i") / 4).cast("int").alias("bd"), F.abs(F.col("x").cast("double")).alias("m"))
    return e.groupBy("bv", "bd").agg(F.max("m").alias("m")).select("bv", "bd", (G.float_exponent("m") + 1).alias("exponent"))


@q("spectrum_parseval", _ENERGY)
def _(s, d):
    f = spectrum.grid_spectrum(cube(s, d, "event_pulse").dense())
    return s.createDataFrame([(round(float((f**2).sum()) / f.size / 1e6),)], "energy long")


@q("dft_events_daily", "WITH c AS (SELECT CAST(hour(ts) AS INT) AS i, count(*) AS v FROM events GROUP BY 1) SELECT CAST(f AS INT) AS freq, round(sum(v * cos(2 * pi() * f * i / 24.0)), 4) AS re, round(-sum(v * sin(2 * pi() * f * i / 24.0)), 4) AS im FROM c CROSS JOIN (SELECT unnest(range(0, 13)) AS f) GROUP BY f")
def _(s, d):
    c = table(s, d, "events").groupBy(F.hour("ts").alias("i")).agg(F.count("*").alias("v"))
    flat = lambda x: F.when(F.round(x, 4) == 0, F.lit(0.0)).otherwise(F.round(x, 4))
    return spectrum.dft_sql(c, 24).select("freq", flat(F.col("re")).alias("re"), flat(F.col("im")).alias("im"))


@q("factor_spectra")
def _(s, d):
    return spectrum.spectrum_rows(s, X.omt(cube(s, d, "event_pulse")).factors)


@q("pencil_spectrum", f"WITH {_DENSE}, f AS (SELECT i1, i3, k, sum(v * cos(2 * pi() * k * i2 / n2)) AS re, sum(v * sin(2 * pi() * k * i2 / n2)) AS im FROM dense CROSS JOIN size JOIN (SELECT unnest(range(0, 24)) AS k) ON k < n2 GROUP BY ALL) SELECT CAST(k AS INT) AS freq, CAST(round(sum(re * re + im * im) / 1e6) AS BIGINT) AS power FROM f GROUP BY k")
def _(s, d):
    """Power of a cube's daily frequencies, in millions, from its fibers along the hours."""
    got = spectrum.pencil_fft(X.unfold(cube(s, d, "event_pulse"), 1))
    return got.groupBy("freq").agg(F.round(F.sum(F.col("re") * F.col("re") + F.col("im") * F.col("im")) / 1e6).cast("long").alias("power"))


_MARGIN = lambda x: f"(SELECT sum(n * n) FROM (SELECT CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY {x}))"


@q("synth_rank1", f"SELECT CAST(1 AS BIGINT) AS nonzero, round(0.5 * log10({_MARGIN('CAST(ts AS DATE)')} * {_MARGIN('hour(ts)')} * {_MARGIN('event_type')}), 8) AS log_peak")
def _(s, d):
    """The grid that events would fill were days, hours and types independent: its core is one coefficient, the product of their norms."""
    t = X.omt(cubes.independent(s, d))
    got, top = t.cells(s), F.max(F.abs("v"))
    peak = got.agg(top.alias("top"))
    return got.crossJoin(F.broadcast(peak)).agg(F.count(F.when(F.abs("v") > 1e-9 * F.col("top"), 1)).alias("nonzero"), F.round(F.log10(top), 8).alias("log_peak"))


@q("slice_norm_energy", "WITH c AS (" + ORACLES["cube_glyph_pairs"] + "), e AS (SELECT CAST(round(sum(CAST(v AS DOUBLE) * v) / 1e3) AS BIGINT) AS energy FROM c) SELECT CAST(mode AS INT) AS mode, energy FROM e CROSS JOIN (SELECT unnest(range(0, 3)) AS mode)")
def _(s, d):
    """Norms of a core's slices hold the grid's energy, in each mode."""
    got = workloads.w8_slice_norms(s, d).groupBy("mode").agg(F.sum(F.col("sigma") * F.col("sigma")).alias("e"))
    return got.select("mode", F.round(F.col("e") / 1e3).cast("long").alias("energy"))


@q("codec_ratios")
def _(s, d):
    rows = [(n, ratio(compress(cube(s, d, n), ErrorTarget.rel(0.1)))) for n in ("event_pulse", "dialog_len")]
    return s.createDataFrame(rows, "cube string, ratio double")


# ---- relational surroundings ----


def t_(s, d, n, *cols):
    df = table(s, d, n)
    return df.select(*cols) if cols else df


q("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")(lambda s, d: t_(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity"))
q("proj_cast", "SELECT event_id, CAST(value AS FLOAT) AS f, CAST(floor(value) AS INT) AS i, CAST(user_id AS VARCHAR) AS u FROM events")(lambda s, d: t_(s, d, "events").select("event_id", F.col("value").cast("float").alias("f"), F.floor("value").cast("int").alias("i"), F.col("user_id").cast("string").alias("u")))
q("axis_bins", "SELECT CAST(year(l_shipdate) * 12 + month(l_shipdate) AS INT) AS month, CAST(round(l_discount * 100) AS INT) AS pct, CAST(least(greatest(floor((l_quantity - 1) / ((51 - 1) / 10.0)), 0), 9) AS INT) AS bucket, count(*) AS n FROM lineitem GROUP BY ALL")(lambda s, d: t_(s, d, "lineitem").groupBy(bin_month(F.col("l_shipdate")).alias("month"), bin_pct(F.col("l_discount")).alias("pct"), bin_width(F.col("l_quantity"), 1, 51, 10).alias("bucket")).agg(F.count("*").alias("n")))
q("subvolume", f"WITH {_DENSE} SELECT CAST(i1 AS INT) AS day, CAST(i2 AS INT) AS hour, CAST(i3 AS INT) AS type, CAST(v AS DOUBLE) AS v FROM dense WHERE i1 >= 3 AND i1 < 9 AND i2 >= 6 AND i2 < 12 AND v <> 0")(lambda s, d: cube(s, d, "event_pulse").where_box({"day": (3, 9), "hour": (6, 12)}).where("v <> 0").select("day", "hour", "type", "v"))
q("stride_pick", f"SELECT month, quantity, discount, v FROM {_SHIP} WHERE quantity % 5 = 0 AND discount % 2 = 0")(lambda s, d: CUBES["ship_density"][0](s, d).where("quantity % 5 = 0 and discount % 2 = 0"))
q("pred_mix", "SELECT o_orderkey FROM orders WHERE o_orderpriority LIKE '1%' AND o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 200000 AND o_custkey IS NOT NULL AND regexp_matches(o_orderpriority, '[A-Z]{4}')")(lambda s, d: t_(s, d, "orders").where(F.col("o_orderpriority").like("1%") & F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 200000) & F.col("o_custkey").isNotNull() & F.col("o_orderpriority").rlike("[A-Z]{4}")).select("o_orderkey"))


@q("join_broadcast", "SELECT n_name, count(*) AS n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(s, d):
    o, c, n = t_(s, d, "orders", "o_custkey", "o_totalprice"), t_(s, d, "customer", F.col("c_custkey").alias("o_custkey"), "c_nationkey"), t_(s, d, "nation", F.col("n_nationkey").alias("c_nationkey"), "n_name")
    return o.join(c, "o_custkey").join(F.broadcast(n), "c_nationkey").groupBy("n_name").agg(F.count("*").alias("n"), F.sum(cents(F.col("o_totalprice"))).alias("cents"))


for _hint in ("shuffle_hash", "merge"):
    q(f"join_{'hash' if _hint == 'shuffle_hash' else 'merge'}", "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(lambda s, d, h=_hint: t_(s, d, "lineitem", F.col("l_orderkey").alias("o_orderkey")).join(t_(s, d, "orders", "o_orderkey", "o_orderstatus").hint(h), "o_orderkey").groupBy("o_orderstatus").agg(F.count("*").alias("n")))
q("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")(lambda s, d: t_(s, d, "customer", "c_custkey").join(t_(s, d, "orders", F.col("o_custkey").alias("c_custkey"), "o_orderkey"), "c_custkey", "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))
q("join_full", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NOT NULL AS has_text, l.doc_id IS NOT NULL AS has_label FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")(lambda s, d: t_(s, d, "documents", "doc_id", F.lit(True).alias("a")).join(t_(s, d, "labels", "doc_id", F.lit(True).alias("b")), "doc_id", "full").select("doc_id", F.col("a").isNotNull().alias("has_text"), F.col("b").isNotNull().alias("has_label")))
q("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda s, d: t_(s, d, "documents", "doc_id").join(t_(s, d, "labels", "doc_id"), "doc_id", "left_semi"))
q("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: t_(s, d, "documents", "doc_id").join(t_(s, d, "labels", "doc_id"), "doc_id", "left_anti"))
q("axis_product", "SELECT r_name, seg AS segment FROM region CROSS JOIN (SELECT DISTINCT c_mktsegment AS seg FROM customer)")(lambda s, d: t_(s, d, "region", "r_name").crossJoin(F.broadcast(t_(s, d, "customer", F.col("c_mktsegment").alias("segment")).distinct())))
q("densified", "SELECT r.m AS mode, t.t AS type, CAST(coalesce(sum(CAST(e.value > 0 AS INT)), 0) AS BIGINT) AS n FROM (SELECT DISTINCT user_id % 50 AS m FROM events) r CROSS JOIN (SELECT DISTINCT event_type AS t FROM events) t LEFT JOIN events e ON e.user_id % 50 = r.m AND e.event_type = t.t GROUP BY ALL")(lambda s, d: relops.densify(t_(s, d, "events").groupBy((F.col("user_id") % 50).alias("mode"), F.col("event_type").alias("type")).agg(F.sum((F.col("value") > 0).cast("long")).alias("n")), ["mode", "type"], "n"))
q("join_interval", "SELECT p.event_id AS purchase_id, c.event_id AS click_id FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND epoch_us(p.ts) - epoch_us(c.ts) BETWEEN 0 AND 86400000000")(lambda s, d: relops.interval_join(t_(s, d, "events").where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("at")), t_(s, d, "events").where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("start")), "user_id", "at", "start", 86400).select("purchase_id", "click_id"))
q("join_asof", "SELECT p.event_id, (SELECT arg_max(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts) AS last_click_id FROM events p WHERE p.event_type = 'purchase'")(lambda s, d: relops.asof_join(t_(s, d, "events").where("event_type = 'purchase'").select("user_id", "ts", "event_id"), t_(s, d, "events").where("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click_id")), "user_id", "ts", "click_id").select("event_id", "last_click_id"))
q("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents, min(l_quantity) AS lo, max(l_quantity) AS hi FROM lineitem GROUP BY 1, 2")(lambda s, d: t_(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents(F.col("l_extendedprice"))).alias("cents"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi")))
q("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY 1")(lambda s, d: t_(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days")))
q("agg_approx")(lambda s, d: t_(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median")))
q("agg_cube", "SELECT month, discount, CAST(sum(v) AS BIGINT) AS v FROM (SELECT month, discount, v FROM " + _SHIP + ") GROUP BY CUBE (month, discount)")(lambda s, d: CUBES["ship_density"][0](s, d).cube("month", "discount").agg(F.sum("v").alias("v")))
q("agg_rollup", "SELECT nation, size, CAST(sum(v) AS BIGINT) AS v FROM " + _TRADE + " GROUP BY ROLLUP (nation, size)")(lambda s, d: CUBES["trade_value"][0](s, d).rollup("nation", "size").agg(F.sum("v").alias("v")))
q("pivot_type", "SELECT CAST(ts AS DATE) AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")(lambda s, d: t_(s, d, "events").groupBy(F.to_date("ts").alias("day")).pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0))
q("unpivot_prices", "SELECT p_partkey, 'p_size' AS what, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")(lambda s, d: t_(s, d, "part", "p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice").unpivot("p_partkey", ["p_size", "p_retailprice"], "what", "v"))
q("agg_cond", "SELECT user_id % 20 AS g, count(*) FILTER (value > 50) AS high, arg_max(event_id, (value, event_id)) AS top, bit_xor(event_id) AS digest FROM events GROUP BY 1")(lambda s, d: t_(s, d, "events").groupBy((F.col("user_id") % 20).alias("g")).agg(F.count_if(F.col("value") > 50).alias("high"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"), F.bit_xor("event_id").alias("digest")))
q("agg_moments", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY 1")(lambda s, d: t_(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r")))


@q("win_rank", "SELECT p_partkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS nt, round(percent_rank() OVER v, 8) AS pr, round(cume_dist() OVER v, 8) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)")
def _(s, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return t_(s, d, "part").select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 8).alias("pr"), F.round(F.cume_dist().over(v), 8).alias("cd"))


@q("win_lag", "SELECT event_id, lag(value) OVER w AS a, lead(value, 2) OVER w AS b, first_value(event_id) OVER w AS f, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t_(s, d, "events").select("event_id", F.lag("value").over(w).alias("a"), F.lead("value", 2).over(w).alias("b"), F.first("event_id").over(w).alias("f"), F.nth_value("event_id", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("n"))


@q("win_rows", "SELECT event_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS box FROM events")
def _(s, d):
    return t_(s, d, "events").select("event_id", F.sum(cents(F.col("value"))).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 2)).alias("box"))


@q("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS near FROM part")
def _(s, d):
    return t_(s, d, "part").select("p_partkey", F.count("*").over(Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-3, 3)).alias("near"))


q("sort_topk", "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 100")(lambda s, d: t_(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(100))
q("topk_group", "SELECT event_type, event_id, CAST(r AS INT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 5")(lambda s, d: relops.top_per_group(t_(s, d, "events", "event_type", "event_id", "value"), "event_type", "value", 5, "event_id").select("event_type", "event_id", "rank"))
q("sorted_segments", "SELECT l_orderkey % 8 AS part, count(*) AS n, min(l_orderkey) AS lo FROM lineitem GROUP BY 1")(lambda s, d: t_(s, d, "lineitem", "l_orderkey").repartitionByRange(8, "l_orderkey").sortWithinPartitions("l_orderkey").groupBy((F.col("l_orderkey") % 8).alias("part")).agg(F.count("*").alias("n"), F.min("l_orderkey").alias("lo")))
for _n, _op, _f in (("union", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    q(f"set_{_n}", f"SELECT c_nationkey AS k FROM customer {_op} SELECT s_nationkey FROM supplier")(lambda s, d, f=_f: f(t_(s, d, "customer", F.col("c_nationkey").alias("k")), t_(s, d, "supplier", F.col("s_nationkey").alias("k"))))
q("fn_math", "SELECT event_id, round(sqrt(value), 6) AS a, round(log10(value + 1), 6) AS b, round(sin(value), 6) AS c, round(pow(value, 1.5), 4) AS e, CAST(sign(value - 50) AS INT) AS f, CAST(floor(value) AS BIGINT) AS g FROM events")(lambda s, d: t_(s, d, "events").select("event_id", F.round(F.sqrt("value"), 6).alias("a"), F.round(F.log10(F.col("value") + 1), 6).alias("b"), F.round(F.sin("value"), 6).alias("c"), F.round(F.pow("value", F.lit(1.5)), 4).alias("e"), F.signum(F.col("value") - 50).cast("int").alias("f"), F.floor("value").alias("g")))
q("fn_bits", "SELECT p_partkey, CAST(bit_count(p_partkey) AS INT) AS bits, p_partkey >> 3 AS r, p_partkey << 2 AS l, xor(p_partkey, 255) AS x, p_partkey & 15 AS a, p_partkey | 16 AS o, bin(p_partkey) AS b FROM part")(lambda s, d: t_(s, d, "part").select("p_partkey", F.bit_count("p_partkey").alias("bits"), F.shiftright("p_partkey", 3).alias("r"), F.shiftleft("p_partkey", 2).alias("l"), F.col("p_partkey").bitwiseXOR(F.lit(255).cast("long")).alias("x"), F.col("p_partkey").bitwiseAND(F.lit(15).cast("long")).alias("a"), F.col("p_partkey").bitwiseOR(F.lit(16).cast("long")).alias("o"), F.bin("p_partkey").alias("b")))
q("fn_array_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 6) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")(lambda s, d: t_(s, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 6).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos")))
q("fn_array_dot", "SELECT a.vec_id, round(list_inner_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = 0")(lambda s, d: t_(s, d, "embeddings").join(F.broadcast(t_(s, d, "embeddings").where("vec_id = 0").select(F.col("embedding").alias("o"))), how="cross").select("vec_id", F.round(F.aggregate(F.zip_with("embedding", "o", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("dot")))
q("fn_map_model", "SELECT event_type, count(*) AS total, count(*) FILTER (hour(ts) = 5) AS at5 FROM events GROUP BY 1")(lambda s, d: t_(s, d, "events").groupBy("event_type", F.hour("ts").alias("h")).agg(F.count("*").alias("n")).groupBy("event_type").agg(F.map_from_entries(F.collect_list(F.struct("h", "n"))).alias("m")).select("event_type", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.coalesce(F.try_element_at("m", F.lit(5)), F.lit(0)).alias("at5")))
q("fn_string", "SELECT doc_id, md5(lower(text)) AS a, unicode(text) AS c, length(replace(text, ' ', '')) AS n, len(string_split(text, chr(10))) AS lines, md5(regexp_replace(text, '[aeiou]', '_', 'g')) AS r FROM documents")(lambda s, d: t_(s, d, "documents").select("doc_id", F.md5(F.lower("text").cast("binary")).alias("a"), F.ascii("text").alias("c"), F.length(F.replace("text", F.lit(" "), F.lit(""))).cast("long").alias("n"), F.size(F.split("text", "\n")).cast("long").alias("lines"), F.md5(F.regexp_replace("text", "[aeiou]", "_").cast("binary")).alias("r")))
q("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS n FROM orders")(lambda s, d: t_(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.trunc("o_orderdate", "month").alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long").alias("n")))
q("json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")(lambda s, d: t_(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))


# ---- streams: run over what is there, equal to the batch ----


def _streamed(f: Callable[[DataFrame], DataFrame], name: str, mode: str = "complete"):
    def run(s: SparkSession, d: str) -> DataFrame:
        streaming.drain(f(streaming.event_stream(s, f"{d}/events.parque[t]")), name, mode)
        return s.table(name)

    return run


_naive = lambda c: F.col(c).cast("timestamp_ntz").alias(c)
q("stream_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY ALL")(lambda s, d: _streamed(streaming.tumbling, "stream_tumbling")(s, d).select(_naive("start"), "event_type", "n", "cents"))
q("stream_sliding", "SELECT date_trunc('hour', ts) - to_hours(k) AS start, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events CROSS JOIN (SELECT unnest(range(0, 2)) AS k) GROUP BY ALL")(lambda s, d: _streamed(streaming.sliding, "stream_sliding")(s, d).select(_naive("start"), "n", "cents"))
q("stream_session", "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM s GROUP BY user_id, k")(lambda s, d: streaming.written(streaming.sessions(streaming.closed(streaming.event_stream(s, f"{d}/events.parque[t]", None))), "stream_session").select("user_id", _naive("start"), _naive("end"), "n", "cents"))


# ---- functions in SQL ----


@q("udf_exponent", "SELECT event_id, CAST(CASE WHEN value > 0 THEN floor(log2(value)) END AS INT) AS e FROM events WHERE value > 0 AND abs(log2(value) - round(log2(value))) > 1e-9")
def _(s, d):
    return t_(s, d, "events").where("value > 0 and abs(log2(value) - round(log2(value))) > 1e-9").select("event_id", G.float_exponent("value").alias("e"))


@q("udaf_entropy", "WITH f AS (SELECT event_type, CAST(floor(value) AS BIGINT) AS b, count(*) AS f FROM events GROUP BY ALL), n AS (SELECT *, sum(f) OVER (PARTITION BY event_type) AS n FROM f) SELECT event_type, round(sum(f * log2(n / f)), 3) AS bits FROM n GROUP BY 1")
def _(s, d):
    return t_(s, d, "events").groupBy("event_type").agg(F.round(G.entropy_bits_udaf(F.floor("value")), 3).alias("bits"))


@q("udtf_planes", "SELECT event_id, CAST(p AS INT) AS plane, CAST((v >> p) & 1 AS INT) AS bit FROM (SELECT event_id, CAST(round(value * 100) AS BIGINT) AS v FROM events) CROSS JOIN (SELECT unnest(range(0, 20)) AS p) WHERE v > 0 AND p < length(bin(v))")
def _(s, d):
    G.register(s)
    t_(s, d, "events", "event_id", cents(F.col("value")).alias("v")).createOrReplaceTempView(view := f"_events_{uuid.uuid4().hex}")
    return s.sql(f"SELECT event_id, b.plane, b.bit FROM {view}, LATERAL bit_planes(v) b")


@q("udtf_segments", f"WITH {_EV}, {_RUNS} SELECT plane, CAST(seq AS INT) AS seq, CAST(run AS BIGINT) AS run FROM runs")
def _(s, d):
    """Runs of each plane, coded as an archive's segments are and read back in SQL."""
    G.register(s)
    fields = "plane int, payload binary, symbols array<long>, freq array<long>"

    def code(key: tuple, t: pa.Table) -> pa.Table:
        runs = t.sort_by("seq")["run"].to_numpy()
        m = Model.of(*np.unique(runs, return_counts=True))
        return pa.table({"plane": pa.array([key[0].as_py()], pa.int32()), "payload": pa.array([CODERS["range"].encode(runs, m)], pa.binary()), "symbols": pa.array([m.symbols.tolist()], pa.list_(pa.int64())), "freq": pa.array([m.freq.tolist()], pa.list_(pa.int64()))})

    P.zero_runs(events_q(s, d), 0, 16).groupBy("plane").applyInArrow(code, fields).createOrReplaceTempView(view := f"_segments_{uuid.uuid4().hex}")
    return s.sql(f"SELECT plane, r.seq, r.run FROM {view}, LATERAL decode_segment(payload, symbols, freq, 'range') r")


@q("sql_psnr", "SELECT event_type, round(20 * log10((max(value) - min(value)) / (2 * stddev_pop(value))), 6) AS db FROM events GROUP BY 1")
def _(s, d):
    G.register(s)
    t_(s, d, "events", "event_type", "value").createOrReplaceTempView(view := f"_events_{uuid.uuid4().hex}")
    return s.sql(f"SELECT event_type, round(db, 6) AS db FROM (SELECT event_type, psnr_db(hi - lo, sd) AS db FROM (SELECT event_type, max(value) AS hi, min(value) AS lo, stddev_pop(value) AS sd FROM {view} GROUP BY event_type))")


# ---- experiments ----

for _name, _f in workloads.WORKLOADS.items():
    q(_name)(_f)
q("quality_curve_small")(lambda s, d: workloads.quality_curve(s, workloads.grids(s, d, ("event_pulse",), ("cosines",)), psnrs=(25.0, 45.0)))
q("lead_zones")(lambda s, d: workloads.lead_zone(workloads.quality_curve(s, workloads.grids(s, d, ("event_pulse",), ("cosines", "bump")))))

