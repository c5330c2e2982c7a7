"""Exact top-k by inner product with two cover trees walked together.

Rows go to shards and queries to blocks, both of a stated size; each pair of the
two is one task, which builds a tree of either side.  A node's centre is one of
its rows.  Its children's centres are rows of it too, its own centre the first
(nesting), all further apart than a reach (separation), and each child's rows
lie within the reach of the child's centre (covering); the reach falls by a
factor from level to level.  A child of one row is kept as a point.

For centres a, b with radii r, s no pair under two nodes scores more than
a.b + |a| s + |b| r + r s, nor more than the product of the largest norms times
the cosine of the angle between the centres less the angles of both cones.  A
pair of nodes is dropped once the lesser of these is under the worst kth score
of the node's queries.  Vectors without clusters (independent directions in many
dimensions) have cones so wide that no bound drops anything: there the walk
meets every pair once, as a plain product would.

Cases: vectors that are null, empty or hold null or non-finite components take no
part; vectors meet vectors of their own length; a query's own id is no candidate;
rows with the same id are separate candidates; equal scores go by smaller id;
fewer candidates than k give fewer rows.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridpress.llm.vectors import matrix, usable
from gridpress.session import ship

SHARD_ROWS, BLOCK_QUERIES = 4096, 1024
LEAF, FACTOR = 24, 1.3


class Node:
    """A row as centre, what lies around it, and inner nodes and points; `near` are all centres below it."""

    __slots__ = ("centre", "children", "cone", "norm", "points", "radius", "rows", "top", "near", "reaches", "norms", "cones", "tops")

    def __init__(self, x: np.ndarray, norms: np.ndarray, rows: np.ndarray):
        self.rows, self.children, self.points = rows, [], rows
        self.centre, self.norm = x[rows[0]], float(norms[rows[0]])
        self.radius = float(np.sqrt(((x[rows] - self.centre) ** 2).sum(axis=1).max()))
        self.top = float(norms[rows].max())
        if self.norm == 0 or (norms[rows] == 0).any():
            self.cone = np.pi
        else:
            self.cone = float(np.arccos(np.clip((x[rows] @ self.centre) / (norms[rows] * self.norm), -1, 1).min()))

    def link(self, x: np.ndarray, norms: np.ndarray) -> None:
        """Centres, radii, norms and cones of children, then of points, as arrays."""
        c, p = self.children, self.points
        self.near = np.concatenate([np.array([n.centre for n in c]).reshape(len(c), x.shape[1]), x[p]])
        zero = np.zeros(len(p))
        self.reaches = np.concatenate([[n.radius for n in c], zero])
        self.cones = np.concatenate([[n.cone for n in c], zero])
        self.norms = np.concatenate([[n.norm for n in c], norms[p]])
        self.tops = np.concatenate([[n.top for n in c], norms[p]])


def build(x: np.ndarray, leaf: int = LEAF) -> Node:
    """Cover tree of the rows of x; nodes of at most `leaf` rows, or of equal rows, hold points only."""
    norms = np.sqrt((x * x).sum(axis=1))
    apart = x @ x.T
    apart *= -2
    apart += norms[:, None] ** 2
    apart += norms[None, :] ** 2
    root = Node(x, norms, np.arange(len(x)))
    todo = [root]
    while todo:
        node = todo.pop()
        rows = node.rows
        if len(rows) > leaf and node.radius > 0:
            reach = node.radius / FACTOR
            groups = [rows]
            while len(groups) == 1:  # all within reach of the centre: the level below
                left, groups = rows, []
                while len(left):
                    near = apart[left[0], left] <= reach * reach
                    near[0] = True
                    groups.append(left[near])
                    left = left[~near]
                reach /= FACTOR
            node.children = [Node(x, norms, g) for g in groups if len(g) > 1]
            node.points = np.array([g[0] for g in groups if len(g) == 1], np.int64)
            todo += node.children
        node.link(x, norms)
    return root


def _bounds(dot: np.ndarray, norm: np.ndarray, radius: np.ndarray, cone: np.ndarray, top: np.ndarray, b: Node) -> np.ndarray:
    """Upper bounds of scores between query rows or nodes and what is below b, from products of centres."""
    ball = dot + norm * b.reaches + b.norms * radius + radius * b.reaches
    with np.errstate(divide="ignore", invalid="ignore"):
        angle = np.arccos(np.clip(dot / (norm * b.norms), -1, 1))
    angle = np.where(norm * b.norms > 0, angle, 0.0)
    wedge = top * b.tops * np.cos(np.clip(angle - cone - b.cones, 0, np.pi))
    wedge = np.where(angle - cone - b.cones >= np.pi / 2, 0.0, wedge)  # small norms may come nearest to nothing
    best = np.minimum(ball, wedge)
    return best + 1e-9 * np.abs(best) + 1e-6


def search(q: np.ndarray, q_ids: np.ndarray, r: np.ndarray, r_ids: np.ndarray, k: int, seen: list | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query row, reference row, score) of each query's k best, ties by smaller id; integers in doubles, so exact.

    Rows of r stand in the order of their ids.  `seen` gets the number of pairs whose score was computed.
    """
    n = len(q)
    score = np.full((n, k), -np.inf)
    which = np.full((n, k), -1, np.int64)
    if not n or not len(r):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    q_norm = np.sqrt((q * q).sum(axis=1))
    met = 0

    def take(rows: np.ndarray, points: np.ndarray, s: np.ndarray) -> None:
        s = np.where(q_ids[rows][:, None] == r_ids[points][None, :], -np.inf, s)
        both = np.concatenate([score[rows], s], axis=1)
        ids = np.concatenate([which[rows], np.broadcast_to(points, s.shape)], axis=1)
        order = np.lexsort((np.where(ids < 0, np.iinfo(np.int64).max, r_ids[ids]), -both), axis=1)[:, :k]
        score[rows], which[rows] = np.take_along_axis(both, order, 1), np.take_along_axis(ids, order, 1)
        which[rows] = np.where(np.isfinite(score[rows]), which[rows], -1)

    ticket = 0
    heap = [(-np.inf, 0, build(q), build(r))]
    while heap:
        minus, _, a, b = heapq.heappop(heap)
        if a is None or -minus < score[a.rows, k - 1].min():
            continue
        if a.children:
            # the query side opens first; its points wait with the bound of the pair
            if len(a.points):
                own = Node(q, q_norm, a.points)
                own.link(q, q_norm)
                ticket += 1
                heapq.heappush(heap, (minus, ticket, own, b))
            for c in a.children:
                top = float(_bounds(b.near @ c.centre, np.float64(c.norm), np.float64(c.radius), np.float64(c.cone), np.float64(c.top), b).max())
                if top >= score[c.rows, k - 1].min():
                    ticket += 1
                    heapq.heappush(heap, (-top, ticket, c, b))
            continue
        rows, inner = a.rows, len(b.children)
        dot = q[rows] @ b.near.T
        own = q_norm[rows][:, None]
        zero = np.zeros((len(rows), 1))
        worst = score[rows, k - 1][:, None]
        if len(b.points):
            met += len(rows) * len(b.points)
            s = dot[:, inner:]
            some = np.flatnonzero((s >= worst).any(axis=0))
            if len(some):
                take(rows, b.points[some], s[:, some])
        if inner:
            tops = _bounds(dot, own, zero, zero, own, b)[:, :inner]
            need = (tops >= score[rows, k - 1][:, None]).any(axis=0)
            for i in np.flatnonzero(need):
                ticket += 1
                heapq.heappush(heap, (-float(tops[:, i].max()), ticket, a, b.children[i]))
    if seen is not None:
        seen.append(met)
    qi, ki = np.nonzero(which >= 0)
    return qi, which[qi, ki], score[qi, ki]


def scaled(vector: Column, scale: int = 1024) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * F.lit(float(scale))).cast("double"))


def top_k(rows: DataFrame, queries: Column, k: int = 10, scale: int = 1024, id_col: str = "vec_id", vector_col: str = "embedding", shard_rows: int = SHARD_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """query_id, rank, vec_id, score of the k best of all rows for each row that `queries` is true for."""
    ship(rows.sparkSession)
    base = rows.where(usable(F.col(vector_col)) & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), scaled(F.col(vector_col), scale).alias("v"), F.coalesce(queries, F.lit(False)).alias("asks"))
    # two counts decide how many shards and blocks there are; a row's place in the input deals out repeated rows
    n, nq = base.agg(F.count("*"), F.count(F.when(F.col("asks"), 1))).first()
    shards, blocks = max(1, -(-n // shard_rows)), max(1, -(-nq // block_queries))
    refs = base.select("id", "v", F.size("v").alias("d"), F.pmod(F.xxhash64("id", F.monotonically_increasing_id()), F.lit(shards)).cast("int").alias("s"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"))
    asks = base.where("asks").dropDuplicates(["id", "v"]).select("id", "v", F.size("v").alias("d"), F.pmod(F.xxhash64("id", "v", F.lit(3)), F.lit(blocks)).cast("int").alias("b"), F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("s"))

    def pair(left: pa.Table, right: pa.Table) -> pa.Table:
        out = ([], [], [])
        if len(left) and len(right):
            q_ids, r_ids = left["id"].to_numpy(), right["id"].to_numpy()
            order = np.argsort(r_ids, kind="stable")
            r_ids, r = r_ids[order], matrix(right["v"])[order]
            qi, ri, sc = search(matrix(left["v"]), q_ids, r, r_ids, k)
            out = (q_ids[qi], r_ids[ri], sc.astype(np.int64))
        return pa.table({"query_id": pa.array(out[0], pa.int64()), "vec_id": pa.array(out[1], pa.int64()), "score": pa.array(out[2], pa.int64())})

    found = asks.groupBy("s", "b", "d").cogroup(refs.groupBy("s", "b", "d")).applyInArrow(pair, "query_id long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.select("query_id", rank.alias("rank"), "vec_id", "score").where(F.col("rank") <= k)
