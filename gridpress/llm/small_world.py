"""Embedding near-duplicates by navigable small-world graphs, one for each shard.

Graphs are built and searched in batches: a batch of rows walks the layers in
lockstep, so each step is one gather and one product.  All rows of a label query
every shard of it.  A query whose beam is full of links gets a wider beam;
queries with and without links are compared with the whole shard, and all beams
widen until that audit misses no link.  Links are checked by cosine in doubles, and what leaves a
task is a count for each query and a spanning forest, never the pairs.

Cases: null or unusable vectors, zero vectors and null labels link with nothing;
equal vectors of a label are one node with a count; repeated rows of one id are
one vector (the least by label and components); rows without an id are left out.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.llm.components import components
from gridpress.llm.textkernels import GOLD, U64, mix
from gridpress.llm.vectors import matrix, usable
from gridpress.session import cut, ship

SHARD_ROWS, BLOCK_QUERIES = 8192, 8192
LINKS, BUILD_BEAM, BEAM, BATCH, AT_ONCE = 16, 48, 48, 512, 4
AUDIT = 64
f32 = np.float32


class Graph:
    """Layers of neighbour lists over unit vectors x (rows x dims)."""

    def __init__(self, x: np.ndarray, seeds: np.ndarray, links: int = LINKS):
        self.x = x.astype(f32)
        n = len(x)
        u = ((mix(seeds.astype(U64) + GOLD) >> U64(11)).astype(np.float64) + 0.5) * 2.0**-53
        height = np.minimum((-np.log(u) / np.log(links)).astype(np.int64), 6)
        self.order = np.lexsort((u, -height))
        self.height = height
        self.top = int(height.max()) if n else 0
        self.nbr = [np.full((n, links * 2 if level == 0 else links), -1, np.int32) for level in range(self.top + 1)]
        done = 0
        while done < n:
            size = min(BATCH, max(1, done), n - done)
            self._insert(self.order[done : done + size], done)
            done += size

    def walk(self, q: np.ndarray, level: int, beam: int, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rows, similarities) of each query's beam on a layer, best first; -1 where it has fewer."""
        n, b = len(self.x), len(q)
        ids = np.full((b, beam), -1, np.int64)
        sim = np.full((b, beam), -np.inf, f32)
        width = min(start.shape[1], beam)
        s0 = np.where(start >= 0, np.einsum("bd,bkd->bk", q, self.x[np.maximum(start, 0)]), -np.inf).astype(f32)
        best = np.argsort(-s0, axis=1, kind="stable")[:, :width]
        ids[:, :width], sim[:, :width] = np.take_along_axis(start, best, 1), np.take_along_axis(s0, best, 1)
        seen = np.zeros((b, n + 1), bool)
        np.put_along_axis(seen, np.where(start >= 0, start, n), True, axis=1)
        opened = ids < 0
        live = np.arange(b)
        step = 1 if beam == 1 else AT_ONCE
        links = self.nbr[level]
        while len(live):
            todo = np.where(opened[live], -np.inf, sim[live])
            pick = np.argpartition(-todo, min(step, beam) - 1, axis=1)[:, :step] if beam > step else np.argsort(-todo, axis=1)[:, :step]
            good = np.isfinite(np.take_along_axis(todo, pick, 1))
            some = good.any(axis=1)
            live, pick, good = live[some], pick[some], good[some]
            if not len(live):
                break
            opened[live[:, None], pick] |= good
            at = np.where(good, ids[live[:, None], pick], -1)
            near = np.where(at[:, :, None] >= 0, links[np.maximum(at, 0)], -1).reshape(len(live), -1).astype(np.int64)
            near = np.sort(np.where(near < 0, n, near), axis=1)
            fresh = near < n
            fresh[:, 1:] &= near[:, 1:] != near[:, :-1]
            fresh &= ~seen[live[:, None], near]
            seen[live[:, None], near] = True
            most = int(fresh.sum(axis=1).max())
            if most == 0:
                continue
            place = np.argsort(~fresh, axis=1, kind="stable")[:, :most]
            near, fresh = np.take_along_axis(near, place, 1), np.take_along_axis(fresh, place, 1)
            s = np.where(fresh, np.einsum("bd,bkd->bk", q[live], self.x[np.where(fresh, near, 0)]), -np.inf).astype(f32)
            all_s = np.concatenate([sim[live], s], axis=1)
            all_i = np.concatenate([ids[live], np.where(fresh, near, -1)], axis=1)
            all_o = np.concatenate([opened[live], ~fresh], axis=1)
            keep = np.argpartition(-all_s, beam - 1, axis=1)[:, :beam] if all_s.shape[1] > beam else np.argsort(-all_s, axis=1)
            sim[live], ids[live], opened[live] = (np.take_along_axis(v, keep, 1) for v in (all_s, all_i, all_o))
        best = np.argsort(-sim, axis=1, kind="stable")
        ids, sim = np.take_along_axis(ids, best, 1), np.take_along_axis(sim, best, 1)
        return np.where(np.isfinite(sim), ids, -1), sim

    def descend(self, q: np.ndarray, level: int) -> np.ndarray:
        """Where queries arrive on a layer, coming from the top with a beam of one."""
        at = np.full((len(q), 1), self.order[0], np.int64)
        for up in range(self.top, level, -1):
            at, _ = self.walk(q, up, 1, at)
        return at

    def _choose(self, q: np.ndarray, ids: np.ndarray, sim: np.ndarray, most: int) -> np.ndarray:
        """Neighbours that are nearer to q than to one already chosen; free places go to the nearest of the others."""
        b, c = ids.shape
        v = self.x[np.maximum(ids, 0)]
        cross = np.einsum("bid,bjd->bij", v, v)
        taken = np.zeros((b, c), bool)
        for j in range(c):
            rival = np.where(taken, cross[:, j], -np.inf).max(axis=1)
            taken[:, j] = (ids[:, j] >= 0) & (sim[:, j] > rival) & (taken.sum(axis=1) < most)
        order = np.lexsort((-sim, ~taken, ids < 0), axis=1)[:, :most]
        out = np.take_along_axis(ids, order, 1)
        if out.shape[1] < most:
            out = np.pad(out, ((0, 0), (0, most - out.shape[1])), constant_values=-1)
        return out

    def _insert(self, new: np.ndarray, done: int) -> None:
        q = self.x[new]
        inner = q @ q.T
        np.fill_diagonal(inner, -np.inf)
        tall = int(self.height[new].max())
        at = self.descend(q, min(tall, self.top)) if done else np.full((len(new), 1), -1, np.int64)
        for level in range(min(tall, self.top), -1, -1):
            on = np.flatnonzero(self.height[new] >= level)
            if done:
                ids, sim = self.walk(q, level, BUILD_BEAM, at)
                # a layer that holds none of the rows met so far has no links; the entry alone is no neighbour there
                ids = np.where((ids >= 0) & (self.height[np.maximum(ids, 0)] >= level), ids, -1)
                at = np.where(ids[:, :1] >= 0, ids[:, :4] if ids.shape[1] >= 4 else ids, at[:, :1])
            else:
                ids, sim = np.full((len(new), 1), -1, np.int64), np.full((len(new), 1), -np.inf, f32)
            if not len(on):
                continue
            peers = inner[on][:, on]
            c = min(LINKS, len(on))
            near = np.argsort(-peers, axis=1)[:, :c]
            ps = np.take_along_axis(peers, near, 1)
            ids2 = np.concatenate([ids[on], np.where(np.isfinite(ps), new[on][near], -1)], axis=1)
            sim2 = np.concatenate([np.where(ids[on] >= 0, sim[on], -np.inf), ps], axis=1)
            best = np.argsort(-sim2, axis=1, kind="stable")[:, : BUILD_BEAM + LINKS]
            ids2, sim2 = np.take_along_axis(ids2, best, 1), np.take_along_axis(sim2, best, 1)
            chosen = self._choose(q[on], ids2, sim2, LINKS)
            self.nbr[level][new[on], :LINKS] = chosen
            self._link_back(level, np.repeat(new[on], LINKS), chosen.ravel())

    def _link_back(self, level: int, frm: np.ndarray, to: np.ndarray) -> None:
        ok = to >= 0
        frm, to = frm[ok], to[ok]
        if not len(to):
            return
        lists = self.nbr[level]
        most = lists.shape[1]
        s = np.einsum("kd,kd->k", self.x[frm], self.x[to])
        order = np.lexsort((-s, to))
        frm, to = frm[order], to[order]
        uniq, lead = np.unique(to, return_index=True)
        place = np.arange(len(to)) - np.repeat(lead, np.diff(np.append(lead, len(to))))
        use = place < most
        extra = np.full((len(uniq), most), -1, np.int64)
        extra[np.searchsorted(uniq, to[use]), place[use]] = frm[use]
        for i in range(0, len(uniq), 1024):
            u = uniq[i : i + 1024]
            both = np.sort(np.concatenate([lists[u], extra[i : i + 1024]], axis=1), axis=1)
            both[:, 1:][both[:, 1:] == both[:, :-1]] = -1
            sim = np.where(both >= 0, np.einsum("bd,bkd->bk", self.x[u], self.x[np.maximum(both, 0)]), -np.inf)
            best = np.argsort(-sim, axis=1, kind="stable")
            both, sim = np.take_along_axis(both, best, 1), np.take_along_axis(sim, best, 1)
            full = (both >= 0).sum(axis=1) > most
            lists[u[~full]] = both[~full][:, :most]
            if full.any():
                lists[u[full]] = self._choose(self.x[u[full]], both[full], sim[full], most)

    def within(self, q: np.ndarray, least: float, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """(query, row) pairs of at least `least`; a beam that is full of them is doubled and walked again."""
        out_q, out_r = [], []
        for i in range(0, len(q), BATCH):
            live, wide = np.arange(i, min(i + BATCH, len(q))), beam
            at = self.descend(q[live], 0)
            while len(live):
                wide = min(wide, len(self.x))
                block = max(1, min(len(live), (BATCH * 128) // wide))
                again, starts = [], []
                for j in range(0, len(live), block):
                    mine = live[j : j + block]
                    ids, sim = self.walk(q[mine], 0, wide, at[j : j + block])
                    hit = (sim >= least) & (ids >= 0)
                    full = hit[:, -1] & (wide < len(self.x))
                    r, c = np.nonzero(hit & ~full[:, None])
                    out_q.append(mine[r])
                    out_r.append(ids[r, c])
                    again.append(mine[full])
                    starts.append(ids[full])
                live, at, wide = np.concatenate(again), np.concatenate(starts), wide * 2
        return np.concatenate(out_q) if out_q else np.zeros(0, np.int64), np.concatenate(out_r) if out_r else np.zeros(0, np.int64)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def linked(q: np.ndarray, r: np.ndarray, q_id: np.ndarray, r_id: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray, float]:
    """(query, row) pairs by cosine >= threshold in doubles, and the recall that the last audit measured.

    The audit compares queries with the whole shard: AUDIT of them at even steps, and as
    many that the walk has found links for.  A query's own row does not count.  Beams are
    doubled and all queries walk again until no audited link is missed; a beam as wide as
    the shard is a plain product.
    """
    g = Graph(r, r_id)
    beam, q32, least = BEAM, q.astype(f32), threshold - 1e-4
    even = np.linspace(0, len(q) - 1, min(AUDIT, len(q))).astype(np.int64)
    while True:
        a, b = g.within(q32, least, beam)
        other = q_id[a] != r_id[b]
        with_links = np.unique(a[other])
        audit = np.union1d(even, with_links[np.linspace(0, len(with_links) - 1, min(AUDIT, len(with_links))).astype(np.int64)])
        truth = (q[audit] @ r.T >= threshold) & (q_id[audit][:, None] != r_id[None, :])
        found = np.zeros_like(truth)
        mine = np.isin(a, audit)
        found[np.searchsorted(audit, a[mine]), b[mine]] = True
        recall = float((found & truth).sum() / truth.sum()) if truth.any() else 1.0
        if recall == 1.0 or beam >= len(r):
            break
        beam *= 2
    keep = other
    for i in range(0, len(a), 1 << 16):
        s = slice(i, i + (1 << 16))
        keep[s] &= np.einsum("kd,kd->k", q[a[s]], r[b[s]]) >= threshold
    return a[keep], b[keep], recall


def forest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest reachable node of each of n nodes."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def near_duplicate_vectors(rows: DataFrame, threshold: float = 0.93, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", shard_rows: int = SHARD_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """vec_id, n_links, component_id, kept of each vector; links only within a label."""
    ship(rows.sparkSession)
    one = rows.where(F.col(id_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("vec_id")).agg(F.min(F.struct(F.col(label_col).alias("label"), F.col(vector_col).alias("v"))).alias("x")).select("vec_id", "x.*")
    norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    fit = usable(F.col("v")) & F.col("label").isNotNull() & (norm > 0)
    one = cut(one.withColumn("fit", F.coalesce(fit, F.lit(False))))
    nodes = cut(one.where("fit").groupBy("label", "v").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies")))
    # one row for each label and length: how many shards and blocks it is dealt to
    plan = nodes.groupBy("label", F.size("v").alias("d")).agg(F.count("*").alias("n")).select("label", "d", F.ceil(F.col("n") / shard_rows).cast("int").alias("shards"), F.ceil(F.col("n") / block_queries).cast("int").alias("blocks"))
    placed = nodes.withColumn("d", F.size("v")).join(plan, ["label", "d"])
    refs = placed.select("label", "d", F.pmod(F.xxhash64("node"), "shards").cast("int").alias("s"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("b"), "node", "v", "copies")
    asks = placed.select("label", "d", F.pmod(F.xxhash64("node", F.lit(5)), "blocks").cast("int").alias("b"), F.explode(F.sequence(F.lit(0), F.col("shards") - 1)).alias("s"), "node", "v")
    asks = asks.toDF("l", "d", "b", "s", "node", "v")  # names of its own, so the two sides can be told apart

    def pair(left: pa.Table, right: pa.Table) -> pa.Table:
        out: tuple = ([], [], [])
        if len(left) and len(right):
            q_id, r_id, copies = left["node"].to_numpy(), right["node"].to_numpy(), right["copies"].to_numpy()
            qo, ro = np.argsort(q_id), np.argsort(r_id)
            q_id, r_id, copies = q_id[qo], r_id[ro], copies[ro]
            a, b, _ = linked(unit(matrix(left["v"])[qo]), unit(matrix(right["v"])[ro]), q_id, r_id, threshold)
            count = np.bincount(a, weights=copies[b], minlength=len(q_id)).astype(np.int64)
            every = np.unique(np.concatenate([q_id, r_id[b]]))
            root = every[forest(np.searchsorted(every, q_id[a]), np.searchsorted(every, r_id[b]), len(every))]
            mine = np.zeros(len(every), np.int64)
            mine[np.searchsorted(every, q_id)] = count
            some = (mine > 0) | (root != every)
            out = (every[some], mine[some], root[some])
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("node", "n", "root"), out, strict=True)})

    found = cut(asks.groupBy("l", "d", "s", "b").cogroup(refs.groupBy("label", "d", "s", "b")).applyInArrow(pair, "node long, n long, root long"))
    roots = components(found.where("node != root").select(F.col("node").alias("a"), F.col("root").alias("b")))
    counts = found.groupBy("node").agg(F.sum("n").alias("n"))
    of = nodes.join(counts, "node", "left").join(roots, "node", "left").select("label", "v", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "node").alias("component_id"))
    fine = one.where("fit").join(of, ["label", "v"]).select("vec_id", "n_links", "component_id")
    rest = one.where("not fit").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return fine.union(rest).select("vec_id", "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"))
