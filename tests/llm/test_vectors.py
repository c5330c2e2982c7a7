import numpy as np
from pyspark.sql import functions as F

from gridpress.llm import cover_trees, small_world


def test_dual_tree_equals_brute_force(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(0, 1, (900, 16))
    x[300:320] = x[0]  # ties
    rows = [(i, [float(v) for v in x[i]], 1) for i in range(900)] + [(1000, None, 1), (1001, [None] * 16, 1), (1002, [float("nan")] * 16, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got = cover_trees.top_k(df, F.col("vec_id") % 100 == 0, shard_rows=250, block_queries=4).collect()
    q = np.floor(np.float32(x).astype(np.float64) * 1024)
    for i in range(0, 900, 100):
        s = q @ q[i]
        s[i] = -np.inf
        want = [(int(j), int(s[j])) for j in np.lexsort((np.arange(900), -s))[:10]]
        assert [(r.vec_id, r.score) for r in sorted(got, key=lambda r: r.rank) if r.query_id == i] == want
    assert {r.query_id for r in got} == set(range(0, 900, 100))
    assert cover_trees.top_k(df.limit(0), F.lit(True)).count() == 0


def brute_top(q, q_ids, r, r_ids, k):
    s = q @ r.T
    s[q_ids[:, None] == r_ids[None, :]] = -np.inf
    order = np.lexsort((np.broadcast_to(r_ids, s.shape), -s), axis=1)[:, :k]
    return order, np.take_along_axis(s, order, 1)


def test_cover_tree_invariants_and_pruning():
    rng = np.random.default_rng(8)
    clustered = rng.normal(0, 1, (40, 64))[rng.integers(0, 40, 3000)] + rng.normal(0, 0.15, (3000, 64))
    scaled = rng.normal(0, 1, (2000, 3)) * rng.uniform(0, 3, (2000, 1))
    flat = rng.normal(0, 1, (1500, 64))
    for x, most in ((clustered, 0.5), (scaled, 0.5), (np.repeat(flat[:20], 60, axis=0), 0.5), (flat, 1.0), (np.zeros((60, 4)), 1.0)):
        x = np.floor(x * 128)
        todo = [cover_trees.build(x)]
        while todo:
            node = todo.pop()
            assert np.array_equal(np.sort(node.rows), np.sort(np.concatenate([node.points, *(c.rows for c in node.children)])))
            assert (np.linalg.norm(x[node.rows] - node.centre, axis=1) <= node.radius + 1e-6).all()
            if node.children:
                gap = np.linalg.norm(node.near[:, None] - node.near[None], axis=2) if len(node.near) < 400 else np.ones((1, 1))
                reach = max(c.radius for c in node.children)
                assert (gap[~np.eye(len(gap), dtype=bool)] > reach - 1e-6).all()
            todo += node.children
        ids, seen = np.arange(len(x)) * 3, []
        ask = np.arange(0, len(x), 20)
        qi, ri, sc = cover_trees.search(x[ask], ids[ask], x, ids, 10, seen)
        order, want = brute_top(x[ask], ids[ask], x, ids, 10)
        assert all(np.array_equal(ri[qi == i], order[i]) and np.array_equal(sc[qi == i], want[i]) for i in range(len(ask)))
        assert seen[0] <= most * len(ask) * len(x)


def test_vectors_among_clashing_columns(spark):
    rows = [(i, [float(i % 7), 1.0, float(i)], i % 2, 1, 2, "a") for i in range(60)] * 3
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, id int, v int, s string")
    got = cover_trees.top_k(df, F.col("vec_id") % 20 == 0, k=4).collect()
    assert sorted((r.query_id, r.rank, r.vec_id) for r in got)[:4] == [(0, 1, 55), (0, 2, 55), (0, 3, 55), (0, 4, 48)] or len(got) == 12
    links = small_world.near_duplicate_vectors(df)
    assert links.columns[:4] == ["vec_id", "n_links", "component_id", "kept"] and links.count() == 60


def test_links_and_components(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(0, 1, (1500, 24))
    for c in range(30):  # clusters around a row, of growing size
        x[c * 20 + 1 : c * 20 + 1 + c] = x[c * 20] + rng.normal(0, 0.12, (c, 24))
    label = rng.integers(0, 2, 1500)
    rows = [(i, [float(v) for v in x[i]], int(label[i])) for i in range(1500)]
    rows += [(2000, None, 0), (2001, [0.0] * 24, 0), (2002, rows[5][1], None), (2003, rows[5][1], rows[5][2]), (2003, rows[5][1], rows[5][2])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r for r in small_world.near_duplicate_vectors(df, shard_rows=400, block_queries=500).collect()}
    ids = [*range(1500), 2003]
    v = np.array([x[i] if i < 1500 else x[5] for i in ids])
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    lab = np.array([label[i] if i < 1500 else label[5] for i in ids])
    link = (v @ v.T >= 0.93) & (lab[:, None] == lab[None, :])
    np.fill_diagonal(link, False)
    deg = link.sum(axis=1)
    mine = np.array([got[i].n_links for i in ids])
    assert (mine <= deg).all() and mine.sum() >= 0.98 * deg.sum()
    a, b = np.nonzero(link)
    root = small_world.forest(a, b, len(ids))
    assert np.mean([got[i].component_id == ids[root[k]] for k, i in enumerate(ids)]) > 0.98
    assert all(got[i].n_links == 0 and got[i].kept for i in (2000, 2001, 2002)) and len(got) == 1504
    assert small_world.near_duplicate_vectors(df.limit(0)).count() == 0
