"""Queries do the whole of their jobs: texts, rows and planes beyond what small inputs show."""

import numpy as np


def test_glyph_pairs_count_whole_texts(spark, tmp_path):
    from gridpress.sources.cubes import glyph_pairs_cells

    texts = [("en", "ab" * 3000), ("en", "x" * 2500 + "Ä漢😀"), ("de", "a"), ("de", None), (None, "zz")]
    spark.createDataFrame(texts, "lang string, text string").write.parquet(str(tmp_path / "documents.parquet"))
    want: dict = {}
    for lang, t in texts:
        code = [min(255, ord(c)) for c in (t or "").lower()]
        for pair in zip(code, code[1:]):
            want[(lang, *pair)] = want.get((lang, *pair), 0) + 1
    assert {(r.lang, r.left, r.right): r.v for r in glyph_pairs_cells(spark, str(tmp_path)).collect()} == want


def test_rank_cut_codes_cover_the_whole_matrix(spark, tmp_path):
    from gridpress.baselines import rank_cut
    from gridpress.catalogue import QUERIES

    a = np.random.default_rng(5).normal(0, 1, (1100, 6))
    a[512:] *= np.arange(1, 7)
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(a.astype(np.float32))]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    codes = [rank_cut.compress(a.astype(np.float32)[i : i + 512].astype(float), energy_tail=0.05).codes.ravel() for i in range(0, 1100, 512)]
    got = {r.code: r.n for r in QUERIES["rank_cut_codes"](spark, str(tmp_path)).collect()}
    v, n = np.unique(np.concatenate(codes), return_counts=True)
    assert len(codes) == 3 and got == dict(zip(v.tolist(), n.tolist()))


def test_centroids_of_all_planes(spark):
    from gridpress.workloads import w4_centroids

    rows = w4_centroids(spark, "/root/testdata/sf0.001").collect()
    assert [r.plane for r in rows] == list(range(63, -1, -1)) and any(r.ones for r in rows if r.plane < 40)
