import random
import zlib

import numpy as np
import pyarrow as pa

from gridpress.llm import pu_quality, toxicity


def test_prior_and_held_out_accuracy(spark, prose):
    rng = random.Random(1)
    rows, labels = [], []
    for i in range(900):
        good = rng.random() < 0.7
        text = prose(60) if good else " ".join(w.upper() + "!!" for w in prose(60).split())
        rows.append((i, text))
        if i % 2:
            labels.append((i, int(good), 0))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    marks = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    fit = pu_quality.fit_quality(docs, marks)
    assert 0.55 < fit[1] < 0.85
    got = pu_quality.score_quality(docs, fit).join(marks, "doc_id").where("held_out").collect()
    assert len(got) > 50 and np.mean([r.predicted == r.quality for r in got]) > 0.97


def test_toxic_words_are_found(spark, prose):
    rng = random.Random(2)
    rows, labels = [], []
    for i in range(700):
        words = prose(rng.randint(10, 120)).split()
        bad = i % 4 == 0
        if bad:
            for w in ("vilegrub", "vilemuck", "vileslop"):
                words.insert(rng.randint(0, len(words)), w)
        rows.append((i, " ".join(words)))
        labels.append((i, 1, int(bad)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    marks = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    net = toxicity.fit_toxicity(docs, marks)
    got = toxicity.score_toxicity(docs, net).join(marks, "doc_id").where("held_out").collect()
    assert len(got) > 80 and np.mean([r.predicted == r.toxic for r in got]) > 0.95
    assert toxicity.drop_toxic(docs, net).count() < 560


def test_gradients():
    rng = np.random.default_rng(0)
    net = toxicity.Network(1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    x = rng.normal(0, 1, (3, toxicity.WINDOW, toxicity.UNITS))
    mask = (np.arange(toxicity.WINDOW) < np.array([24, 5, 10])[:, None]).astype(float)
    _, kept = net.forward(x, mask, keep=True)
    g, _ = net.back(np.ones(3), kept)
    for name in ("f_in", "b_rec", "att", "out", "f_b"):
        w = net.p[name]
        at = (0,) * w.ndim
        old, ends = w[at], []
        for step in (1e-3, -1e-3):
            w[at] = old + step
            ends.append(net.forward(x, mask).sum())
        w[at] = old
        assert abs((ends[0] - ends[1]) / 2e-3 - g[name][at]) < 1e-3


def test_windows_cover_every_word():
    doc, start, held = toxicity.windows(np.array([0, 0, 5, 100]))
    assert doc[0] == 0 and held[0] == 0
    seen = set()
    for d, s, n in zip(doc, start, held, strict=True):
        seen |= set(range(s, s + n))
    assert seen == set(range(100))


def test_messy(spark, messy):
    labels = spark.createDataFrame([(1, 1, 0), (2, None, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert pu_quality.score_quality(messy, pu_quality.fit_quality(messy, labels)).count() == 8
    assert toxicity.score_toxicity(messy, toxicity.fit_toxicity(messy, labels)).count() == 8
    none = messy.limit(0)
    assert pu_quality.fit_quality(none, labels) is None and toxicity.fit_toxicity(none, labels) is None
    assert np.isfinite(pu_quality.features(pa.array([None, "", " ", "x"]))).all()


def test_long_labelled_texts_are_learnt_from(spark, monkeypatch):
    rows = [(i, ("plain words here " * 300 + "vile " * 40) if i % 3 == 0 else "plain words here") for i in range(60)]
    assert min(len(t) for i, t in rows if i % 3 == 0) > 3000
    labels = spark.createDataFrame([(i, 1, int(i % 3 == 0)) for i, _ in rows], "doc_id long, quality int, toxic int")
    met, train = [], toxicity.train
    monkeypatch.setattr(toxicity, "train", lambda texts, y: met.append((len(texts), int(y.sum()))) or train(texts, y))
    assert toxicity.fit_toxicity(spark.createDataFrame(rows, "doc_id long, text string"), labels) is not None
    learnt = [i for i, _ in rows if zlib.crc32(str(i).encode()) % 5]
    assert met == [(len(learnt), sum(i % 3 == 0 for i in learnt))]


def test_queries_on_the_given_table(spark):
    """Held-out accuracy of both queries over whole documents and labels."""
    from gridpress.llm.queries import QUERIES

    small = "/root/testdata/sf0.01"
    labels = {r.doc_id: r for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    n = spark.read.parquet(f"{small}/documents.parquet").count()
    for name, column, least in (("op1_pu_quality", "quality", 0.97), ("op8_toxicity", "toxic", 0.93)):
        rows = QUERIES[name](spark, small).collect()
        assert len(rows) == n and all(0 <= r.score <= 1 for r in rows)
        assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
        held = [(r.predicted, labels[r.doc_id][column]) for r in rows if r.held_out and r.doc_id in labels and labels[r.doc_id][column] is not None]
        assert len(held) > 40 and np.mean([a == b for a, b in held]) >= least, name
