import numpy as np
import pyarrow as pa

from gridpress.llm import darts
from gridpress.llm.textkernels import Words, shingles, text_bytes


def test_agreement_is_weighted_similarity():
    e = np.array([7, 9, 7, 9], np.uint64)
    c = darts.cells(e, np.array([0, 0, 1, 1]), np.array([2.5, 1.0, 1.25, 2.0]))
    s = darts.signatures(c[0], c[1], 2, 4000, c[2])
    assert abs((s[0] == s[1]).mean() - 2.25 / 4.5) < 0.05


def test_words_like_split():
    texts = ["", "  a  bb\tc\n", None, "d", "é x", ""]
    w = Words(*text_bytes(pa.array(texts)))
    assert np.diff(w.first).tolist() == [0, 3, 0, 1, 2, 0]
    _, doc = shingles(w)
    assert np.bincount(doc, minlength=6).tolist() == [0, 1, 0, 1, 1, 0]


def brute(texts):
    sets = {i: {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if (w := (t or "").lower().split()) else set() for i, t in texts.items()}
    root = {i: i for i in texts}
    for _ in texts:
        for a in texts:
            for b in texts:
                if sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                    root[a] = root[b] = min(root[a], root[b])
    return root


def test_classes_equal_brute_force(spark, prose):
    base = prose(120).split()
    texts = {}
    for i in range(24):  # a chain of edits: neighbours alike, ends not
        if i % 3 == 2:
            base = base[: 5 * i] + ["new", str(i)] + base[5 * i + 2 :]
        texts[i] = " ".join(base)
    for i in range(24, 40):
        texts[i] = prose(60)
    texts |= {40: None, 41: "", 42: "two words", 43: "Two  words", 44: texts[30]}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in darts.near_duplicates(df).collect()}
    assert got == brute(texts)


def test_messy(spark, messy):
    got = {r.doc_id: r for r in darts.near_duplicates(messy).collect()}
    assert set(got) == {1, 2, 3, 4, 5, 6}
    assert got[5].class_id == 1 and got[2].kept and got[3].kept and got[6].kept
    assert darts.near_duplicates(messy.limit(0)).count() == 0
    assert darts.near_duplicates(messy, weights="count").where("doc_id = 5").first().class_id == 1


def test_large_weights_cost_by_element_not_by_weight():
    rng = np.random.default_rng(3)
    e = np.arange(1, 1001, dtype=np.uint64)
    w = rng.uniform(50_000, 200_000, (2, 1000))
    c = darts.cells(np.tile(e, 2), np.repeat([0, 1], 1000), w.ravel())
    assert len(c[0]) < 2000 * 20
    s = darts.signatures(c[0], c[1], 2, 4000, c[2])
    assert abs((s[0] == s[1]).mean() - np.minimum(*w).sum() / np.maximum(*w).sum()) < 0.04


def counted_brute(texts):
    from collections import Counter

    bags = {i: Counter(tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))) if (w := (t or "").lower().split()) else Counter() for i, t in texts.items()}
    root = {i: i for i in texts}
    for _ in texts:
        for a in texts:
            for b in texts:
                if bags[a] and bags[b] and (bags[a] & bags[b]).total() >= 0.8 * (bags[a] | bags[b]).total():
                    root[a] = root[b] = min(root[a], root[b])
    return root


def test_counts_as_weights_equal_brute_force(spark, prose):
    texts = {}
    for i in range(8):
        head, line = prose(30), prose(12)
        for j, times in enumerate((1, 2, 3, 9, 10, 11)):  # alike as sets, unlike by counts until the line rules
            texts[10 * i + j] = " ".join([head, *[line] * times])
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in darts.near_duplicates(df, weights="count").collect()}
    assert got == counted_brute(texts) and len(set(got.values())) > 8


def test_group_alike_to_its_original_and_not_to_each_other(spark, prose):
    """Edits on either side of the threshold: members apart from the hub are found by the exact join."""
    import random

    rng = random.Random(11)
    base = prose(90).split()
    texts = {0: " ".join(base)}
    for i in range(1, 90):
        own = list(base)
        for at in rng.sample(range(90), rng.choice((1, 2, 3, 4, 5))):
            own[at] = f"edit{rng.randint(0, 12)}"
        texts[i] = " ".join(own[: rng.choice((90, 90, 74))])
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    want = brute(texts)
    assert {r.doc_id: r.class_id for r in darts.near_duplicates(df).collect()} == want
    assert len(set(want.values())) > 3


def test_texts_of_one_id_are_one_class(spark, prose):
    a, b, c = prose(40), prose(40), prose(40)
    rows = [(5, a), (5, b), (2, b), (7, a), (9, c), (9, None)]
    got = {r.doc_id: (r.class_id, r.class_size) for r in darts.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {5: (2, 3), 2: (2, 3), 7: (2, 3), 9: (9, 1)}
