"""Weighted minwise signatures from hashed darts, and near-duplicate classes from them.

Each element owns a strip of a board, as wide as its weight, and hashing alone
decides where darts fall on it: at rank r (a Poisson stream in rank for each
unit of width), each for one of k coordinates.  A signature keeps, for each
coordinate, the dart of least rank that falls within the document's strips; two
documents agree on a coordinate with the probability of their weighted Jaccard
similarity.  Only about k (ln k + c) darts of a document are ever thrown, so
signatures cost its elements plus that, and not elements times k.

A strip of weight w is cut at 1, 2, 4, 8 and so on, so it has about log w pieces.
Ranks on a piece of width s come s times as densely, and the last piece is met
in part: a dart there counts if its position is within what w covers.  Work thus
follows the number of elements and of darts, not the sum of the weights.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.llm.components import components
from gridpress.llm.textkernels import GOLD, U64, Words, mix, pieces, powers, sequence_keys, shingles, stream, text_bytes
from gridpress.session import arrow_rows, cut, ship

COORDINATES, BANDS, BAND_ROWS = 125, 25, 5
WIDTH, THRESHOLD, ESTIMATE_SLACK = 5, 0.8, 0.2


def cells(elem: np.ndarray, doc: np.ndarray, weight: np.ndarray, unit: float = 1.0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pieces of the strips of weighted elements: hash, document, and (width, share met) by row.

    Pieces end at unit, 2 unit, 4 unit ...; weights far under the unit cost idle darts, so choose it by the least weight.
    """
    levels = 1 + np.ceil(np.log2(np.maximum(weight / unit, 1.0))).astype(np.int64)
    at = np.repeat(np.arange(len(elem)), levels)
    number = np.arange(len(at)) - np.repeat(np.cumsum(levels) - levels, levels)
    start = np.where(number > 0, unit * 2.0 ** (number - 1), 0.0)
    wide = np.where(number > 0, start, unit)
    with np.errstate(over="ignore"):
        return mix(elem[at] + number.astype(U64) * GOLD), doc[at], np.column_stack([wide, np.minimum(1.0, (weight[at] - start) / wide)])


def signatures(elem: np.ndarray, doc: np.ndarray, n_docs: int, k: int = COORDINATES, width: np.ndarray | None = None) -> np.ndarray:
    """k dart hashes for each document from its pieces; 0 throughout for a document without any.

    Rows of one document are together.  Repeated pieces met whole throw the same
    darts, so they change nothing.  Without widths all pieces are whole units.
    """
    best = np.full(n_docs * k, np.inf)
    sig = np.zeros(n_docs * k, U64)
    met = None if width is None else width[:, 0] * width[:, 1]
    size = np.bincount(doc, met, minlength=n_docs) if len(doc) else np.zeros(n_docs)
    bound = np.where(size > 0, k * (np.log(k) + 3.0) / np.where(size > 0, size, 1.0), 0.0)
    todo = size > 0
    while todo.any():
        act = np.flatnonzero(todo[doc])
        rank, count = np.zeros(len(act)), 0
        thrown: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        own = elem[act]
        with np.errstate(over="ignore"):
            while len(act):
                count += 1
                x = mix(own + U64(count) * GOLD)
                gap = -np.log(((x >> U64(11)).astype(np.float64) + 0.5) * 2.0**-53)
                rank = rank + (gap if width is None else gap / width[act, 0])
                d = doc[act]
                keep = rank <= bound[d]
                act, own, rank, x, d = act[keep], own[keep], rank[keep], x[keep], d[keep]
                y = mix(x ^ GOLD)
                key = d * k + (((y >> U64(32)) * U64(k)) >> U64(32)).astype(np.int64)
                if width is None:
                    hit = slice(None)
                else:
                    hit = (mix(y) >> U64(11)).astype(np.float64) * 2.0**-53 < width[act, 1]
                np.minimum.at(best, key[hit], rank[hit])
                thrown.append((key[hit], rank[hit], y[hit]))
        for key, r, y in thrown:
            won = best[key] == r
            sig[key[won]] = y[won] | U64(1)
        todo &= ~np.isfinite(best.reshape(n_docs, k)).all(axis=1)
        bound = np.where(todo, bound * 2, bound)
    return sig.reshape(n_docs, k)


def band_keys(sig: np.ndarray, bands: int = BANDS, rows: int = BAND_ROWS) -> np.ndarray:
    with np.errstate(over="ignore"):
        cut_ = sig[:, : bands * rows].reshape(len(sig), bands, rows) * powers(U64(int(stream(1, 67)[0]) | 1), rows)
        return mix(cut_.sum(axis=2, dtype=U64) + np.arange(bands, dtype=U64) * GOLD)


def weighted(elem: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct elements of each document with their counts, sorted by (document, element)."""
    order = np.lexsort((elem, doc))
    e, d = elem[order], doc[order]
    new = np.ones(len(e), bool)
    new[1:] = (e[1:] != e[:-1]) | (d[1:] != d[:-1])
    at = np.flatnonzero(new)
    return e[at], d[at], np.diff(np.append(at, len(e)))


def sketch_texts(texts: pa.Array, counted: bool = False, k: int = COORDINATES, bands: int = BANDS, rows: int = BAND_ROWS):
    """Per text: shingle count, two sequence keys, band keys and one byte of each coordinate."""
    for lo, hi in pieces(texts):
        w = Words(*text_bytes(texts[lo:hi], lower=True))
        elem, doc = shingles(w, WIDTH)
        n = np.bincount(doc, minlength=hi - lo)
        k1, k2 = sequence_keys(w)
        if counted:
            elem, doc, c = weighted(elem, doc)
        elem, doc, width = cells(elem, doc, c.astype(np.float64) if counted else np.ones(len(elem)))
        sig = signatures(elem, doc, hi - lo, k, width)
        yield lo, hi, n, k1, k2, band_keys(sig, bands, rows), (sig >> U64(56)).astype(np.uint8)


def sketches(docs: DataFrame, id_col: str, text_col: str, counted: bool) -> DataFrame:
    ship(docs.sparkSession)
    arrow_rows(docs.sparkSession)

    def run(batches):
        for b in batches:
            ids, texts = b.column("doc_id"), b.column("_text")
            for lo, hi, n, k1, k2, bands, sig in sketch_texts(texts, counted):
                m = hi - lo
                yield pa.RecordBatch.from_arrays(
                    [
                        ids[lo:hi],
                        pa.array(n, pa.int64()),
                        pa.array(k1.view(np.int64)),
                        pa.array(k2.view(np.int64)),
                        pa.ListArray.from_arrays(pa.array(np.arange(m + 1, dtype=np.int32) * bands.shape[1]), pa.array(bands.view(np.int64).ravel())),
                        pa.array([r.tobytes() for r in sig], pa.binary()),
                    ],
                    names=["doc_id", "n", "k1", "k2", "bands", "sig"],
                )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(run, "doc_id long, n long, k1 long, k2 long, bands array<long>, sig binary")


def shingle_sets(docs: DataFrame, id_col: str, text_col: str, counted: bool) -> DataFrame:
    """(k1, k2, set) by text: its sequence keys and its distinct shingles as sorted 64-bit words.

    Counted, the second and later occurrences of a shingle are words of their own, so the
    overlap of two sets is the sum of the lesser counts.
    """

    def run(batches):
        for b in batches:
            texts = b.column("_text")
            for lo, hi in pieces(texts):
                w = Words(*text_bytes(texts[lo:hi], lower=True))
                k1, k2 = sequence_keys(w)
                e, d, c = weighted(*shingles(w, WIDTH))
                if counted:
                    nth = np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c)
                    with np.errstate(over="ignore"):
                        e, d = np.where(nth > 0, mix(np.repeat(e, c) ^ (nth.astype(U64) * GOLD)), np.repeat(e, c)), np.repeat(d, c)
                    e = e[np.lexsort((e, d))]
                edge = np.searchsorted(d, np.arange(hi - lo + 1))
                sets = [e[i:j].tobytes() for i, j in zip(edge, edge[1:], strict=False)]
                yield pa.RecordBatch.from_arrays([pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.array(sets, pa.binary())], names=["k1", "k2", "set"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(run, "k1 long, k2 long, set binary")


def jaccard(x: bytes, y: bytes) -> float:
    a, b = np.frombuffer(x, U64), np.frombuffer(y, U64)
    same = len(np.intersect1d(a, b, assume_unique=True))
    return same / max(1, len(a) + len(b) - same)


def _estimated(pairs: DataFrame, reps: DataFrame, threshold: float) -> DataFrame:
    """Pairs whose signatures do not rule out the threshold, five deviations below it."""
    sig = reps.select("node", "sig")
    j = pairs.join(sig.withColumnRenamed("node", "a").withColumnRenamed("sig", "sa"), "a").join(sig.withColumnRenamed("node", "b").withColumnRenamed("sig", "sb"), "b")

    def run(batches):
        for t in batches:
            if not len(t):
                continue
            a, b = (np.frombuffer(b"".join(t.column(c).to_pylist()), np.uint8).reshape(len(t), -1) for c in ("sa", "sb"))
            ok = (a == b).mean(axis=1) >= threshold - ESTIMATE_SLACK
            yield t.select(["a", "b"]).filter(pa.array(ok))

    return j.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def _verified(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    j = pairs.join(sets.withColumnRenamed("node", "a").withColumnRenamed("set", "x"), "a").join(sets.withColumnRenamed("node", "b").withColumnRenamed("set", "y"), "b")

    def run(batches):
        for t in batches:
            ok = [jaccard(x, y) >= threshold for x, y in zip(t.column("x").to_pylist(), t.column("y").to_pylist(), strict=True)]
            yield t.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return j.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _listed(sets: DataFrame) -> DataFrame:
    """(node, e): one row for each shingle of each set."""

    def run(batches):
        for t in batches:
            for node, x in zip(t.column("node").to_pylist(), t.column("set").to_pylist(), strict=True):
                e = np.frombuffer(x, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(e), node)), pa.array(e)], names=["node", "e"])

    return sets.select("node", "set").mapInArrow(run, "node long, e long")


def _prefix_pairs(sets: DataFrame, roots: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) of sets in different classes that can be as alike as the threshold; no such pair is left out.

    Shingles are put in one order, rarest first.  Two sets that are alike share a shingle
    near the start of both, and where the first shared one stands bounds what can follow:
    sets with many shingles of their own meet nobody, whatever bands they share.
    """
    t = float(threshold)
    shared = cut(_listed(sets).groupBy("e").agg(F.count("*").alias("f")).where("f > 1"))
    ranked = _listed(sets).join(shared, "e").groupBy("node").agg(F.sort_array(F.collect_list(F.struct("f", "e"))).alias("es"))
    size = sets.join(roots, "node").select("node", "root", (F.octet_length("set") / 8).cast("long").alias("n"))
    # shingles of one set alone come first; a small allowance keeps products like 0.8 * 35 from rounding up
    lone = F.col("n") - F.size("es")
    reach = F.col("n") - F.ceil(F.lit(t) * F.col("n") - 1e-9) + 1
    short = F.col("n") - F.ceil(F.lit(2 * t / (1 + t)) * F.col("n") - 1e-9) + 1
    near = ranked.join(size, "node").withColumn("lone", lone).withColumn("near", (reach - lone).cast("int")).where("near > 0")
    # one list an entry: (place, shingle) of the prefix, and whether it is in the shorter prefix that a smaller set needs
    spread = near.select("node", "root", "n", "lone", short.alias("short"), F.posexplode(F.slice("es", 1, F.col("near"))).alias("k", "fe"))
    entry = cut(spread.select(F.col("fe.e").alias("e"), "node", "root", "n", (F.col("lone") + F.col("k")).alias("at"), (F.col("lone") + F.col("k") < F.col("short")).alias("early")))
    x = entry.where("early").select("e", *(F.col(c).alias(f"{c}_x") for c in ("node", "root", "n", "at")))
    y = entry.select("e", *(F.col(c).alias(f"{c}_y") for c in ("node", "root", "n", "at")))
    most = F.least(F.col("n_x") - F.col("at_x"), F.col("n_y") - F.col("at_y"))
    meet = (
        (x["e"] == y["e"])
        & (F.struct("n_x", "node_x") < F.struct("n_y", "node_y"))
        & (F.col("root_x") != F.col("root_y"))
        & (F.col("n_x") >= F.lit(t) * F.col("n_y") - 1e-9)
        & (most >= F.lit(t / (1 + t)) * (F.col("n_x") + F.col("n_y")) - 1e-9)
    )
    return x.join(y, meet).select(F.greatest("node_x", "node_y").alias("a"), F.least("node_x", "node_y").alias("b")).distinct()


def _one_document(keyed: DataFrame, reps: DataFrame) -> DataFrame:
    """Links (a, b) between the different texts of one id."""
    key = F.struct("k1", "k2")
    several = keyed.groupBy("doc_id").agg(F.min(key).alias("lo"), F.max(key).alias("hi")).where("lo != hi").select("doc_id")
    texts = keyed.select("doc_id", "k1", "k2").join(several, "doc_id").join(reps.select("k1", "k2", "node"), ["k1", "k2"])
    ends = texts.groupBy("doc_id").agg(F.min("node").alias("b"))
    return texts.join(ends, "doc_id").where("node != b").select(F.col("node").alias("a"), "b").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, weights: str = "set") -> DataFrame:
    """doc_id, class_id, class_size, kept: classes of documents linked by similarity of five-word shingles.

    weights "set" gives each shingle weight 1, "count" its count.  Words are split
    at ASCII blanks, in lower case.  Texts of the same words form one
    representative; representatives meet in bands of dart signatures.  Each member
    of a band's bucket is tested against the bucket's hub, the member that meets
    most others over all bands: the text that copies were made of.  Members of
    buckets that still hold more than one class are then joined exactly, by the
    prefixes of their shingles in order of rarity, across classes only.  No step
    pairs all members of a bucket, and none has a cap.

    Cases: a null or wordless text is a class of its own; fewer than five words
    make one shingle; repeated rows of one id are one document; different texts
    under one id are that document's texts, so they and their classes are one class;
    a null id is left out.
    """
    counted = weights == "count"
    slim = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_t")).where("_id is not null")
    sk = cut(sketches(slim, "_id", "_t", counted))
    keyed = sk.where("n > 0")
    # node numbers are fixed by the write; ties below go by the keys of the texts
    first = keyed.groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "bands", "sig")).alias("r"))
    reps = cut(first.select(F.monotonically_increasing_id().alias("node"), "k1", "k2", "r.*"))
    members = reps.select("node", "k1", F.explode("bands").alias("band"))
    full = members.groupBy("band").agg(F.count("*").alias("c")).where("c > 1")
    buckets = cut(members.join(full, "band"))
    meets = buckets.groupBy("node").agg(F.sum("c").alias("met"))
    hubs = buckets.join(meets, "node").groupBy("band").agg(F.max(F.struct("met", "k1", "node")).alias("h")).select("band", F.col("h.node").alias("hub"))
    pairs = buckets.join(hubs, "band").where("node != hub").select(F.greatest("node", "hub").alias("a"), F.least("node", "hub").alias("b")).distinct()
    met = cut(buckets.select("node").distinct())
    texts = slim.join(reps.join(met, "node").select(F.col("doc_id").alias("_id")).distinct(), "_id", "left_semi")
    of = reps.join(met, "node").select("node", "k1", "k2")
    sets = cut(shingle_sets(texts, "_id", "_t", counted).join(of, ["k1", "k2"]).groupBy("node").agg(F.min("set").alias("set")))
    links = cut(_verified(_estimated(pairs, reps, threshold), sets, threshold).union(_one_document(keyed, reps)))
    roots = components(links)
    rooted = lambda nodes: nodes.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    apart = rooted(buckets.select("band", "node")).groupBy("band").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo != hi").select("band")
    open_ = cut(rooted(buckets.join(apart, "band", "left_semi").select("node").distinct()))
    if not open_.isEmpty():
        left = cut(sets.join(open_.select("node"), "node", "left_semi"))
        more = cut(_verified(_prefix_pairs(left, open_, threshold), left, threshold))
        if not more.isEmpty():
            roots = components(links.union(more))
    place = rooted(reps.select("k1", "k2", "node")).select("k1", "k2", "root")
    placed = keyed.select("doc_id", "k1", "k2").join(place, ["k1", "k2"]).groupBy("doc_id").agg(F.min("root").alias("root"))
    alone = sk.where("n = 0").select("doc_id").distinct().join(placed, "doc_id", "left_anti").select("doc_id", F.col("doc_id").alias("class_id"), F.lit(1).cast("long").alias("class_size"))
    # written down, so that the join can deal out a class of very many members
    named = cut(placed.groupBy("root").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("class_size")))
    every = placed.join(named, "root").select("doc_id", "class_id", "class_size").union(alone)
    return every.withColumn("kept", F.col("doc_id") == F.col("class_id"))
