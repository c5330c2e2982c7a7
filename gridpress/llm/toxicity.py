"""Toxicity scorer: a bidirectional gated recurrent network with attention pooling.

Each word enters with LEARNED trained units (its hashed word vector plus the
pooled vectors of its hashed character 4-grams, edges marked) and with ODDS
units: the shrunken log-odds of the word, of its first 5 and 8 bytes, and the
mean and the most of its 4-grams.  In training a text's odds come from other
folds than its own, so the network meets words as it will meet them later.  Windows of WINDOW words, starting
every STRIDE words, run through both directions; attention pools the states and
a logit scores the window.  A text's score is that of its worst window, and all
windows of the whole text are scored.

Training is in numpy on a bounded sample: labels belong to texts, so each round
picks the worst windows of every text under the current model and learns on
those (word log-odds serve as the model before the first round).  Rounds go over
the whole texts in pieces and hold tokens of one piece and of chosen windows.

Cases: null and wordless texts have one empty window, scored like any other;
without both labels to learn from all scores are 0.
"""

from __future__ import annotations

import gc

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.llm.labelled import held_out, labelled_ids, sample_texts
from gridpress.llm.textkernels import GOLD, U64, Words, mix, pieces, text_bytes
from gridpress.session import arrow_rows, ship

TOXIC, CLEAN = 1200, 2000
TRAIN_PIECE = 1 << 19
WINDOW, STRIDE = 24, 12
ODDS, LEARNED = 5, 3
UNITS, WORD_BITS, GRAM_BITS, ODDS_BITS = ODDS + LEARNED, 15, 15, 17
ROUNDS, EPOCHS, BATCH, FOLDS, SHRINK = 3, 3, 256, 8, 8.0
THRESHOLD = 0.5
f32 = np.float32


def _bucket(h: np.ndarray) -> np.ndarray:
    return (h >> U64(64 - ODDS_BITS)).astype(np.int32)


class Tokens:
    """Hashes of words, of their first bytes and of their character grams, of a piece of texts."""

    __slots__ = ("first", "gram", "gram_at", "gram_n", "starts", "word")

    def __init__(self, offsets: np.ndarray, data: np.ndarray):
        w = Words(offsets, data)
        self.first, self.word = w.first, _bucket(w.hash)
        n = w.end - w.start
        # grams start at the edge before the word and at each byte but the last two; short words give one
        self.gram_n = np.maximum(n - 1, 1)
        self.gram_at = np.cumsum(self.gram_n) - self.gram_n
        total = int(self.gram_n.sum())
        gram, self.gram, self.starts = np.zeros(total, U64), np.zeros(total, np.int32), []
        if not total:
            self.starts = [self.word, self.word]
            return
        inside = np.arange(total) - np.repeat(self.gram_at, self.gram_n)
        start, end = np.repeat(w.start, self.gram_n), np.repeat(w.end, self.gram_n)
        at = start + inside - 1
        with np.errstate(over="ignore"):
            for t in range(4):
                p = at + t
                here = np.where((p >= start) & (p < end), data[np.clip(p, 0, len(data) - 1)], np.uint8(0))
                gram = gram * U64(257) + here.astype(U64) + U64(1)
            self.gram = _bucket(mix(gram * GOLD))
            code = np.zeros(len(n), U64)
            for t in range(8):
                p = w.start + t
                code = code * U64(257) + np.where(p < w.end, data[np.minimum(p, len(data) - 1)], np.uint8(0)).astype(U64)
                if t in (4, 7):
                    self.starts.append(_bucket(mix(code * GOLD + U64(t))))

    def buckets(self) -> list[np.ndarray]:
        """Buckets of the odds tables: word, first bytes twice, grams."""
        return [self.word, *self.starts, self.gram]

    def odds(self, tables: list[np.ndarray], shift: np.ndarray | int = 0) -> np.ndarray:
        """ODDS units of each word from tables by the same kinds; shift is where each word's table starts in stacked ones."""
        if not len(self.word):
            return np.zeros((0, ODDS), f32)
        b = [x + shift for x in self.buckets()[:3]]
        b.append(self.gram + (np.repeat(shift, self.gram_n) if np.ndim(shift) else shift))
        g = tables[3][b[3]]
        return np.stack([tables[0][b[0]], tables[1][b[1]], tables[2][b[2]], np.add.reduceat(g, self.gram_at) / self.gram_n.astype(f32), np.maximum.reduceat(g, self.gram_at)], axis=1)

    def learned(self, words: np.ndarray, grams: np.ndarray) -> np.ndarray:
        if not len(self.word):
            return np.zeros((0, LEARNED), f32)
        pooled = np.add.reduceat(grams[self.gram >> (ODDS_BITS - GRAM_BITS)], self.gram_at, axis=0)
        return words[self.word >> (ODDS_BITS - WORD_BITS)] + pooled / np.sqrt(self.gram_n)[:, None].astype(f32)


def windows(first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, first word, words) of all overlapping windows; each document has one at least."""
    count = np.diff(first)
    n = 1 + np.maximum(0, -(-(count - WINDOW) // STRIDE))
    doc = np.repeat(np.arange(len(count)), n)
    k = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
    start = first[:-1][doc] + k * STRIDE
    return doc, start, np.minimum(WINDOW, first[1:][doc] - start)


def _sig(x: np.ndarray) -> np.ndarray:
    return f32(1) / (f32(1) + np.exp(-np.clip(x, -30, 30)))


class Network:
    """Parameters in one dict; words/grams are embeddings, f_ and b_ the two directions."""

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        g = lambda *s, a=0.3: rng.normal(0, a, s).astype(f32)
        u = UNITS
        self.odds: list[np.ndarray] = []
        self.p = {"words": g(1 << WORD_BITS, LEARNED, a=0.02), "grams": g(1 << GRAM_BITS, LEARNED, a=0.02), "att": g(2 * u, 1), "out": g(4 * u, 1), "bias": np.zeros(1, f32)}
        for d in "fb":
            self.p |= {f"{d}_in": g(u, 3 * u), f"{d}_rec": g(u, 3 * u), f"{d}_b": np.zeros(3 * u, f32)}

    def forward(self, x: np.ndarray, mask: np.ndarray, keep: bool = False):
        """x: windows x WINDOW x UNITS; mask marks words.  Returns logits (and what back needs)."""
        p, u = self.p, UNITS
        n, t, _ = x.shape
        states, memory = [], {}
        for d in "fb":
            pre = x.reshape(-1, u) @ p[f"{d}_in"] + p[f"{d}_b"]
            pre = pre.reshape(n, t, 3 * u)
            h = np.zeros((n, u), f32)
            hs = np.zeros((n, t, u), f32)
            trail = []
            for i in range(t) if d == "f" else range(t - 1, -1, -1):
                rec = h @ p[f"{d}_rec"]
                zr = _sig(pre[:, i, : 2 * u] + rec[:, : 2 * u])
                z, r = zr[:, :u], zr[:, u:]
                c = np.tanh(pre[:, i, 2 * u :] + r * rec[:, 2 * u :])
                m = mask[:, i, None]
                new = h + m * z * (c - h)
                if keep:
                    trail.append((i, h, z, r, c, rec[:, 2 * u :]))
                h = new
                hs[:, i] = h
            states.append(hs)
            memory[d] = trail
        s = np.concatenate(states, axis=2)
        e = (s @ p["att"])[:, :, 0]
        e = np.where(mask > 0, e, f32(-1e9))
        a = np.exp(e - e.max(axis=1, keepdims=True)) * mask
        a = a / np.maximum(a.sum(axis=1, keepdims=True), f32(1e-6))
        pooled = np.einsum("nt,ntu->nu", a, s)
        peak = np.where(mask[:, :, None] > 0, s, f32(-1)).max(axis=1)
        both = np.concatenate([pooled, peak], axis=1)
        logit = (both @ p["out"])[:, 0] + p["bias"][0]
        return (logit, (x, mask, s, a, both, peak, memory)) if keep else logit

    def back(self, slope: np.ndarray, kept) -> tuple[dict[str, np.ndarray], np.ndarray]:
        """Gradients of the parameters and of x for slopes of the logits."""
        p, u = self.p, UNITS
        x, mask, s, a, both, peak, memory = kept
        n, t, _ = x.shape
        g = {"out": both.T @ slope[:, None], "bias": slope.sum(keepdims=True)}
        db = slope[:, None] * p["out"].T
        dpool, dpeak = db[:, : 2 * u], db[:, 2 * u :]
        ds = a[:, :, None] * dpool[:, None, :]
        da = np.einsum("ntu,nu->nt", s, dpool)
        de = a * (da - (a * da).sum(axis=1, keepdims=True))
        ds += de[:, :, None] * p["att"][:, 0]
        g["att"] = np.einsum("ntu,nt->u", s, de)[:, None]
        hit = (s == peak[:, None, :]) & (mask[:, :, None] > 0)
        ds += hit * dpeak[:, None, :]
        dx = np.zeros_like(x)
        for k, d in enumerate("fb"):
            part = ds[:, :, k * u : (k + 1) * u]
            dpre = np.zeros((n, t, 3 * u), f32)
            drec = np.zeros_like(p[f"{d}_rec"])
            dh = np.zeros((n, u), f32)
            for i, h, z, r, c, rc in reversed(memory[d]):
                dh = dh + part[:, i]
                m = mask[:, i, None]
                dz = dh * m * (c - h) * z * (1 - z)
                dc = dh * m * z * (1 - c * c)
                dr = dc * rc * r * (1 - r)
                dpre[:, i, :u], dpre[:, i, u : 2 * u], dpre[:, i, 2 * u :] = dz, dr, dc
                into = np.concatenate([dz, dr, dc * r], axis=1)
                drec += h.T @ into
                dh = dh * (1 - m * z) + into @ p[f"{d}_rec"].T
            flat = dpre.reshape(-1, 3 * u)
            g |= {f"{d}_in": x.reshape(-1, u).T @ flat, f"{d}_b": flat.sum(axis=0), f"{d}_rec": drec}
            dx += (flat @ p[f"{d}_in"].T).reshape(n, t, u)
        return g, dx

    def vectors(self, tok: Tokens) -> np.ndarray:
        return np.concatenate([tok.odds(self.odds), tok.learned(self.p["words"], self.p["grams"])], axis=1)

    def score_windows(self, vec: np.ndarray, start: np.ndarray, held: np.ndarray, block: int = 4096) -> np.ndarray:
        out = np.zeros(len(start), f32)
        vec = np.concatenate([vec, np.zeros((1, UNITS), f32)])
        for i in range(0, len(start), block):
            at = start[i : i + block, None] + np.arange(WINDOW)
            mask = np.arange(WINDOW) < held[i : i + block, None]
            at = np.where(mask, at, len(vec) - 1)
            out[i : i + block] = self.forward(vec[at], mask.astype(f32))
        return out


def document_logits(net: Network, texts: pa.Array) -> np.ndarray:
    out = np.zeros(len(texts), f32)
    for lo, hi in pieces(texts, 1 << 20):
        tok = Tokens(*text_bytes(texts[lo:hi], lower=True))
        doc, start, held = windows(tok.first)
        z = net.score_windows(net.vectors(tok), start, held)
        out[lo:hi] = np.maximum.reduceat(z, np.searchsorted(doc, np.arange(hi - lo)))
    return out


def _counts(bucket: np.ndarray, edge: np.ndarray, y: np.ndarray, fold: np.ndarray, block: int = 256) -> np.ndarray:
    """Texts of each fold and label that a bucket occurs in: (FOLDS, 2, buckets); edge bounds each text's entries."""
    size = 1 << ODDS_BITS
    out = np.zeros((FOLDS * 2, size), np.int32)
    for i in range(0, len(y), block):
        j = min(len(y), i + block)
        d = np.repeat(np.arange(j - i), np.diff(edge[i : j + 1]))
        pair = np.unique(d * size + bucket[edge[i] : edge[j]])
        b, d = pair % size, pair // size + i
        np.add.at(out, (fold[d] * 2 + y[d], b), 1)
    return out.reshape(FOLDS, 2, size)


def _log_odds(neg: np.ndarray, pos: np.ndarray, share: float) -> np.ndarray:
    """Log-odds of toxic given the bucket, less the prior's; rare buckets shrink to 0."""
    z = np.log((pos + SHRINK * share) / (neg + SHRINK * (1 - share))) - np.log(share / (1 - share))
    return (np.clip(z, -1, 4) / 2).astype(f32)


def train(texts: list[str] | pa.Array, y: np.ndarray, seed: int = 3, rounds: int = ROUNDS, epochs: int = EPOCHS) -> Network:
    rng = np.random.default_rng(seed)
    net = Network(seed)
    p = net.p
    column = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.large_string())
    bounds = list(pieces(column, TRAIN_PIECE))
    fold = rng.permutation(len(y)) % FOLDS
    share = float(y.mean())
    size = 1 << ODDS_BITS
    counts = [np.zeros((FOLDS, 2, size), np.int32) for _ in range(4)]
    for lo, hi in bounds:
        tok = Tokens(*text_bytes(column[lo:hi], lower=True))
        gram_edge = np.append(tok.gram_at, len(tok.gram))[tok.first]
        for c, b, e in zip(counts, tok.buckets(), (tok.first, tok.first, tok.first, gram_edge), strict=True):
            c += _counts(b, e, y[lo:hi], fold[lo:hi])
    net.odds = [_log_odds(*c.sum(axis=0), share) for c in counts]
    # one table a fold, of the other folds, one after the other
    others = [np.concatenate([_log_odds(*(c.sum(axis=0) - c[f]), share) for f in range(FOLDS)]) for c in counts]
    del counts
    slot = np.arange(WINDOW)
    m = {k: np.zeros_like(v) for k, v in p.items()}
    v = {k: np.zeros_like(x) for k, x in p.items()}
    steps = 0
    for turn in range(rounds):
        # all windows of all texts are met, a piece of texts at a time; only tokens of chosen windows stay
        kept_parts = []
        for lo, hi in bounds:
            tok = Tokens(*text_bytes(column[lo:hi], lower=True))
            odds = tok.odds(others, np.repeat(fold[lo:hi], np.diff(tok.first)) * size)
            doc, start, held = windows(tok.first)
            lead = np.searchsorted(doc, np.arange(hi - lo + 1))
            if turn == 0:
                at = np.where(slot < held[:, None], start[:, None] + slot, len(odds))
                z = np.append(odds.max(axis=1, initial=-1), f32(-1))[at].max(axis=1)
            else:
                z = net.score_windows(np.concatenate([odds, tok.learned(p["words"], p["grams"])], axis=1), start, held)
            chosen = []
            for d in range(hi - lo):
                ws = np.arange(lead[d], lead[d + 1])
                worst = ws[np.argsort(-z[ws], kind="stable")[:3]]
                chosen.append(worst[:1] if y[lo + d] else np.unique(np.append(worst, rng.choice(ws))))
            at = np.concatenate(chosen)
            word = (start[at, None] + slot)[slot < held[at, None]]
            gn = tok.gram_n[word]
            grams = np.arange(int(gn.sum())) - np.repeat(np.cumsum(gn) - gn - tok.gram_at[word], gn)
            kept_parts.append((doc[at] + lo, held[at], odds[word], tok.word[word] >> (ODDS_BITS - WORD_BITS), gn, tok.gram[grams] >> (ODDS_BITS - GRAM_BITS)))
        pick_doc, held, odds, word_at, gram_n, gram_at = (np.concatenate(x) for x in zip(*kept_parts, strict=True))
        del kept_parts
        start, gram_from = np.cumsum(held) - held, np.cumsum(gram_n) - gram_n
        pick = np.arange(len(pick_doc))
        goal = y[pick_doc].astype(f32)
        weight = np.where(goal == 1, 0.2 / max(1.0, (goal == 1).sum()), 0.8 / max(1.0, (goal == 0).sum())) * len(goal)
        for e in range(epochs):
            rate = f32(0.002 if (turn, e) == (rounds - 1, epochs - 1) else 0.01)
            order = rng.permutation(len(pick))
            for i in range(0, len(order), BATCH):
                o = order[i : i + BATCH]
                mask = slot < held[pick[o], None]
                rows, cols = np.nonzero(mask)
                word = (start[pick[o], None] + slot)[rows, cols]
                gn = gram_n[word]
                edge = np.cumsum(gn) - gn
                grams = np.arange(int(gn.sum())) - np.repeat(edge - gram_from[word], gn)
                norm = np.sqrt(gn)[:, None].astype(f32)
                x = np.zeros((len(o), WINDOW, UNITS), f32)
                if len(word):
                    x[rows, cols, :ODDS] = odds[word]
                    x[rows, cols, ODDS:] = p["words"][word_at[word]] + np.add.reduceat(p["grams"][gram_at[grams]], edge, axis=0) / norm
                logit, kept = net.forward(x, mask.astype(f32), keep=True)
                g, dx = net.back(((_sig(logit) - goal[o]) * weight[o] / len(o)).astype(f32), kept)
                dv = dx[rows, cols, ODDS:]
                steps += 1
                fix = f32(np.sqrt(1 - 0.999**steps) / (1 - 0.9**steps))
                for k, gk in g.items():
                    m[k] += f32(0.1) * (gk + f32(1e-4) * p[k] - m[k])
                    v[k] += f32(0.001) * (gk * gk - v[k])
                    p[k] -= rate * fix * m[k] / (np.sqrt(v[k]) + f32(1e-7))
                # of the vectors only the rows met move; small plain steps, so single texts are not learnt by heart
                for k, at_rows, gk in (("words", word_at[word], dv), ("grams", gram_at[grams], np.repeat(dv / norm, gn, axis=0))):
                    np.add.at(p[k], at_rows, -rate * gk)
    return net


def fit_toxicity(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", toxic: int = TOXIC, clean: int = CLEAN) -> Network | None:
    """Learn from at most `toxic` + `clean` labelled texts of the learning folds, whole whatever their length.

    None only where those texts do not have both labels.
    """
    ship(docs.sparkSession)
    ids = labelled_ids(labels, "toxic", 1, toxic).union(labelled_ids(labels, "toxic", 0, clean))
    rows = sample_texts(docs, ids, id_col, text_col).groupBy("doc_id").agg(F.min(F.struct("text", "y")).alias("r")).select("doc_id", "r.y", "r.text").toArrow().sort_by("doc_id")
    y = rows["y"].to_numpy().astype(np.int64)
    if not y.any() or y.all():
        return None
    net = train(rows["text"].cast(pa.large_string()).combine_chunks(), y)
    # what learning held goes back to the system: the driver plans later stages beside it
    del rows, y
    gc.collect()
    pa.default_memory_pool().release_unused()
    return net


def score_toxicity(docs: DataFrame, net: Network | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """id_col, held_out, score, predicted for each row; the text is all that a score sees."""
    spark = docs.sparkSession
    ship(spark)
    arrow_rows(spark)
    kind = docs.schema[id_col].dataType.simpleString()
    shared = spark.sparkContext.broadcast(net)  # 2 x 2^15 vectors of 8 floats, whatever the data

    def run(bs):
        model = shared.value
        for b in bs:
            z = document_logits(model, b.column("_text")) if model else np.full(len(b), -40.0)
            yield pa.RecordBatch.from_arrays([b.column("_key"), pa.array(_sig(z).astype(np.float64))], names=["_key", "score"])

    got = docs.select(F.col(id_col).alias("_key"), F.col(text_col).alias("_text")).mapInArrow(run, f"_key {kind}, score double")
    return got.select(F.col("_key").alias(id_col), held_out(F.col("_key")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, net: Network | None, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """Rows, all columns, whose text scores under the threshold."""
    spark = docs.sparkSession
    ship(spark)
    arrow_rows(spark)
    if net is None:
        return docs
    shared = spark.sparkContext.broadcast(net)
    at = docs.columns.index(text_col)

    def run(bs):
        for b in bs:
            yield b.filter(pa.array(_sig(document_logits(shared.value, b.column(at))) < threshold))

    return docs.mapInArrow(run, docs.schema)
