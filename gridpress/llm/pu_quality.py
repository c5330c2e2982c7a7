"""Quality classifier from positives and unlabelled text, by the non-negative unbiased risk.

Trusted positives are documents marked 1; the unlabelled sample is any text of
the learning folds.  A first fit (positives against unlabelled) gives the class
prior: the least ratio of unlabelled to positive mass over the tops of its
ranking.  The second fit minimises pi R+(+1) + max(0, R_u(-1) - pi R+(-1)) and,
where the inner risk falls below zero, steps back along it.  The model is a
small network on shape features of whole texts.

Cases: null and empty texts have all-zero features and get a score; with no
positives or no texts to learn from every score is 0.5; repeated rows are scored alike.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridpress.llm.labelled import any_ids, held_out, labelled_ids, sample_texts
from gridpress.llm.textkernels import Words, pieces, text_bytes
from gridpress.session import arrow_rows, ship

POSITIVES, UNLABELLED = 6000, 12000
THRESHOLD = 0.3
WINDOW = 40
HIDDEN, EPOCHS = 12, 40

_CLASSES = {
    "upper": list(range(65, 91)),
    "lower": list(range(97, 123)),
    "digit": list(range(48, 58)),
    "mark": [ord(c) for c in "#&$%*@^~=+<>{}[]\\_"],
    "shout": [ord("!"), ord("?")],
    "bar": [ord("|")],
    "stop": [ord("."), ord(",")],
    "blank": [0x20, *range(0x09, 0x0E)],
    "wide": list(range(128, 256)),
}
_SHAPES = ("same1", "same2", "again")


def feature_names() -> list[str]:
    whole = [*_CLASSES, *_SHAPES, "marked", "words", "word_length"]
    return whole + [f"most_{c}" for c in ("upper", "mark", "shout", "bar", "digit", *_SHAPES)] + ["odd_windows"]


def features(texts: pa.Array) -> np.ndarray:
    """One row of features for each whole text."""
    out = np.zeros((len(texts), len(feature_names())), np.float32)
    for lo, hi in pieces(texts):
        out[lo:hi] = _piece_features(*text_bytes(texts[lo:hi]))
    return out


_TABLE = np.zeros(256, np.uint8)
for _i, _c in enumerate(_CLASSES.values()):
    _TABLE[_c] = _i + 1


def _piece_features(offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
    n, names = len(offsets) - 1, feature_names()
    out = np.zeros((n, len(names)), np.float32)
    if not len(data):
        return out
    w = Words(offsets, data)
    kind = _TABLE[data]
    size = np.maximum(np.diff(offsets), 1)
    at = {c: i for i, c in enumerate(names)}
    per_word, full = {}, np.flatnonzero(np.diff(offsets))
    for i, c in enumerate(_CLASSES):
        run = np.zeros(len(data) + 1, np.int32)
        np.cumsum(kind == i + 1, out=run[1:])
        out[full, at[c]] = (run[offsets[1:]] - run[offsets[:-1]])[full] / size[full]
        per_word[c] = run[w.end] - run[w.start]
    if not len(w.start):
        return out
    length = np.maximum(w.end - w.start, 1)
    h, doc = w.hash, w.doc
    same1, same2 = np.zeros(len(h)), np.zeros(len(h))
    same1[1:] = (h[1:] == h[:-1]) & (doc[1:] == doc[:-1])
    same2[2:] = (h[2:] == h[:-2]) & (doc[2:] == doc[:-2])
    # three words in a row that the text has had before
    again = np.zeros(len(h))
    if len(h) > 2:
        with np.errstate(over="ignore"):
            tri = h[:-2] * np.uint64(3) + h[1:-1] * np.uint64(5) + h[2:] * np.uint64(7) + doc[:-2].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        order = np.argsort(tri, kind="stable")
        dup = np.zeros(len(tri), bool)
        dup[order[1:]] = tri[order[1:]] == tri[order[:-1]]
        again[:-2] = dup & (doc[:-2] == doc[2:])
    word = {
        "upper": (per_word["upper"] * 2 > length) & (length > 2),
        "mark": per_word["mark"] > 0,
        "shout": per_word["shout"] > 0,
        "bar": per_word["bar"] > 0,
        "digit": per_word["digit"] * 2 > length,
        "same1": same1,
        "same2": same2,
        "again": again,
    }
    # windows of WINDOW words; the rest of a text joins its last window
    inside = np.arange(len(h)) - w.first[:-1][doc]
    count = np.diff(w.first)
    number = np.minimum(inside // WINDOW, np.maximum(count[doc] // WINDOW, 1) - 1)
    starts = np.flatnonzero((number[1:] != number[:-1]) | (doc[1:] != doc[:-1])) + 1
    starts = np.concatenate([[0], starts])
    held = np.diff(np.append(starts, len(h)))
    of = doc[starts]
    some = np.flatnonzero(count)
    lead = np.searchsorted(of, some)
    odd = np.zeros(len(starts))
    for c, v in word.items():
        share = np.add.reduceat(v.astype(np.float64), starts) / held
        out[some, at[f"most_{c}"]] = np.maximum.reduceat(share, lead)
        odd = np.maximum(odd, share)
        if c in _SHAPES:
            out[some, at[c]] = np.add.reduceat(v.astype(np.float64), w.first[:-1][some]) / count[some]
    out[some, at["marked"]] = np.add.reduceat(word["mark"].astype(np.float64), w.first[:-1][some]) / count[some]
    out[some, at["odd_windows"]] = np.add.reduceat((odd > 0.3).astype(np.float64), lead) / np.diff(np.append(lead, len(of)))
    out[some, at["words"]] = np.log1p(count[some]) / 10
    out[some, at["word_length"]] = np.add.reduceat(length.astype(np.float64), w.first[:-1][some]) / count[some] / 10
    return out


class Net:
    """Two tanh layers of HIDDEN units and a logit; numpy, Adam."""

    def __init__(self, mean: np.ndarray, scale: np.ndarray, seed: int = 5):
        rng = np.random.default_rng(seed)
        d = len(mean)
        self.mean, self.scale, self.steps = mean, scale, 0
        self.p = [rng.normal(0, d**-0.5, (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, (HIDDEN, 1)), np.zeros(1)]
        self.m, self.v = [np.zeros_like(x) for x in self.p], [np.zeros_like(x) for x in self.p]

    def _forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        z = np.clip((x - self.mean) / self.scale, -6, 6)
        h = np.tanh(z @ self.p[0] + self.p[1])
        return z, h, (h @ self.p[2] + self.p[3])[:, 0]

    def logit(self, x: np.ndarray) -> np.ndarray:
        return self._forward(x)[2]

    def step(self, x: np.ndarray, slope: np.ndarray, rate: float, decay: float = 1e-4) -> None:
        """One Adam step down the summed slopes of each row's logit."""
        z, h, _ = self._forward(x)
        back = (slope[:, None] @ self.p[2].T) * (1 - h * h)
        grads = [z.T @ back + decay * self.p[0], back.sum(0), h.T @ slope[:, None] + decay * self.p[2], slope.sum(keepdims=True)]
        self.steps += 1
        for p, g, m, v in zip(self.p, grads, self.m, self.v, strict=True):
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            p -= rate * (m / (1 - 0.9**self.steps)) / (np.sqrt(v / (1 - 0.999**self.steps)) + 1e-8)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def class_prior(pos: np.ndarray, unl: np.ndarray) -> float:
    """Least ratio of unlabelled to positive mass above a threshold, with room for both samples' noise."""
    grid = np.quantile(pos, np.linspace(0.0, 0.9, 91))
    above = lambda s: 1 - np.searchsorted(np.sort(s), grid, side="left") / len(s)
    q_p, q_u = np.maximum(above(pos), 1e-9), above(unl)
    noise = np.sqrt(np.log(20) / 2) * (len(pos) ** -0.5 + len(unl) ** -0.5)
    k = int(np.argmin((q_u + noise) / q_p))
    return float(np.clip(q_u[k] / q_p[k], 0.02, 0.98))


def fit_pu(pos: np.ndarray, unl: np.ndarray, seed: int = 5, epochs: int = EPOCHS) -> tuple[Net, float]:
    """The model and the prior from features of positives and of unlabelled texts."""
    every = np.concatenate([pos, unl])
    mean, scale = every.mean(0), np.maximum(every.std(0), 1e-3)
    rng = np.random.default_rng(seed)

    def batches():
        u = rng.permutation(len(unl))
        for i in range(0, len(u), 512):
            yield pos[rng.integers(0, len(pos), 256)], unl[u[i : i + 512]]

    first = Net(mean, scale, seed)
    for _ in range(max(3, epochs // 4)):
        for p, u in batches():
            x = np.concatenate([p, u])
            y = np.concatenate([np.ones(len(p)), np.zeros(len(u))])
            first.step(x, (sigmoid(first.logit(x)) - y) / len(x), 0.01)
    prior = class_prior(first.logit(pos), first.logit(unl))

    net = Net(mean, scale, seed + 1)
    for e in range(epochs):
        rate = 0.01 * (1 - e / epochs) + 0.0005
        for p, u in batches():
            zp, zu = net.logit(p), net.logit(u)
            # logistic loss: softplus(-z) for the positive side, softplus(z) for the negative
            inner = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
            neg_u, neg_p = sigmoid(zu) / len(u), -prior * sigmoid(zp) / len(p)
            if inner >= 0:
                slope = np.concatenate([prior * (sigmoid(zp) - 1) / len(p) + neg_p, neg_u])
            else:
                slope = -np.concatenate([neg_p, neg_u])
            net.step(np.concatenate([p, u]), slope, rate)
    return net, prior


def fit_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> tuple[Net, float] | None:
    """Fit on at most `positives` and `unlabelled` documents of the learning folds."""
    ship(docs.sparkSession)
    arrow_rows(docs.sparkSession)
    ids = labelled_ids(labels, "quality", 1, positives).union(any_ids(docs, unlabelled, -1, id_col))

    def run(bs):
        for b in bs:
            f = features(b.column("text"))
            yield pa.RecordBatch.from_arrays([b.column("y"), pa.ListArray.from_arrays(pa.array(np.arange(len(f) + 1, dtype=np.int32) * f.shape[1]), pa.array(f.ravel()))], names=["y", "f"])

    rows = sample_texts(docs, ids, id_col, text_col).select("y", "text").mapInArrow(run, "y int, f array<float>").toPandas()
    pos, unl = (np.array(rows.f[rows.y == y].tolist(), np.float64) for y in (1, -1))
    if not len(pos) or not len(unl):
        return None
    # partitions return in any order; the fit sees one order
    pos, unl = (x[np.lexsort(x.T)] for x in (pos, unl))
    return fit_pu(pos, unl)


def score_quality(docs: DataFrame, fitted: tuple[Net, float] | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """id_col, held_out, score, predicted for each row; the text is all that a score sees."""
    ship(docs.sparkSession)
    arrow_rows(docs.sparkSession)
    net = fitted[0] if fitted else None
    kind = docs.schema[id_col].dataType.simpleString()

    def run(bs):
        for b in bs:
            s = sigmoid(net.logit(features(b.column("_text")).astype(np.float64))) if net else np.full(len(b), 0.5)
            yield pa.RecordBatch.from_arrays([b.column("_key"), pa.array(s)], names=["_key", "score"])

    got = docs.select(F.col(id_col).alias("_key"), F.col(text_col).alias("_text")).mapInArrow(run, f"_key {kind}, score double")
    return got.select(F.col("_key").alias(id_col), held_out(F.col("_key")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_quality(docs: DataFrame, fitted: tuple[Net, float] | None, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """Rows, all columns, whose text scores at least the threshold."""
    ship(docs.sparkSession)
    arrow_rows(docs.sparkSession)
    if fitted is None:
        return docs
    net, at = fitted[0], docs.columns.index(text_col)

    def run(bs):
        for b in bs:
            yield b.filter(pa.array(sigmoid(net.logit(features(b.column(at)).astype(np.float64))) >= threshold))

    return docs.mapInArrow(run, docs.schema)
