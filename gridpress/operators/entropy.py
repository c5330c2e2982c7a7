"""Entropy coding of run symbols with a stored static model: interleaved range lanes, or a prefix code.

A model keeps the commonest runs and an escape; what escapes follows in Elias
gamma bits.  Few symbols do not repay a model: they go by a Rice code, whose one
parameter is then the model (no symbols, the parameter as the only frequency).  Lanes are independent coder states over every n-th symbol, so a
step of all lanes is one vector operation.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass

import numpy as np

BITS = 12
ALPHABET = 1024
ESCAPE = -1
LOW = 1 << 16


@dataclass
class Model:
    """symbols (runs, the escape last where there is one) and frequencies that add to 2^BITS."""

    symbols: np.ndarray
    freq: np.ndarray

    @staticmethod
    def of(runs: np.ndarray, counts: np.ndarray) -> Model:
        """Model of a histogram; the least common runs share the escape."""
        if len(runs):
            k = _rice_parameter(np.asarray(runs), np.asarray(counts))
            n = float(np.sum(counts))
            ideal = float((counts * np.log2(n / counts)).sum()) + 32
            if len(runs) <= ALPHABET and _rice_bits(np.asarray(runs), np.asarray(counts), k) <= ideal + BITS * len(runs) + sum(2 * math.floor(math.log2(int(r) + 2)) + 1 for r in runs):
                return Model(np.zeros(0, np.int64), np.array([k]))
        order = np.lexsort((runs, -counts))
        runs, counts = runs[order].astype(np.int64), counts[order].astype(np.float64)
        if len(runs) > ALPHABET:
            runs, counts = np.append(runs[: ALPHABET - 1], ESCAPE), np.append(counts[: ALPHABET - 1], counts[ALPHABET - 1 :].sum())
        if not len(runs):
            return Model(np.array([ESCAPE]), np.array([1 << BITS]))
        f = np.maximum(1, np.floor(counts / counts.sum() * (1 << BITS))).astype(np.int64)
        while f.sum() > 1 << BITS:
            f[np.argmax(f)] -= min(f.sum() - (1 << BITS), f.max() - 1)
        f[0] += (1 << BITS) - f.sum()
        return Model(runs, f)

    @property
    def rice(self) -> bool:
        return not len(self.symbols)

    @property
    def bits(self) -> int:
        """Stored size: a gamma-coded run and BITS bits of frequency for each entry; a byte for a Rice parameter."""
        if self.rice:
            return 8
        return int(sum(2 * math.floor(math.log2(max(int(s), 0) + 2)) + 1 for s in self.symbols)) + BITS * len(self.symbols)

    def index(self, runs: np.ndarray) -> np.ndarray:
        order = np.argsort(self.symbols)
        at = np.searchsorted(self.symbols[order], runs)
        at = np.minimum(at, len(order) - 1)
        found = self.symbols[order][at] == runs
        escape = np.flatnonzero(self.symbols == ESCAPE)
        if not found.all() and not len(escape):
            raise ValueError("a run is missing from its model")
        return np.where(found, order[at], escape[0] if len(escape) else 0)


def _rice_bits(runs: np.ndarray, counts: np.ndarray, k: int) -> float:
    return float((counts * ((runs >> k) + 1 + k)).sum())


def _rice_parameter(runs: np.ndarray, counts: np.ndarray) -> int:
    return min(range(32), key=lambda k: _rice_bits(runs, counts, k))


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    return bytes([*out, n])


class RiceCoder:
    """Quotients in unary, remainders in k bits."""

    @staticmethod
    def encode(runs: np.ndarray, k: int) -> bytes:
        bits = "".join(["0" * (int(r) >> k) + "1" + (format(int(r) & ((1 << k) - 1), f"0{k}b") if k else "") for r in runs])
        return _varint(len(runs)) + np.packbits(np.frombuffer(bits.encode(), np.uint8) - 48).tobytes()

    @staticmethod
    def decode(blob: bytes, k: int) -> np.ndarray:
        n = shift = at = 0
        while True:
            n |= (blob[at] & 127) << shift
            at, shift = at + 1, shift + 7
            if blob[at - 1] < 128:
                break
        bits = np.unpackbits(np.frombuffer(blob, np.uint8, -1, at)) if len(blob) > at else np.zeros(0, np.uint8)
        s, p, out = (bits + 48).tobytes().decode(), 0, np.empty(n, np.int64)
        for i in range(n):
            e = s.index("1", p)
            out[i] = (e - p) << k | (int(s[e + 1 : e + 1 + k], 2) if k else 0)
            p = e + 1 + k
        return out


def _gamma(values: np.ndarray) -> np.ndarray:
    out = []
    for v in values:
        b = bin(int(v) + 1)[2:]
        out.append("0" * (len(b) - 1) + b)
    return np.frombuffer("".join(out).encode(), np.uint8) - 48 if out else np.zeros(0, np.uint8)


def _ungamma(bits: np.ndarray, n: int) -> list[int]:
    s, at, out = bits.tobytes().translate(bytes([48, 49] + [49] * 254)).decode(), 0, []
    for _ in range(n):
        z = s.index("1", at) - at
        out.append(int(s[at + z : at + 2 * z + 1], 2) - 1)
        at += 2 * z + 1
    return out


def _lanes(n: int) -> int:
    return max(1, min(256, n // 512))


class RangeCoder:
    """Lanes of a 32-bit range coder state with 16-bit renormalisation, last symbol first."""

    @staticmethod
    def encode(runs: np.ndarray, model: Model) -> bytes:
        if model.rice:
            return RiceCoder.encode(runs, int(model.freq[0]))
        n = len(runs)
        sym = model.index(np.asarray(runs, np.int64))
        escaped = _gamma(np.asarray(runs)[model.symbols[sym] == ESCAPE])
        lanes = _lanes(n)
        cum = np.concatenate([[0], np.cumsum(model.freq)]).astype(np.uint64)
        freq = model.freq.astype(np.uint64)
        state = np.full(lanes, LOW, np.uint64)
        words: list[np.ndarray] = []
        for i in range(-(-n // lanes) - 1, -1, -1):
            s = sym[i * lanes : (i + 1) * lanes]
            f, c = freq[s], cum[s]
            x = state[: len(s)]
            full = x >= f << np.uint64(32 - BITS)
            if full.any():
                words.append((x[full] & np.uint64(0xFFFF)).astype("<u2")[::-1])
                x = np.where(full, x >> np.uint64(16), x)
            state[: len(s)] = ((x // f) << np.uint64(BITS)) + x % f + c
        body = np.concatenate(words)[::-1] if words else np.zeros(0, "<u2")
        return np.array([n, len(body)], "<u4").tobytes() + state.astype("<u4").tobytes() + body.astype("<u2").tobytes() + np.packbits(escaped).tobytes()

    @staticmethod
    def decode(blob: bytes, model: Model) -> np.ndarray:
        if model.rice:
            return RiceCoder.decode(blob, int(model.freq[0]))
        n, m = (int(x) for x in np.frombuffer(blob, "<u4", 2))
        lanes = _lanes(n)
        state = np.frombuffer(blob, "<u4", lanes, 8).astype(np.uint64)
        at = 8 + 4 * lanes
        body = np.frombuffer(blob, "<u2", m, at).astype(np.uint64)
        rest = np.unpackbits(np.frombuffer(blob, np.uint8, -1, at + 2 * m)) if len(blob) > at + 2 * m else np.zeros(0, np.uint8)
        cum = np.concatenate([[0], np.cumsum(model.freq)]).astype(np.uint64)
        freq = model.freq.astype(np.uint64)
        slot_of = np.repeat(np.arange(len(freq)), model.freq)
        out, used = np.empty(n, np.int64), 0
        for i in range(-(-n // lanes)):
            k = min(lanes, n - i * lanes)
            x = state[:k]
            low = x & np.uint64((1 << BITS) - 1)
            s = slot_of[low.astype(np.int64)]
            out[i * lanes : i * lanes + k] = s
            x = freq[s] * (x >> np.uint64(BITS)) + low - cum[s]
            need = x < LOW
            c = int(need.sum())
            if c:
                x[need] = (x[need] << np.uint64(16)) | body[used : used + c]
                used += c
            state[:k] = x
        runs = model.symbols[out] if n else np.zeros(0, np.int64)
        gone = np.flatnonzero(runs == ESCAPE)
        if len(gone):
            runs = runs.copy()
            runs[gone] = _ungamma(rest, len(gone))
        return runs


class PrefixCoder:
    """The ablation: a prefix code by the model's frequencies."""

    @staticmethod
    def lengths(model: Model) -> np.ndarray:
        heap = [(int(f), i, (i,)) for i, f in enumerate(model.freq)]
        heapq.heapify(heap)
        size = np.zeros(len(heap), np.int64)
        if len(heap) == 1:
            return np.ones(1, np.int64)
        tick = len(heap)
        while len(heap) > 1:
            (f, _, a), (g, _, b) = heapq.heappop(heap), heapq.heappop(heap)
            size[list(a + b)] += 1
            tick += 1
            heapq.heappush(heap, (f + g, tick, a + b))
        return size

    @staticmethod
    def codes(model: Model) -> list[str]:
        size = PrefixCoder.lengths(model)
        code, last, out = 0, 0, [""] * len(size)
        for i in np.lexsort((np.arange(len(size)), size)):
            code <<= int(size[i]) - last
            last = int(size[i])
            out[i] = format(code, f"0{last}b")
            code += 1
        return out

    @staticmethod
    def encode(runs: np.ndarray, model: Model) -> bytes:
        if model.rice:
            return RiceCoder.encode(runs, int(model.freq[0]))
        sym, codes = model.index(np.asarray(runs, np.int64)), PrefixCoder.codes(model)
        escaped = _gamma(np.asarray(runs)[model.symbols[sym] == ESCAPE])
        bits = np.frombuffer("".join([codes[s] for s in sym]).encode(), np.uint8) - 48 if len(sym) else np.zeros(0, np.uint8)
        return np.array([len(sym), len(bits)], "<u4").tobytes() + np.packbits(np.concatenate([bits, escaped])).tobytes()

    @staticmethod
    def decode(blob: bytes, model: Model) -> np.ndarray:
        if model.rice:
            return RiceCoder.decode(blob, int(model.freq[0]))
        n, m = (int(x) for x in np.frombuffer(blob, "<u4", 2))
        bits = np.unpackbits(np.frombuffer(blob, np.uint8, -1, 8)) if len(blob) > 8 else np.zeros(0, np.uint8)
        back = {c: i for i, c in enumerate(PrefixCoder.codes(model))}
        out, held = [], ""
        for b in bits[:m]:
            held += "1" if b else "0"
            if held in back:
                out.append(back[held])
                held = ""
        runs = model.symbols[np.array(out, np.int64)] if n else np.zeros(0, np.int64)
        gone = np.flatnonzero(runs == ESCAPE)
        if len(gone):
            runs[gone] = _ungamma(bits[m:], len(gone))
        return runs


CODERS = {"range": RangeCoder, "huffman": PrefixCoder}


def ideal_bits(runs: np.ndarray) -> float:
    _, f = np.unique(runs, return_counts=True)
    return float((f * np.log2(f.sum() / f)).sum()) if len(f) else 0.0
