"""Set partitioning with an absolute tolerance: sets of values within twice the tolerance share their middle; LZMA on top."""

from __future__ import annotations

import lzma
from dataclasses import dataclass

import numpy as np

PRESET = 6


@dataclass
class Parts:
    shape: tuple[int, ...]
    blob: bytes
    scope: str

    def bytes(self) -> int:
        return len(self.blob) + 16


def runs_within(v: np.ndarray, tol: float) -> np.ndarray:
    """Starts of greedy runs, in C order, whose values spread at most 2 tol."""
    starts, lo, hi = [0], v[0], v[0]
    for i, x in enumerate(v.tolist()):
        nlo, nhi = (x if x < lo else lo), (x if x > hi else hi)
        if nhi - nlo > 2 * tol:
            starts.append(i)
            lo = hi = x
        else:
            lo, hi = nlo, nhi
    return np.array(starts)


def _halve(a: np.ndarray, tol: float, mids: list, tree: list) -> None:
    lo, hi = a.min(), a.max()
    if hi - lo <= 2 * tol:
        tree.append(0)
        mids.append((lo + hi) / 2)
        return
    tree.append(1)
    axis = int(np.argmax(a.shape))
    h = a.shape[axis] // 2
    _halve(a.take(range(h), axis), tol, mids, tree)
    _halve(a.take(range(h, a.shape[axis]), axis), tol, mids, tree)


def compress(a: np.ndarray, tol: float, scope: str = "run") -> Parts:
    if scope == "run":
        v = a.ravel()
        s = runs_within(v, tol)
        lo, hi = np.minimum.reduceat(v, s), np.maximum.reduceat(v, s)
        raw = np.array([len(s)], "<u4").tobytes() + ((lo + hi) / 2).astype("<f4").tobytes() + np.diff(np.append(s, len(v))).astype("<u4").tobytes()
    else:
        mids: list[float] = []
        tree: list[int] = []
        _halve(a, tol, mids, tree)
        raw = np.array([len(mids), len(tree)], "<u4").tobytes() + np.array(mids, "<f4").tobytes() + np.packbits(tree).tobytes()
    return Parts(a.shape, lzma.compress(raw, preset=PRESET), scope)


def decompress(c: Parts) -> np.ndarray:
    raw = lzma.decompress(c.blob)
    if c.scope == "run":
        n = int(np.frombuffer(raw, "<u4", 1)[0])
        return np.repeat(np.frombuffer(raw, "<f4", n, 4).astype(float), np.frombuffer(raw, "<u4", n, 4 + 4 * n)).reshape(c.shape)
    n, m = (int(x) for x in np.frombuffer(raw, "<u4", 2))
    mids = iter(np.frombuffer(raw, "<f4", n, 8).astype(float))
    tree = iter(np.unpackbits(np.frombuffer(raw, np.uint8, -1, 8 + 4 * n))[:m])
    out = np.zeros(c.shape)

    def fill(view: np.ndarray) -> None:
        if next(tree) == 0:
            view[...] = next(mids)
            return
        axis = int(np.argmax(view.shape))
        h = view.shape[axis] // 2
        at = [slice(None)] * view.ndim
        at[axis] = slice(0, h)
        fill(view[tuple(at)])
        at[axis] = slice(h, None)
        fill(view[tuple(at)])

    fill(out)
    return out
