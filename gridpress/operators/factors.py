"""Factor matrices: weighting by slice norms, plane coding to the core's price, and back."""

from __future__ import annotations

import numpy as np

from gridpress.operators.entropy import CODERS, Model, ideal_bits
from gridpress.operators.planes import join_plane, lead_array, low_bits, quantise_array, restore, scale_exponent, split_plane, sse_by_plane, stop_by_budget

PRICE_BLOCK = 256


def weighted_factor(u: np.ndarray, sigma: np.ndarray) -> np.ndarray:
    return u * sigma[None, :]


def unweighted(w: np.ndarray, sigma: np.ndarray) -> np.ndarray:
    """Columns divided by their norms; columns of zero norm stay zero."""
    return np.divide(w, sigma[None, :], out=np.zeros_like(w), where=sigma[None, :] > 0)


def array_slice_norms(core: np.ndarray) -> list[np.ndarray]:
    return [np.sqrt((np.moveaxis(core, n, 0).reshape(core.shape[n], -1) ** 2).sum(axis=1)) for n in range(core.ndim)]


def price_of_planes(q: np.ndarray, lead: np.ndarray, neg: np.ndarray, exponent: int, sse: np.ndarray | None = None) -> np.ndarray:
    """Squared error in grid units that each plane removes, for each of its bits; 64 values."""
    sse = sse_by_plane(q) if sse is None else sse
    unit = 4.0 ** (exponent - 63)
    out = np.zeros(64)
    for p in range(63, -1, -1):
        runs, raw, signs = split_plane(q, lead, neg, p)
        bits = ideal_bits(runs) + len(raw) + len(signs)
        drop = (sse[p + 1] - sse[p]) * unit
        out[p] = drop / bits if bits > 0 else (np.inf if drop > 0 else 0.0)
    return out


def drops(q: np.ndarray, p: int) -> np.ndarray:
    """Squared error in scaled units that each bit of plane p removes."""
    rest = low_bits(q, p + 1).astype(np.float64)
    return np.where((q >> np.uint64(p)) & np.uint64(1) == 1, rest**2 - (rest - 2.0**p) ** 2, 0.0)


def gains(q: np.ndarray, lead: np.ndarray, neg: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """(squared error removed, ideal bits) of each coefficient in plane p.

    Verbatim bits and signs cost one; a run costs what the plane's histogram of runs
    makes it, where its 1 stands.
    """
    bits = (lead > p).astype(np.float64)
    at = np.flatnonzero(lead == p)
    if len(at):
        runs = split_plane(q, lead, neg, p)[0]
        v, back, f = np.unique(runs, return_inverse=True, return_counts=True)
        bits[at] += 1 + np.log2(f.sum() / f)[back][: len(at)]
    return drops(q, p), bits


def stop_by_price(q: np.ndarray, lead: np.ndarray, neg: np.ndarray, exponent: int, price: float, most_sse: float | None = None, block: int = PRICE_BLOCK) -> tuple[int, int]:
    """(plane, coefficients of it) to send: up to the bit where the price of the last plane's worth of bits falls to `price`.

    Looked at after each block of coefficients, from the first 1 on; the window slides over
    what the plane has so far and the rest of the one before.  With most_sse bits go on
    until the error left is within it, whatever they cost.
    """
    if not q.any():
        return 64, 0
    unit = 4.0 ** (exponent - 63)
    at = (0, len(q))
    ends = np.append(np.arange(block, len(q), block), len(q))
    starts = np.append(0, ends[:-1])
    old = np.zeros((2, len(ends)))
    for p in range(int(lead.max()), -1, -1):
        new = np.array([np.add.reduceat(x, starts) for x in gains(q, lead, neg, p)])
        drop, bits = np.cumsum(new, axis=1) + (old.sum(axis=1)[:, None] - np.cumsum(old, axis=1))
        low = np.flatnonzero((bits >= 1) & (drop * unit <= price * bits))
        if len(low):
            at = (p, int(ends[low[0]]))
            break
        old = new
    if most_sse is not None:
        # the later of the two bits
        at = min(at, stop_by_budget(q, most_sse / unit), key=lambda x: (x[0], -x[1]))
    return at


def encode_vector(c: np.ndarray, p: int, sent: int, exponent: int, coder: str = "range") -> list[tuple[int, Model, bytes, bytes, bytes, int]]:
    """Planes 63..p of a small vector as (plane, model, runs, raw, signs, bits)."""
    q, neg, lead = quantise_array(c.ravel(), exponent)
    out = []
    for plane in range(int(lead.max(initial=-1)), p - 1, -1):
        runs, raw, signs = split_plane(q, lead, neg, plane, sent if plane == p else None)
        m = Model.of(*np.unique(runs, return_counts=True))
        out.append((plane, m, CODERS[coder].encode(runs, m), np.packbits(raw).tobytes(), np.packbits(signs).tobytes(), len(raw)))
    return out


def decode_vector(planes: list[tuple[int, Model, bytes, bytes, bytes, int]], n: int, p: int, sent: int, exponent: int, coder: str = "range", midpoint: bool = True) -> np.ndarray:
    q, seen, neg = np.zeros(n, np.uint64), np.zeros(n, bool), np.zeros(n, bool)
    for plane, model, runs, raw, signs, n_raw in planes:
        r = CODERS[coder].decode(runs, model)
        bits = np.unpackbits(np.frombuffer(raw, np.uint8))[:n_raw] if n_raw else np.zeros(0, np.uint8)
        limit = sent if plane == p else n
        total = int((~seen[:limit]).sum())
        ones = int((np.cumsum(r + 1) <= total).sum())
        s = np.unpackbits(np.frombuffer(signs, np.uint8))[:ones] if ones else np.zeros(0, np.uint8)
        join_plane(q, seen, neg, plane, r, bits, s, limit)
    return restore(q, neg, p, sent, exponent, midpoint)


def encode_factor(u: np.ndarray, sigma: np.ndarray, price: float, weight: bool = True, stop: str = "price", core_plane: int = 64, most_sse: float | None = None, coder: str = "range") -> dict:
    """Coded factor; `stop` may be "price", or the poorer "core_plane"."""
    w = weighted_factor(u, sigma) if weight else u
    e = scale_exponent(float(np.abs(w).max(initial=0.0)))
    q, neg, lead = quantise_array(w.ravel(), e)
    n = w.size
    if stop == "core_plane":
        p, sent = (min(64, max(0, core_plane)), n) if q.any() else (64, 0)
    elif most_sse is not None and stop == "budget":
        p, sent = stop_by_budget(q, most_sse / 4.0 ** (e - 63))
    else:
        p, sent = stop_by_price(q, lead, neg, e, price, most_sse)
    # rounding to the middle of what is unknown is worse on values that end early; each factor takes what fits it
    low = np.minimum(p + (np.arange(n) >= sent), 63).astype(np.uint64)
    kept = np.where(p + (np.arange(n) >= sent) < 64, q >> low << low, np.uint64(0))
    err = [float(((restore(kept, neg, min(p, 63), sent, e, mid) - w.ravel()) ** 2).sum()) for mid in (True, False)]
    return {"shape": u.shape, "exponent": e, "plane": p, "sent": sent, "weight": weight, "midpoint": err[0] <= err[1], "error": min(err), "planes": encode_vector(w, p, sent, e, coder) if p < 64 else []}


def decode_factor(f: dict, sigma: np.ndarray, coder: str = "range") -> np.ndarray:
    rows, cols = f["shape"]
    w = decode_vector(f["planes"], rows * cols, f["plane"], f["sent"], f["exponent"], coder, f["midpoint"]).reshape(rows, cols)
    return unweighted(w, sigma) if f["weight"] else w


def factor_bytes(f: dict) -> int:
    return sum(len(r) + len(v) + len(s) + -(-m.bits // 8) + 1 for _, m, r, v, s, _ in f["planes"]) + 8


def plane_depth(f: dict) -> int:
    """Planes spent on a factor from its first 1 bit."""
    return len(f["planes"])


def encode_all(factors: list[np.ndarray], norms: list[np.ndarray], price: float, **options) -> list[dict]:
    return [encode_factor(u, s, price, **options) for u, s in zip(factors, norms, strict=True)]


__all__ = ["array_slice_norms", "decode_factor", "encode_all", "encode_factor", "factor_bytes", "lead_array", "plane_depth"]
