"""Resampling in the compressed domain: only factor rows change, the core is untouched."""

from __future__ import annotations

from dataclasses import replace

import numpy as np

from gridpress.operators.codec import Archive


def _with(a: Archive, factors: list[np.ndarray]) -> Archive:
    return replace(a, resampled=factors)


def take(a: Archive, keys: tuple) -> Archive:
    """Ranges, strides (negative too) and single indices of each axis."""
    out = []
    for n, u in enumerate(a.factors()):
        k = keys[n] if n < len(keys) else slice(None)
        out.append(u[k] if isinstance(k, slice) else u[[k]])
    return _with(a, out)


def lanczos_taps(k: int, lobes: int = 2, literal: bool = False) -> np.ndarray:
    """Windowed-sinc taps for a stride of k, adding to one; `literal` samples at whole numbers, which picks."""
    step = 1 if literal else k
    j = np.arange(-lobes * step, lobes * step + 1)
    x = j / step
    w = np.where(np.abs(x) < lobes, np.sinc(x) * np.sinc(x / lobes), 0.0)
    return w / w.sum()


def convolve_rows(u: np.ndarray, taps: np.ndarray, fft_over: int = 64) -> np.ndarray:
    """Columns of u convolved with taps; taps that stick out at a border are left out and the rest rescaled."""
    r, n = len(taps) // 2, len(u)
    if len(taps) > fft_over:
        size = 1 << int(np.ceil(np.log2(n + len(taps))))
        f = np.fft.rfft(taps, size)[:, None]
        full = np.fft.irfft(np.fft.rfft(u, size, axis=0) * f, size, axis=0)[r : r + n]
        norm = np.fft.irfft(np.fft.rfft(np.ones(n), size) * f[:, 0], size)[r : r + n]
        return full / norm[:, None] * taps.sum()
    out, norm = np.zeros_like(u), np.zeros(n)
    for t, w in enumerate(taps):
        s = t - r
        if abs(s) >= n:
            continue
        lo, hi = max(0, s), min(n, n + s)
        out[lo:hi] += w * u[lo - s : hi - s]
        norm[lo:hi] += w
    return out / norm[:, None] * taps.sum()


def decimated(u: np.ndarray, k: int, how: str) -> np.ndarray:
    if how == "pick":
        return u[::k]
    if how == "box":
        at = np.arange(0, len(u), k)
        return np.add.reduceat(u, at, axis=0) / np.diff(np.append(at, len(u)))[:, None]
    if how in ("lanczos2", "literal"):
        return convolve_rows(u, lanczos_taps(k, literal=how == "literal"))[::k]
    raise ValueError(how)


def decimate(a: Archive, k: int, how: str = "lanczos2") -> Archive:
    return _with(a, [decimated(u, k, how) for u in a.factors()])


def filter_separable(a: Archive, taps_by_axis: dict[int, np.ndarray]) -> Archive:
    return _with(a, [convolve_rows(u, taps_by_axis[n]) if n in taps_by_axis else u for n, u in enumerate(a.factors())])


def frame(a: Archive, axis: int, t: int) -> Archive:
    return _with(a, [u[[t]] if n == axis else u for n, u in enumerate(a.factors())])


def project_axis(a: Archive, axis: int, how: str = "sum") -> Archive:
    return _with(a, [(u.sum(axis=0) if how == "sum" else u.mean(axis=0))[None, :] if n == axis else u for n, u in enumerate(a.factors())])


def brick(a: Archive, centre: tuple[int, ...], edge: int) -> Archive:
    return take(a, tuple(slice(max(0, c - edge // 2), c - edge // 2 + edge) for c in centre))


def scale(a: Archive, k: float) -> Archive:
    f = a.factors()
    return _with(a, [f[0] * k, *f[1:]])


def permute(a: Archive, axis: int, order: list[int]) -> Archive:
    return _with(a, [u[order] if n == axis else u for n, u in enumerate(a.factors())])


def pad(a: Archive, axis: int, before: int, after: int) -> Archive:
    return _with(a, [np.pad(u, ((before, after), (0, 0))) if n == axis else u for n, u in enumerate(a.factors())])


def shift(a: Archive, axis: int, by: int) -> Archive:
    """Move along an axis; what leaves is lost and zeros come in."""
    out = []
    for n, u in enumerate(a.factors()):
        if n == axis:
            v = np.zeros_like(u)
            if by >= 0:
                v[by:] = u[: len(u) - by]
            else:
                v[:by] = u[-by:]
            u = v
        out.append(u)
    return _with(a, out)


def upsample_linear(a: Archive, axis: int, k: int) -> Archive:
    """Multilinear interpolation to k points for each step."""
    out = []
    for n, u in enumerate(a.factors()):
        if n == axis:
            x = np.arange((len(u) - 1) * k + 1) / k
            lo = np.minimum(x.astype(int), len(u) - 2) if len(u) > 1 else np.zeros(len(x), int)
            w = (x - lo)[:, None]
            u = u[lo] * (1 - w) + u[np.minimum(lo + 1, len(u) - 1)] * w
        out.append(u)
    return _with(a, out)
