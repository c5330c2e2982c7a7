"""Rank truncation with fixed quantisation: 8-bit core codes, 32-bit factors."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from gridpress.operators.factors import array_slice_norms
from gridpress.operators.transform import Transformed, inverse_array, omt_array


@dataclass
class RankCut:
    codes: np.ndarray
    factors: list[np.ndarray]
    peak: float
    floor: float
    quantiser: str

    def bytes(self) -> int:
        return self.codes.nbytes + sum(u.nbytes for u in self.factors) + 32


def ranks_by_energy(core: np.ndarray, tail: float) -> tuple[int, ...]:
    """Fewest slices of each mode that leave at most `tail` of the energy out, by their norms."""
    out = []
    for s in array_slice_norms(core):
        e = s**2
        rest = e[::-1].cumsum()[::-1]
        keep = int((rest > tail * e.sum() / core.ndim).sum())
        out.append(max(1, keep))
    return tuple(out)


def compress(a: np.ndarray, ranks: tuple[int, ...] | None = None, energy_tail: float | None = None, quantiser: str = "linear", transformed: Transformed | None = None) -> RankCut:
    t = transformed or omt_array(a)
    ranks = ranks or ranks_by_energy(t.core, energy_tail if energy_tail is not None else 1e-4)
    core = t.core[tuple(slice(0, r) for r in ranks)]
    peak = float(np.abs(core).max(initial=0.0))
    m, sign = np.abs(core), core < 0
    if quantiser == "linear":
        codes = np.rint(core / peak * 127).astype(np.int8) if peak else np.zeros(core.shape, np.int8)
        return RankCut(codes, [u[:, :r].astype(np.float32) for u, r in zip(t.factors, ranks, strict=True)], peak, 0.0, quantiser)
    # a sign and seven bits of the logarithm; code 0 is zero
    floor = peak * 2.0**-24
    k = np.where(m > floor, np.rint(1 + 126 * np.log2(np.maximum(m, floor) / floor) / 24) if peak else 0, 0).astype(np.uint8)
    return RankCut(k | (sign.astype(np.uint8) << 7), [u[:, :r].astype(np.float32) for u, r in zip(t.factors, ranks, strict=True)], peak, floor, quantiser)


def decompress(c: RankCut) -> np.ndarray:
    if c.quantiser == "linear":
        core = c.codes.astype(float) / 127 * c.peak
    else:
        k = (c.codes & 0x7F).astype(float)
        core = np.where(k > 0, c.floor * 2.0 ** ((k - 1) * 24 / 126), 0.0) * np.where(c.codes >> 7, -1, 1)
    return inverse_array(core, [u.astype(float) for u in c.factors])
