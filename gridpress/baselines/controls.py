"""Controls: lossless byte coders and plain casts."""

from __future__ import annotations

import lzma
import zlib

import numpy as np


def lossless(a: np.ndarray, codec: str = "lzma", dtype: str = "<f8") -> int:
    """Bytes of the original type under a lossless coder."""
    raw = a.astype(dtype).tobytes()
    return len(lzma.compress(raw, preset=6)) if codec == "lzma" else len(zlib.compress(raw, 6))


def to_float32(a: np.ndarray) -> tuple[np.ndarray, int]:
    return a.astype(np.float32).astype(float), a.size * 4
