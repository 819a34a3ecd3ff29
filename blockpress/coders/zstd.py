"""The dictionary coder of practice: Zstandard, one byte a symbol or bits packed."""

from __future__ import annotations

import numpy as np
import zstandard

LEVEL = 12
#: By level: one that is used again need not take its tables anew.
_compressors: dict[int, zstandard.ZstdCompressor] = {}


def to_bytes(seq: np.ndarray, pack: str = "byte", k: int = 256) -> bytes:
    """Symbols as bytes; ``pack="bits"`` puts as many into a byte as their width allows."""
    seq = np.asarray(seq, np.uint8)
    if pack == "byte":
        return seq.tobytes()
    width = next(w for w in (1, 2, 4, 8) if k <= 1 << w)
    bits = np.unpackbits(seq[:, None], axis=1)[:, 8 - width :].ravel()
    return np.packbits(bits).tobytes()


def from_bytes(data: bytes, n: int, pack: str = "byte", k: int = 256) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    if pack == "byte":
        return raw[:n]
    width = next(w for w in (1, 2, 4, 8) if k <= 1 << w)
    bits = np.unpackbits(raw)[: n * width].reshape(n, width)
    return np.packbits(np.pad(bits, ((0, 0), (8 - width, 0))), axis=1)[:, 0]


def encode(seq: np.ndarray, pack: str = "byte", k: int = 256, level: int = LEVEL) -> bytes:
    if level not in _compressors:
        _compressors[level] = zstandard.ZstdCompressor(level=level)
    return _compressors[level].compress(np.ascontiguousarray(seq, np.uint8) if pack == "byte" else to_bytes(seq, pack, k))


def decode(data: bytes, n: int, pack: str = "byte", k: int = 256) -> np.ndarray:
    return from_bytes(zstandard.ZstdDecompressor().decompress(data), n, pack, k)
