"""Canonical Huffman code from counts."""

from __future__ import annotations

import heapq
from collections.abc import Sequence


def code_lengths(counts: Sequence[int]) -> list[int]:
    """Bits of each symbol's code; a symbol that does not occur has none, a lone one has one bit."""
    heap = [(c, k, (k,)) for k, c in enumerate(counts) if c > 0]
    size = [0] * len(counts)
    if len(heap) == 1:
        size[heap[0][1]] = 1
        return size
    heapq.heapify(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for k in a[2] + b[2]:
            size[k] += 1
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), a[2] + b[2]))
    return size


def codes(lengths: Sequence[int]) -> dict[int, str]:
    out, value, before = {}, 0, 0
    for size, k in sorted((n, k) for k, n in enumerate(lengths) if n):
        value <<= size - before
        out[k], before = format(value, f"0{size}b"), size
        value += 1
    return out


def total_bits(counts: Sequence[int]) -> int:
    return sum(c * n for c, n in zip(counts, code_lengths(counts), strict=True))


def encode(seq: Sequence[int], lengths: Sequence[int]) -> str:
    table = codes(lengths)
    return "".join(table[s] for s in seq)


def decode(bits: str, n: int, lengths: Sequence[int]) -> list[int]:
    table = {c: k for k, c in codes(lengths).items()}
    out, at, end = [], 0, 0
    while len(out) < n:
        end += 1
        if (s := table.get(bits[at:end])) is not None:
            out.append(s)
            at = end
    return out
