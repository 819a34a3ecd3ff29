"""Static arithmetic coder on whole numbers: within two bits of the sequence's ideal length."""

from __future__ import annotations

from collections.abc import Sequence

from blockpress.coders.elias import packed, unpacked

TOP = 1 << 48
HALF, QUARTER = TOP >> 1, TOP >> 2


def _cumulative(counts: Sequence[int]) -> list[int]:
    out = [0]
    for c in counts:
        out.append(out[-1] + c)
    return out


def encode(seq: Sequence[int], counts: Sequence[int]) -> tuple[bytes, int]:
    """Code and its bits."""
    cum = _cumulative(counts)
    low, high, held, bits = 0, TOP - 1, 0, []

    def put(bit: int) -> None:
        nonlocal held
        bits.append(str(bit) + str(1 - bit) * held)
        held = 0

    for s in seq:
        span = high - low + 1
        low, high = low + span * cum[s] // cum[-1], low + span * cum[s + 1] // cum[-1] - 1
        while True:
            if high < HALF:
                put(0)
            elif low >= HALF:
                put(1)
                low, high = low - HALF, high - HALF
            elif low >= QUARTER and high < 3 * QUARTER:
                held += 1
                low, high = low - QUARTER, high - QUARTER
            else:
                break
            low, high = 2 * low, 2 * high + 1
    if seq:
        held += 1
        put(0 if low < QUARTER else 1)
    text = "".join(bits)
    return packed(text), len(text)


def decode(data: bytes, n: int, counts: Sequence[int]) -> list[int]:
    from bisect import bisect_right

    cum, bits = _cumulative(counts), unpacked(data)
    if not n:
        return []
    value, at = int(bits[:48].ljust(48, "0"), 2), 48
    low, high, out = 0, TOP - 1, []
    for _ in range(n):
        span = high - low + 1
        s = bisect_right(cum, ((value - low + 1) * cum[-1] - 1) // span) - 1
        out.append(s)
        low, high = low + span * cum[s] // cum[-1], low + span * cum[s + 1] // cum[-1] - 1
        while True:
            if high < HALF:
                pass
            elif low >= HALF:
                low, high, value = low - HALF, high - HALF, value - HALF
            elif low >= QUARTER and high < 3 * QUARTER:
                low, high, value = low - QUARTER, high - QUARTER, value - QUARTER
            else:
                break
            low, high = 2 * low, 2 * high + 1
            value = 2 * value + (int(bits[at]) if at < len(bits) else 0)
            at += 1
    return out
