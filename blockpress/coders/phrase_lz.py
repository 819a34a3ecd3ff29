"""The dictionary coder of the theory: greedy phrases that point into the past.

At each place the longest string that began earlier is taken, which may run into itself. A phrase is a
pointer of fixed width and a length in a prefix-free code; a symbol never seen points below one. When
all phrases cost more than plain coding, the plain code is sent.

An automaton of all substrings read so far grows with the input, symbol by symbol, while the match in
hand walks along it, so a parse takes time in proportion to the sequence.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from blockpress.coders.elias import LENGTH_CODES, packed, plain_bits, unpacked


@dataclass(frozen=True)
class Phrase:
    start: int  # places count from 1
    length: int
    pointer: int  # place of the earlier occurrence; minus the symbol where it is new


class _Substrings:
    """Online automaton of the substrings of a sequence; each state keeps where it first ended."""

    def __init__(self):
        self.step: list[dict] = [{}]
        self.link, self.size, self.first = [-1], [0], [-1]
        self.last = 0

    def add(self, symbol: int, end: int) -> tuple[int, int] | None:
        """Read one symbol; returns (state, its copy) if a state was split."""
        new = len(self.size)
        self.step.append({})
        self.link.append(0)
        self.size.append(self.size[self.last] + 1)
        self.first.append(end)
        p, split = self.last, None
        while p >= 0 and symbol not in self.step[p]:
            self.step[p][symbol] = new
            p = self.link[p]
        if p >= 0:
            q = self.step[p][symbol]
            if self.size[p] + 1 == self.size[q]:
                self.link[new] = q
            else:
                copy = len(self.size)
                self.step.append(dict(self.step[q]))
                self.link.append(self.link[q])
                self.size.append(self.size[p] + 1)
                self.first.append(self.first[q])
                while p >= 0 and self.step[p].get(symbol) == q:
                    self.step[p][symbol] = copy
                    p = self.link[p]
                self.link[q] = self.link[new] = copy
                split = (q, copy)
        self.last = new
        return split


def parse(seq: Sequence[int], tie: str = "latest") -> list[Phrase]:
    """Phrases of ``seq`` (symbols 0..255). ``tie`` picks the latest or the earliest earlier start."""
    if tie not in ("latest", "earliest"):
        raise ValueError(tie)
    data, known, out, k = bytes(seq), _Substrings(), [], 0
    while k < len(data):
        state, size, begin = 0, 0, -1
        while k + size < len(data) and (onward := known.step[state].get(data[k + size])) is not None:
            state, size = onward, size + 1
            begin = known.first[state] - size + 1
            split = known.add(data[k + size - 1], k + size - 1)
            if split and split[0] == state and size <= known.size[split[1]]:
                state = split[1]
        if not size:
            known.add(data[k], k)
            out.append(Phrase(k + 1, 1, -data[k]))
            k += 1
            continue
        if tie == "latest":
            begin = data.rfind(data[k : k + size], 0, k + size - 1)
        out.append(Phrase(k + 1, size, begin + 1))
        k += size
    return out


def pointer_bits(n: int, k: int) -> int:
    """Width of a pointer: enough for every place and every new symbol."""
    return max(n + k - 1, 0).bit_length()


def phrase_bits(phrases: list[Phrase], n: int, k: int, length_code: str = "gamma") -> int:
    size = LENGTH_CODES[length_code][0]
    return len(phrases) * pointer_bits(n, k) + sum(size(p.length) for p in phrases)


def encode(seq: Sequence[int], k: int, tie: str = "latest", length_code: str = "gamma") -> tuple[bytes, int, bool]:
    """Code, its bits, and whether it is the plain code."""
    n = len(seq)
    phrases = parse(seq, tie)
    coded, plain = phrase_bits(phrases, n, k, length_code), plain_bits(n, k)
    if coded > plain:
        width = max(k - 1, 0).bit_length()
        bits = "".join(format(x, f"0{width}b") for x in seq) if width else ""
        return packed(bits), plain, True
    wide, write = pointer_bits(n, k), LENGTH_CODES[length_code][1]
    bits = "".join(format(p.pointer + k - 1, f"0{wide}b") + write(p.length) for p in phrases)
    return packed(bits), coded, False


def decode(data: bytes, n: int, k: int, plain: bool, length_code: str = "gamma") -> list[int]:
    bits, out = unpacked(data), []
    if plain:
        width = max(k - 1, 0).bit_length()
        return [int(bits[i * width : (i + 1) * width], 2) for i in range(n)] if width else [0] * n
    wide, read, at = pointer_bits(n, k), LENGTH_CODES[length_code][2], 0
    while len(out) < n:
        pointer = int(bits[at : at + wide], 2) - k + 1
        size, at = read(bits, at + wide)
        if pointer < 1:
            out.append(-pointer)
        else:
            for j in range(pointer - 1, pointer - 1 + size):
                out.append(out[j])
    return out
