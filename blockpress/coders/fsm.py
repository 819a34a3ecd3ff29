"""Encoders with finitely many states: output and next state are tables of (symbol, state)."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from itertools import product


@dataclass(frozen=True)
class FiniteStateEncoder:
    states: int
    output: dict[tuple[int, int], str]
    step: dict[tuple[int, int], int]
    start: int = 0

    def encode(self, seq: Sequence[int]) -> str:
        state, bits = self.start, []
        for x in seq:
            bits.append(self.output[x, state])
            state = self.step[x, state]
        return "".join(bits)

    def alphabet(self) -> list[int]:
        return sorted({x for x, _ in self.output})

    def is_lossless(self, max_len: int) -> bool:
        """Whether no two sequences of one length up to ``max_len`` share a code: by trying all."""
        for n in range(1, max_len + 1):
            seen = set()
            for seq in product(self.alphabet(), repeat=n):
                code = self.encode(seq)
                if code in seen:
                    return False
                seen.add(code)
        return True

    def is_degenerate(self) -> bool:
        """Whether the machine can walk around a loop without writing a bit."""
        silent = {s: {self.step[x, s] for x in self.alphabet() if not self.output[x, s]} for s in range(self.states)}
        for s in range(self.states):
            seen, front = set(), {s}
            while front:
                front = {b for a in front for b in silent[a]} - seen
                if s in front:
                    return True
                seen |= front
        return False
