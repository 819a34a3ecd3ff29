"""Prefix-free codes of positive whole numbers, and fixed-width coding."""

from __future__ import annotations


def gamma_bits(x: int) -> int:
    """Length of the gamma code: twice the whole part of log2, plus one."""
    return 2 * (x.bit_length() - 1) + 1


def delta_bits(x: int) -> int:
    """Length of the delta code: the number's bits but the leading one, and its size in gamma."""
    n = x.bit_length()
    return n - 1 + gamma_bits(n)


def plain_bits(n: int, k: int) -> int:
    """``n`` symbols of an alphabet of ``k`` at a whole number of bits each."""
    return n * max(k - 1, 0).bit_length()


def gamma(x: int) -> str:
    b = bin(x)[2:]
    return "0" * (len(b) - 1) + b


def delta(x: int) -> str:
    b = bin(x)[2:]
    return gamma(len(b)) + b[1:]


def read_gamma(bits: str, at: int) -> tuple[int, int]:
    """Number and the place behind it."""
    zeros = bits.index("1", at) - at
    return int(bits[at + zeros : at + 2 * zeros + 1], 2), at + 2 * zeros + 1


def read_delta(bits: str, at: int) -> tuple[int, int]:
    size, at = read_gamma(bits, at)
    return int("1" + bits[at : at + size - 1], 2), at + size - 1


#: By name: length, writer, reader.
LENGTH_CODES = {"gamma": (gamma_bits, gamma, read_gamma), "delta": (delta_bits, delta, read_delta)}


def packed(bits: str) -> bytes:
    """Bits to bytes, filled up with zeros."""
    return int(bits.ljust(-(-len(bits) // 8) * 8, "0") or "0", 2).to_bytes(-(-len(bits) // 8), "big")


def unpacked(data: bytes) -> str:
    return bin(int.from_bytes(b"\1" + data, "big"))[3:]
