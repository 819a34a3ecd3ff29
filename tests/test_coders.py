"""Coders give back what they took, and their sizes are what the theory says."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from blockpress.coders import arith, elias, huffman, phrase_lz, rans, zstd
from blockpress.coders.fsm import FiniteStateEncoder
from blockpress.functions import theory as T

SEQUENCES = [[], [0], [0] * 300, list(range(256)), [0, 1] * 50, [0, 1, 0, 1, 0, 1, 1], np.random.default_rng(0).choice(3, 5000, p=[0.7, 0.2, 0.1]).tolist()]


def brute_phrases(seq, tie):
    """Every earlier start is tried at every place."""
    out, k, n = [], 0, len(seq)
    while k < n:
        best, at = 0, -1
        for j in range(k):
            size = 0
            while k + size < n and seq[j + size] == seq[k + size]:
                size += 1
            if size > best or size == best and size and tie == "latest":
                best, at = size, j
        out.append((k + 1, best, at + 1) if best else (k + 1, 1, -seq[k]))
        k += max(best, 1)
    return out


@pytest.mark.parametrize("tie", ["latest", "earliest"])
@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(0, 2), max_size=40))
def test_phrases_are_the_longest(tie, seq):
    assert [(p.start, p.length, p.pointer) for p in phrase_lz.parse(seq, tie)] == brute_phrases(seq, tie)


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(0, 5), max_size=80), st.sampled_from(["gamma", "delta"]), st.sampled_from(["latest", "earliest"]))
def test_phrase_code_round_trip(seq, code, tie):
    data, bits, plain = phrase_lz.encode(seq, 6, tie, code)
    assert phrase_lz.decode(data, len(seq), 6, plain, code) == seq
    assert bits <= elias.plain_bits(len(seq), 6)


def test_worked_example():
    seq = [0, 1, 0, 1, 0, 1, 1]
    assert [(p.start, p.length, p.pointer) for p in phrase_lz.parse(seq)] == [(1, 1, 0), (2, 1, -1), (3, 4, 1), (7, 1, 6)]
    assert phrase_lz.parse(seq, "earliest")[-1].pointer == 2
    assert phrase_lz.phrase_bits(phrase_lz.parse(seq), 7, 2) == 24
    assert phrase_lz.encode(seq, 2)[1:] == (7, True)


def test_long_repeats_take_few_phrases():
    seq = ([0, 1, 2, 3] * 3000)[:10000]
    phrases = phrase_lz.parse(seq)
    assert len(phrases) == 5 and phrases[-1].length == 9996
    data, _, plain = phrase_lz.encode(seq, 4)
    assert not plain and phrase_lz.decode(data, len(seq), 4, plain) == seq


def test_elias():
    assert [elias.gamma_bits(x) for x in (1, 2, 3, 4, 8)] == [1, 3, 3, 5, 7]
    assert [elias.delta_bits(x) for x in (1, 2, 3, 4, 8)] == [1, 4, 4, 5, 8]
    for x in (1, 2, 7, 8, 1000, 1 << 40):
        assert len(elias.gamma(x)) == elias.gamma_bits(x) and elias.read_gamma("1" + elias.gamma(x), 1)[0] == x
        assert len(elias.delta(x)) == elias.delta_bits(x) and elias.read_delta(elias.delta(x), 0) == (x, elias.delta_bits(x))
    assert elias.plain_bits(10, 1) == 0 and elias.plain_bits(10, 5) == 30


@pytest.mark.parametrize("seq", SEQUENCES, ids=range(len(SEQUENCES)))
def test_round_trips(seq):
    a, k = np.array(seq, np.int64), max(seq, default=0) + 1
    counts = np.bincount(a, minlength=k)
    freq, bits = rans.scaled(counts)
    assert rans.decode(rans.encode(a, freq, bits), len(a), freq, bits).tolist() == seq
    data, size = arith.encode(seq, counts.tolist())
    assert arith.decode(data, len(seq), counts.tolist()) == seq
    if seq:
        ideal = len(seq) * T.entropy(counts / len(seq))
        assert size <= ideal + 2.01
        lengths = huffman.code_lengths(counts.tolist())
        text = huffman.encode(seq, lengths)
        assert huffman.decode(text, len(seq), lengths) == seq
        assert len(text) == huffman.total_bits(counts.tolist()) >= ideal - 1e-6
    for pack in ("byte", "bits"):
        assert zstd.decode(zstd.encode(a, pack, k), len(a), pack, k).tolist() == seq


def test_frequency_coder_is_near_ideal():
    rng = np.random.default_rng(1)
    for q in ([0.9, 0.1], [0.5, 0.25, 0.25], np.full(200, 1 / 200), [0.999, 0.001]):
        seq = rng.choice(len(q), 200_000, p=q)
        counts = np.bincount(seq, minlength=len(q))
        freq, bits = rans.scaled(counts)
        assert freq.sum() == 1 << bits
        data = rans.encode(seq, freq, bits)
        assert (rans.decode(data, len(seq), freq, bits) == seq).all()
        assert 8 * len(data) <= len(seq) * T.entropy(counts / len(seq)) * 1.01 + 32 * rans.lanes_for(len(seq)) + 64


def test_finite_state_machines():
    plain = FiniteStateEncoder(1, {(0, 0): "0", (1, 0): "1"}, {(0, 0): 0, (1, 0): 0})
    assert plain.is_lossless(6) and not plain.is_degenerate() and plain.encode([1, 0, 1]) == "101"
    silent = FiniteStateEncoder(1, {(0, 0): "", (1, 0): "1"}, {(0, 0): 0, (1, 0): 0})
    assert not silent.is_lossless(3) and silent.is_degenerate()
    pairs = FiniteStateEncoder(3, {(0, 0): "", (1, 0): "", (0, 1): "0", (1, 1): "10", (0, 2): "110", (1, 2): "111"}, {(0, 0): 1, (1, 0): 2, (0, 1): 0, (1, 1): 0, (0, 2): 0, (1, 2): 0})
    assert not pairs.is_degenerate()


def test_rans_lengths_of_many_sequences_at_once():
    """Short, long, empty and one-symbol sequences under alphabets of several sizes: as long as their codes."""
    import numpy as np

    from blockpress.coders import rans

    rng = np.random.default_rng(5)
    seqs = []
    for n, k in ((0, 3), (1, 2), (17, 5), (4095, 2), (9000, 256), (70_001, 4), (8192, 1), (300_000, 9)):
        seq = np.minimum(rng.geometric(0.4, n) - 1, k - 1)
        seqs.append((seq, *rans.scaled(np.bincount(seq, minlength=k) + (n == 0))))
    assert rans.coded_lengths(seqs) == [len(rans.encode(*s)) for s in seqs]


def test_two_symbol_lengths_are_those_of_codes():
    """Sparse, dense and even sequences, empty and one-sided ones, with lanes that end early."""
    rng = np.random.default_rng(3)
    seqs = []
    for n, p in ((0, 0.5), (1, 0.5), (5000, 0.001), (9001, 0.3), (40000, 0.002), (33333, 0.97), (8192, 0.0), (8200, 1.0)):
        seq = (rng.random(n) < p).astype(np.uint8)
        seqs.append((seq, *rans.scaled(np.bincount(seq, minlength=2) + (n == 5000))))
    assert rans.coded_lengths(seqs) == [len(rans.encode(*s)) for s in seqs]
    cells = (rng.random((300, 7)) < 0.1).astype(np.uint8)
    laws = [rans.scaled(np.bincount(c, minlength=2)) for c in cells.T]
    got = rans.column_lengths(cells, np.stack([f for f, _ in laws]), np.array([b for _, b in laws]))
    assert got.tolist() == [len(rans.encode(c, *law)) for c, law in zip(cells.T, laws, strict=True)]
