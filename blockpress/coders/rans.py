"""Frequency coder: range asymmetric numeral systems with interleaved lanes in numpy.

States are 32 bits wide and shed 16 bits at a time. Symbols go to lanes in turn, all lanes take a step
together, and the lanes' words of a step stand in lane order, so that decoding repeats the steps
forwards with the same array operations.
"""

from __future__ import annotations

import numpy as np

LOW = np.uint64(1 << 16)
#: Ones a lane below which lanes step only from their first one to their last, and steps after which lanes join in or leave.
FEW_ONES, STRETCH = 8, 256


def lanes_for(n: int) -> int:
    """Lanes for ``n`` symbols: their final states cost 32 bits each."""
    return max(1, min(1024, n // 4096))


def scaled(counts: np.ndarray, bits: int | None = None) -> tuple[np.ndarray, int]:
    """Frequencies that add up to a power of two, at least one for each symbol present."""
    counts = np.asarray(counts, np.int64)
    present = int((counts > 0).sum())
    bits = bits or max(12, min(16, present.bit_length() + 6))
    total = counts.sum()
    if not total:
        return counts, bits
    freq = np.where(counts > 0, np.maximum(1, counts * (1 << bits) // total), 0)
    gap = (1 << bits) - int(freq.sum())
    while gap:  # the most frequent symbols bear what is over or short
        order = np.argsort(-freq, kind="stable")[:present]
        if gap > 0:
            freq[order[0]] += gap
            gap = 0
        else:
            take = np.minimum(freq[order] - 1, np.maximum(1, -gap // present))
            for j, t in zip(order, take, strict=True):
                t = min(int(t), -gap)
                freq[j] -= t
                gap += t
    return freq, bits


def encode(seq: np.ndarray, freq: np.ndarray, bits: int) -> bytes:
    """Code of ``seq`` under scaled frequencies: final states, then words."""
    seq = np.asarray(seq, np.int64)
    n = len(seq)
    lanes = lanes_for(n)
    f = np.asarray(freq, np.uint64)
    c = np.cumsum(f) - f
    state = np.full(lanes, LOW)
    shift, out = np.uint64(bits), []
    for at in range((n - 1) // lanes * lanes if n else -1, -1, -lanes):
        s = seq[at : at + lanes]
        x, fs = state[: len(s)], f[s]
        full = x >= (fs << (np.uint64(32) - shift))
        out.append((x[full] & np.uint64(0xFFFF)).astype("<u2"))
        x = np.where(full, x >> np.uint64(16), x)
        state[: len(s)] = (x // fs << shift) + x % fs + c[s]
    return state.astype("<u4").tobytes() + b"".join(w.tobytes() for w in reversed(out))


def coded_lengths(seqs: list[tuple[np.ndarray, np.ndarray, int]]) -> list[int]:
    """Bytes of ``encode`` for each ``(seq, freq, bits)``, without them: the lanes of all sequences take their steps together.

    Whole numbers below 2^53 are exact as doubles, so states are held as such. A sequence joins in at its own last
    step; lanes without a symbol there take one that changes nothing.
    """
    if seqs and all(len(freq) == 2 for _, freq, _ in seqs):
        return _two_symbol_lengths(seqs)
    lanes = np.array([lanes_for(len(s)) for s, _, _ in seqs], np.int64)
    steps = np.array([-(-len(s) // k) for (s, _, _), k in zip(seqs, lanes.tolist(), strict=True)], np.int64)
    order = np.argsort(-steps, kind="stable")
    top, total = int(steps.max(initial=0)), int(lanes.sum())
    symbol = np.zeros((top, total), np.int32)
    tables = [np.array([[1.0], [0.0], [np.inf], [0.0]])]
    at, base = 0, 1
    width = np.zeros(top + 1, np.int64)
    for i in order.tolist():
        seq, freq, bits = seqs[i]
        k, m = int(lanes[i]), int(steps[i])
        flat = np.zeros(m * k, np.int32)
        flat[: len(seq)] = seq
        flat[: len(seq)] += base
        symbol[:m, at : at + k] = flat.reshape(m, k)
        f = np.asarray(freq, np.float64)
        tables.append(np.stack([f, (1 << bits) - f, f * (1 << (32 - bits)), np.cumsum(f) - f]))
        at, base = at + k, base + len(f)
        width[:m] = at
    share, rest, full_at, before = np.concatenate(tables, axis=1)
    state, words = np.full(total, float(LOW)), np.zeros(total, np.int64)
    for t in range(top - 1, -1, -1):
        x, s = state[: width[t]], symbol[t, : width[t]]
        full = x >= full_at[s]
        words[: width[t]] += full
        np.copyto(x, np.floor(x * 2.0**-16), where=full)
        x += np.floor(x / share[s]) * rest[s] + before[s]
    out = np.zeros(len(seqs), np.int64)
    ends = np.cumsum(lanes[order])
    sums = np.concatenate([[0], np.cumsum(words)])
    out[order] = 4 * lanes[order] + 2 * (sums[ends] - sums[ends - lanes[order]])
    return out.tolist()


def _two_symbol_lengths(seqs: list[tuple[np.ndarray, np.ndarray, int]]) -> list[int]:
    """``coded_lengths`` over two symbols: all lanes step as for a zero, and those that have a one there, or no symbol, are put right."""
    places = [np.flatnonzero(s.view(bool) if s.dtype == np.uint8 else s) for s, _, _ in seqs]
    if sum(map(len, places)) < FEW_ONES * sum(lanes_for(len(s)) for s, _, _ in seqs):
        return lengths_by_ones([(len(s), at, freq, bits) for (s, freq, bits), at in zip(seqs, places, strict=True)])
    lanes = np.array([lanes_for(len(s)) for s, _, _ in seqs], np.int64)
    steps = np.array([-(-len(s) // k) for (s, _, _), k in zip(seqs, lanes.tolist(), strict=True)], np.int64)
    order = np.argsort(-steps, kind="stable")
    top, total = int(steps.max(initial=0)), int(lanes.sum())
    law = np.zeros((3, 4, total))  # symbol (2: none); share, rest, where full, before
    law[2] = np.array([1.0, 0.0, np.inf, 0.0])[:, None]
    width, at = np.zeros(top + 1, np.int64), 0
    when, where, kind = [], [], []
    for i in order.tolist():
        seq, freq, bits = seqs[i]
        k, m = int(lanes[i]), int(steps[i])
        for x, f in enumerate(np.asarray(freq, np.float64).tolist()):
            law[x, :, at : at + k] = np.array([f, (1 << bits) - f, f * (1 << (32 - bits)), x * float(freq[0])] if f else [1.0, 0.0, np.inf, 0.0])[:, None]
        other = np.concatenate([places[i], np.arange(len(seq), m * k)])
        when.append(other // k)
        where.append(other % k + at)
        kind.append(np.where(other < len(seq), 1, 2))
        at += k
        width[:m] = at
    when, where, kind = (np.concatenate(x) for x in (when, where, kind))
    by_step = np.argsort(when, kind="stable")
    where, kind = where[by_step], kind[by_step]
    first = np.searchsorted(when[by_step], np.arange(top + 1))
    state, words, ratio = np.full(total, float(LOW)), np.zeros(total, np.int64), np.empty(total)
    share, rest, full_at, _ = np.ascontiguousarray(law[0])
    for t in range(top - 1, -1, -1):
        w, mine, own = width[t], where[first[t] : first[t + 1]], kind[first[t] : first[t + 1]]
        x, q, old = state[:w], ratio[:w], state[mine]
        full = x >= full_at[:w]
        full[mine] = False
        full = np.flatnonzero(full)
        if len(full):
            words[full] += 1
            x[full] = np.floor(x[full] * 2.0**-16)
        np.divide(x, share[:w], out=q)
        np.floor(q, out=q)
        q *= rest[:w]
        x += q
        if len(mine):
            one = law[own, :, mine].T
            full = old >= one[2]
            words[mine] += full
            old = np.where(full, np.floor(old * 2.0**-16), old)
            x[mine] = old + np.floor(old / one[0]) * one[1] + one[3]
    out = np.zeros(len(seqs), np.int64)
    ends = np.cumsum(lanes[order])
    sums = np.concatenate([[0], np.cumsum(words)])
    out[order] = 4 * lanes[order] + 2 * (sums[ends] - sums[ends - lanes[order]])
    return out.tolist()


def lengths_by_ones(seqs: list[tuple[int, np.ndarray, np.ndarray, int]]) -> list[int]:
    """``coded_lengths`` of sequences of zeros and few ones, each ``(length, places of the ones, freq, bits)`` with its places in order.

    Until its first one a lane's state is that of any lane of zeros, so one of these steps for all; two a sequence, as lanes
    without a symbol in the last step begin a step later. After its last one a lane leaves once zeros alone can't fill its state.
    """
    lanes = np.array([lanes_for(m) for m, *_ in seqs], np.int64)
    steps = np.array([-(-m // k) for (m, *_), k in zip(seqs, lanes.tolist(), strict=True)], np.int64)
    base, q, r = np.cumsum(lanes) - lanes, len(seqs), 2 * len(seqs)
    law = np.zeros((2, 4, q))  # symbol; share, rest, where full, before
    for i, (_, _, freq, bits) in enumerate(seqs):
        for x, f in enumerate(np.asarray(freq, np.float64).tolist()):
            law[x, :, i] = [f, (1 << bits) - f, f * (1 << (32 - bits)), x * float(freq[0])] if f else [1.0, 0.0, np.inf, 0.0]
    own = np.repeat(np.arange(q), lanes)
    late = np.concatenate([np.arange(k) >= size - (m - 1) * k for (size, *_), k, m in zip(seqs, lanes.tolist(), steps.tolist(), strict=True)])
    start = np.concatenate([steps - 1, steps - 2])  # of lanes of zeros: of each sequence one of either kind
    model = own + q * late
    places = [at for _, at, _, _ in seqs]
    when = np.concatenate([x // k for x, k in zip(places, lanes.tolist(), strict=True)])
    where = np.concatenate([x % k + b for x, k, b in zip(places, lanes.tolist(), base.tolist(), strict=True)])
    by_step = np.argsort(when, kind="stable")
    when, where = when[by_step], where[by_step]
    first, last = np.full(len(own), -1), np.full(len(own), -1)
    first[where] = when  # the greatest comes last
    last[where[::-1]] = when[::-1]
    coming = np.flatnonzero(first >= 0)
    coming = coming[np.argsort(-first[coming], kind="stable")]
    comes = -first[coming]
    top = int(steps.max(initial=0))
    edges = np.unique(np.concatenate([np.arange(0, top + 1, STRETCH), [top], np.clip(start + 1, 0, None)]))[::-1]
    zeros, zero_words = np.full(r, float(LOW)), np.zeros(r, np.int64)
    at, place, words = np.zeros(0, np.int64), np.zeros(len(own), np.int64), np.full(len(own), -1)
    state, shed, joined = np.zeros(0), np.zeros(0, np.int64), 0
    growth = np.log((law[0, 0] + law[0, 1]) / law[0, 0])
    for hi, lo in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        new = coming[joined : (joined := int(np.searchsorted(comes, -lo, "right")))]
        at = np.concatenate([at, new])
        running = np.flatnonzero(start >= hi - 1)
        x = np.concatenate([zeros[running], state, zeros[model[new]]])
        count = np.concatenate([zero_words[running], shed, zero_words[model[new]]])
        place[at] = np.arange(len(at)) + len(running)
        seq = np.concatenate([running % q, own[at]])
        share, rest, full_at, _ = law[0][:, seq]
        begin, end = np.searchsorted(when, [lo, hi])
        ones = place[where[begin:end]]
        one = law[1][:, seq[ones]]
        bounds = np.searchsorted(when[begin:end], np.arange(lo, hi + 1)).tolist()
        ratio = np.empty(len(x))
        for t in range(hi - lo - 1, -1, -1):
            a, b = bounds[t], bounds[t + 1]
            full = x >= full_at
            if a < b:
                mine = ones[a:b]
                old, full[mine] = x[mine], False
            if full.any():
                count += full
                np.copyto(x, np.floor(x * 2.0**-16), where=full)
            np.divide(x, share, out=ratio)
            np.floor(ratio, out=ratio)
            ratio *= rest
            x += ratio
            if a < b:
                full = old >= one[2, a:b]
                count[mine] += full
                old = np.where(full, np.floor(old * 2.0**-16), old)
                x[mine] = old + np.floor(old / one[0, a:b]) * one[1, a:b] + one[3, a:b]
        zeros[running], zero_words[running] = x[: len(running)], count[: len(running)]
        state, shed, mine = x[len(running) :], count[len(running) :], own[at]
        done = (last[at] >= lo) & (np.log(state) + lo * growth[mine] < np.log(law[0, 2, mine]) - 1e-9)
        words[at[done]] = shed[done]
        at, state, shed = at[~done], state[~done], shed[~done]
    words[at] = shed
    words = np.where(words < 0, zero_words[model], words)
    return (4 * lanes + 2 * np.bincount(own, words, minlength=q).astype(np.int64)).tolist()


def column_lengths(cells: np.ndarray, freq: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Bytes of ``encode`` for each column of ``cells`` under its own ``freq`` (columns x symbols), where a column is short enough for one lane."""
    m, n = cells.shape
    if lanes_for(m) > 1:
        raise ValueError("columns of several lanes")
    f = np.asarray(freq, np.float64)
    if f.shape[1] == 2 and not (some := cells.any(axis=0)).all():  # columns of zeros under one law are alike
        alike = np.flatnonzero(~some)
        law = (f[alike, 0] * (1 << 17) + f[alike, 1]).astype(np.int64) * 32 + np.asarray(bits)[alike]  # frequencies are 2^16 at most
        _, one, which = np.unique(law, return_index=True, return_inverse=True)
        few, out = np.flatnonzero(some), np.zeros(n, np.int64)
        both = np.concatenate([few, alike[one]])
        cells, f, bits, n = np.ascontiguousarray(cells[:, both]), f[both], np.asarray(bits)[both], len(both)
        spread = lambda got: (out.__setitem__(few, got[: len(few)]), out.__setitem__(alike, got[len(few) :][which]), out)[-1]
    else:
        spread = lambda got: got
    full = np.ones(n, np.float64)
    np.ldexp(full, bits, out=full)
    shed = np.ldexp(f, 32 - np.asarray(bits)[:, None]).T.copy()
    rest, before, share = (full[:, None] - f).T.copy(), (np.cumsum(f, axis=1) - f).T.copy(), f.T.copy()
    state, words, two = np.full(n, float(LOW)), np.zeros(n, np.int64), f.shape[1] == 2
    at = np.arange(n)
    for t in range(m - 1, -1, -1):
        s = cells[t]
        pick = (lambda x, s=s: np.where(s, x[1], x[0])) if two else (lambda x, s=s: x[s, at])
        over = state >= pick(shed)
        words += over
        np.copyto(state, np.floor(state * 2.0**-16), where=over)
        state += np.floor(state / pick(share)) * pick(rest) + pick(before)
    return spread(4 + 2 * words)


def decode(data: bytes, n: int, freq: np.ndarray, bits: int) -> np.ndarray:
    lanes = lanes_for(n)
    f = np.asarray(freq, np.uint64)
    c = np.cumsum(f) - f
    symbol = np.repeat(np.arange(len(f)), f.astype(np.int64))
    state = np.frombuffer(data, "<u4", lanes).astype(np.uint64)
    words, at = np.frombuffer(data, "<u2", offset=4 * lanes).astype(np.uint64), 0
    out, mask, shift = np.empty(n, np.int64), np.uint64((1 << bits) - 1), np.uint64(bits)
    for lo in range(0, n, lanes):
        m = min(lanes, n - lo)
        x = state[:m]
        slot = x & mask
        s = symbol[slot.astype(np.int64)]
        out[lo : lo + m] = s
        x = f[s] * (x >> shift) + slot - c[s]
        low = x < LOW
        k = int(low.sum())
        x[low] = x[low] << np.uint64(16) | words[at : at + k]
        at += k
        state[:m] = x
    return out
