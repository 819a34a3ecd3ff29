"""Exact token ids through the ``tokenizers`` library, with a cache of blank-free pieces.

A piece is what stands between spaces, line feeds and, in texts without runs of punctuation, before
full stops and commas. For the two kinds of vocabulary used here (byte-level BPE whose words carry
their leading space; BPE with word ends and white space dropped) the library's own pre-tokenizers
never join characters across such a place, so the ids of a text are the ids of its pieces. Arrow
cuts the texts and numbers their distinct pieces, and each distinct piece goes through the library
once in a Python worker. Texts for which that could fail go through the library whole.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from blockpress.llm.common import _BASE, _BYTE, mixed, text_bytes

#: Distinct pieces that a worker keeps.
CACHE_PIECES = 1_200_000
_BLANK = re.compile(r"\s")
#: Places where a full stop or comma could belong to a longer run of signs.
_RUNS = r"(^|[^\pL\pN])[.,]|[.,][^\pL\pN \n]"
_BLANKS = r"[\s\pZ\x{85}\x{0b}\x{1c}-\x{1f}]{2}"
_CUT = "\0"


def _piece_hashes(pieces: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit hashes of each piece."""
    raw, at = text_bytes(pieces)
    size = np.diff(at)
    full = np.flatnonzero(size)
    a, b = np.zeros(len(size), np.uint64), np.zeros(len(size), np.uint64)
    if len(full):
        place = np.arange(len(raw)) - np.repeat(at[:-1], size)
        power = np.multiply.accumulate(np.full(int(size.max()) + 1, _BASE, np.uint64))[place]
        a[full] = np.add.reduceat(_BYTE[raw] * power, at[full])
        b[full] = np.add.reduceat(_BYTE[raw ^ 0xFF] * (power >> np.uint64(7) | np.uint64(1)), at[full])
    return mixed(a + size.astype(np.uint64)), mixed(b)


class Encoder:
    """``encode(texts)``: all ids of an array of texts, and offsets by text."""

    def __init__(self, path: str, byte_level: bool):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = True  # their strings in a text are ordinary text
        self.byte_level = byte_level
        self.mark = "\n" if byte_level else " 0 "
        mark = self._whole(["\n" if byte_level else "0"])[0]
        if len(mark) != 1:
            raise ValueError("the separator must be one id")
        self.mark_id = int(mark[0])
        self._reset()

    def _reset(self) -> None:
        self.name = np.zeros(0, np.uint64)  # pieces' hashes, sorted
        self.check = np.zeros(0, np.uint64)  # second hashes of the same
        self.begin = np.zeros(0, np.int64)
        self.size = np.zeros(0, np.int32)
        self.ids = np.zeros(1 << 16, np.uint32)
        self.used = 0

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: pa.Array, name: np.ndarray, check: np.ndarray) -> None:
        """Encode new pieces: many in one text, kept apart by a separator that never merges."""
        text = pieces.to_pylist()
        if self.byte_level:
            odd = [k for k, p in enumerate(text) if not p or p == "\n" or _BLANK.search(p, 1)]
        else:
            odd = [k for k, p in enumerate(text) if not p or "0" in p]
        apart = np.zeros(len(text), bool)
        apart[odd] = True
        plain = np.flatnonzero(~apart)
        which, sizes, parts = [], [], []
        for lo in range(0, len(plain), 1000):
            part = plain[lo : lo + 1000]
            ids = self._whole([self.mark.join([text[k] for k in part.tolist()])])[0]
            cut = np.flatnonzero(ids == self.mark_id)
            if len(cut) != len(part) - 1:
                odd += part.tolist()
                continue
            which.append(part)
            sizes.append(np.diff(np.concatenate([[-1], cut, [len(ids)]])) - 1)
            parts.append(np.delete(ids, cut))
        if odd:
            arrays = self._whole([text[k] for k in odd])
            which.append(np.array(odd))
            sizes.append(np.array([len(a) for a in arrays]))
            parts += arrays
        which, sizes, ids = np.concatenate(which), np.concatenate(sizes), np.concatenate(parts)
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        self.ids[self.used : self.used + len(ids)] = ids
        begin = self.used + np.cumsum(sizes) - sizes
        self.used += len(ids)
        order = np.argsort(name[which])
        which, begin, sizes = which[order], begin[order], sizes[order]
        at = np.searchsorted(self.name, name[which])
        self.name, self.check = np.insert(self.name, at, name[which]), np.insert(self.check, at, check[which])
        self.begin, self.size = np.insert(self.begin, at, begin), np.insert(self.size, at, sizes)

    def _find(self, name: np.ndarray, check: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Slots of pieces, and whether each is known."""
        at = np.searchsorted(self.name, name)
        if not len(self.name):
            return at, np.zeros(len(name), bool)
        at = np.minimum(at, len(self.name) - 1)
        return at, (self.name[at] == name) & (self.check[at] == check)

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.combine_chunks()
        texts = texts.cast(pa.large_string()).fill_null("")
        data = texts.buffers()[2]
        unsafe = pc.match_substring(texts, _CUT) if data is not None and _CUT.encode() in memoryview(data).tobytes() else pa.array(np.zeros(len(texts), bool))
        if self.byte_level:
            unsafe = pc.or_(unsafe, pc.match_substring_regex(texts, _BLANKS))
        whole = np.flatnonzero(unsafe.to_numpy(zero_copy_only=False))
        kept = pc.if_else(unsafe, "", texts) if len(whole) else texts
        signs = pc.replace_substring(pc.replace_substring(kept, ".", _CUT + "."), ",", _CUT + ",")
        kept = pc.if_else(pc.match_substring_regex(kept, _RUNS), kept, signs)
        if self.byte_level:
            kept = pc.replace_substring(pc.replace_substring(kept, " ", _CUT + " "), "\n", f"{_CUT}\n{_CUT}")
        else:
            kept = pc.replace_substring(pc.replace_substring(kept, " ", _CUT), "\n", _CUT)
        lists = pc.split_pattern(kept, _CUT)
        coded = lists.flatten().dictionary_encode()
        if len(self.name) > CACHE_PIECES:
            self._reset()
        name, check = _piece_hashes(coded.dictionary)
        slot, known = self._find(name, check)
        if not known.all():
            new = np.flatnonzero(~known)
            self._learn(coded.dictionary.take(pa.array(new)), name[new], check[new])
            slot, known = self._find(name, check)
            if not known.all():
                raise RuntimeError("two pieces share a hash")
        index = coded.indices.to_numpy()
        size = self.size[slot][index]
        ends = np.cumsum(size, dtype=np.int64)
        lead = self.begin[slot][index] - (ends - size)
        total = int(ends[-1]) if len(ends) else 0
        at = np.arange(total)
        at += np.repeat(lead, size)
        ids = self.ids[at]
        places = lists.offsets.to_numpy() - lists.offsets[0].as_py()
        offsets = np.concatenate([[0], ends])[places]
        if len(whole):
            parts = [ids[a:b] for a, b in zip(offsets, offsets[1:], strict=False)]
            for k, a in zip(whole.tolist(), self._whole(texts.take(pa.array(whole)).to_pylist()), strict=True):
                parts[k] = a
            ids = np.concatenate(parts)
            offsets = np.concatenate([[0], np.cumsum([len(p) for p in parts])])
        return ids, offsets

    def encode_ended(self, texts: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """As ``encode``, with ``end_id`` behind each text's ids."""
        ids, offsets = self.encode(texts)
        n = len(offsets) - 1
        ends = offsets[1:] + np.arange(1, n + 1)
        out = np.empty(len(ids) + n, np.uint32)
        own = np.ones(len(out), bool)
        own[ends - 1] = False
        out[own] = ids
        out[ends - 1] = end_id
        return out, np.concatenate([[0], ends])


_encoders: dict[str, Encoder] = {}


def encoder(path: str, byte_level: bool) -> Encoder:
    """One encoder for each Python worker."""
    if path not in _encoders:
        _encoders[path] = Encoder(path, byte_level)
    return _encoders[path]
