"""Unigram token counts without tokenising (operator 3).

An Aho-Corasick automaton lists the vocabulary's pieces that end at each character; dynamic
programming carries the best score and the number of pieces up to there, and nothing is traced back.
The rules are those of the ``tokenizers`` library's Unigram model: of equal scores the one that
begins first wins, a character without a piece of its own costs ten below the least score, and such
characters in a row count once. Words are what stands between spaces, each with the space mark in
front; no piece goes beyond a mark within, so words count apart, and each distinct word counts once in a
worker.

Cases: null or empty text: no tokens; repeated rows: each its own; texts of any length are counted
whole, and a word without a blank takes no more room than its own characters; further columns are ignored; no rows: no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from blockpress.llm.common import free_columns, slices

MARK = "▁"
#: Below the least score, for a character that the vocabulary lacks (fixed value of the library).
UNKNOWN_PENALTY = 10.0
CACHE_WORDS = 1_000_000


def unigram_vocabulary(model_file: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece file, in id order."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    return [(sp.id_to_piece(i), sp.get_score(i)) for i in range(sp.get_piece_size())]


class Counter:
    """``count(text)``: how many tokens the Unigram model gives."""

    def __init__(self, vocabulary: list[tuple[str, float]], unknown_id: int = 0):
        import ahocorasick

        self.trie = ahocorasick.Automaton()
        self.single: set[str] = set()
        scores = dict(reversed(vocabulary)) if len({p for p, _ in vocabulary}) == len(vocabulary) else dict(vocabulary)
        self.unknown = min(s for _, s in vocabulary) - UNKNOWN_PENALTY
        for piece, score in scores.items():
            if piece:
                self.trie.add_word(piece, (len(piece), score))
                if len(piece) == 1:
                    self.single.add(piece)
        self.trie.make_automaton()
        self.longest = max(map(len, scores), default=1)
        self.cache: dict[str, int] = {}

    def word(self, word: str) -> int:
        """Tokens of one word, its mark included."""
        ring = self.longest + 1  # no piece reaches back farther, however long the word
        best, count, lost = [0.0] * ring, [0] * ring, [False] * ring
        matches = self.trie.iter(word)
        last, match = next(matches, (-1, None))
        for end in range(1, len(word) + 1):
            found = None
            while match is not None and last == end - 1:  # the longest first: it begins first
                size, score = match
                total = score + best[(end - size) % ring]
                if found is None or total > found:
                    found, begin = total, (end - size) % ring
                last, match = next(matches, (-1, None))
            unknown, here = False, end % ring
            if word[end - 1] not in self.single:
                total = self.unknown + best[(end - 1) % ring]
                if found is None or total > found:
                    found, begin, unknown = total, (end - 1) % ring, True
            tokens = count[begin] + (0 if unknown and lost[begin] else 1)
            best[here], count[here], lost[here] = found, tokens, unknown
        return count[len(word) % ring]

    def words(self, text: str) -> list[str]:
        if not text:
            return []
        if MARK in text:
            text = text.replace(MARK, " ")
        return text.removeprefix(" ").split(" ")

    def count(self, texts: list[str]) -> list[int]:
        split = [self.words(t) for t in texts]
        if len(self.cache) > CACHE_WORDS:
            self.cache.clear()
        cache = self.cache
        for w in {w for s in split for w in s} - cache.keys():
            cache[w] = self.word(MARK + w)
        get = cache.__getitem__
        return [sum(map(get, s)) for s in split]


_counters: dict[tuple, Counter] = {}


def count_tokens(docs: DataFrame, model_file: str) -> DataFrame:
    """``(doc_id, n_chars, n_tokens)`` of ``docs(doc_id, text)``: one scan, no shuffle."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if model_file not in _counters:
            _counters[model_file] = Counter(unigram_vocabulary(model_file))
        counter = _counters[model_file]
        for batch in slices(batches, "text"):
            texts = batch.column("text").fill_null("").to_pylist()
            yield pa.record_batch([batch.column("doc_id"), pa.array(list(map(len, texts)), pa.int64()), pa.array(counter.count(texts), pa.int64())], names=["doc_id", "n_chars", "n_tokens"])

    return free_columns(docs, ["doc_id", "text"]).mapInArrow(emit, "doc_id long, n_chars long, n_tokens long")
