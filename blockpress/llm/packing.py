"""Best-fit-decreasing packing of token documents into sequences (operator 8).

What best-fit-decreasing does depends only on how many pieces there are of each length, and lengths
are whole numbers up to the capacity. So the packing is planned on counts: open bins are kept by
remaining capacity, and a segment tree over capacities finds the tightest open bin for a length in
logarithmic time; equal pieces that meet equal bins move together. The plan is a list of runs, whose
number depends on the capacity and not on the data's size, and each piece finds its slot from its
length and its rank among the pieces of that length. The result is that of the one-at-a-time method.

Cases: null or empty text: the end id alone; repeated ``doc_id``: rows are packed one by one, as if
they were different; further columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.llm.common import free_columns, slices, stored
from blockpress.llm.tokens import encoder

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long"
#: Bytes of text tokenised in one step.
BATCH_BYTES = 3 << 20


class CapacityTree:
    """Segment tree over remaining capacities 0..capacity: which of them open bins have."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.any = [False] * (2 * self.size)

    def put(self, r: int, there: bool) -> None:
        k = r + self.size
        self.any[k] = there
        while k > 1:
            k >>= 1
            self.any[k] = self.any[2 * k] or self.any[2 * k + 1]

    def tightest(self, need: int) -> int | None:
        """The least capacity of an open bin that is ``need`` or more."""
        k = need + self.size
        if self.any[k]:
            return need
        while k > 1:
            if not k & 1 and self.any[k + 1]:
                k += 1
                while k < self.size:
                    k = 2 * k if self.any[2 * k] else 2 * k + 1
                return k - self.size
            k >>= 1
        return None


def plan(counts: dict[int, int], capacity: int) -> tuple[np.ndarray, int]:
    """Runs ``(length, first rank, last rank + 1, first bin, pieces a bin, offset)`` and the number of bins.

    Ranks from ``first`` on fill bins ``first bin``, ``first bin + 1`` ..., so many pieces each.
    """
    tree = CapacityTree(capacity)
    open_bins: dict[int, list[tuple[int, int]]] = defaultdict(list)  # remaining -> (first bin, number)
    runs: list[tuple[int, int, int, int, int, int]] = []
    bins = 0

    def keep(r: int, first: int, number: int) -> None:
        if r > 0 and number > 0:
            if not open_bins[r]:
                tree.put(r, True)
            open_bins[r].append((first, number))

    for length in sorted((x for x, c in counts.items() if c > 0), reverse=True):
        if not 0 < length <= capacity:
            raise ValueError("lengths must be from 1 to the capacity")
        left, rank = counts[length], 0
        while left:
            r = tree.tightest(length)
            if r is None:
                r, first, number = capacity, bins, -(-left // (capacity // length))
                bins += number
            else:
                first, number = open_bins[r].pop()
                if not open_bins[r]:
                    tree.put(r, False)
            each = r // length  # a bin once chosen stays the tightest until the length no longer fits
            full = min(number, left // each)
            if full:
                runs.append((length, rank, rank + full * each, first, each, capacity - r))
                keep(r - each * length, first, full)
                rank, left = rank + full * each, left - full * each
            if full < number:
                rest = min(left, each - 1) if left < each else 0
                if rest:
                    runs.append((length, rank, rank + rest, first + full, rest, capacity - r))
                    keep(r - rest * length, first + full, 1)
                    rank, left, full = rank + rest, left - rest, full + 1
                keep(r, first + full, number - full)
    return np.array(runs, np.int64).reshape(-1, 6), bins


def pieces_of(docs: DataFrame, tokenizer: str, capacity: int, end_id: int = 0, byte_level: bool = False) -> DataFrame:
    """Token pieces of at most ``capacity`` ids, with their rank among those of their length and task."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part = encoder(tokenizer, byte_level), TaskContext.get().partitionId()
        seen: dict[int, int] = defaultdict(int)
        for batch in slices(batches, "text", BATCH_BYTES):
            ids, at = enc.encode_ended(batch.column("text"), end_id)
            view, rows = memoryview(ids.astype("<u4").tobytes()), []
            for doc_id, lo, hi in zip(batch.column("doc_id").to_pylist(), at[:-1].tolist(), at[1:].tolist(), strict=True):
                for k, begin in enumerate(range(lo, hi, capacity)):
                    size = min(capacity, hi - begin)
                    rows.append((doc_id, k, begin - lo, size, zlib.crc32(view[4 * begin : 4 * (begin + size)]), part, seen[size]))
                    seen[size] += 1
            cols = list(zip(*rows, strict=True))
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=[f.split()[0] for f in PIECES.split(", ")])

    return free_columns(docs, ["doc_id", "text"]).mapInArrow(cut, PIECES)


def place(pieces: DataFrame, capacity: int) -> DataFrame:
    """Assign each piece its ``sequence_id`` and ``offset``. ``pieces`` must be stored: ranks may not change."""
    held = pieces.groupBy("part", "length").agg(F.count("*").alias("n"))
    base = held.select("part", "length", (F.sum("n").over(Window.partitionBy("length").orderBy("part")) - F.col("n")).alias("base"))
    counts = {r.length: r.n for r in held.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # `capacity` rows at most
    runs, _ = plan(counts, capacity)
    key = runs[:, 0] * (1 << 44) + runs[:, 1] if len(runs) else np.zeros(0, np.int64)
    order = np.argsort(key)
    key, runs = key[order], runs[order]
    names = ["doc_id", "piece", "start", "length", "ids_crc32"]

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            run = runs[np.searchsorted(key, length * (1 << 44) + rank, side="right") - 1]
            nth = rank - run[:, 1]
            seq = run[:, 3] + nth // run[:, 4]
            off = run[:, 5] + (nth % run[:, 4]) * length
            yield pa.record_batch([*(batch.column(c) for c in names), pa.array(seq), pa.array(off)], names=[*names, "sequence_id", "offset"])

    ranked = pieces.join(base, ["part", "length"]).select(*names, (F.col("base") + F.col("nth")).alias("rank"))
    return ranked.mapInArrow(assign, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def best_fit_pack(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, byte_level: bool = False) -> DataFrame:
    """Pack all of ``docs(doc_id, text)``; documents of more than ``capacity`` ids are cut, others stay whole."""
    return place(stored(pieces_of(docs, tokenizer, capacity, end_id, byte_level), "pieces"), capacity)
