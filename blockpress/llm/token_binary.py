"""Token-id files: Simple-8b word-aligned coding (operator 5).

A 64-bit word holds a 4-bit selector and 60 bits of payload. Selector ``s`` of ``COUNTS`` packs that
many ids of ``60 // count`` bits each; ``ESCAPE`` holds one id too wide for all of them. Blocks carry
the number of ids of each of their documents, so that a block decodes with a handful of array
operations and any document is reached without decoding what precedes its block.

Cases: null or empty text: the end id alone; a null ``doc_id`` sorts first; repeated ``doc_id``: each
row is kept, in no set order among themselves; further columns are ignored; an empty table gives an
empty file.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.llm.common import free_columns, shared_dir, slices
from blockpress.llm.tokens import encoder

# fixed values: ids to a word, by selector
COUNTS = (60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2)
ESCAPE = len(COUNTS)
#: Ids that a block holds at least, but for the last one of a shard.
BLOCK_IDS = 1 << 16
#: Bytes of text tokenised in one step.
BATCH_BYTES = 3 << 20

FILE_SCHEMA = "shard int, block long, doc_ids array<long>, lengths array<long>, n_ids long, words binary"


def pack(ids: np.ndarray) -> np.ndarray:
    """Simple-8b words of unsigned ids below 2**60: the fullest selector that fits, from left to right."""
    ids = ids.astype(np.uint64)
    n = len(ids)
    if not n:
        return np.zeros(0, np.uint64)
    if int(ids.max()) >= 1 << 60:
        raise ValueError("ids must be below 2**60")
    edges = np.array(sorted({60 // c for c in COUNTS}), np.uint64)  # payload widths
    need = np.searchsorted(np.left_shift(np.uint64(1), edges), ids, side="right").astype(np.uint8)  # index of the width that an id needs
    width_at = {int(w): k for k, w in enumerate(edges)}
    choice = np.full(n, ESCAPE, np.uint8)
    for s in reversed(range(len(COUNTS))):
        c = COUNTS[s]
        if c > n:
            continue
        most = _window_max(need, c)
        ok = most <= width_at[60 // c]
        choice[: len(ok)][ok] = s
    heads = _heads(np.array([*COUNTS, 1])[choice])
    sel = choice[heads]
    words = sel.astype(np.uint64) << np.uint64(60)
    for s in np.unique(sel):
        rows = np.flatnonzero(sel == s)
        if s == ESCAPE:
            words[rows] |= ids[heads[rows]]
            continue
        width = 60 // COUNTS[s]
        for j in range(COUNTS[s]):
            words[rows] |= ids[heads[rows] + j] << np.uint64(width * j)
    return words


def _heads(step: np.ndarray) -> np.ndarray:
    """Places met when each place leads ``step`` places on, from 0: all stretches of the way at once.

    Ways into a stretch soon join, so each stretch is walked from its first ``60`` places in parallel
    and then only the place where the stretch before really ends counts.
    """
    n, wide = len(step), max(COUNTS)
    stretch = 4096
    if n <= 2 * stretch:
        heads, i, steps = [], 0, step.tolist()
        while i < n:
            heads.append(i)
            i += steps[i]
        return np.array(heads)
    begins = np.arange(0, n, stretch)
    # one walk a stretch from its first place, kept as marks; entries elsewhere walk until they meet a mark
    onto = np.arange(n) + step
    marks = np.zeros(n + wide + 1, bool)
    at, ends = begins.copy(), np.minimum(begins + stretch, n)
    live = np.arange(len(begins))
    while len(live):
        marks[at[live]] = True
        at[live] = onto[at[live]]
        live = live[at[live] < ends[live]]
    out = np.zeros(n, bool)
    entry = 0
    for k, (lo, hi) in enumerate(zip(begins.tolist(), ends.tolist(), strict=True)):
        i = entry
        while i < hi and not marks[i]:
            out[i] = True
            i = int(onto[i])
        if i < hi:
            out[i:hi] = marks[i:hi]
            entry = int(at[k])
        else:
            entry = i
    return np.flatnonzero(out)


def _window_max(x: np.ndarray, c: int) -> np.ndarray:
    """Maximum of each ``c`` values in a row."""
    best, have = x, 1
    while have < c:
        step = min(have, c - have)
        best = np.maximum(best[: len(best) - step], best[step:])
        have += step
    return best


def unpack(words: np.ndarray) -> np.ndarray:
    """The ids of ``pack``'s words, a selector at a time."""
    sel = (words >> np.uint64(60)).astype(np.int64)
    count = np.array([*COUNTS, 1])[sel]
    at = np.cumsum(count) - count
    out = np.zeros(int(count.sum()), np.uint64)
    for s in np.unique(sel):
        rows = np.flatnonzero(sel == s)
        c = 1 if s == ESCAPE else COUNTS[s]
        mask = np.uint64((1 << (60 // c)) - 1)
        for j in range(c):
            out[at[rows] + j] = (words[rows] >> np.uint64((60 // c) * j)) & mask
    return out


def write_token_file(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, byte_level: bool = True) -> None:
    """Encode ``docs(doc_id, text)`` and write blocks in ascending ``doc_id`` order to ``path``.

    One shuffle: texts by range of ``doc_id``. The container is Parquet, so any store that Spark
    writes to will do; a shard is what one range holds.
    """
    n = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ordered = free_columns(docs, ["doc_id", "text"]).repartitionByRange(n, "doc_id").sortWithinPartitions("doc_id")

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, shard, block = encoder(tokenizer, byte_level), TaskContext.get().partitionId(), 0
        doc_ids: list = []
        sizes: list[np.ndarray] = []
        parts: list[np.ndarray] = []
        held = 0

        def flush() -> pa.RecordBatch:
            ids = np.concatenate(parts)
            cols = [[shard], [block], [doc_ids], [np.concatenate(sizes)], [len(ids)], [pack(ids).astype("<u8").tobytes()]]
            types = [pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64(), pa.binary()]
            return pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["shard", "block", "doc_ids", "lengths", "n_ids", "words"])

        for batch in slices(batches, "text", BATCH_BYTES):
            ids, at = enc.encode_ended(batch.column("text"), end_id)
            names, lo, n = batch.column("doc_id").to_pylist(), 0, batch.num_rows
            while lo < n:  # blocks end with the document that fills them
                hi = min(n, int(np.searchsorted(at, at[lo] + BLOCK_IDS - held, side="left")))
                hi = max(hi, lo + 1)
                doc_ids += names[lo:hi]
                sizes.append(np.diff(at[lo : hi + 1]))
                parts.append(ids[at[lo] : at[hi]])
                held += int(at[hi] - at[lo])
                lo = hi
                if held >= BLOCK_IDS:
                    yield flush()
                    doc_ids, sizes, parts, held, block = [], [], [], 0, block + 1
        if parts:
            yield flush()

    ordered.mapInArrow(blocks, FILE_SCHEMA).write.parquet(path)


def read_token_file(spark, path: str) -> DataFrame:
    """``(doc_id, shard, block, at, ids)``: ``at`` counts the ids before the document in its block."""

    def docs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids = unpack(np.frombuffer(row["words"], "<u8")).astype(np.uint32)
                at = np.concatenate([[0], np.cumsum(row["lengths"])]).astype(np.int64)
                lists = pa.LargeListArray.from_arrays(pa.array(at), pa.array(ids.astype(np.int64)))
                n = len(row["doc_ids"])
                yield pa.record_batch([pa.array(row["doc_ids"], pa.int64()), pa.array([row["shard"]] * n, pa.int32()), pa.array([row["block"]] * n, pa.int64()), pa.array(at[:-1]), lists.cast(pa.list_(pa.int64()))], names=["doc_id", "shard", "block", "at", "ids"])

    return _blocks(spark, path).mapInArrow(docs, "doc_id long, shard int, block long, at long, ids array<long>")


def _blocks(spark, path: str) -> DataFrame:
    return spark.read.schema(FILE_SCHEMA).parquet(path)


def document_digests(spark, path: str) -> DataFrame:
    """Per document of a token file: its place, number of ids and their CRC-32, from the words alone."""

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids = unpack(np.frombuffer(row["words"], "<u8")).astype("<u4")
                ends = np.cumsum(row["lengths"]).astype(np.int64)
                n, view = len(ends), memoryview(ids.tobytes())
                begins = ends - np.array(row["lengths"], np.int64)
                crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(begins.tolist(), ends.tolist(), strict=True)]
                yield pa.record_batch([pa.array(row["doc_ids"], pa.int64()), pa.array([row["shard"]] * n, pa.int32()), pa.array([row["block"]] * n, pa.int64()), pa.array(begins), pa.array(ends - begins), pa.array(crc, pa.int64())], names=["doc_id", "shard", "block", "at", "n_tokens", "ids_crc32"])

    docs = _blocks(spark, path).mapInArrow(digests, "doc_id long, shard int, block long, at long, n_tokens long, ids_crc32 long")
    sizes = _blocks(spark, path).select("shard", "block", "n_ids")
    before = sizes.select("shard", "block", (F.sum("n_ids").over(Window.partitionBy("shard").orderBy("block")) - F.col("n_ids")).alias("in_shard"))
    shards = sizes.groupBy("shard").agg(F.sum("n_ids").alias("n"))  # a row for each shard
    shards = shards.select("shard", (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("in_file"))
    return docs.join(before.join(shards, "shard"), ["shard", "block"]).select("doc_id", (F.col("in_file") + F.col("in_shard") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def encode_to_file_and_back(docs: DataFrame, tokenizer: str, end_id: int = 0) -> DataFrame:
    """Write a token file to shared storage, read it back, and give what it holds of each document."""
    spark = docs.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/token-file-{uuid.uuid4().hex}"
    write_token_file(docs, path, tokenizer, end_id)
    return document_digests(spark, path)
