"""What the corpus operators share: table access, shared storage, text buffers."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from blockpress.sources.storage import kept, shared_dir  # noqa: F401

#: Bytes of text that one vectorised step handles at a time; longer texts stand alone.
STEP_BYTES = 1 << 19


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to shared storage and read it back: cuts lineage, survives lost executors."""
    return kept(df, name, "zstd")


#: Rows of an Arrow batch: texts are long, and a batch stands in memory on both sides of the hand-over.
BATCH_ROWS = 1000


def small_batches(spark: SparkSession) -> None:
    """Lower the session's limit of rows in an Arrow batch to ``BATCH_ROWS``: a setting of the session, which stays."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def free_columns(df: DataFrame, wanted: list[str]) -> DataFrame:
    """Only the columns an operator reads: further columns, whatever their names, do no harm."""
    small_batches(df.sparkSession)
    return df.select(*[df[c] for c in wanted])


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column as one array, and the offsets of its values (null: empty)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64, count=len(column) + 1 + column.offset)[column.offset :]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def give_back() -> None:
    """Return what a worker has freed to the system: workers live on between stages and share an executor's memory."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # a C library without it
        ctypes.CDLL(None).malloc_trim(0)


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that each holds about ``limit`` bytes of text at most, one row at least."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        give_back()
        _, at = text_bytes(batch.column(batch.schema.get_field_index(column)))
        lo = 0
        while lo < n:
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + limit, side="right")) - 1)
            yield batch.slice(lo, hi - lo)
            lo = hi


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values (constants of the public splitmix64 generator)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
#: A random 64-bit value for each byte value.
_BYTE = np.random.default_rng(20240131).integers(1, 1 << 63, 256, dtype=np.uint64)
_BASE = np.uint64(0x9E3779B97F4A7C15)


def word_hashes(raw: np.ndarray, at: np.ndarray, drop: np.ndarray | None = None, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words between ASCII blanks: 64-bit hashes, starts, ends, and the number of the first word of each text.

    ``drop`` marks byte values that do not count (punctuation, say); words made of such bytes alone vanish.
    """
    n = len(raw)
    first = np.zeros(len(at), np.int64)
    if not n:
        none = np.zeros(0, np.int64)
        return np.zeros(0, np.uint64), none, none, first
    if lower:
        raw = np.where((raw >= 65) & (raw <= 90), raw + 32, raw).astype(np.uint8)
    inside = ~_SPACE[raw]
    edge = inside.copy()
    edge[1:] &= ~inside[:-1]
    border = at[1:-1][(at[1:-1] > 0) & (at[1:-1] < n)]
    edge[border] = inside[border]
    starts = np.flatnonzero(edge)
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    last[border - 1] = inside[border - 1]
    ends = np.flatnonzero(last) + 1
    if not len(starts):
        return np.zeros(0, np.uint64), starts, ends, first
    kept = np.flatnonzero(inside if drop is None else inside & ~drop[raw])
    word = np.searchsorted(starts, kept, side="right") - 1 if drop is not None else np.cumsum(edge)[kept] - 1
    lead = np.searchsorted(word, np.arange(len(starts)))  # first kept byte of each word
    count = np.diff(np.append(lead, len(word)))
    place = np.arange(len(word)) - lead[word]
    power = np.multiply.accumulate(np.full(int(count.max(initial=0)) + 1, _BASE, np.uint64))
    term = _BYTE[raw[kept]] * power[place]
    full = count > 0
    starts, ends = starts[full], ends[full]
    h = mixed(np.add.reduceat(term, lead[full])) if full.any() else np.zeros(0, np.uint64)
    return h, starts, ends, np.searchsorted(starts, at)


def shingle_hashes(h: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each run of ``k`` words within a text (fewer words: the whole run; none: nothing), and offsets by text."""
    words = np.diff(first)
    count = np.where(words >= k, words - k + 1, (words > 0).astype(np.int64))
    out = np.zeros(len(count) + 1, np.int64)
    np.cumsum(count, out=out[1:])
    power = [np.uint64(pow(int(_BASE), e + 1, 1 << 64)) for e in range(k)]
    pos = np.repeat(first[:-1] - out[:-1], count) + np.arange(out[-1])
    total = np.zeros(out[-1], np.uint64)
    end = np.repeat(first[1:], count)
    for j in range(k):
        here = pos + j
        ok = here < end
        total += np.where(ok, h[np.minimum(here, max(len(h) - 1, 0))] * power[j], np.uint64(0)) if len(h) else np.uint64(0)
    return mixed(total), out
