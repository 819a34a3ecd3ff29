"""Benchmark decontamination by spaced-seed hashing (operator 9).

A mask such as ``11101011`` is laid over each run of words; the words under a 0 do not count, so the
hash stays when such a word is replaced. Test items' seed hashes are rows, and so are the documents';
Spark joins them. Each hit fixes how an item lies over a document; along that line the windows around
the seed are compared word by word, and the document is contaminated where some window of ``WINDOW``
words (the whole item, if shorter) agrees in ``SHARE`` of its words. A hit carries the words around it
on both sides, which is all that such a window can hold, so nothing is looked up again.

Of any 13 words with two replaced the words under one of ``LONG_MASKS`` are left, and of 6 to 12 words
with as many replaced as ``SHARE`` allows those under one of ``MASKS``; so no window within the share is
missed. Items of fewer than ``LEAST`` words are too common to mean anything and are not searched unless
``least`` is lowered; those below six words then count where all their words follow one another.

Only document seeds that pass a bitmap of the items' seeds leave the scan. The bitmap has ``BITS`` bits a
seed, 2^``MOST_BITS`` at most (64 MB): with more seeds it lets more through and the join does the rest.
A seed with many hits (a phrase of everyday) has its item rows dealt out and its hits spread over them.

Words: between ASCII blanks, lower-cased, ASCII punctuation dropped.

Cases: null or empty texts match nothing; rows equal in id and text are one row of the result, a null
``doc_id`` or ``item_id`` stays null and its rows are told apart by their texts; repeated items count one
by one; long texts whole; further columns are ignored; an empty benchmark or corpus: no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.llm.common import free_columns, mixed, slices, small_batches, stored, text_bytes, word_hashes

# fixed values: seed masks for items below a window's length, and for the others
MASKS = ("1111", "11011", "1101001", "10110001")
LONG_MASKS = ("11101011", "110100111")
WINDOW, SHARE, LEAST = 13, 0.8, 6
#: Words of a hit's surroundings: those that a window over the seed's first word can hold.
AROUND = 2 * WINDOW - 1
BITS, MOST_BITS = 32, 29
PROBES = 4
#: Hits of a seed that one row of an item's seed meets.
HOT = 20_000
FOUND = "doc_id long, item_id long, matched int, window int, doc_word int, item_word int"

_PUNCTUATION = np.zeros(256, bool)
_PUNCTUATION[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = True
_FACTOR = np.random.default_rng(104729).integers(1, 1 << 63, 16, dtype=np.uint64) | np.uint64(1)


def words_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of texts, and the number of the first word of each text."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    raw, at = text_bytes(pc.utf8_lower(texts.fill_null("")))
    h, _, _, first = word_hashes(raw, at, drop=_PUNCTUATION, lower=False)
    return h, first


def seed_hashes(h: np.ndarray, mask: str) -> np.ndarray:
    """Hash of the words under the mask's ones, for each place where the mask fits in the array."""
    n = max(0, len(h) - len(mask) + 1)
    total = np.zeros(n, np.uint64)
    for j, bit in enumerate(mask):
        if bit == "1":
            total += h[j : j + n] * _FACTOR[j]
    return mixed(total)


def seed_places(first: np.ndarray, span: int, n: int) -> np.ndarray:
    """Places where a mask lies within one text."""
    ok = np.ones(n, bool)
    for j in range(1, span):
        cut = first[1:-1] - j
        ok[cut[(cut >= 0) & (cut < n)]] = False
    return np.flatnonzero(ok)


def masks_for(size: int) -> tuple[str, ...]:
    """Masks under which an item of so many words is searched."""
    return LONG_MASKS if size >= WINDOW else MASKS if size >= 6 else ("1" * size,)


#: All masks, each with a number of its own that goes into its hashes.
_EVERY = (*LONG_MASKS, *MASKS, *("1" * k for k in (1, 2, 3, 5)))


def salted(h: np.ndarray, mask: str) -> np.ndarray:
    """Seed hashes that differ from mask to mask."""
    return mixed(seed_hashes(h, mask) + np.uint64(_EVERY.index(mask) + 1))


def around(h: np.ndarray, begin: np.ndarray, end: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The words around places ``at`` of texts that begin and end there; zero outside."""
    idx = at[:, None] + np.arange(-(WINDOW - 1), WINDOW)
    inside = (idx >= begin[:, None]) & (idx < end[:, None])
    return np.where(inside, np.maximum(h, np.uint64(1))[np.clip(idx, 0, max(len(h) - 1, 0))], np.uint64(0)) if len(h) else np.zeros((len(at), AROUND), np.uint64)


def _binary(rows: np.ndarray) -> pa.Array:
    raw = np.ascontiguousarray(rows)
    at = np.arange(len(raw) + 1, dtype=np.int32) * raw.shape[1] * 8
    return pa.Array.from_buffers(pa.binary(), len(raw), [None, pa.py_buffer(at), pa.py_buffer(raw)])


def item_seeds(benchmark: DataFrame, least: int = LEAST) -> DataFrame:
    """``seed, item_no, item_id, place, size, words`` of every item of ``least`` words or more; stored."""
    schema = "seed long, item_no long, item_id long, place int, size int, words binary"

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            h, first = words_of(batch.column("text"))
            sizes = np.diff(first)
            for mask in _EVERY:
                s = salted(h, mask)
                place = seed_places(first, len(mask), len(s))
                item = np.searchsorted(first, place, side="right") - 1
                mine = np.array([n >= least and mask in masks_for(n) for n in sizes.tolist()], bool)
                place, item = place[mine[item]], item[mine[item]]
                words = around(h, first[item], first[item + 1], place)
                row = pa.array(item)
                cols = [pa.array(s[place].view(np.int64)), batch.column("item_no").take(row), batch.column("item_id").take(row), pa.array((place - first[item]).astype(np.int32)), pa.array(sizes[item].astype(np.int32)), _binary(words)]
                yield pa.record_batch(cols, names=[c.split()[0] for c in schema.split(", ")])

    items = free_columns(benchmark, ["item_id", "text"]).where("text is not null").withColumn("item_no", F.monotonically_increasing_id())
    return stored(items.mapInArrow(emit, schema), "item-seeds")


def bitmap_of(seeds: DataFrame) -> np.ndarray:
    """Bits of the seeds, ``PROBES`` each; set in tasks and joined by a grouped OR."""
    n = seeds.count()
    bits = min(MOST_BITS, max(16, (n * BITS).bit_length()))

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = np.unique(np.concatenate([*_probes(batch.column("seed").to_numpy().view(np.uint64), bits)]))
            yield pa.record_batch([pa.array((at >> np.uint64(6)).astype(np.int64)), pa.array(np.left_shift(np.uint64(1), at & np.uint64(63)).view(np.int64))], names=["word", "bits"])

    words = seeds.select("seed").mapInArrow(emit, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()  # bounded by MOST_BITS
    out = np.zeros(1 << bits - 6, np.uint64)
    out[words.column("word").to_numpy()] = words.column("bits").to_numpy().view(np.uint64)
    return out


def _probes(x: np.ndarray, bits: int) -> Iterator[np.ndarray]:
    for k in range(PROBES):
        yield (x if not k else mixed(x + np.uint64(k))) >> np.uint64(64 - bits)


def _known(bitmap: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Places of ``x`` that the bitmap lets through."""
    bits = len(bitmap).bit_length() + 5
    live = np.arange(len(x))
    for k in range(PROBES):
        y = x[live]
        p = (y if not k else mixed(y + np.uint64(k))) >> np.uint64(64 - bits)
        live = live[(bitmap[p >> np.uint64(6)] >> (p & np.uint64(63))) & np.uint64(1) == 1]
    return live


def document_hits(docs: DataFrame, bitmap: np.ndarray, masks: list[str]) -> DataFrame:
    """``seed, doc_id, text_hash, at, words`` of the seeds of ``docs(doc_id, text)`` that pass the bitmap. One scan."""
    schema = "seed long, doc_id long, text_hash long, at int, words binary"

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            h, first = words_of(batch.column("text"))
            for mask in masks:
                s = salted(h, mask)
                maybe = _known(bitmap, s)
                if not len(maybe):
                    continue
                place = maybe[np.isin(maybe, seed_places(first, len(mask), len(s)), assume_unique=True)]
                doc = np.searchsorted(first, place, side="right") - 1
                row = pa.array(doc)
                cols = [pa.array(s[place].view(np.int64)), batch.column("doc_id").take(row), batch.column("text_hash").take(row), pa.array((place - first[doc]).astype(np.int32)), _binary(around(h, first[doc], first[doc + 1], place))]
                yield pa.record_batch(cols, names=[c.split()[0] for c in schema.split(", ")])

    rows = free_columns(docs, ["doc_id", "text"]).where("text is not null").withColumn("text_hash", F.xxhash64("text"))
    return rows.mapInArrow(emit, schema)


def best_windows(doc: np.ndarray, item: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of aligned surroundings: words that agree in the best window, its length, and where it starts from the seed's first word."""
    window = np.minimum(WINDOW, size)
    same = np.cumsum(np.pad((doc == item) & (doc != 0), ((0, 0), (1, 0))), axis=1)
    both = np.cumsum(np.pad((doc != 0) & (item != 0), ((0, 0), (1, 0))), axis=1)
    most, start = np.full(len(size), -1), np.zeros(len(size), np.int64)
    for w in np.unique(window).tolist():
        mine = np.flatnonzero(window == w)
        agree, full = same[mine, w:] - same[mine, :-w], both[mine, w:] - both[mine, :-w] == w
        agree = np.where(full, agree, -1)
        start[mine] = agree.argmax(axis=1)
        most[mine] = agree[np.arange(len(mine)), start[mine]]
    return most, window, start - (WINDOW - 1)


def overlaps(docs: DataFrame, benchmark: DataFrame, least: int = LEAST) -> DataFrame:
    """``FOUND`` and ``text_hash, item_no``: the best verified window of each different document and item."""
    seeds = item_seeds(benchmark, least)
    masks = [m for m in _EVERY if least < 6 or m in (*LONG_MASKS, *MASKS)]
    hits = stored(document_hits(docs, bitmap_of(seeds), masks), "seed-hits")
    often = hits.groupBy("seed").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("seed", F.ceil(F.col("n") / HOT).cast("int").alias("parts"))
    often = stored(often, "hot-seeds")
    dealt = seeds.join(often, "seed", "left").withColumn("part", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    spread = hits.join(often, "seed", "left").withColumn("part", F.coalesce(F.pmod(F.xxhash64("text_hash", "at"), F.col("parts")), F.lit(0)).cast("int")).drop("parts")
    pairs = spread.withColumnRenamed("words", "doc_words").join(dealt.withColumnRenamed("words", "item_words"), ["seed", "part"])
    schema = "doc_id long, text_hash long, item_no long, item_id long, matched int, window int, doc_word int, item_word int"

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, item = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint64).reshape(-1, AROUND) for c in ("doc_words", "item_words"))
            most, window, start = best_windows(doc, item, batch.column("size").to_numpy())
            good = np.flatnonzero(most >= np.ceil(SHARE * window - 1e-9))
            row = pa.array(good)
            cols = [batch.column(c).take(row) for c in ("doc_id", "text_hash", "item_no", "item_id")]
            cols += [pa.array(x[good].astype(np.int32)) for x in (most, window, batch.column("at").to_numpy() + start, batch.column("place").to_numpy() + start)]
            yield pa.record_batch(cols, names=[c.split()[0] for c in schema.split(", ")])

    found = pairs.select("doc_id", "text_hash", "at", "doc_words", "item_no", "item_id", "place", "size", "item_words").mapInArrow(verify, schema)
    best = F.max(F.struct("matched", (-F.col("doc_word")).alias("d"), (-F.col("item_word")).alias("i"), "window")).alias("b")
    rows = found.groupBy("doc_id", "text_hash", "item_no", "item_id").agg(best)
    return rows.select("doc_id", "item_id", "b.matched", "b.window", (-F.col("b.d")).alias("doc_word"), (-F.col("b.i")).alias("item_word"), "text_hash", "item_no")


def contaminated(docs: DataFrame, benchmark: DataFrame, least: int = LEAST) -> DataFrame:
    """``FOUND`` rows: one for each different document and item with a verified overlap."""
    return overlaps(docs, benchmark, least).select(*[c.split()[0] for c in FOUND.split(", ")])


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, least: int = LEAST) -> DataFrame:
    """``docs`` without contaminated documents: an anti-join that Spark broadcasts if the list is small by its files' size."""
    small_batches(docs.sparkSession)
    gone = stored(overlaps(docs, benchmark, least).select(F.col("doc_id").alias("_d"), F.col("text_hash").alias("_t")).distinct(), "contaminated")
    rows = docs.select("doc_id", F.xxhash64("text").alias("_h"), F.struct(*docs.columns).alias("_row"))
    clean = rows.join(gone, rows["doc_id"].eqNullSafe(gone["_d"]) & (rows["_h"] == gone["_t"]), "left_anti")
    return clean.select("_row.*")


def worst_overlap(found: DataFrame) -> DataFrame:
    """The best overlap of each contaminated document, ties by item."""
    order = Window.partitionBy("doc_id").orderBy(F.desc(F.col("matched") / F.col("window")), F.desc("matched"), "item_id")
    return found.withColumn("n", F.row_number().over(order)).where("n = 1").drop("n")
