"""MinHash fingerprints (operator 2).

A text is the set of its five-word shingles (fewer words: the whole sequence). ``PERMUTATIONS``
universal hash functions (multiply, add, keep the high bits) each keep their least value over the
set; a fingerprint holds 8 bits of each. The share of equal places, less what chance makes equal,
estimates Jaccard similarity.

Cases: null, empty or wordless text: an empty set, whose fingerprint is all ones and equals that of
any other empty set; repeated ``doc_id``: each row is kept, ordered by text among its equals; a null
``doc_id`` comes after all others; further columns are ignored; no rows: no rows; one row: it is its
own next document.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpress.llm.common import STEP_BYTES, free_columns, mixed, shingle_hashes, slices, stored, text_bytes, word_hashes
from blockpress.sources.storage import discard

PERMUTATIONS = 256
SHINGLE = 5
_rng = np.random.default_rng(7919)
_MULTIPLY = _rng.integers(0, 1 << 63, PERMUTATIONS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 1 << 63, PERMUTATIONS, dtype=np.uint64)


def shingle_sets(texts: pa.Array, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of texts, and offsets by text."""
    raw, at = text_bytes(texts)
    h, _, _, first = word_hashes(raw, at)
    return shingle_hashes(h, first, k)


def signatures(texts: pa.Array, k: int = SHINGLE) -> np.ndarray:
    """``PERMUTATIONS`` 8-bit places for each text."""
    h, at = shingle_sets(texts, k)
    n = len(at) - 1
    out = np.full((n, PERMUTATIONS), 0xFF, np.uint8)
    full = np.flatnonzero(np.diff(at))
    if len(full):
        cut = at[full]
        for j in range(PERMUTATIONS):
            least = np.minimum.reduceat(h * _MULTIPLY[j] + _ADD[j] >> np.uint64(16), cut)
            out[full, j] = (least & np.uint64(0xFF)).astype(np.uint8)
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Share of equal places of signatures, row by row, corrected for the one in 256 that chance makes equal."""
    return np.maximum(0.0, ((a == b).mean(axis=1) - 1 / 256) / (1 - 1 / 256)) if len(a) else np.zeros(0)


def with_next(docs: DataFrame) -> DataFrame:
    """``(part, copy, rank, doc_id, text)``: ranges of ``doc_id`` whose last row is followed by the next range's first.

    One shuffle of the texts. A range is a part; the row that follows a part's last one comes as a
    copy, so that no task needs another's rows. Sorted: part, copy last, rank descending.
    """
    spark = docs.sparkSession
    docs = free_columns(docs, ["doc_id", "text"]).withColumn("rank", F.coalesce("doc_id", F.lit(-(1 << 63))))
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    cuts = sorted(set(docs.select("rank").stat.approxQuantile("rank", [k / n for k in range(1, n)], 0.002 if n < 250 else 0.0005))) if n > 1 else []
    edges = [float("-inf"), *(cuts or [0.0]), float("inf")]
    dealt = Bucketizer(splits=edges, inputCol="place", outputCol="part").transform(docs.withColumn("place", F.col("rank").cast("double"))).drop("place")
    heads = sorted((r.part, r.top) for r in dealt.groupBy("part").agg(F.max("rank").alias("top")).collect())  # a row for each range
    if not heads:
        return dealt.select(F.col("part").cast("int"), F.lit(0).alias("copy"), "rank", "doc_id", "text")
    follow = spark.createDataFrame([(top, heads[(k + 1) % len(heads)][0]) for k, (_, top) in enumerate(heads)], "rank long, to double")
    copies = dealt.where(F.col("rank").isin([t for _, t in heads])).join(F.broadcast(follow), "rank")
    both = dealt.select("part", F.lit(0).alias("copy"), "rank", "doc_id", "text").unionByName(copies.select(F.col("to").alias("part"), F.lit(1).alias("copy"), "rank", "doc_id", "text"))
    return both.withColumn("part", F.col("part").cast("int")).repartition(n, "part").sortWithinPartitions("part", "copy", F.desc("rank"), "text")


def edited_fingerprints(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """Fingerprint each text and its edited text, whose second half is the next document's beginning."""
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # the last row seen: part, copy, doc_id, text, signature
        for batch in slices(batches, "text", STEP_BYTES):
            texts = batch.column("text").fill_null("")
            sig = signatures(texts, k)
            rows = list(zip(batch.column("part").to_pylist(), batch.column("copy").to_pylist(), batch.column("doc_id").to_pylist(), texts.to_pylist(), sig, strict=True))
            rows = [held, *rows] if held else rows
            held = rows[-1]
            pairs = [(a, b) for a, b in zip(rows, rows[1:], strict=False) if a[0] == b[0] and not a[1]]
            if not pairs:
                continue
            edited = []
            for (_, _, _, text, _), (_, _, _, after, _) in pairs:
                half = len(text) // 2
                edited.append(text[: len(text) - half] + after[:half])
            own, nxt = np.stack([a[4] for a, _ in pairs]), np.stack([b[4] for _, b in pairs])
            new = signatures(pa.array(edited, pa.large_string()), k)
            hexed = lambda m: [r.tobytes().hex() for r in m]
            cols = [
                pa.array([a[2] for a, _ in pairs], pa.int64()), pa.array([len(a[3]) for a, _ in pairs], pa.int64()),
                pa.array([hashlib.sha256(e.encode()).hexdigest() for e in edited]), pa.array(hexed(own)), pa.array(hexed(new)),
                pa.array(likeness(own, new)), pa.array(likeness(own, nxt)),
            ]
            yield pa.record_batch(cols, names=[f.split()[0] for f in schema.split(", ")])

    return with_next(docs).select("part", "copy", "doc_id", "text").mapInArrow(emit, schema)


#: Classes in a block of a band value whose classes are compared with one another.
BLOCK = 256


def band_keys(sig: np.ndarray, bands: int) -> np.ndarray:
    """A 64-bit key for each band of each signature; equal bands of one place have equal keys."""
    rows = PERMUTATIONS // bands
    cut = sig[:, : bands * rows].reshape(-1, bands, rows).astype(np.uint64)
    key = np.broadcast_to(mixed(np.arange(1, bands + 1, dtype=np.uint64)), cut.shape[:2])
    for j in range(rows):
        key = mixed(key + cut[:, :, j])
    return key.view(np.int64)


def similar_links(docs: DataFrame, threshold: float = 0.8, bands: int = 64, k: int = SHINGLE) -> tuple[DataFrame, DataFrame]:
    """Near-duplicates: ``members(doc_id, text_hash, class_id)`` and verified ``links(a, b, jaccard)`` between classes.

    A class is the documents with one shingle set. It is named after its least ``doc_id`` where no other
    class has that name, else by a negative number of its own; so rows that share an id or have none keep
    their links. Classes whose signatures agree in a band are joined; every pair that meets is verified by
    exact Jaccard similarity of the shingle sets, which are made anew for the classes that meet another.
    Band values with the same classes count once; one with many classes is dealt out as pairs of blocks. A pair
    that shares several is a link under the least of them alone.
    At 0.8, 64 bands of four places miss a pair once in 10^14 times. The class of empty sets has no links.
    """

    def sets_of(column: pa.Array) -> list[bytes]:
        h, at = shingle_sets(column, k)
        return [np.unique(h[a:b]).tobytes() for a, b in zip(at, at[1:], strict=False)]

    def digests(sets: list[bytes]) -> pa.Array:
        return pa.array([hashlib.sha256(s).digest() for s in sets], pa.binary())

    def prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            sets = sets_of(batch.column("text"))
            sig = [s.tobytes() if have else None for s, have in zip(signatures(batch.column("text"), k), sets, strict=True)]
            yield pa.record_batch([batch.column("doc_id"), batch.column("text_hash"), digests(sets), pa.array(sig, pa.binary())], names=["doc_id", "text_hash", "same", "sig"])

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.uint8).reshape(-1, PERMUTATIONS)
            ids = batch.column("class_id").take(pa.array(np.repeat(np.arange(len(sig)), bands)))
            yield pa.record_batch([ids, pa.array(band_keys(sig, bands).ravel())], names=["class_id", "key"])

    def emit_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            sets = sets_of(batch.column("text"))
            yield pa.record_batch([digests(sets), pa.array(sets, pa.binary())], names=["same", "shingles"])

    texts = free_columns(docs, ["doc_id", "text"]).withColumn("text_hash", F.xxhash64(F.coalesce("text", F.lit(""))))
    found = stored(texts.mapInArrow(prints, "doc_id long, text_hash long, same binary, sig binary"), "minhash")
    least = found.groupBy("same").agg(F.min("doc_id").alias("least"), F.min(F.struct("doc_id", "text_hash")).alias("at"), F.first("sig").alias("sig"))
    least = stored(least.withColumn("own", -1 - F.monotonically_increasing_id()), "class-rows")
    taken = least.where("least >= 0").groupBy("least").agg(F.min("own").alias("owner"))
    named = F.when(F.col("own") == F.col("owner"), F.col("least")).otherwise(F.col("own")).alias("class_id")
    classes = stored(least.join(taken, "least", "left").select(named, "same", "sig", "at"), "classes")
    discard(least)
    members = found.select("doc_id", "text_hash", "same").join(classes.select("same", "class_id"), "same").select("doc_id", "text_hash", "class_id")

    keyed = stored(classes.where("sig is not null").select("class_id", "sig").mapInArrow(keys, "class_id long, key long"), "band-keys")
    prints_ = [F.sum(F.xxhash64("class_id").cast("decimal(38,0)")).alias("p"), F.sum(F.xxhash64("class_id", F.lit(1)).cast("decimal(38,0)")).alias("q")]
    many = keyed.groupBy("key").agg(F.count("*").alias("n"), *prints_).where("n > 1")
    many = many.groupBy("n", "p", "q").agg(F.min("key").alias("key")).select("key", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"))
    meeting = stored(keyed.join(many, "key"), "band-meeting")
    discard(keyed)
    wanted = classes.select("class_id", "same", F.col("at.doc_id").alias("d"), F.col("at.text_hash").alias("t")).join(meeting.select("class_id").distinct(), "class_id", "left_semi")
    rows = texts.join(wanted.select("d", "t").distinct(), texts["doc_id"].eqNullSafe(F.col("d")) & (texts["text_hash"] == F.col("t")), "left_semi")
    made = rows.select("text").mapInArrow(emit_sets, "same binary, shingles binary").dropDuplicates(["same"])
    known = stored(made.join(wanted.select("class_id", "same"), "same").select("class_id", "shingles"), "band-sets")
    known = known.join(meeting.groupBy("class_id").agg(F.collect_set("key").alias("keys")), "class_id")
    dealt = meeting.withColumn("own", F.pmod(F.xxhash64("class_id"), F.col("blocks")).cast("int"))
    dealt = dealt.select("key", "class_id", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    dealt = dealt.select("key", "class_id", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi")).join(known, "class_id")

    def verify(_, part):
        sets = [np.frombuffer(s.as_buffer(), np.uint64) for s in part.column("shingles")]
        size = np.array([len(s) for s in sets], np.int64)
        ids, own = part.column("class_id").to_numpy(), part.column("own").to_numpy()
        key, lo, hi = (part.column(c)[0].as_py() for c in ("key", "lo", "hi"))
        first, second = np.flatnonzero(own == lo), np.flatnonzero(own == hi)
        # a pair counts under the least key it shares: lesser keys by class
        at = np.repeat(np.arange(len(ids)), pc.list_value_length(part.column("keys")).to_numpy())
        all_keys = pc.list_flatten(part.column("keys")).to_numpy()
        _, place, often = np.unique(all_keys[all_keys < key], return_inverse=True, return_counts=True)
        earlier = np.zeros((len(ids), int((often > 1).sum())), bool)
        column, two = np.cumsum(often > 1) - 1, often[place] > 1
        earlier[at[all_keys < key][two], column[place][two]] = True
        codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
        ends = np.append(0, np.cumsum(size))
        theirs = np.concatenate([codes[ends[j] : ends[j + 1]] for j in second]) if len(second) else codes[:0]
        cut, mine = np.append(0, np.cumsum(size[second])[:-1]), np.zeros(len(codes), bool)
        out = []
        for i in first.tolist() if len(second) else []:
            own_codes = codes[ends[i] : ends[i + 1]]
            mine[own_codes] = True
            both = np.add.reduceat(mine[theirs], cut, dtype=np.int64)
            mine[own_codes] = False
            like = both / (size[i] + size[second] - both)
            hit = np.flatnonzero((like >= threshold) & ((ids[second] > ids[i]) if lo == hi else True))
            hit = hit[~(earlier[second[hit]] & earlier[i]).any(axis=1)]
            out.append((np.minimum(ids[i], ids[second[hit]]), np.maximum(ids[i], ids[second[hit]]), like[hit]))
        a, b, like = (np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"a": a, "b": b, "jaccard": like})

    links = dealt.groupBy("key", "lo", "hi").applyInArrow(verify, "a long, b long, jaccard double")
    return members, links


def similar_documents(docs: DataFrame, threshold: float = 0.8, bands: int = 64, k: int = SHINGLE) -> DataFrame:
    """``(doc_id, class_id, n_links)`` of every row: its class, and how many other classes are alike in ``threshold`` or more."""
    members, links = similar_links(docs, threshold, bands, k)
    ends = links.select(F.explode(F.array("a", "b")).alias("class_id")).groupBy("class_id").agg(F.count("*").alias("n_links"))
    return members.join(ends, "class_id", "left").select("doc_id", "class_id", F.coalesce("n_links", F.lit(0)).alias("n_links"))
