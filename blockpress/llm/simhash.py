"""SimHash near-duplicates with pigeonring filtering (operator 4).

A fingerprint is cut into a ring of ``SEGMENTS`` segments. If two fingerprints differ in ``limit``
bits at most, some segment starts a chain whose first 1, 2, 3 ... segments differ in no more than
their proportional share of the limit: with five segments and three bits the shares are 0, 1, 1, 2
and 3. So a chain's head is equal, and of the two segments behind it one is equal too, which gives
the join keys: head and successor, or head and the one after (ten keys of about 26 bits). Pairs that
meet under a key must pass the whole chain's shares before their full Hamming distance is taken.

Equal fingerprints are one node from the start, so copies never meet. A key with few fingerprints
joins with itself in the plan; one with many is dealt out as pairs of blocks, and each such task
gives no more links than it has fingerprints, enough to keep together all that belongs together.

Cases: null, empty or wordless text: fingerprint zero, linked like any other; fewer words than a
shingle: the whole sequence is the one shingle; repeated rows: each its own row of the result;
further columns are ignored; no rows: no rows.

``near_groups`` is for pipelines, which want every pair that is alike in 0.8 of its five-word shingles:
such pairs may differ in a dozen fingerprint bits, more than any exact search reaches. To the pairs with
near fingerprints it adds those that agree in a sample of their shingles' least hashes, and links a pair
only when the shingle sets themselves are that alike.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpress.llm.common import free_columns, slices, stored
from blockpress.llm.minhash import PERMUTATIONS, likeness, shingle_sets, signatures
from blockpress.operators.components import connected_components
from blockpress.sources.storage import discard

SEGMENTS = 5
#: First bit and width of each segment of a 64-bit fingerprint.
WIDTHS = (13, 13, 13, 13, 12)
STARTS = (0, 13, 26, 39, 52)
#: Fingerprints under one key that still join with themselves in the plan.
JOINED = 48
#: Fingerprints in a block of a key with more.
BLOCK = 1024
WORDS = re.compile(rb"[^\x20\x09-\x0d]+")


def fingerprint(text: bytes, shingle: int = 3, seed: int = 42) -> int:
    """SimHash of a text's word shingles under XXH64."""
    words = text.lower().split()  # of bytes: A-Z alone, and just the six ASCII blanks
    if not words:
        return 0
    joined, n = b" ".join(words), max(1, len(words) - shingle + 1)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(size)
    begins = (ends - size)[:n].tolist()
    ends = (ends[min(shingle, len(words)) - 1 :] - 1).tolist()
    h = xxhash.xxh64_intdigest
    hashes = np.fromiter((h(joined[a:b], seed) for a, b in zip(begins, ends, strict=True)), np.uint64, n)
    counts = np.zeros(64, np.int64)
    for lo in range(0, n, 1 << 15):
        counts += np.unpackbits(hashes[lo : lo + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, shingle: int = 3, seed: int = 42) -> DataFrame:
    """``(doc_id, fp)``: fingerprints as signed longs."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            texts = batch.column("text").cast(pa.binary()).fill_null(b"").to_pylist()
            fp = np.array([fingerprint(t, shingle, seed) for t in texts], np.uint64).view(np.int64)
            yield pa.record_batch([batch.column("doc_id"), pa.array(fp)], names=["doc_id", "fp"])

    return free_columns(docs, ["doc_id", "text"]).mapInArrow(emit, "doc_id long, fp long")


def shares(limit: int) -> list[int]:
    """Bits that a chain's first 1, 2 ... segments may differ in."""
    return [limit * k // SEGMENTS for k in range(1, SEGMENTS + 1)]


def _segment(column: str, k: int) -> str:
    return f"(shiftrightunsigned({column}, {STARTS[k % SEGMENTS]}) & {(1 << WIDTHS[k % SEGMENTS]) - 1})"


def ring_keys(limit: int) -> list[tuple[int, int]]:
    """Pairs (head, other) of segments of which one is equal in any two fingerprints within the limit."""
    if shares(limit)[2] > 1:
        raise ValueError("with this limit two equal segments are not certain")
    return [(k, (k + d) % SEGMENTS) for k in range(SEGMENTS) for d in (1, 2)]


def chain_holds(x: np.ndarray, head: np.ndarray, limit: int) -> np.ndarray:
    """Whether the chain from ``head`` keeps its shares in differences ``x``."""
    diff = np.stack([np.bitwise_count((x >> np.uint64(s)) & np.uint64((1 << w) - 1)) for s, w in zip(STARTS, WIDTHS, strict=True)])
    ok, run, col = np.ones(len(x), bool), np.zeros(len(x), np.int64), np.arange(len(x))
    for k, share in enumerate(shares(limit)):
        run += diff[(head + k) % SEGMENTS, col]
        ok &= run <= share
    return ok


def links(fps: DataFrame, limit: int = 3) -> DataFrame:
    """``(a, b)``: links between different fingerprints, enough to give all components.

    ``fps(fp)`` holds each fingerprint once and must be stored.
    """
    keys = ring_keys(limit)
    key = F.array(*[F.expr(f"{_segment('fp', i)} + {_segment('fp', j)} * 8192L + {n}L * 67108864L") for n, (i, j) in enumerate(keys)])
    keyed = fps.select("fp", F.explode(key).alias("key"))
    met = stored(keyed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "keys")
    few, many = met.where(F.col("n") <= JOINED), met.where(F.col("n") > JOINED)

    # few: a self-join under the key, the chain tested in the plan
    small = stored(keyed.join(few.select("key"), "key"), "few")
    left, right = small.select("key", F.col("fp").alias("a")), small.select("key", F.col("fp").alias("b"))
    total, within = "0", []
    budget = shares(limit)
    for k in range(SEGMENTS):
        shift = f"element_at(array({', '.join(f'{s}' for s in STARTS)}), cast((head + {k}) % {SEGMENTS} as int) + 1)"
        width = f"element_at(array({', '.join(f'{(1 << w) - 1}L' for w in WIDTHS)}), cast((head + {k}) % {SEGMENTS} as int) + 1)"
        total += f" + bit_count(shiftrightunsigned(x, {shift}) & {width})"
        within.append(f"({total}) <= {budget[k]}")
    pairs = left.join(right, "key").where("a < b").selectExpr("a", "b", "a ^ b as x", "cast(floor(shiftrightunsigned(key, 26) / 2) as int) as head")
    near = pairs.where(f"bit_count(x) <= {limit}").where(" and ".join(within)).select("a", "b")

    # many: blocks under the key, each pair of blocks in a task of its own
    dealt = keyed.join(many.select("key", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks")), "key")
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int"))
    dealt = dealt.select("key", "fp", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    dealt = dealt.select("key", "fp", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own")

    def spanning(_, part):
        fp = part.column("fp").to_numpy().view(np.uint64)
        head = int(part.column("key")[0].as_py() >> 26) // 2
        lo, hi = part.column("lo")[0].as_py(), part.column("hi")[0].as_py()
        own = part.column("own").to_numpy()
        first, second = np.flatnonzero(own == lo), np.flatnonzero(own == hi)
        parent = list(range(len(fp)))

        def root(i: int) -> int:
            while parent[i] != i:
                parent[i] = parent[parent[i]]
                i = parent[i]
            return i

        out: list[tuple[int, int]] = []
        label = np.arange(len(fp))
        for i in first.tolist():
            x = fp[second] ^ fp[i]
            close = np.flatnonzero((np.bitwise_count(x) <= limit) & (label[second] != label[i]))
            if len(close):
                close = close[chain_holds(x[close], np.full(len(close), head), limit)]
            for j in second[close].tolist():
                a, b = root(i), root(j)
                if a != b:
                    parent[a] = b
                    out.append((i, j))
            if len(close):
                label = np.array([root(k) for k in range(len(fp))]) if len(close) > 8 else label
        signed = fp.view(np.int64)
        a, b = np.array([signed[i] for i, _ in out], np.int64), np.array([signed[j] for _, j in out], np.int64)
        return pa.table({"a": a, "b": b})

    hot = dealt.groupBy("key", "lo", "hi").applyInArrow(spanning, "a long, b long")
    return near.unionByName(hot)


def near_duplicates(docs: DataFrame, shingle: int = 3, seed: int = 42, limit: int = 3) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``: the least ``doc_id`` reachable over near fingerprints."""
    prints = stored(fingerprints(docs, shingle, seed), "fingerprints")
    distinct = stored(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    found = stored(connected_components(links(distinct.select("fp"), limit)), "components")
    least = distinct.join(found, F.col("fp") == F.col("node")).groupBy("component").agg(F.min("least").alias("component_id"))
    linked = stored(found.join(least, "component").select(F.col("node").alias("fp"), "component_id"), "linked")
    named = stored(distinct.join(linked, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id")), "named")
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return prints.join(named, "fp").select("doc_id", hexed.alias("fingerprint"), "component_id")


#: Keys of four least hashes each: texts alike in 0.8 share none of them once in 5,000 times.
SAMPLES = 16
#: Classes in a block of a key whose classes are compared with one another.
COMPARED = 256
#: Standard errors below the bound at which the estimate still sends a pair to the exact test.
LOOSE = 5


#: Gives ``(id, shingles)`` of the ids in a table ``(id)``.
Sets = Callable[[DataFrame], DataFrame]


def loose_floor(similarity: float) -> float:
    """The estimate under which a pair is not tested exactly."""
    return similarity - LOOSE * (similarity * (1 - similarity) / PERMUTATIONS) ** 0.5


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard similarity of two sets of hashes, each sorted and without repeats; of two empty ones: 1."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both) if len(a) or len(b) else 1.0


def _sketches(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, PERMUTATIONS)


def verified(pairs: DataFrame, classes: DataFrame, similarity: float, sets: Sets) -> DataFrame:
    """Those ``pairs(a, b)`` of ``classes(id, sig)`` whose shingle sets are exactly that alike; the estimate only thins them out."""
    floor = loose_floor(similarity)

    def side(df: DataFrame, end: str, column: str, source: DataFrame = classes) -> DataFrame:
        return df.join(source.select(F.col("id").alias(end), F.col(column).alias(f"{column}_{end}")), end)

    def thin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            close = likeness(_sketches(batch.column("sig_a")), _sketches(batch.column("sig_b"))) >= floor
            yield pa.record_batch([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(close, pa.bool_()))

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = zip(batch.column("shingles_a"), batch.column("shingles_b"), strict=True)
            alike = [jaccard(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)) >= similarity for x, y in sets]
            yield pa.record_batch([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(alike, pa.bool_()))

    both = side(stored(side(pairs, "b", "sig"), "sample-half"), "a", "sig").select("a", "b", "sig_a", "sig_b")
    close = stored(both.mapInArrow(thin, "a long, b long"), "sample-close")
    known = stored(sets(close.select(F.explode(F.array("a", "b")).alias("id")).distinct()), "sample-known")
    both = side(stored(side(close, "b", "shingles", known), "sample-sets"), "a", "shingles", known).select("a", "b", "shingles_a", "shingles_b")
    return both.mapInArrow(test, "a long, b long")


def sample_links(classes: DataFrame, similarity: float, more: DataFrame, sets: Sets | None = None) -> DataFrame:
    """``(a, b)``: exactly verified links of ``classes(id, sig, shingles)`` under shared keys, and of the pairs in ``more(a, b)``.

    Under each key all classes are compared with the first. Where that does not put them into one component,
    all of different components are compared: a key is dealt out as pairs of blocks, and each such task gives
    no more links than it has classes. Keys with the same classes count once. ``sets`` gets the shingle sets
    of the classes that need them, where ``classes`` has none.
    """
    sets = sets or (lambda ids: classes.select("id", "shingles").join(ids, "id"))

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sig = _sketches(batch.column("sig"))
            part = np.ascontiguousarray(sig[:, : 4 * SAMPLES]).view("<u4").astype(np.int64) + (np.arange(SAMPLES) << 32)
            yield pa.record_batch([batch.column("id").take(pa.array(np.repeat(np.arange(len(sig)), SAMPLES))), pa.array(part.ravel())], names=["id", "key"])

    floor = loose_floor(similarity)
    keyed = stored(classes.select("id", "sig").mapInArrow(keys, "id long, key long"), "sample-keys")
    ends = keyed.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo < hi")
    pairs = keyed.join(ends, "key").where("id <> lo").select(F.col("lo").alias("a"), F.col("id").alias("b")).unionByName(more)
    first = stored(verified(stored(pairs.distinct(), "sample-pairs"), classes, similarity, sets), "sample-first")
    found = connected_components(first).select(F.col("node").alias("id"), "component")
    placed = stored(keyed.join(ends.select("key"), "key").join(found, "id", "left").select("key", "id", F.coalesce("component", "id").alias("part")), "sample-placed")
    print_ = [F.sum(F.xxhash64("id").cast("decimal(38,0)")).alias("p"), F.sum(F.xxhash64("id", F.lit(1)).cast("decimal(38,0)")).alias("q")]
    apart = placed.groupBy("key").agg(F.count("*").alias("n"), F.min("part").alias("lo"), F.max("part").alias("hi"), *print_)
    left = apart.where("lo < hi and n > 2").groupBy("n", "p", "q").agg(F.min("key").alias("key"))
    left = stored(left.select("key", F.ceil(F.col("n") / COMPARED).cast("int").alias("blocks")), "sample-left")
    if left.isEmpty():
        return first
    dealt = placed.join(left, "key").withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    dealt = dealt.select("key", "id", "part", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    dealt = dealt.select("key", "id", "part", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))
    known = stored(sets(placed.join(left, "key").select("id").distinct()), "sample-known")
    dealt = dealt.join(classes.select("id", "sig").join(known, "id"), "id")

    def spanning(_, part):
        ids, own = part.column("id").to_numpy(), part.column("own").to_numpy()
        _, label = np.unique(part.column("part").to_numpy(), return_inverse=True)
        sig = _sketches(part.column("sig"))
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in part.column("shingles")]
        first, second = (np.flatnonzero(own == part.column(c)[0].as_py()) for c in ("lo", "hi"))
        out: list[tuple[int, int]] = []
        for i in first.tolist():
            away = second[label[second] != label[i]]
            for j in away[likeness(np.broadcast_to(sig[i], (len(away), PERMUTATIONS)), sig[away]) >= floor].tolist():
                if label[i] != label[j] and jaccard(sets[i], sets[j]) >= similarity:
                    label[label == label[j]] = label[i]
                    out.append((i, j))
        return pa.table({"a": pa.array([int(ids[i]) for i, _ in out], pa.int64()), "b": pa.array([int(ids[j]) for _, j in out], pa.int64())})

    return first.unionByName(dealt.groupBy("key", "lo", "hi").applyInArrow(spanning, "a long, b long"))


def near_groups(docs: DataFrame, similarity: float = 0.8, shingle: int = 5, limit: int = 3) -> DataFrame:
    """``(doc_id, text_hash, group_id, component_id)``: groups over shingle sets alike in ``similarity``; near fingerprints are among the pairs tested.

    A node is a set of shingles, never a ``doc_id``: rows that share an id, or have none, meet only by their
    texts. ``group_id`` names a group, ``component_id`` is its least ``doc_id`` (null if it has none).
    """

    def sets(batch: pa.RecordBatch) -> list[bytes]:
        h, at = shingle_sets(batch.column("text"), shingle)
        return [np.unique(h[a:b]).tobytes() for a, b in zip(at, at[1:], strict=False)]

    def digests(found: list[bytes]) -> list[bytes]:
        return [hashlib.blake2b(s, digest_size=16).digest() for s in found]

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            texts = batch.column("text").cast(pa.binary()).fill_null(b"").to_pylist()
            fp = np.array([fingerprint(t, shingle) for t in texts], np.uint64).view(np.int64)
            sig = [s.tobytes() for s in signatures(batch.column("text"), shingle)]
            yield pa.record_batch([batch.column("doc_id"), batch.column("text_hash"), pa.array(fp), pa.array(digests(sets(batch)), pa.binary()), pa.array(sig, pa.binary())], names=["doc_id", "text_hash", "fp", "same", "sig"])

    def emit_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            found = sets(batch)
            yield pa.record_batch([pa.array(digests(found), pa.binary()), pa.array(found, pa.binary())], names=["same", "shingles"])

    texts = with_text_hash(free_columns(docs, ["doc_id", "text"]))
    prints = stored(texts.mapInArrow(emit, "doc_id long, text_hash long, fp long, same binary, sig binary"), "prints")
    # documents with one shingle set are one node; the table, once written, fixes the nodes' numbers
    alike = prints.groupBy("same").agg(F.first("sig").alias("sig"), F.min(F.struct("doc_id", "text_hash")).alias("at"))
    classes = stored(alike.select(F.monotonically_increasing_id().alias("id"), "same", "sig", "at"), "classes")
    named = stored(prints.select("doc_id", "text_hash", "fp", "same").join(classes.select("id", "same"), "same").drop("same"), "named")
    discard(prints)

    def sets_of(ids: DataFrame) -> DataFrame:
        """Sets of chosen nodes, made anew from one text each: those of all would take more room than the texts."""
        wanted = classes.select("id", "same", F.col("at.doc_id").alias("d"), F.col("at.text_hash").alias("t")).join(ids, "id", "left_semi")
        rows = texts.join(wanted.select("d", "t").distinct(), texts["doc_id"].eqNullSafe(F.col("d")) & (texts["text_hash"] == F.col("t")), "left_semi")
        made = rows.select("text").mapInArrow(emit_sets, "same binary, shingles binary").dropDuplicates(["same"])
        return made.join(wanted.select("id", "same"), "same").select("id", "shingles")

    # candidates by fingerprint: the first of an equal one, and the firsts of near ones
    by_fp = stored(named.groupBy("fp").agg(F.min("id").alias("first_fp")), "by-fp")
    equal = named.join(by_fp, "fp").select(F.col("first_fp").alias("a"), F.col("id").alias("b"))
    near = stored(links(by_fp.select("fp"), limit), "near")
    near = near.join(by_fp.select(F.col("fp").alias("a"), F.col("first_fp").alias("x")), "a").join(by_fp.select(F.col("fp").alias("b"), F.col("first_fp").alias("y")), "b")
    more = equal.unionByName(near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))).where("a <> b").distinct()
    groups = stored(connected_components(sample_links(classes.select("id", "sig"), similarity, more, sets_of)), "groups")
    placed = stored(named.join(groups, F.col("id") == F.col("node"), "left").select("doc_id", "text_hash", F.coalesce("component", "id").alias("group_id")), "placed")
    least = placed.groupBy("group_id").agg(F.min("doc_id").alias("component_id"))
    return placed.join(least, "group_id").select("doc_id", "text_hash", "group_id", "component_id")


def with_text_hash(docs: DataFrame) -> DataFrame:
    """``docs`` and ``text_hash``, which with ``doc_id`` tells rows apart; a null text counts as an empty one."""
    return docs.withColumn("text_hash", F.xxhash64(F.coalesce("text", F.lit(""))))


def one_of_each(docs: DataFrame, **how) -> DataFrame:
    """``docs(doc_id, text, ...)`` with one row of each near-duplicate group: the least ``doc_id``, null before all, then the least text hash.

    Rows equal in id and text are repeats of one another, of which one stays as well.
    """
    groups = stored(near_groups(docs, **how), "near-groups")
    first = groups.groupBy("group_id").agg(F.min(F.struct("doc_id", "text_hash")).alias("k"), F.count("*").alias("n"))
    rows = groups.groupBy("doc_id", "text_hash").agg(F.count("*").alias("copies"))
    keepers = first.select(F.col("k.doc_id").alias("_d"), F.col("k.text_hash").alias("_t"))
    same = keepers["_d"].eqNullSafe(rows["doc_id"]) & (keepers["_t"] == rows["text_hash"])
    keepers = stored(keepers.join(rows, same).select("_d", "_t", (F.col("copies") > 1).alias("_many")), "keepers")
    names = docs.columns
    whole = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("_text"), F.struct(*names).alias("_row")).withColumn("_h", F.xxhash64("_text"))
    kept_rows = whole.join(keepers, whole["doc_id"].eqNullSafe(keepers["_d"]) & (whole["_h"] == keepers["_t"]))
    single = kept_rows.where("not _many").select("_row.*")
    repeats = kept_rows.where("_many").groupBy("_d", "_t").agg(F.first("_row").alias("_row")).select("_row.*")
    return single.unionByName(repeats)
