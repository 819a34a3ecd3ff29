"""Removal of repeated byte strings by a sparse, distributed suffix array (operator 1).

A string of ``length`` bytes that starts twice is found by sorting suffixes and comparing neighbours'
prefixes. Sorting every suffix of the corpus would move many times its size, so the array is built in
the manner of a difference cover: sort a sample of the suffixes, then merge in the rest by the bytes
before the sample and the sample's rank.

1. Sample. Of each ``length``-byte window, the sample position is the leftmost least hash of its
   ``GRAM``-byte strings. Equal windows have their sample position at the same offset, which is what a
   difference cover is for; each window start belongs to one sample position, its anchor.
2. Prune, without loss. Windows with one anchor all hold the anchor's core, the bytes that no window
   start of it can leave out. Anchors whose core occurs once in the corpus have no repeated window.
   Anchors with equal contexts (the core and all its windows) are one row from here on; contexts are told
   apart by a cryptographic hash of all their bytes, beside the core's.
3. Sort sampled triples, recurse on names. The bytes behind an anchor are cut into words of eight;
   distinct triples of words are sorted and named by rank, triples of names again, and again, until
   one name orders the whole suffix up to ``length`` bytes. The bytes before an anchor likewise,
   backwards.
4. Merge the remaining suffixes, compare adjacent prefixes. The suffix that starts ``d`` bytes before
   an anchor has its place by the run of sampled suffixes that agree in ``length - d`` bytes (adjacent
   prefixes in the array) and by the run of heads that agree in ``d`` bytes. Two starts with the same
   ``d`` and the same two runs are equal strings; no other pairs are.

Steps 3 and 4 run in tasks that hold all contexts of their cores, which is a stretch of the suffix
array. A core with more than ``CORE_CONTEXTS`` different contexts is too much for one task; its
contexts are cut into runs of fewer window starts, which share longer cores, and sorted under those.

Cases: null text: empty; texts shorter than ``length``: nothing removed; overlapping repeats inside
one text count; repeated rows (equal ``doc_id`` and text) repeat each other's strings; equal ``doc_id``
with other texts are documents of their own; null ``doc_id`` likewise; further columns are ignored; no
rows: no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpress.llm.common import _BASE, _BYTE, free_columns, mixed, slices, small_batches, stored, text_bytes
from blockpress.sources.storage import discard

LENGTH = 200
GRAM = 16
#: Different contexts of a core that one task sorts.
CORE_CONTEXTS = 600
#: Head sizes in a run, where a core has more.
SPANS = (24, 4, 1)
ANCHORS = "doc_id long, uid long, core long, ctx long, place long"


def _reach(length: int) -> int:
    """Window positions that may hold the sample: all whose gram lies well inside."""
    return length - GRAM - length // 5


def _fixed_hash(term: np.ndarray, k: int) -> np.ndarray:
    """Polynomial hash of each ``k`` values in a row, by doubling."""
    out, have, power, m = None, 0, term, 1
    while k:
        if k & 1:
            if out is None:
                out, have = power, m
            else:
                n = min(len(out), len(power) - have)
                out = out[: max(n, 0)] * np.uint64(pow(int(_BASE), m, 1 << 64)) + power[have : have + max(n, 0)]
                have += m
        k >>= 1
        if k:
            n = max(len(power) - m, 0)
            power = power[:n] * np.uint64(pow(int(_BASE), m, 1 << 64)) + power[m : m + n]
            m *= 2
    return out


def anchors_of(raw: np.ndarray, at: np.ndarray, length: int, contexts: bool = True) -> tuple[np.ndarray, ...]:
    """Text number, core hash, context hash (zero unless asked for), first start, anchor and last start of each anchor's windows."""
    reach, n = _reach(length), len(raw)
    none = np.zeros(0, np.int64)
    ok = np.diff(at) >= length
    if not ok.any():
        return none, none.view(np.uint64), none.view(np.uint64), none, none, none
    term = _BYTE[raw]
    value = (mixed(_fixed_hash(term, GRAM)) & ~np.uint64(0xFFFFFFFF)) | np.arange(n - GRAM + 1, dtype=np.uint64)
    have = 1
    while have < reach:
        step = min(have, reach - have)
        value = np.minimum(value[: len(value) - step], value[step:])
        have += step
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, at[:-1][ok], 1)
    np.add.at(edge, at[1:][ok] - length + 1, -1)
    start = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
    anchor = (value[start] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    new = np.ones(len(start), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (start[1:] != start[:-1] + 1)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(start)) - 1
    p, lo, hi = anchor[first], start[first], start[last]
    core = mixed(_fixed_hash(term, length - reach + 1)[p])
    if contexts:  # a cryptographic hash: equal ones stand for equal bytes whatever the texts are made of
        data, shape = raw.tobytes(), ((p - lo) * 1024 + (hi - lo)).tolist()
        digest = (hashlib.blake2b(data[a : b + length], digest_size=8, salt=s.to_bytes(8, "little")).digest() for a, b, s in zip(lo.tolist(), hi.tolist(), shape, strict=True))
        ctx = np.frombuffer(b"".join(digest), np.uint64)
    else:
        ctx = np.zeros(len(p), np.uint64)
    return np.searchsorted(at, lo, side="right") - 1, core, ctx, lo, p, hi


def _core_rows(docs: DataFrame, length: int) -> DataFrame:
    """``core`` of every anchor of ``docs(text)``."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            core = anchors_of(*text_bytes(batch.column("text")), length, contexts=False)[1]
            yield pa.record_batch([pa.array(core.view(np.int64))], names=["core"])

    return docs.select("text").mapInArrow(emit, "core long")


def _anchor_rows(docs: DataFrame, length: int) -> DataFrame:
    """``ANCHORS`` of ``docs(doc_id, uid, text)``; ``place`` packs first start, anchor and last start."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            raw, at = text_bytes(batch.column("text"))
            doc, core, ctx, lo, p, hi = anchors_of(raw, at, length)
            row = pa.array(doc)
            place = (lo - at[doc]) << 20 | (p - lo) << 10 | (hi - lo)
            yield pa.record_batch([batch.column("doc_id").take(row), batch.column("uid").take(row), pa.array(core.view(np.int64)), pa.array(ctx.view(np.int64)), pa.array(place)], names=["doc_id", "uid", "core", "ctx", "place"])

    return docs.mapInArrow(emit, ANCHORS)


def _named(triples: np.ndarray) -> np.ndarray:
    """Names of rows of values: ranks of the distinct rows, sorted."""
    order = np.lexsort(triples.T[::-1])
    ranked = triples[order]
    new = np.ones(len(order), bool)
    new[1:] = (ranked[1:] != ranked[:-1]).any(axis=1)
    out = np.empty(len(order), np.uint64)
    out[order] = np.cumsum(new) - 1
    return out


def sorted_by_names(parts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffix-array order of byte strings up to ``width`` bytes, and each one's common prefix with the one before.

    Strings are filled up with zeros; a common prefix counts only as far as both strings go.
    """
    words = -(-width // 8)
    levels = 0
    while 3**levels < words:
        levels += 1
    padded = 8 * 3**levels
    raw = np.frombuffer(b"".join(p[:width].ljust(padded, b"\0") for p in parts), np.uint8).reshape(len(parts), padded)
    names = raw.reshape(len(parts), -1, 8).copy().view(">u8")[:, :, 0].astype(np.uint64)
    while names.shape[1] > 1:
        names = _named(names.reshape(-1, 3)).reshape(len(parts), -1)
    order = np.argsort(names[:, 0], kind="stable")
    common = np.zeros(len(parts), np.int64)
    for lo in range(1, len(parts), 1 << 14):
        hi = min(len(parts), lo + (1 << 14))
        differ = raw[order[lo:hi]] != raw[order[lo - 1 : hi - 1]]
        common[lo:hi] = np.where(differ.any(axis=1), differ.argmax(axis=1), padded)
    return order, common


def repeated_starts(texts: list[bytes], head: np.ndarray, width: np.ndarray, length: int) -> np.ndarray:
    """Contexts by head size ``d``: whether the window that starts ``d`` bytes before the anchor occurs twice.

    Context ``c`` has its anchor at ``head[c]`` and window starts at 0..``width[c]``.
    """
    n, reach = len(texts), _reach(length)
    out = np.zeros((n, reach), bool)
    if n < 2:
        return out
    heads = head.tolist()
    right, common = sorted_by_names([t[h:] for t, h in zip(texts, heads, strict=True)], length)
    left, shared = sorted_by_names([t[:h][::-1] for t, h in zip(texts, heads, strict=True)], reach)
    least, most = head - width, head
    tail_run, head_run = np.empty(n, np.int64), np.empty(n, np.int64)
    for d in range(reach):
        live = np.flatnonzero((least <= d) & (d <= most))
        if len(live) < 2:
            continue
        tail_run[right] = np.cumsum(common < length - d)
        head_run[left] = np.cumsum(shared < d)
        key = tail_run[live] << 32 | head_run[live]
        _, which, count = np.unique(key, return_inverse=True, return_counts=True)
        out[live[count[which] > 1], d] = True
    return out


def _flags(contexts: DataFrame, length: int) -> DataFrame:
    """``(core, ctx, bits)`` of contexts with a repeated window; all contexts of a core are in one partition."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [b for b in batches if b.num_rows]
        if not tables:
            return
        part = pa.Table.from_batches(tables).combine_chunks()
        place = part.column("place").to_numpy()
        found = repeated_starts(part.column("bytes").to_pylist(), place >> 10 & 1023, place & 1023, length)
        hit = np.flatnonzero(found.any(axis=1))
        bits = np.packbits(found[hit], axis=1)
        row = pa.array(hit)
        yield pa.record_batch([part.column("core").take(row).combine_chunks(), part.column("ctx").take(row).combine_chunks(), pa.array([b.tobytes() for b in bits], pa.binary())], names=["core", "ctx", "bits"])

    return contexts.mapInArrow(emit, "core long, ctx long, bits binary")


def _split(contexts: DataFrame, length: int, span: int) -> DataFrame:
    """Contexts cut into runs of ``span`` head sizes: ``(core0, ctx0, core, ctx, place, bytes)``.

    A run's core is what all windows of those head sizes hold, which is more than the anchor's core:
    contexts that differ only beyond it part ways, and equal runs become one again.
    """

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for core, ctx, place, text in zip(*(batch.column(c).to_pylist() for c in ("core", "ctx", "place", "bytes")), strict=True):
                head, width = place >> 10 & 1023, place & 1023
                for run in range((head - width) // span, head // span + 1):
                    least, most = max(run * span, head - width), min(run * span + span - 1, head)
                    kept = text[head - most : head - least + length]
                    common = text[head - run * span : head - run * span - span + 1 + length]
                    key = hashlib.blake2b(common, digest_size=8, salt=run.to_bytes(2, "big")).digest()
                    name = hashlib.blake2b(kept, digest_size=8, salt=most.to_bytes(2, "big") + least.to_bytes(2, "big")).digest()
                    rows.append((core, ctx, int.from_bytes(key, "big", signed=True), int.from_bytes(name, "big", signed=True), most << 10 | (most - least), kept))
            cols = list(zip(*rows, strict=True)) or [()] * 6
            types = [*[pa.int64()] * 5, pa.binary()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["core0", "ctx0", "core", "ctx", "place", "bytes"])

    return contexts.mapInArrow(emit, "core0 long, ctx0 long, core long, ctx long, place long, bytes binary")


def _joined(length: int, runs: DataFrame) -> DataFrame:
    """``(core, ctx, bits)`` of contexts from the flags of their runs, ``runs(core0, ctx0, flags)``."""
    reach = _reach(length)

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = np.zeros((batch.num_rows, reach), bool)
            for k, flags in enumerate(batch.column("flags").to_pylist()):
                for f in flags:
                    if f["bits"] is None:
                        head = f["place"] >> 10 & 1023
                        bits[k, head - (f["place"] & 1023) : head + 1] = True
                    else:
                        bits[k] |= np.unpackbits(np.frombuffer(f["bits"], np.uint8))[:reach].astype(bool)
            yield pa.record_batch([batch.column("core0"), batch.column("ctx0"), pa.array([b.tobytes() for b in np.packbits(bits, axis=1)], pa.binary())], names=["core", "ctx", "bits"])

    return runs.mapInArrow(emit, "core long, ctx long, bits binary")


def _all_flags(pieces: DataFrame, length: int, spans: tuple[int, ...] = SPANS) -> DataFrame:
    """``(core, ctx, bits)`` of ``pieces(core, ctx, place, n, bytes)``, stored; ``n`` is the core's number of contexts.

    Cores within ``CORE_CONTEXTS`` go to tasks whole. Contexts of larger ones are cut into runs of fewer
    head sizes and come back here under the runs' cores; a run of one head size is a single window, and
    all windows of its core are equal, so this ends.
    """
    parts = max(1, int(pieces.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    whole = _flags(pieces.where(F.col("n") <= CORE_CONTEXTS).drop("n").repartition(parts, "core"), length)
    large = pieces.where(F.col("n") > CORE_CONTEXTS)
    if not spans or large.isEmpty():
        return whole
    runs = stored(_split(large, length, spans[0]), "runs")
    different = runs.groupBy("core", "ctx").agg(F.count("*").alias("copies"), F.first("place").alias("place"), F.first("bytes").alias("bytes"))
    different = stored(different, "different")
    groups = stored(different.groupBy("core").agg(F.count("*").alias("n")).where("n > 1"), "groups")
    inner = stored(different.join(groups, "core").select("core", "ctx", "place", "n", "bytes"), "pieces")
    often = different.where("copies > 1").select("core", "ctx", F.lit(None).cast("binary").alias("bits"))
    found = stored(often.unionByName(_all_flags(inner, length, spans[1:]).join(often.select("core", "ctx"), ["core", "ctx"], "left_anti")), "flags")
    marked = runs.select("core0", "ctx0", "core", "ctx", "place").join(found, ["core", "ctx"])
    lists = marked.groupBy("core0", "ctx0").agg(F.collect_list(F.struct("place", "bits")).alias("flags"))  # as many as there are runs
    return whole.unionByName(_joined(length, lists))


def _freed(spark) -> None:
    """Let Spark drop the shuffle files of finished steps, whose results stand in shared storage."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def repeated_marks(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``(doc_id, uid, marks)``: for each text with repeated strings, packed places and start bits."""
    spark = docs.sparkSession
    anchors = _anchor_rows(docs, length)
    often = _core_rows(docs, length).groupBy("core").agg(F.count("*").alias("n")).where("n > 1").select("core")
    often = stored(often, "cores")
    live = stored(anchors.join(often, "core"), "anchors")
    _freed(spark)
    # one row for each different context, with a place to read it from
    contexts = live.groupBy("core", "ctx").agg(F.count("*").alias("copies"), F.min(F.struct("doc_id", "uid", "place")).alias("at"))
    contexts = stored(contexts.select("core", "ctx", "copies", "at.*"), "contexts")
    groups = stored(contexts.groupBy("core").agg(F.count("*").alias("n")).where("n > 1"), "groups")
    _freed(spark)
    sought = contexts.join(groups, "core").select("doc_id", "uid", F.struct("core", "ctx", "place", "n").alias("c"))
    lists = sought.groupBy("doc_id", "uid").agg(F.collect_list("c").alias("cs"))  # bounded by the text's length
    same = docs["doc_id"].eqNullSafe(lists["doc_id"]) & (docs["uid"] == lists["uid"])
    both = docs.join(lists, same).select(docs["text"], lists["cs"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            out: list[tuple] = []
            for text, cs in zip(batch.column("text").cast(pa.binary()).to_pylist(), batch.column("cs").to_pylist(), strict=True):
                for c in cs:
                    lo, width = c["place"] >> 20, c["place"] & 1023
                    out.append((c["core"], c["ctx"], c["place"], c["n"], text[lo : lo + width + length]))
            cols = list(zip(*out, strict=True))
            types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["core", "ctx", "place", "n", "bytes"])

    pieces = stored(both.mapInArrow(cut, "core long, ctx long, place long, n long, bytes binary"), "pieces")
    _freed(spark)
    some = stored(_all_flags(pieces, length), "some-flags")
    discard(pieces, groups)
    # contexts that occur more than once: all their windows do
    whole = contexts.where("copies > 1").select("core", "ctx", F.lit(None).cast("binary").alias("bits"))
    once = some.join(whole.select("core", "ctx"), ["core", "ctx"], "left_anti")
    flags = stored(whole.unionByName(once), "flags")
    _freed(spark)
    marked = live.join(flags, ["core", "ctx"]).select("doc_id", "uid", F.struct("place", "bits").alias("mark"))
    marks = stored(marked.groupBy("doc_id", "uid").agg(F.collect_list("mark").alias("marks")), "marks")
    discard(often, live, contexts, some, flags)
    return marks


def repeated_bytes(size: int, marks: list[dict] | None, length: int) -> np.ndarray:
    """Which bytes of a text of ``size`` bytes its repeated windows cover."""
    edge = np.zeros(size + 1, np.int64)
    for m in marks or ():
        lo, head, width = m["place"] >> 20, m["place"] >> 10 & 1023, m["place"] & 1023
        if m["bits"] is None:
            starts = np.arange(lo, lo + width + 1)
        else:
            d = np.flatnonzero(np.unpackbits(np.frombuffer(m["bits"], np.uint8)))
            starts = lo + head - d
        np.add.at(edge, starts, 1)
        np.add.at(edge, starts + length, -1)
    return np.cumsum(edge[:-1]) > 0


def _with_marks(docs: DataFrame, length: int) -> DataFrame:
    """``docs`` and, where there are any, ``marks``."""
    marks = repeated_marks(docs.select("doc_id", "uid", "text"), length).select(F.col("doc_id").alias("m_id"), F.col("uid").alias("m_uid"), "marks")
    return docs.join(marks, docs["doc_id"].eqNullSafe(marks["m_id"]) & (docs["uid"] == marks["m_uid"]), "left").drop("m_id", "m_uid")


def _identified(docs: DataFrame) -> DataFrame:
    """A row's identity: its ``doc_id`` and a hash of it and its text; null text: empty."""
    return docs.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("uid", F.xxhash64("doc_id", "text"))


def removal_digests(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """Per document: bytes, bytes and runs removed, and the SHA-256 of what is left."""
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            rows = []
            for text, marks in zip(batch.column("text").cast(pa.binary()).to_pylist(), batch.column("marks").to_pylist(), strict=True):
                if not marks:
                    rows.append((len(text), 0, 0, hashlib.sha256(text).hexdigest()))
                    continue
                gone = repeated_bytes(len(text), marks, length)
                runs = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum())
                rows.append((len(text), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(text, np.uint8)[~gone].tobytes()).hexdigest()))
            cols = list(zip(*rows, strict=True))
            yield pa.record_batch([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3])], names=[c.split()[0] for c in schema.split(", ")])

    return _with_marks(_identified(free_columns(docs, ["doc_id", "text"])), length).select("doc_id", "text", "marks").mapInArrow(emit, schema)


def without_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``docs`` with repeated strings cut from ``text``; other columns stay, ``n_chars`` follows where there is one.

    Cuts widen to whole characters. No row goes; a text that is nothing but repeats comes out empty.
    """
    names, schema = docs.columns, docs.schema
    others = [c for c in names if c != "text"]  # apart in a struct: whatever they are called

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            texts = []
            for text, marks in zip(batch.column("text").cast(pa.binary()).to_pylist(), batch.column("marks").to_pylist(), strict=True):
                if marks:
                    raw = np.frombuffer(text, np.uint8)
                    gone = repeated_bytes(len(text), marks, length)
                    lead = (raw & 0xC0) != 0x80
                    char = np.cumsum(lead) - 1
                    lost = np.zeros(int(char[-1]) + 1, bool)
                    lost[char[gone]] = True
                    text = raw[~lost[char]].tobytes()
                texts.append(text.decode("utf-8", "replace"))
            cols = dict(zip(others, batch.column("row").flatten(), strict=True))
            cols["text"] = pa.array(texts, pa.string())
            if "n_chars" in cols:
                cols["n_chars"] = pa.array([len(t) for t in texts], pa.int64())
            yield pa.record_batch([cols[c] for c in names], names=names)

    small_batches(docs.sparkSession)
    own = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.xxhash64("doc_id", F.coalesce("text", F.lit(""))).alias("uid"), F.struct(*others).alias("row"))
    return _with_marks(own, length).select("text", "marks", "row").mapInArrow(emit, schema)
