"""The latent scheme: cut a table into blocks by row and column label, code each, and undo it.

Rows go to groups of one row label and one stretch of row numbers (a chunk), so that a group is bounded
whatever the labels' sizes; within it each column label's cells are one sequence. Frequency tables are
those of the whole block. A chunk has ``CHUNK_CELLS`` cells at most; each one starts its coder anew, which
costs the frequency coder its final states and the dictionary coders what they had learnt.

A container is a table of segments: header, coded labels of the columns and, chunk by chunk, of the rows,
symbol counts, and blocks. Sizes are those of the segments' bytes, and ``decompress`` reads nothing else
but the alphabets' sizes, which the codebook has. The baselines are the same code with one label: row
order, column order, one table or one for each column.
"""

from __future__ import annotations

import math
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpress.coders import phrase_lz, rans, zstd
from blockpress.operators.cells import cells_of, holds_bits, packed_bytes, unpacked
from blockpress.operators.entropy import block_histogram, ideal_sizes, with_labels
from blockpress.sources.storage import discard, kept

#: Of ``row_latents`` the field ``u`` holds the bytes of the row numbers' gaps, which stand in front (dense numbers: none).
SEGMENTS = "segment string, u int, v int, chunk_id long, n_symbols long, n_bits long, coder string, crc long, payload binary"
NAMES = tuple(f.split()[0] for f in SEGMENTS.split(", "))
#: Cells of a chunk, and its most rows.
CHUNK_CELLS = 1 << 23
CHUNK_ROWS = 1 << 17
#: Tasks that sizes should have work for, where a table is small.
LEAST_GROUPS = 16
#: Columns with a label each, and cells that are counted at once, beyond which arrays stand for lists.
WIDE_COLUMNS, SLICE_CELLS = 64, 1 << 21
#: Cells a one above which zeros and ones are counted by the ones' places.
FEW_ONES = 50
CODERS = ("zstd", "rans", "lz", "raw")
#: Magic, rows, columns, row and column labels, chunk rows, block coder, label coder, packing, scan order, whether all is plain.
HEADER = struct.Struct("<4sQIHIQBB4s3sB")
MAGIC = b"LBT1"


@dataclass
class Container:
    """``segments`` (see ``SEGMENTS``) and the alphabets' sizes; the rest is read from the segments."""

    segments: DataFrame
    cards: list[int]
    bits: dict[str, float] = field(default_factory=dict)

    def __post_init__(self):
        small = {(r.segment, r.u, r.v): r for r in self.segments.where("segment in ('header', 'col_latents', 'counts')").collect()}  # labels x labels rows
        head = bytes(small["header", 0, 0].payload)
        magic, self.m, self.n, self.k_r, self.k_c, self.chunk_rows, coder, coder_l, pack, order, plain = HEADER.unpack_from(head)
        if magic != MAGIC:
            raise ValueError("not a container")
        self.coder, self.coder_labels, self.pack, self.order, self.plain = CODERS[coder], CODERS[coder_l], pack.decode().strip(), order.decode(), bool(plain)
        self.freq = {(u, v): rans.scaled(read_counts(bytes(r.payload), max(self.cards))) for (s, u, v), r in small.items() if s == "counts"}
        if self.k_c == self.n:
            self.columns = np.arange(self.n)
        elif self.k_c == 1:
            self.columns = np.zeros(self.n, int)
        else:
            r = small["col_latents", 0, 0]
            self.columns = label_decode(bytes(r.payload), self.n, self.k_c, r.coder, self.pack)
        if not self.bits:
            got = {r.segment: float(r.b) for r in self.segments.groupBy("segment").agg(F.sum("n_bits").alias("b")).collect()}
            self.bits = {k: got.get(k, 0.0) for k in ("header", "row_latents", "col_latents", "counts", "blocks")}

    @property
    def blocks(self) -> DataFrame:
        return self.segments.where("segment = 'blocks'")

    @property
    def labels(self) -> DataFrame:
        """``row_id, u`` of every row, from the coded labels."""
        k_r, pack, step = self.k_r, self.pack, self.chunk_rows

        def emit(batches):
            for batch in batches:
                for r in batch.to_pylist():
                    row_id, u = chunk_labels(r, k_r, pack, step)
                    yield pa.record_batch([pa.array(row_id, pa.int64()), pa.array(u.astype(np.int32))], names=["row_id", "u"])

        return self.segments.where("segment = 'row_latents'").mapInArrow(emit, "row_id long, u int")

    @property
    def coded_bits(self) -> float:
        return sum(self.bits.values())


def block_counts(hist: DataFrame, cards: list[int]) -> dict[tuple[int, int], np.ndarray]:
    """Symbol counts of each block: labels x labels x symbols at most."""
    out: dict[tuple[int, int], np.ndarray] = {}
    for r in hist.collect():
        out.setdefault((r.u, r.v), np.zeros(max(cards), np.int64))[r.code] = r.cnt
    return out


def write_counts(counts: np.ndarray) -> bytes:
    """Which symbols occur, a bit each, and a 64-bit count for each that does."""
    return np.packbits(counts > 0).tobytes() + counts[counts > 0].astype("<i8").tobytes()


def read_counts(data: bytes, card: int) -> np.ndarray:
    out, lead = np.zeros(card, np.int64), -(-card // 8)
    there = np.unpackbits(np.frombuffer(data, np.uint8, lead))[:card].astype(bool)
    out[there] = np.frombuffer(data, "<i8", int(there.sum()), lead)
    return out


def plain_encode(seq: np.ndarray, card: int) -> bytes:
    """Symbols at a whole number of bits each."""
    width = max(card - 1, 0).bit_length()
    if not width:
        return b""
    return np.packbits((np.asarray(seq, np.int64)[:, None] >> np.arange(width - 1, -1, -1)) & 1).tobytes()


def plain_decode(data: bytes, n: int, card: int) -> np.ndarray:
    width = max(card - 1, 0).bit_length()
    if not width:
        return np.zeros(n, np.int64)
    bits = np.unpackbits(np.frombuffer(data, np.uint8))[: n * width].reshape(n, width).astype(np.int64)
    return bits @ (1 << np.arange(width - 1, -1, -1))


def _encode(seq: np.ndarray, coder: str, pack: str, card: int, freq: tuple[np.ndarray, int] | None) -> bytes:
    if coder == "zstd":
        return zstd.encode(seq, pack, card)
    if coder == "rans":
        return rans.encode(seq, *freq)
    if coder == "lz":
        data, _, plain = phrase_lz.encode(seq.tolist(), card)
        return bytes([plain]) + data
    if coder == "raw":
        return plain_encode(seq, card)
    raise ValueError(coder)


def _decode(data: bytes, n: int, coder: str, pack: str, card: int, freq: tuple[np.ndarray, int] | None) -> np.ndarray:
    if coder == "zstd":
        return zstd.decode(data, n, pack, card)
    if coder == "rans":
        return rans.decode(data, n, *freq)
    if coder == "raw":
        return plain_decode(data, n, card)
    return np.array(phrase_lz.decode(data[1:], n, card, bool(data[0])))


def _shortest(seq: np.ndarray, coder: str, pack: str, card: int, freq: tuple[np.ndarray, int] | None, fallback: bool) -> tuple[str, bytes]:
    """The coder used and its bytes: with ``fallback`` the plain code where that is shorter."""
    data = _encode(seq, coder, pack, card, freq)
    if fallback and len(data) * 8 > len(seq) * max(card - 1, 0).bit_length() + 7:
        return "raw", plain_encode(seq, card)
    return coder, data


def label_encode(labels: np.ndarray, k: int, coder: str, pack: str) -> bytes:
    """Coded labels; the frequency coder's counts stand in front."""
    labels = np.asarray(labels, np.int64)
    if coder != "rans":
        return _encode(labels, coder, pack, k, None)
    counts = np.bincount(labels, minlength=k)
    return write_counts(counts) + rans.encode(labels, *rans.scaled(counts))


def label_decode(data: bytes, n: int, k: int, coder: str, pack: str) -> np.ndarray:
    if coder != "rans":
        return np.asarray(_decode(data, n, coder, pack, k, None), np.int64)
    counts = read_counts(data, k)
    return rans.decode(data[-(-k // 8) + 8 * int((counts > 0).sum()) :], n, *rans.scaled(counts))


def chunk_labels(r: dict, k: int, pack: str, step: int) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers and labels of a ``row_latents`` segment."""
    m, gaps, first = r["n_symbols"], r["u"], r["chunk_id"] * step
    row_id = np.arange(first, first + m)
    if gaps:
        row_id = first + np.cumsum(np.frombuffer(zstd.zstandard.ZstdDecompressor().decompress(r["payload"][:gaps]), "<i8"))
    return row_id, label_decode(r["payload"][gaps:], m, k, r["coder"], pack) if k > 1 else np.zeros(m, np.int64)


def _segment_table(rows: list[tuple]) -> pa.Table:
    types = [pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.binary()]
    return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=list(NAMES))


def _row(segment: str, u: int, v: int, chunk: int, n: int, coder: str, data: bytes) -> tuple:
    return segment, u, v, chunk, n, 8 * len(data), coder, zlib.crc32(data), data


def compress(codes: DataFrame, cards: list[int], columns: np.ndarray, coder: str = "rans", coder_labels: str | None = None, order: str = "row", pack: str = "byte", chunk_rows: int | None = None, fallback: bool = False) -> Container:
    """Code ``codes(row_id, u, codes)`` with column labels ``columns``.

    One shuffle: each row once, by (row label, chunk), and the labels by chunk. ``order`` is the scan within a
    block. ``fallback`` sends plain code for a block or a label chunk that it makes shorter, and all of the
    table plain if that is shorter still, so that the whole is never more than the raw table and a header.
    Row numbers should be dense; the gaps of those that are not are stored with the labels.
    """
    coder_labels = coder_labels or coder
    columns = np.asarray(columns)
    codes = unpacked(codes, len(cards))
    n, card, k_c = len(cards), max(cards), int(columns.max()) + 1
    chunk_rows = chunk_rows or max(1, min(CHUNK_ROWS, CHUNK_CELLS // n))
    freq: dict[tuple[int, int], tuple[np.ndarray, int]] = {}
    fixed: list[tuple] = []
    if coder == "rans":
        counts = block_counts(block_histogram(with_labels(codes, columns.tolist())), cards)
        freq = {key: rans.scaled(c) for key, c in counts.items()}
        fixed += [_row("counts", u, v, 0, int(c.sum()), "raw", write_counts(c)) for (u, v), c in sorted(counts.items())]
    members = [np.flatnonzero(columns == v) for v in range(k_c)]
    size = codes.agg(F.count("*").alias("m"), F.max("u").alias("u")).first()
    m, k_r = size.m, int(size.u or 0) + 1
    if k_c not in (1, n):
        fixed.append(_row("col_latents", 0, 0, 0, n, coder_labels, label_encode(columns, k_c, coder_labels, pack)))

    def code_group(key, table):
        u, chunk = key[0].as_py(), key[1].as_py()
        table = table.sort_by("row_id").combine_chunks()
        cells = table.column("codes").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, n)
        rows = []
        for v in range(k_c):
            part = cells[:, members[v]]
            seq = (part if order == "row" else part.T).ravel().astype(np.int64)
            rows.append(_row("blocks", u, v, chunk, len(seq), *_shortest(seq, coder, pack, card, freq.get((u, v)), fallback)))
        return _segment_table(rows)

    def code_labels(key, table):
        chunk = key[0].as_py()
        table = table.sort_by("row_id")
        u, row_id = table.column("u").to_numpy().astype(np.int64), table.column("row_id").to_numpy()
        dense = row_id[0] == chunk * chunk_rows and (np.diff(row_id) == 1).all()
        gaps = b"" if dense else zstd.zstandard.ZstdCompressor(level=zstd.LEVEL).compress(np.diff(row_id, prepend=chunk * chunk_rows).astype("<i8").tobytes())
        used, data = coder_labels, label_encode(u, k_r, coder_labels, pack) if k_r > 1 else b""
        if fallback and k_r > 1 and len(data) > len(plain := plain_encode(u, k_r)):
            used, data = "raw", plain
        return _segment_table([_row("row_latents", len(gaps), 0, chunk, len(u), used, gaps + data)])

    chunked = codes.select("row_id", F.col("u").cast("int").alias("u"), "codes", F.floor(F.col("row_id") / chunk_rows).alias("chunk_id"))
    coded = chunked.groupBy("u", "chunk_id").applyInArrow(code_group, SEGMENTS)
    coded = coded.unionByName(chunked.select("row_id", "u", "chunk_id").groupBy("chunk_id").applyInArrow(code_labels, SEGMENTS))
    spark = codes.sparkSession
    coded = kept(coded, "segments")
    if fallback and k_r * k_c > 1:
        total = (coded.agg(F.sum("n_bits")).first()[0] or 0) + sum(r[5] for r in fixed)
        if total > m * n * max(card - 1, 0).bit_length():
            return compress(codes.withColumn("u", F.lit(0)), cards, np.zeros(n, int), "raw", "raw", order, pack, chunk_rows)
    lengths = {(r.u, r.v): r.b for r in coded.where("segment = 'blocks'").groupBy("u", "v").agg(F.sum("n_bits").alias("b")).collect()}
    labels = coded.where("segment = 'row_latents'").agg(F.sum("n_bits")).first()[0] or 0
    parts = [labels, sum(r[5] for r in fixed if r[0] == "col_latents"), *(lengths.get((u, v), 0) for u in range(k_r) for v in range(k_c))]
    width = max(math.ceil(math.log2(m * n + 1)), max(parts).bit_length())
    packed = plain_encode(np.array(parts, np.int64), 1 << width) if k_r * k_c > 1 else b""
    head = HEADER.pack(MAGIC, m, n, k_r, k_c, chunk_rows, CODERS.index(coder), CODERS.index(coder_labels), pack.encode().ljust(4), order.encode(), coder == "raw")
    fixed.append(_row("header", 0, 0, 0, len(parts), "raw", head + packed))
    whole = kept(spark.createDataFrame(_segment_table(fixed)).select(*NAMES).coalesce(1), "fixed-segments")
    return Container(coded.unionByName(whole), list(cards))


def compress_reordered(codes: DataFrame, cards: list[int], columns: np.ndarray, coder: str = "zstd", pack: str = "byte") -> Container:
    """Sort rows by label and number, columns by label, and code the result as one sequence: an ablation."""
    from blockpress.plans.encode import assign_row_ids

    order = np.argsort(columns, kind="stable")
    moved = F.transform(F.array(*[F.lit(int(j) + 1) for j in order]), lambda j: F.element_at("codes", j))
    named = codes.select("row_id", "u", moved.alias("codes")).withColumnRenamed("row_id", "_r")
    flat = assign_row_ids(named, ["u", "_r"]).select("row_id", F.lit(0).alias("u"), "codes")
    return compress(flat, [cards[j] for j in order], np.zeros(len(cards), int), coder, pack=pack)


def decompress(box: Container, chunk_rows: int | None = None, only: list[int] | None = None, only_u: list[int] | None = None) -> DataFrame:
    """``row_id, codes`` again, from the segments alone. ``only`` names columns: blocks of other labels are not read; ``only_u`` row labels likewise.

    Chunk by chunk: a chunk's coded labels tell which row each block's cells belong to. ``chunk_rows``, where
    given, must be the container's.
    """
    if chunk_rows is not None and chunk_rows != box.chunk_rows:
        raise ValueError(f"the container has chunks of {box.chunk_rows} rows")
    n, card, columns, k_r = box.n, max(box.cards), box.columns, box.k_r
    members = [np.flatnonzero(columns == v) for v in range(box.k_c)]
    wanted = sorted({int(columns[j]) for j in only}) if only is not None else list(range(len(members)))
    show = np.array(only if only is not None else range(n))
    blocks = box.blocks.where(F.col("v").isin(wanted)) if only is not None else box.blocks
    blocks = blocks.where(F.col("u").isin(only_u)) if only_u is not None else blocks
    rows = box.segments.where("segment = 'row_latents'").unionByName(blocks)
    pack, order, freq, step = box.pack, box.order, box.freq, box.chunk_rows

    def decode_chunk(key, parts):
        held = parts.to_pylist()
        if any(zlib.crc32(p["payload"]) != p["crc"] for p in held):
            raise ValueError(f"chunk {key[0].as_py()} is damaged")
        head = next(p for p in held if p["segment"] == "row_latents")
        row_id, u = chunk_labels(head, k_r, pack, step)
        m = len(u)
        cells, there = np.zeros((m, n), np.int16), np.zeros(m, bool)
        for b in held:
            if b["segment"] != "blocks":
                continue
            seq = _decode(b["payload"], b["n_symbols"], b["coder"], pack, card, freq.get((b["u"], b["v"])))
            own, mine = members[b["v"]], np.flatnonzero(u == b["u"])
            cells[np.ix_(mine, own)] = seq.reshape(-1, len(own)) if order == "row" else seq.reshape(len(own), -1).T
            there[mine] = True
        shown = cells[there][:, show]
        at = np.arange(len(shown) + 1, dtype=np.int32) * shown.shape[1]
        return pa.table({"row_id": row_id[there], "codes": pa.ListArray.from_arrays(pa.array(at), pa.array(shown.ravel()))})

    return rows.groupBy("chunk_id").applyInArrow(decode_chunk, "row_id long, codes array<smallint>")


def size_breakdown(box: Container) -> DataFrame:
    """``segment, n_bits`` and their total."""
    spark = box.segments.sparkSession
    rows = [(k, v) for k, v in box.bits.items()] + [("total", box.coded_bits)]
    return spark.createDataFrame(rows, "segment string, n_bits double")


@dataclass(frozen=True)
class Coding:
    """One way to code a table: a coder, a scan order, column labels, and which of a row's labels it takes (-1: none)."""

    name: str
    coder: str
    columns: tuple[int, ...]
    which: int = -1
    order: str = "row"


SIZES = "coding int, u int, n_bits double"


def _pieces(codes: DataFrame, n: int, card: int, chunk_rows: int) -> DataFrame:
    """``codes(row_id, us, codes)`` packed: the rows of a batch that lie in one chunk are a row, with cells of a byte each where they fit, or of a bit."""
    small, bits = np.uint8 if card <= 256 else np.int16, holds_bits(codes)

    def emit(batches):
        for batch in batches:
            m = batch.num_rows
            if not m:
                continue
            ids = batch.column("row_id").to_numpy()
            us = batch.column("us").flatten().to_numpy(zero_copy_only=False).reshape(m, len(batch.column("us").flatten()) // m).astype(np.uint16)
            cells = packed_bytes(batch.column("codes")) if bits else cells_of(batch.column("codes"), n).astype(small)
            chunk = ids // chunk_rows
            for c in np.unique(chunk).tolist():
                mine = np.flatnonzero(chunk == c)
                mine = slice(int(mine[0]), int(mine[-1]) + 1) if mine[-1] - mine[0] + 1 == len(mine) else mine
                parts = ids[mine], us[mine], cells[mine]
                yield pa.record_batch([pa.array([c], pa.int64()), pa.array([len(parts[0])], pa.int32()), *[pa.array([x.tobytes()], pa.binary()) for x in parts]], names=["chunk", "m", "ids", "us", "cells"])

    return kept(codes.select("row_id", "us", "codes").mapInArrow(emit, "chunk long, m int, ids binary, us binary, cells binary"), "pieces", None if bits else "none")


def _opened(piece: dict, n: int, card: int, bits: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row numbers, labels and cells (or their bits, by rows) of a piece."""
    m = piece["m"]
    us = np.frombuffer(piece["us"], np.uint16)
    kind = np.uint8 if bits or card <= 256 else np.int16
    return np.frombuffer(piece["ids"], np.int64), us.reshape(m, len(us) // m), np.frombuffer(piece["cells"], kind).reshape(m, -1)


def _combined(us: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different rows of labels, and which of them each row has."""
    if not us.shape[1]:
        return us[:1], np.zeros(len(us), np.int64)
    base = us.max(axis=0).astype(np.int64) + 1
    if np.log2(base).sum() < 62:
        key = us.astype(np.int64) @ (np.cumprod(base) // base)
        _, first, at = np.unique(key, return_index=True, return_inverse=True)
        return us[first], at
    return np.unique(us, axis=0, return_inverse=True)


def coded_sizes(codes: DataFrame, cards: list[int], codings: list[Coding], pack: str = "byte") -> list[dict[str, float]]:
    """Size by segment of ``codes(row_id, us, codes)`` under each coding, as ``compress`` would make it: all in one shuffle.

    Rows are packed to pieces once. Symbol counts of all codings come from one scan of these; then each piece goes once to its
    chunk, where all codings and the labels are sized, the frequency coder's blocks together. Where chunks are few, each goes to
    several tasks that share the codings out. Nothing but sizes is kept.
    """
    n, card = len(cards), max(cards)
    chunk_rows = max(1, min(CHUNK_ROWS, CHUNK_CELLS // n))
    cols = [np.array(c.columns) for c in codings]
    k_c = [int(v.max()) + 1 for v in cols]
    which = [c.which for c in codings]
    spark, bits_held = codes.sparkSession, holds_bits(codes)
    table = _pieces(codes, n, card, chunk_rows)
    counted = [i for i, c in enumerate(codings) if c.coder == "rans"]
    told = sorted({which[i] for i in counted if which[i] >= 0})
    places, widths = np.arange(n) * card, [np.bincount(v) for v in cols]

    step = max(1, SLICE_CELLS // n)

    def labels_of(us, i):
        return us[:, which[i]] if which[i] >= 0 else np.zeros(len(us), np.uint16)

    def count(batches):
        totals: dict[tuple[int, int], np.ndarray] = {}
        blocks: dict[tuple[int, int], np.ndarray] = {}
        combined: dict[tuple[int, ...], np.ndarray] = {}
        seen: dict[int, int] = {}
        rows_read = 0

        def add(key, t):
            totals[key] = totals[key] + t if key in totals else t

        def by_ones(us, at):
            row, col = at // n, at % n
            for i in counted:
                own = labels_of(us, i).astype(np.int64)
                rows = np.bincount(own)
                one = np.bincount(own[row] * k_c[i] + cols[i][col], minlength=len(rows) * k_c[i]).reshape(-1, k_c[i])
                for u in np.flatnonzero(rows).tolist():
                    t = np.stack([rows[u] * widths[i] - one[u], one[u]], axis=1)
                    blocks[i, u] = blocks[i, u] + t if (i, u) in blocks else t

        def spread():
            for labels, t in combined.items():
                for i in counted:
                    add((i, labels[told.index(which[i])] if which[i] >= 0 else 0), t)
            combined.clear()

        for batch in batches:
            for piece in batch.to_pylist():
                _, all_us, held = _opened(piece, n, card, bits_held)
                rows_read += len(held)
                for w in {w for w in which if w >= 0}:
                    seen[w] = max(seen.get(w, 0), int(all_us[:, w].max()))
                for lo in range(0, len(held) if counted else 0, step):
                    us, cells = all_us[lo : lo + step], held[lo : lo + step]
                    if card == 2:  # by column: one product for all codings
                        cells = np.unpackbits(cells, axis=1, count=n) if bits_held else cells
                        if np.count_nonzero(cells) * FEW_ONES < cells.size:
                            by_ones(us, np.flatnonzero(cells.view(bool)))
                            continue
                        own = {i: labels_of(us, i) for i in counted}
                        names = [(i, u) for i in counted for u in np.unique(own[i]).tolist()]
                        member = np.array([own[i] == u for i, u in names], np.float32).reshape(-1, len(us))
                        ones = np.rint(member @ cells.astype(np.float32)).astype(np.int64)  # at most so many rows: exact
                        for key, one, rows in zip(names, ones, member.sum(axis=1).astype(np.int64).tolist(), strict=True):
                            add(key, np.stack([rows - one, one], axis=1))
                        continue
                    different, at = _combined(us[:, told])
                    part = max(1, SLICE_CELLS // (n * card))  # so many different rows of labels at once
                    for first in range(0, len(different), part):
                        few = different[first : first + part]
                        mine = slice(None) if len(different) <= part else (at >= first) & (at < first + part)
                        flat = ((at[mine] - first) * (n * card))[:, None] + places + cells[mine]
                        got = np.bincount(flat.ravel(), minlength=len(few) * n * card).reshape(len(few), n, card)
                        for labels, t in zip(few.tolist(), got, strict=True):
                            key = tuple(labels)
                            combined[key] = combined[key] + t if key in combined else t.copy()
                    if len(combined) * n * card > 4 * SLICE_CELLS:
                        spread()
        spread()
        for i, u in dict.fromkeys([*totals, *blocks]):
            each = np.zeros((k_c[i], card), np.int64)
            if (i, u) in totals:
                np.add.at(each, cols[i], totals[i, u])
            each += blocks.get((i, u), 0)
            j = np.flatnonzero(each)
            yield pa.record_batch([pa.array(np.full(len(j), i, np.int32)), pa.array(np.full(len(j), u, np.int32)), pa.array(j.astype(np.int32)), pa.array(each.ravel()[j])], names=["i", "u", "j", "c"])
        told_of = [(w, u, -1, 0) for w, u in seen.items()] + [(-1, 0, -1, rows_read)]
        yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*told_of, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.int64()), strict=True)], names=["i", "u", "j", "c"])

    freq: dict[tuple[int, int, int], tuple[np.ndarray, int]] = {}
    out = [{"header": 0.0, "row_latents": 0.0, "col_latents": 0.0, "counts": 0.0, "blocks": 0.0} for _ in codings]
    found = table.mapInArrow(count, "i int, u int, j int, c long").groupBy("i", "u", "j").agg(F.sum("c").alias("c")).collect()  # codings x labels x symbols
    m = sum(r.c for r in found if r.j < 0)
    most = {w: max([r.u for r in found if r.j < 0 and r.i == w], default=0) for w in which}
    k_r = [1 + most[w] if w >= 0 else 1 for w in which]
    if counted:
        sums: dict[tuple[int, int, int], np.ndarray] = {}
        for r in (r for r in found if r.j >= 0):
            sums.setdefault((r.i, r.u, r.j // card), np.zeros(card, np.int64))[r.j % card] = r.c
        for (i, u, v), c in sums.items():
            freq[i, u, v] = rans.scaled(c)
            out[i]["counts"] += 8 * len(write_counts(c))
    #: Codings that give each of many columns a label: their frequencies as two arrays for each row label.
    wide = {i: {} for i in counted if k_c[i] == n and rans.lanes_for(chunk_rows) == 1 and n > WIDE_COLUMNS}
    for i in wide:
        for u in {u for j, u, _ in freq if j == i}:
            wide[i][u] = np.stack([freq[i, u, v][0] for v in range(n)]), np.array([freq[i, u, v][1] for v in range(n)])
    freq = {key: f for key, f in freq.items() if key[0] not in wide}

    members = [[] if i in wide else [np.flatnonzero(v == j) for j in range(k)] for i, (v, k) in enumerate(zip(cols, k_c, strict=True))]
    shares = min(len(codings), max(1, LEAST_GROUPS * chunk_rows // max(m, 1)))
    labelled = [i for i, k in enumerate(k_r) if k > 1]

    def ranked(labels, k):
        """Numbers of each label, and each one's place among its like."""
        many, order = np.bincount(labels, minlength=k), np.argsort(labels, kind="stable")
        place = np.empty(len(labels), np.int64)
        place[order] = np.arange(len(labels)) - np.repeat(np.cumsum(many) - many, many)
        return many, place

    def add_by_ones(i, own, ones, bits, thin):
        """Sizes of a chunk's blocks under a coding from the places of the ones: the dictionary coder's are added to ``bits``, the frequency coder's wait in ``thin``."""
        c, k = codings[i], k_c[i]
        (tall, down), (broad, along) = ranked(own, k_r[i]), ranked(cols[i], k)
        row, col = ones // n, ones % n
        u, v = own[row], cols[i][col]
        at = down[row] * broad[v] + along[col] if c.order == "row" else along[col] * tall[u] + down[row]
        order = np.lexsort((at, u * k + v))
        at, ends = at[order], np.searchsorted((u * k + v)[order], np.arange(len(tall) * k + 1))
        for u, v in ((u, v) for u in np.flatnonzero(tall).tolist() for v in range(k)):
            mine, size = at[ends[u * k + v] : ends[u * k + v + 1]], int(tall[u] * broad[v])
            if c.coder == "rans":
                thin.append((i, u, size, mine, *freq[i, u, v]))
                continue
            seq = np.zeros(size, np.uint8)
            seq[mine] = 1
            bits[i, u] = bits.get((i, u), 0.0) + 8 * len(_encode(seq if c.coder == "zstd" else seq.astype(np.int64), c.coder, pack, card, None))

    def code_chunk(key, part):
        ids, us, cells = (np.concatenate(x) for x in zip(*[_opened(p, n, card, bits_held) for p in part.to_pylist()], strict=True))
        if (np.diff(ids) < 0).any():
            by_row = np.argsort(ids, kind="stable")
            us, cells = us[by_row], cells[by_row]
        cells = np.unpackbits(cells, axis=1, count=n) if bits_held else cells
        bits: dict[tuple[int, int], float] = {}
        waiting: list[tuple] = []
        thin: list[tuple] = []

        def flush():
            for (i, u, *_), length in zip(waiting, rans.coded_lengths([w[2:] for w in waiting]), strict=True):
                bits[i, u] = bits.get((i, u), 0.0) + 8 * length
            waiting.clear()

        held = 0
        ones = np.flatnonzero(cells.view(bool)) if bits_held else None
        few = bits_held and len(ones) * FEW_ONES < cells.size
        for i in range(key[1].as_py(), len(codings), shares):
            c = codings[i]
            own = labels_of(us, i)
            if few and i not in wide:
                add_by_ones(i, own.astype(np.int64), ones, bits, thin)
                continue
            for u in np.unique(own).tolist() if which[i] >= 0 else [0]:
                mine = cells[own == u] if which[i] >= 0 else cells
                if i in wide:
                    mine = mine if (cols[i] == np.arange(n)).all() else mine[:, cols[i].argsort()]
                    bits[i, u] = 8.0 * float(rans.column_lengths(mine, *wide[i][u]).sum())
                    continue
                for v, at in enumerate(members[i]):
                    block = mine if len(at) == n else mine[:, at]
                    seq = (block if c.order == "row" else block.T).ravel()
                    if c.coder == "rans":
                        waiting.append((i, u, seq, *freq[i, u, v]))
                        held += len(seq)
                    else:
                        bits[i, u] = bits.get((i, u), 0.0) + 8 * len(_encode(seq if c.coder == "zstd" else seq.astype(np.int64), c.coder, pack, card, None))
                    if held > (8 * CHUNK_CELLS if card == 2 else CHUNK_CELLS):  # two symbols are held in a byte each, or as ones' places
                        flush()
                        held = 0
        if waiting:
            flush()
        for (i, u, *_), length in zip(thin, rans.lengths_by_ones([w[2:] for w in thin]) if thin else (), strict=True):
            bits[i, u] = bits.get((i, u), 0.0) + 8 * length
        if key[1].as_py() == 0:
            bits |= {(i, -1): b for i, b in zip(labelled, label_bits(us), strict=True)}
        return pa.table({"coding": pa.array([i for i, _ in bits], pa.int32()), "u": pa.array([u for _, u in bits], pa.int32()), "n_bits": pa.array(list(bits.values()), pa.float64())})

    def label_bits(us):
        bits, waiting = [0.0] * len(labelled), []
        for j, i in enumerate(labelled):
            own = us[:, which[i]].astype(np.int64)
            if codings[i].coder == "rans":
                counts = np.bincount(own, minlength=k_r[i])
                bits[j] = 8.0 * len(write_counts(counts))
                waiting.append((j, own, *rans.scaled(counts)))
            else:
                bits[j] = 8.0 * len(label_encode(own, k_r[i], codings[i].coder, pack))
        if waiting:
            for (j, *_), length in zip(waiting, rans.coded_lengths([w[1:] for w in waiting]), strict=True):
                bits[j] += 8.0 * length
        return bits

    each = table.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))))
    # too short for its work to be dealt out by size
    each = each.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(512, -(-m // chunk_rows) * shares)), "chunk", "share")
    for r in each.groupBy("chunk", "share").applyInArrow(code_chunk, SIZES).groupBy("coding", F.col("u") < 0).agg(F.sum("n_bits").alias("b")).collect():  # two rows a coding
        out[r.coding]["row_latents" if r[1] else "blocks"] += r.b
    discard(table)
    width = math.ceil(math.log2(m * n + 1)) if m else 1
    for i, c in enumerate(codings):
        if k_c[i] not in (1, n):
            out[i]["col_latents"] = 8.0 * len(label_encode(cols[i], k_c[i], c.coder, pack))
        pairs = k_r[i] * k_c[i]
        out[i]["header"] = 8.0 * (HEADER.size + (-(-(pairs + 2) * width // 8) if pairs > 1 else 0))
    return out


def row_scores(codes: DataFrame, logq: np.ndarray, log_row: np.ndarray, columns: np.ndarray) -> DataFrame:
    """``row_id, u, entropy``: likeliest label of each row under a block model, and the labels' posterior entropy in bits."""
    k_r = len(log_row)
    per_col = logq[:, columns, :]  # labels x columns x symbols

    def emit(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            cells = batch.column("codes").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(batch.num_rows, -1)
            score = np.stack([per_col[u][np.arange(cells.shape[1]), cells].sum(axis=1) for u in range(k_r)], axis=1) + log_row
            top = score.max(axis=1, keepdims=True)
            p = np.exp2(score - top)
            p /= p.sum(axis=1, keepdims=True)
            ent = -(p * np.log2(np.maximum(p, 1e-300))).sum(axis=1)
            yield pa.record_batch([batch.column("row_id"), pa.array(score.argmax(axis=1).astype(np.int32)), pa.array(ent)], names=["row_id", "u", "entropy"])

    return codes.select("row_id", "codes").mapInArrow(emit, "row_id long, u int, entropy double")


def _model(codes: DataFrame, columns: np.ndarray, card: int) -> tuple[np.ndarray, np.ndarray]:
    """log2 of smoothed block laws and row-label law."""
    counts = block_counts(block_histogram(with_labels(codes, columns.tolist())), [card])
    k_r, k_c = max(u for u, _ in counts) + 1, max(v for _, v in counts) + 1
    q = np.full((k_r, k_c, card), 0.5)
    for (u, v), c in counts.items():
        q[u, v] += c
    rows = q.sum(axis=(1, 2))
    return np.log2(q / q.sum(axis=2, keepdims=True)), np.log2(rows / rows.sum())


def bits_back_savings(codes: DataFrame, cards: list[int], columns: np.ndarray) -> dict[str, float]:
    """Row-label bits, and how many of them the labels' posterior entropy gives back."""
    logq, log_row = _model(codes, columns, max(cards))
    scored = row_scores(codes, logq, log_row, columns)
    got = scored.agg(F.sum("entropy").alias("back"), F.count("*").alias("m")).first()
    p = np.exp2(log_row)
    label_bits = float(-(p * log_row).sum()) * got.m
    return {"label_bits": label_bits, "saved_bits": min(got.back, label_bits), "rows": got.m}


def refine_labels(codes: DataFrame, cards: list[int], columns: np.ndarray, sweeps: int = 1) -> DataFrame:
    """``row_id, u, codes`` with each row moved to the label under which it codes shortest, so many times."""
    for _ in range(sweeps):
        logq, log_row = _model(codes, columns, max(cards))
        moved = kept(row_scores(codes, logq, log_row, columns).select("row_id", "u"), "refined")
        codes = codes.drop("u").join(moved, "row_id").select("row_id", "u", "codes")
    return codes


def search_latents(codes: DataFrame, factors, n: int, cards: list[int], grid_r: list[int], grid_c: list[int], seed: int = 42, objective: str = "entropy", coder: str = "rans") -> DataFrame:
    """``k_r, k_c, bits, drr, rank``: coded size for each pair of label sizes; (1, 1), (1, n) and each (k, n) are tried too.

    ``objective``: ``entropy`` takes ideal sizes, from one scan whose tasks add up the counts of all pairs and one
    aggregation that turns them into bits, so the driver sees a row a pair; ``coded`` runs the coder on all pairs.
    """
    from blockpress.operators.latents import kmeans_many, kmeans_small
    from blockpress.plans.encode import raw_bits

    grid_r, grid_c = sorted({1, *grid_r}), sorted({1, *(min(c, n) for c in grid_c), n})
    width = len(factors.sigma)
    found = kmeans_many(factors.rows, [(k, min(width, max(1, k - 1)), seed) for k in grid_r])
    rows = kept(codes.select("row_id", "codes").join(found, "row_id").select("row_id", "us", "codes"), "search")
    columns = [np.arange(n) if c >= n else np.zeros(n, int) if c == 1 else kmeans_small(factors.columns[:, : max(1, c - 1)], c, seed) for c in grid_c]
    m, card = rows.count(), max(cards)
    raw = raw_bits(cards, m)
    pairs = [(i, j) for i in range(len(grid_r)) for j in range(len(grid_c))]
    if objective == "coded":
        sizes = coded_sizes(rows, cards, [Coding("", coder, tuple(columns[j].tolist()), i) for i, j in pairs])
        bits = [sum(s.values()) for s in sizes]
    else:

        def count(batches):
            totals: dict[tuple[int, int], np.ndarray] = {}
            for batch in batches:
                if not batch.num_rows:
                    continue
                cells = batch.column("codes").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(batch.num_rows, n)
                us = batch.column("us").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                for i in range(len(grid_r)):
                    for u in np.unique(us[:, i]).tolist():
                        own = cells[us[:, i] == u]
                        for j, v in enumerate(columns):
                            add = np.bincount((own + v * card).ravel(), minlength=(int(v.max()) + 1) * card)
                            p = i * len(grid_c) + j
                            totals[p, u] = totals.get((p, u), 0) + add
            got = [(p, u, b // card, b % card, int(t[b])) for (p, u), t in totals.items() for b in np.flatnonzero(t).tolist()]
            cols = list(zip(*got, strict=True)) or [()] * 5
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, (*[pa.int32()] * 4, pa.int64()), strict=True)], names=["pair", "u", "v", "code", "cnt"])

        hist = rows.select("us", "codes").mapInArrow(count, "pair int, u int, v int, code int, cnt long").groupBy("pair", "u", "v", "code").agg(F.sum("cnt").alias("cnt"))
        got = ideal_sizes(hist, ["pair", "u", "v"]).groupBy("pair").agg(F.sum(F.col("code_bits") + F.col("count_bits")).alias("b")).collect()  # a row a pair
        blocks = {r.pair: r.b for r in got}
        sizes_r = rows.select(F.posexplode("us").alias("i", "u")).groupBy("i", "u").agg(F.count("*").alias("c")).collect()  # grid x labels
        bits = []
        for p, (i, j) in enumerate(pairs):
            k, c = grid_r[i], grid_c[j]
            b = blocks.get(p, 0.0)
            if k > 1:
                lab = np.array([r.c for r in sizes_r if r.i == i], float)
                b += float((lab * np.log2(m / lab)).sum()) + 64.0 * len(lab)
            if 1 < c < n:
                cv = np.bincount(columns[j]).astype(float)
                b += float((cv[cv > 0] * np.log2(n / cv[cv > 0])).sum()) + 64.0 * len(cv)
            bits.append(b + ((k * c + 2) * math.ceil(math.log2(m * n + 1)) if k * c > 1 else 0))
    out = sorted(((grid_r[i], grid_c[j], float(b), float(1 - b / raw)) for (i, j), b in zip(pairs, bits, strict=True)), key=lambda r: r[2])
    return codes.sparkSession.createDataFrame([(*r, i + 1) for i, r in enumerate(out)], "k_r int, k_c int, bits double, drr double, rank int")
