"""The experiments' tables, rebuilt on the given ones, and the report of all methods on each."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.operators import codec as C
from blockpress.operators import latents as L
from blockpress.operators.cells import cells_of, holds_bits, unpacked
from blockpress.operators.codec import compress
from blockpress.plans.encode import Codebook, ColumnCodes, assign_row_ids, encode_rows, encode_table, fit_codebook, image, raw_bits, shuffle_rows
from blockpress.sources.storage import discard, kept

SEPARATORS = " \n\t.,;:!?|"
WORD = f"[^{SEPARATORS}]+".replace("\n", r"\n").replace("\t", r"\t")


@dataclass
class Workload:
    name: str
    codes: DataFrame  # row_id, codes
    cards: list[int]
    k_lz: tuple[int, int]
    k_ans: tuple[int, int]
    truth: DataFrame | None = None  # row_id, label
    pack: str = "byte"

    @property
    def n(self) -> int:
        return len(self.cards)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _tabular(df: DataFrame, order: list[str], exact: bool = True) -> tuple[DataFrame, list[int]]:
    numbered = assign_row_ids(df, order)  # written once: joins below are not made again for the codebook
    book = fit_codebook(numbered.select(df.columns), exact=exact)
    return kept(encode_rows(numbered, book, "row_id"), "codes"), book.cards


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All line items with their order, customer, part and supplier."""
    line, orders, customer = (read(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    part, supplier = (read(spark, sf_dir, t) for t in ("part", "supplier"))
    out = line.join(orders, line.l_orderkey == orders.o_orderkey).join(customer, F.col("o_custkey") == customer.c_custkey)
    return out.join(part, F.col("l_partkey") == part.p_partkey).join(supplier, F.col("l_suppkey") == supplier.s_suppkey)


LINE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]


def flat_table(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    return _tabular(read(spark, sf_dir, "lineitem").select(LINE), LINE)


def flat_table_18(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    line, orders = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders")
    both = line.join(orders, line.l_orderkey == orders.o_orderkey).drop("o_orderkey")
    both = both.withColumn("ship_month", F.month("l_shipdate")).withColumn("order_month", F.month("o_orderdate"))
    return _tabular(both, LINE)


TRANSACTION = ["l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_returnflag", "l_shipdate", "o_custkey", "o_totalprice", "o_orderdate", "c_nationkey", "c_acctbal"]


def transactions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    return _tabular(star(spark, sf_dir).select("l_orderkey", *TRANSACTION).drop("l_orderkey"), TRANSACTION)


NEIGHBOURS = ["l_orderkey", "l_linenumber", "l_quantity", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority", "c_nationkey", "c_mktsegment"]


def neighbours(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    """Lines in order: those of one order repeat what the order says."""
    return _tabular(star(spark, sf_dir).select(NEIGHBOURS), NEIGHBOURS)


NUMBERS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_size", "p_retailprice", "c_acctbal", "s_acctbal", "l_shipdate"]
#: Columns that become one indicator for each value.
INDICATED = ["p_brand", "p_type", "c_mktsegment", "o_orderpriority", "o_orderstatus"]


def with_indicators(df: DataFrame) -> tuple[DataFrame, list[str]]:
    """One 0/1 column for each value of the indicated columns; the values are few and sorted."""
    sets = df.agg(*[F.array_sort(F.collect_set(c)).alias(c) for c in INDICATED]).first()
    made = [(f"is_{c}_{k}", (F.col(c) == v).cast("int")) for c in INDICATED for k, v in enumerate(sets[c])]
    return df.select("*", *[e.alias(name) for name, e in made]), [name for name, _ in made]


def spread(codes: DataFrame, book: Codebook, names: list[str]) -> tuple[DataFrame, Codebook]:
    """Codes and codebook with an indicator for each value in place of the columns ``names``, as ``with_indicators`` and a fit have them."""
    columns, steps = [], []
    for j, c in enumerate(book.columns):
        if c.name in names:
            steps.append((j, len(c.values)))
            columns += [ColumnCodes(f"is_{c.name}_{k}", "C", [0, 1] if len(c.values) > 1 else [1], has_null=c.has_null) for k in range(len(c.values))]
        else:
            steps.append((j, 0))
            columns.append(c)

    def emit(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, max(1, TILE_CELLS // max(1, len(columns)))):
                part = batch.slice(lo, max(1, TILE_CELLS // max(1, len(columns))))
                cells, out, at = cells_of(part.column("codes"), book.n), np.zeros((part.num_rows, len(columns)), np.int16), 0
                for j, q in steps:
                    if not q and book.columns[j].name not in names:
                        out[:, at] = cells[:, j]
                        at += 1
                    elif q:
                        if q > 1:
                            out[:, at : at + q] = cells[:, j, None] == np.arange(q)
                        out[cells[:, j] == q, at : at + q] = min(q, 2)  # null is coded behind the values
                        at += q
                ends = np.arange(len(out) + 1, dtype=np.int32) * len(columns)
                yield pa.record_batch([part.column("row_id"), pa.ListArray.from_arrays(pa.array(ends), pa.array(out.ravel()))], names=["row_id", "codes"])

    return codes.select("row_id", "codes").mapInArrow(emit, "row_id long, codes array<smallint>"), Codebook(columns, book.dropped)


def _wide(df: DataFrame, after: list[str]) -> tuple[DataFrame, list[int]]:
    """Codes of ``NUMBERS``, an indicator for each value of ``INDICATED`` and ``after``, in the order of all these.

    The indicated columns themselves are joined, sorted and coded, and codes are spread to indicators. In the indicators' order
    a column's values descend: a later value has a zero where an earlier one has its one.
    """
    narrow = df.select(*NUMBERS, *INDICATED, *after)
    numbered = assign_row_ids(narrow, [*NUMBERS, *[F.desc_nulls_first(c) for c in INDICATED], *after])
    book = fit_codebook(numbered.select(narrow.columns))
    if set(INDICATED) & set(book.dropped):  # more values than codes
        df, made = with_indicators(df)
        names = [*NUMBERS, *made, *after]
        return _tabular(df.select(names), names)
    codes, wide = spread(kept(encode_rows(numbered, book, "row_id"), "codes"), book, INDICATED)
    return codes, wide.cards


def wide_55(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    return _wide(star(spark, sf_dir), ["l_returnflag"])


def wide_68(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    df, dates = star(spark, sf_dir), []
    for c in ("l_shipdate", "o_orderdate"):
        for part, f in (("year", F.year), ("quarter", F.quarter), ("month", F.month), ("week", F.weekofyear), ("weekday", F.weekday), ("day", F.dayofmonth)):
            df = df.withColumn(f"{c}_{part}", f(F.col(c)))
            dates.append(f"{c}_{part}")
    df = df.withColumn("ship_lag", F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date")))
    return _wide(df, ["l_returnflag", *dates, "ship_lag"])


def rating_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``c_custkey, n_rated`` and a cell for each brand and size band: mean quantity, 99 where none."""
    df = star(spark, sf_dir).withColumn("band", F.least(F.lit(3), F.floor((F.col("p_size") - 1) / 13)).cast("int"))
    brands = sorted(r[0] for r in read(spark, sf_dir, "part").select("p_brand").distinct().collect())  # 25 values
    cell = F.concat_ws("_", F.lit("r"), "p_brand", "band")
    names = [f"r_{b}_{k}" for b in brands for k in range(4)]
    wide = df.withColumn("cell", cell).groupBy("c_custkey").pivot("cell", names).agg(F.avg("l_quantity"))
    rated = sum((F.when(F.col(f"`{c}`").isNotNull(), 1).otherwise(0) for c in names), F.lit(0))
    return wide.select("c_custkey", rated.alias("n_rated"), *[F.coalesce(F.round(F.col(f"`{c}`")), F.lit(99.0)).alias(c) for c in names])


def ratings(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    df = kept(rating_cells(spark, sf_dir), "ratings")
    book = fit_codebook(df.drop("c_custkey"))
    return kept(encode_table(assign_row_ids(df, ["c_custkey"]), book, ["row_id"]), "codes"), book.cards


def dense(ones: DataFrame, n: int) -> DataFrame:
    """``row_id, codes`` of 0/1 rows given as ``ones(row_id, at array<int>)``; at most ``TILE_CELLS`` cells (or one row) are held at once."""

    step = max(1, TILE_CELLS // n)

    def slices(batches):
        for batch in batches:
            yield from (batch.slice(lo, step) for lo in range(0, batch.num_rows, step))

    def emit(batches):
        for batch in slices(batches):
            lists = batch.column("at")
            size = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            cells = np.zeros((batch.num_rows, n), np.int16)
            cells[np.repeat(np.arange(batch.num_rows), size), lists.flatten().to_numpy(zero_copy_only=False)] = 1
            at = np.arange(batch.num_rows + 1, dtype=np.int32) * n
            yield pa.record_batch([batch.column("row_id"), pa.ListArray.from_arrays(pa.array(at), pa.array(cells.ravel()))], names=["row_id", "codes"])

    return ones.mapInArrow(emit, "row_id long, codes array<smallint>")


def tasks_for(m: int, n: int, df: DataFrame) -> int:
    """Tasks for a table of so many rows and columns: what is packed or thin is too short for its work to be dealt out by size."""
    least = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return min(max(1, m), max(least, -(-m * n // C.CHUNK_CELLS // 4)))


def packed(ones: DataFrame, n: int) -> DataFrame:
    """As ``dense``, with a row's cells packed to bits: an eighth of a byte a cell."""
    step = max(1, TILE_CELLS // n)

    def emit(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, step):
                part = batch.slice(lo, step)
                lists = part.column("at")
                size = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
                cells = np.zeros((part.num_rows, n), np.uint8)
                cells[np.repeat(np.arange(part.num_rows), size), lists.flatten().to_numpy(zero_copy_only=False)] = 1
                yield pa.record_batch([part.column("row_id"), pa.array([r.tobytes() for r in np.packbits(cells, axis=1)], pa.binary())], names=["row_id", "codes"])

    return ones.mapInArrow(emit, "row_id long, codes binary")


def document_words(docs: DataFrame) -> DataFrame:
    """``doc_id, word``: each document's different words, lower-cased."""
    return docs.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(WORD), 0))).alias("word"))


def top_words(docs: DataFrame, n: int = 200) -> DataFrame:
    """``col_id, word, df`` of the words in most documents; ties by word."""
    from pyspark.sql.window import Window

    top = document_words(docs).groupBy("word").agg(F.count("*").alias("df")).orderBy(F.desc("df"), "word").limit(n)
    return top.select((F.row_number().over(Window.orderBy(F.desc("df"), "word")) - 1).alias("col_id"), "word", "df")  # n rows


def frequent_words(docs: DataFrame, n: int = 200) -> DataFrame:
    """``doc_id, word`` of the ``n`` words in most documents."""
    return document_words(docs).join(F.broadcast(top_words(docs, n).select("word")), "word").select("doc_id", "word")


def frequent_sets(docs: DataFrame, n: int = 200) -> DataFrame:
    """``doc_id, words``: which of the ``n`` words in most documents each document has; documents without any have an empty set."""
    sets = frequent_words(docs, n).groupBy("doc_id").agg(F.collect_list("word").alias("words"))
    return docs.select("doc_id").join(sets, "doc_id", "left").select("doc_id", F.coalesce("words", F.array().cast("array<string>")).alias("words"))


def word_presence(spark: SparkSession, sf_dir: str, n: int = 200) -> tuple[DataFrame, list[int]]:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    top = kept(top_words(docs, n), "top-words")
    hits = document_words(docs).join(F.broadcast(top), "word")  # n rows
    ones = docs.select("doc_id").join(hits.groupBy("doc_id").agg(F.collect_list("col_id").alias("at")), "doc_id", "left")
    rows = dense(ones.select(F.col("doc_id").alias("row_id"), F.coalesce("at", F.array().cast("array<int>")).alias("at")), n)
    return kept(rows, "codes"), [2] * n


#: Rows in a block of the all-pairs comparison, and words of these (each counted once a row) where words bound it too.
PAIR_BLOCK, BLOCK_WORDS = 8192, 1 << 20
#: Opened blocks that a task holds on to.
OPEN_BLOCKS = 4
#: Rows of vectors in a block, and cells of a block pair's table that are held at once.
VECTOR_BLOCK, TILE_CELLS = 1024, 1 << 21
#: Numbers of words up to which a block's words are marked in an array.
MARKED_WORDS = 1 << 24
#: Cells of a matrix product that cost as much as one common word found by lists.
LIST_COST = 1000
PACKED = "block long, least long, most long, ids binary, copies binary, sizes binary, words binary, ends binary, rows binary"


def _block_pairs(rows: DataFrame, key: str) -> DataFrame:
    """``rows`` dealt out as pairs of blocks: ``lo, hi`` and each row's ``own`` block. Every two rows meet in one pair of blocks."""
    blocks = max(1, -(-rows.count() // VECTOR_BLOCK))
    dealt = rows.withColumn("own", F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    return dealt.withColumn("lo", F.least("own", "other")).withColumn("hi", F.greatest("own", "other")).drop("other")


def _sides(part: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    own = part.column("own").to_numpy()
    return tuple(np.flatnonzero(own == part.column(c)[0].as_py()) for c in ("lo", "hi"))


def numbered_words(sets: DataFrame) -> DataFrame:
    """``doc_id, copies, size, at`` of ``sets(doc_id, copies, words)``: ``at`` holds the bytes of the numbers, ascending, of the words that other sets have too."""
    rows = _numbered(sets.select("doc_id", "words", F.col("copies").alias("kin")))
    out = rows.withColumnRenamed("kin", "copies")
    out._kept_at = rows._kept_at
    return out


def _kin(docs: DataFrame) -> Column:
    """Documents that are rather alike than others have one number: those of a language, where ``docs`` has one as ``lang``."""
    return (F.xxhash64("lang") if "lang" in docs.columns else F.lit(0).cast("long")).alias("kin")


def document_classes(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Of ``sets(doc_id, words)``, or ``text`` for words and perhaps ``lang``, the members ``doc_id, class_id`` and the different sets ``doc_id, kin, copies, size, at``: a class has one set and its least document's id.

    Equal sets have no words but shared ones, so their numbers tell them; a set with a word of its own is a class of its own.
    """
    rows = numbered_texts(sets.select("doc_id", "text", _kin(sets))) if "text" in sets.columns else _numbered(sets.select("doc_id", "words", _kin(sets)))
    key = F.when(F.length("at") == 4 * F.col("size"), F.sha2("at", 256)).otherwise(F.concat_ws(" ", F.lit("own"), "doc_id", F.sha2("at", 256)))
    keyed = rows.select("doc_id", key.alias("key"))
    names = kept(keyed.groupBy("key").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("copies")), "classes")
    own = rows.join(names.select(F.col("class_id").alias("doc_id"), "copies"), "doc_id")
    return keyed.join(names, "key").select("doc_id", "class_id"), own.select("doc_id", "kin", "copies", "size", "at")


def packed_blocks(rows: DataFrame, order: list[str], cut: bool = False) -> DataFrame:
    """``PACKED`` blocks of ``rows(doc_id, copies, size, at)`` in the order given, a row each; ``least`` and ``most`` are of the sets' sizes.

    With ``cut`` a block has ``BLOCK_WORDS`` words too at most, or a sixteenth of the rows.
    """
    step = PAIR_BLOCK
    small = max(1, step // 16) if cut else step
    names = [f.split()[0] for f in PACKED.split(", ")]

    def pack(key, part):
        part = part.sort_by("row_id").combine_chunks()
        ids, copies, size = (part.column(c).to_numpy().astype(t) for c, t in (("doc_id", np.int64), ("copies", np.int64), ("size", np.int32)))
        blobs = part.column("at").to_pylist()
        row = np.repeat(np.arange(len(ids)), [len(x) // 4 for x in blobs])
        held = _Block(ids, copies, size, row, np.frombuffer(b"".join(blobs), np.int32))
        raw = [ids.tobytes(), copies.tobytes(), size.tobytes(), *_by_word(held)]
        return pa.table([pa.array([key[0].as_py()]), pa.array([int(size.min())]), pa.array([int(size.max())]), *[pa.array([x], pa.binary()) for x in raw]], names=names)

    placed = assign_row_ids(rows, order).withColumn("piece", F.floor(F.col("row_id") / small))
    pieces = placed.groupBy("piece").agg(F.count("*").alias("m"), F.sum(F.length("at") / 4).alias("w")).collect()  # a row a piece
    block, m, w, found = 0, 0, 0, []
    for r in sorted(pieces, key=lambda r: r.piece):
        if m and (m + r.m > step or cut and w + r.w > BLOCK_WORDS):
            block, m, w = block + 1, 0, 0
        m, w = m + r.m, w + r.w
        found.append((r.piece, block))
    placed = placed.join(F.broadcast(rows.sparkSession.createDataFrame(found, "piece long, block long")), "piece").drop("piece")
    # a file each, or nearly: pairs are dealt out by file
    placed = placed.repartition(max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(512, 4 * (block + 1))), "block")
    return kept(placed.groupBy("block").applyInArrow(pack, PACKED), "blocks", "none")


@dataclass
class _Block:
    """A packed block opened: ids, copies and sizes of its sets, and row and word of each of their words."""

    ids: np.ndarray
    copies: np.ndarray
    sizes: np.ndarray
    row: np.ndarray
    at: np.ndarray

    @classmethod
    def of(cls, r: dict) -> _Block:
        block = _by_row(np.frombuffer(r["ids"], np.int64), np.frombuffer(r["sizes"], np.int32), r["words"], r["ends"], r["rows"])
        return replace(block, copies=np.frombuffer(r["copies"], np.int64))


def _shared(a: _Block, b: _Block) -> tuple[np.ndarray, tuple, tuple]:
    """The words that both blocks have, and row and place among these of each side's."""
    top = max(int(a.at.max(initial=-1)), int(b.at.max(initial=-1))) + 1
    if top > MARKED_WORDS:
        words, sides = np.intersect1d(a.at, b.at), []
        for x in (a, b):
            place = np.minimum(np.searchsorted(words, x.at), max(len(words) - 1, 0))
            there = words[place] == x.at if len(words) else np.zeros(len(x.at), bool)
            sides.append((x.row[there], place[there]))
        return words, *sides
    marks = np.zeros((2, top), bool)
    marks[0, a.at] = marks[1, b.at] = True
    both = marks[0] & marks[1]
    place = np.cumsum(both) - 1
    there = [both[x.at] for x in (a, b)]
    return np.flatnonzero(both), *[(x.row[t], place[x.at[t]]) for x, t in zip((a, b), there, strict=True)]


def _common(a: _Block, b: _Block):
    """``rows, common``: numbers of common words of stretches of ``a``'s sets with all of ``b``'s.

    Words in many sets of both sides are columns of a matrix product, the others are looked up in lists.
    """
    m, n = len(a.ids), len(b.ids)
    words, (row_a, at_a), (row_b, at_b) = _shared(a, b)
    in_a, in_b = (np.bincount(at, minlength=len(words)).astype(np.float64) for at in (at_a, at_b))
    dense = in_a * in_b * LIST_COST > m * n
    column = np.cumsum(dense) - 1
    right = np.zeros((n, int(dense.sum())), np.float32)
    right[row_b[dense[at_b]], column[at_b[dense[at_b]]]] = 1
    full_row, full_at = row_a[dense[at_a]], column[at_a[dense[at_a]]]
    row_a, at_a = row_a[~dense[at_a]], at_a[~dense[at_a]]
    row_b, at_b = row_b[~dense[at_b]], at_b[~dense[at_b]]
    row_b, many = row_b[np.argsort(at_b, kind="stable")].astype(np.int32), np.bincount(at_b, minlength=len(words))
    start = np.cumsum(many) - many
    first, filled = (np.searchsorted(x, np.arange(m + 1)) for x in (row_a, full_row))  # rows ascend
    work = np.concatenate([[0], np.cumsum(many[at_a])])[first] + np.arange(m + 1) * n
    lo = 0
    while lo < m:
        hi = max(lo + 1, int(np.searchsorted(work, work[lo] + TILE_CELLS, "right")) - 1)
        hi = min(hi, lo + max(1, TILE_CELLS // n))
        left, whole = np.zeros((hi - lo, right.shape[1]), np.float32), slice(filled[lo], filled[hi])
        left[full_row[whole] - lo, full_at[whole]] = 1
        common = left @ right.T
        mine = slice(first[lo], first[hi])
        times = many[at_a[mine]]
        if len(times) and times.sum():
            kind = np.int32 if max(int(times.sum()) + len(row_b), (hi - lo) * n) < 1 << 31 else np.int64
            pick = np.arange(int(times.sum()), dtype=kind)
            pick += np.repeat((start[at_a[mine]] - (np.cumsum(times) - times)).astype(kind), times)
            flat = row_b[pick].astype(kind)
            flat += np.repeat(((row_a[mine] - lo) * n).astype(kind), times)
            common += np.bincount(flat, minlength=(hi - lo) * n).reshape(hi - lo, n)
        yield slice(lo, hi), common
        lo = hi


def _needed(threshold: float, top: int) -> np.ndarray:
    """Fewest common words of two sets with so many words together that make them that alike."""
    t = np.arange(top + 1)
    tried = np.floor(threshold * t / (1 + threshold)).astype(np.int64)[:, None] + np.arange(-1, 3)
    return np.where(tried >= threshold * (t[:, None] - tried), tried, top + 1).min(axis=1).astype(np.float32)


def _alike(a: _Block, b: _Block, threshold: float):
    """``rows, hits``: which of ``b``'s sets each of ``a``'s is alike."""
    need = _needed(threshold, int(a.sizes.max()) + int(b.sizes.max()))
    _, *sides = _shared(a, b)
    enough = [np.bincount(row, minlength=len(x.ids)) >= need[x.sizes + y.sizes.min()] for (row, _), x, y in zip(sides, (a, b), (b, a), strict=True)]
    whole, (at_a, at_b) = all(e.all() for e in enough), [np.flatnonzero(e) for e in enough]
    n, few = len(b.ids), max(1, TILE_CELLS // len(b.ids))
    if not whole:  # rows that can't be alike to any with the words the other block has at all are not compared
        a, b = _part(a, enough[0]), _part(b, enough[1])
    done = 0
    for rows, common in _common(a, b) if len(at_a) and len(at_b) else ():
        mine = a.sizes[rows]
        hits = np.empty(common.shape, bool)
        for size in np.unique(mine):
            hits[mine == size] = common[mine == size] >= need[size + b.sizes]
        if whole:
            yield rows, hits
            continue
        lo, hi = rows.start, rows.stop
        while lo < hi:  # back to all rows and columns, so many at once
            to = int(np.searchsorted(at_a, max(done, int(at_a[lo])) + few))
            to = min(hi, max(lo + 1, to))
            first, stop = int(at_a[lo]), int(at_a[to - 1]) + 1
            if first > done:
                yield from _none(done, first, n, few)
            spread = np.zeros((stop - first, n), bool)
            spread[np.ix_(at_a[lo:to] - first, at_b)] = hits[lo - rows.start : to - rows.start]
            yield slice(first, stop), spread
            lo, done = to, stop
    if not whole:
        yield from _none(done, len(enough[0]), n, few)


def _none(lo: int, hi: int, n: int, step: int):
    """``rows, hits`` of rows that are alike to none."""
    for first in range(lo, hi, step):
        stop = min(hi, first + step)
        yield slice(first, stop), np.zeros((stop - first, n), bool)


def _met(blocks: DataFrame, threshold: float, each: Callable, schema: str) -> DataFrame:
    """``each`` of every two blocks that their sizes let be alike, and of a block with itself: it gets the blocks' numbers, ascending, and the blocks opened.

    A task reads its blocks from where they are kept: no copy of a block is written for the pairs it is in.
    """
    names = [f.split()[0] for f in PACKED.split(", ")]
    a, b = (blocks.select(*[F.col(c).alias(f"{side}_{c}") for c in names]) for side in "ab")
    x, y = F.col("a_block"), F.col("b_block")
    turn = F.when((x + y) % 2 == 0, x <= y).otherwise(x > y)  # once a pair, and both halves of the square have work
    near = (F.col("a_most") >= threshold * F.col("b_least")) & (F.col("b_most") >= threshold * F.col("a_least"))

    def run(batches):
        opened: dict[int, _Block] = {}
        for batch in batches:
            for k in range(batch.num_rows):
                r, held = batch.slice(k, 1), []
                for side in "ab":
                    block = r.column(f"{side}_block")[0].as_py()
                    if block not in opened:
                        if len(opened) >= OPEN_BLOCKS:
                            opened.pop(next(iter(opened)))
                        opened[block] = _Block.of({c: r.column(f"{side}_{c}")[0].as_py() for c in names})
                    held.append((block, opened[block]))
                held.sort(key=lambda h: h[0])
                yield from each(held[: 1 + (held[0][0] != held[1][0])]).to_batches()

    return a.hint("shuffle_replicate_nl").join(b, turn & near).mapInArrow(run, schema)


def link_counts(sets: DataFrame, threshold: float) -> DataFrame:
    """``doc_id, class_id, n_links`` of ``sets(doc_id, words)``, or ``text`` for words and perhaps ``lang``: a class has one set of words, a link goes to each other document that is that alike.

    Classes are compared in pairs of blocks, of one language and like sizes, and copies are counted, not expanded.
    Documents without words are alike to none.
    """
    members, classes = document_classes(sets)
    blocks = packed_blocks(classes.where("size > 0"), ["kin", "size", "doc_id"], cut=True)

    def count(held):
        (_, a), (_, b) = held[0], held[-1]
        same = len(held) == 1
        to_a, to_b = np.zeros(len(a.ids), np.int64), np.zeros(len(b.ids), np.int64)
        exact = np.float32 if max(a.copies.sum(), b.copies.sum()) < 1 << 24 else np.float64
        for rows, hits in _alike(a, b, threshold):
            if same:  # a class's own links are those of its copies
                hits[np.arange(len(hits)), np.arange(rows.start, rows.stop)] = False
            hits = hits.astype(exact)
            to_a[rows] += (hits @ b.copies.astype(exact)).astype(np.int64)
            if not same:
                to_b += (a.copies[rows].astype(exact) @ hits).astype(np.int64)
        out = [(*held[0], to_a + a.copies - 1)] if same else [(*held[0], to_a), (*held[-1], to_b)]
        return pa.table({"block": pa.array([k for k, *_ in out]), "ids": pa.array([x.ids.tobytes() if same else None for _, x, _ in out], pa.binary()), "links": pa.array([n.tobytes() for *_, n in out], pa.binary())})

    def add(_, part):
        ids = next(x for x in part.column("ids").to_pylist() if x is not None)
        return pa.table({"class_id": np.frombuffer(ids, np.int64), "n": sum(np.frombuffer(x, np.int64) for x in part.column("links").to_pylist())})

    counted = _met(blocks, threshold, count, "block long, ids binary, links binary")
    links = kept(counted.groupBy("block").applyInArrow(add, "class_id long, n long"), "links")
    return members.join(links, "class_id", "left").select("doc_id", "class_id", F.coalesce("n", F.lit(0)).alias("n_links"))


def jaccard_pairs(words: DataFrame, threshold: float) -> DataFrame:
    """``src, dst`` with ``src < dst``: documents whose sets in ``words(doc_id, word)`` are that alike, in pairs of blocks."""
    sets = kept(words.groupBy("doc_id").agg(F.collect_set("word").alias("words")).withColumn("copies", F.lit(1).cast("long")), "words")
    blocks = packed_blocks(numbered_words(sets), ["size", "doc_id"], cut=True)

    def alike(held):
        (_, a), (_, b), found = held[0], held[-1], []
        for rows, hits in _alike(a, b, threshold):
            i, j = np.nonzero(hits)
            x, y = a.ids[rows][i], b.ids[j]
            once = x < y if len(held) == 1 else x != y
            found.append(pa.table({"src": np.minimum(x, y)[once], "dst": np.maximum(x, y)[once]}))
        return pa.concat_tables(found)

    return _met(blocks, threshold, alike, "src long, dst long")


def likeness_table(words: DataFrame, ids: DataFrame, threshold: float) -> tuple[DataFrame, list[int]]:
    """0/1 table over ``ids(doc_id)``, packed to bits, of the documents whose sets in ``words(doc_id, word)`` are that alike; rows and columns in id order.

    A pair of blocks gives its cells as bits, both ways round, and never a row for each link; a stretch of a block's rows takes
    its bits from all blocks and puts the columns in id order.
    """
    nodes = kept(assign_row_ids(ids.select("doc_id").distinct(), ["doc_id"]), "nodes")
    n = nodes.count()
    sets = words.groupBy("doc_id").agg(F.collect_set("word").alias("words")).join(nodes, "doc_id")
    sets = kept(sets.select(F.col("row_id").alias("doc_id"), "words", F.lit(1).cast("long").alias("copies")), "words")
    numbered = numbered_words(sets)
    blocks = packed_blocks(numbered, ["size", "doc_id"], cut=True)
    discard(numbered)
    columns = {r.block: np.frombuffer(bytes(r.ids), np.int64) for r in blocks.select("block", "ids").collect()}  # a number a document
    step = max(8, TILE_CELLS // max(1, n) // 8 * 8)

    def cells(held):
        (first, a), (last, b) = held[0], held[-1]
        bits = np.concatenate([np.packbits(hits, axis=1) for _, hits in _alike(a, b, threshold)])
        out = [(first, lo // step, last, bits[lo : lo + step].tobytes()) for lo in range(0, len(a.ids), step)]
        if first != last:
            for lo in range(0, len(b.ids), step):  # a stretch of the other's rows: so many columns, a multiple of eight
                turned = np.unpackbits(bits[:, lo // 8 : (lo + step) // 8], axis=1, count=min(step, len(b.ids) - lo)).T
                out.append((last, lo // step, first, np.packbits(turned, axis=1).tobytes()))
        types = (pa.int64(), pa.int32(), pa.int64(), pa.binary())
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=["block", "stretch", "other", "bits"])

    def rows(key, part):
        lo = key[1].as_py() * step
        own = columns[key[0].as_py()][lo : lo + step]
        whole = np.zeros((len(own), n), np.uint8)
        for other, bits in zip(part.column("other").to_pylist(), part.column("bits").to_pylist(), strict=True):
            there = columns[other]
            whole[:, there] = np.unpackbits(np.frombuffer(bits, np.uint8).reshape(len(own), -1), axis=1, count=len(there))
        whole[np.arange(len(own)), own] = 0  # no document is alike to itself
        return pa.table({"row_id": pa.array(own), "codes": pa.array([r.tobytes() for r in np.packbits(whole, axis=1)], pa.binary())})

    found = kept(_met(blocks, threshold, cells, "block long, stretch int, other long, bits binary"), "bits", "zstd")
    discard(blocks)
    tasks = max(tasks_for(n, n, found), len(columns))
    made = found.repartition(tasks, "block", "stretch").groupBy("block", "stretch").applyInArrow(rows, "row_id long, codes binary")
    bare = nodes.join(sets.select(F.col("doc_id").alias("row_id")), "row_id", "left_anti")
    none = packed(bare.select("row_id", F.array().cast("array<int>").alias("at")), n)
    codes = kept(made.unionByName(none), "codes", "zstd")
    discard(found, sets, nodes)
    return codes, [2] * n


def _first(likeness: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of each row's ``k`` greatest cells, ties by the columns' ids; only cells that reach a row's ``k``-th are sorted."""
    if likeness.shape[1] > k:
        row, col = np.nonzero(likeness >= np.partition(likeness, -k, axis=1)[:, -k, None])
    else:
        row, col = (x.ravel() for x in np.indices(likeness.shape))
    order = np.lexsort((ids[col], -likeness[row, col], row))
    row, col = row[order], col[order]
    keep = np.arange(len(row)) - np.searchsorted(row, row) < k
    return row[keep], col[keep]


def _nearest(dealt: DataFrame, likeness: Callable, k: int) -> DataFrame:
    """``src, dst``: the ``k`` likeliest others of each row, ties by id; a block pair gives ``k`` for each of its rows at most."""
    from pyspark.sql.window import Window

    def best(_, part):
        ids, out = part.column("doc_id").to_numpy(), []
        first, second = _sides(part)
        like = likeness(part, first, second)
        turns = [(first, second, like)] if part.column("lo")[0] == part.column("hi")[0] else [(first, second, like), (second, first, like.T)]
        for mine, others, m in turns:
            m = np.where(ids[mine][:, None] == ids[others][None, :], -np.inf, m)  # no row is a neighbour of its own
            row, col = _first(m, ids[others], k)
            there = m[row, col] > -np.inf
            out.append((ids[mine[row[there]]], ids[others[col[there]]], m[row[there], col[there]]))
        src, dst, s = (np.concatenate(x) for x in zip(*out, strict=True))
        return pa.table({"src": src.astype(np.int64), "dst": dst.astype(np.int64), "s": s.astype(np.float64)})

    found = dealt.groupBy("lo", "hi").applyInArrow(best, "src long, dst long, s double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))
    return found.withColumn("n", rank).where(F.col("n") <= k).select("src", "dst")


def word_sets(docs: DataFrame) -> DataFrame:
    """``doc_id, words``: each document's different words; documents without any have an empty set."""
    return docs.select("doc_id", F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(WORD), 0)).alias("words"))


def top_documents(docs: DataFrame, k: int = 10, every: int = 1) -> DataFrame:
    """``src, dst``: of each document whose id is divisible by ``every`` the ``k`` documents whose whole word sets are likest, ties by id."""
    from pyspark.sql.window import Window

    if every == 1:
        return nearest_documents(docs, k)
    sets = kept(word_sets(docs).withColumn("copies", F.lit(1).cast("long")), "word-sets")
    rows = numbered_words(sets)
    names = [f.split()[0] for f in PACKED.split(", ")]
    blocks = packed_blocks(rows, ["doc_id"])
    asked = packed_blocks(rows.where(F.col("doc_id") % every == 0), ["doc_id"])
    turns = blocks.agg(F.max("block")).first()[0] or 0
    others = asked.agg(F.max("block")).first()[0] or 0
    dealt = asked.withColumn("side", F.lit(0)).withColumn("q", F.col("block")).withColumn("b", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(turns).cast("long"))))
    dealt = dealt.unionByName(blocks.withColumn("side", F.lit(1)).withColumn("b", F.col("block")).withColumn("q", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(others).cast("long")))))

    def best(_, part):
        held = {r["side"]: _Block.of(r) for r in part.to_pylist()}
        if len(held) < 2:
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})
        a, b = held[0], held[1]
        src, dst, like = [], [], []
        for rows, common in _common(a, b):
            joint = a.sizes[rows][:, None].astype(np.int64) + b.sizes[None, :] - common
            s = common.astype(np.float64) / np.maximum(joint, 1)
            s[a.ids[rows][:, None] == b.ids[None, :]] = -1  # a document is no neighbour of its own
            row, col = _first(s, b.ids, k)
            there = s[row, col] >= 0
            src.append(a.ids[rows][row[there]])
            dst.append(b.ids[col[there]])
            like.append(s[row[there], col[there]])
        return pa.table({"src": np.concatenate(src), "dst": np.concatenate(dst), "s": np.concatenate(like)})

    found = dealt.select("q", "b", "side", *names).groupBy("q", "b").applyInArrow(best, "src long, dst long, s double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))
    return found.withColumn("n", rank).where(F.col("n") <= k).select("src", "dst")


#: Words of documents (each counted once a document) whose places a task holds at once, and rows of a block in a search of all.
HELD_WORDS, SEARCH_BLOCK = 1 << 21, 4096
POSTINGS = "held long, word string, c long, docs binary, kin binary, sizes binary"


def numbered_texts(docs: DataFrame) -> DataFrame:
    """``doc_id, kin, size, at`` of ``docs(doc_id, text, kin)``, as ``numbered_words`` has them of ``word_sets``; numbers are in no order of the words."""
    return _numbered(docs.select("doc_id", F.lower(F.coalesce("text", F.lit(""))).alias("text"), "kin"))


def _numbered(docs: DataFrame) -> DataFrame:
    """``doc_id, kin, size, at`` of ``docs(doc_id, text, kin)``, lower-cased, or ``docs(doc_id, words, kin)``.

    Tasks hold a stretch of documents as its words, each with its documents' places, so that words meet their numbers once a stretch and not once a document.
    """
    source = "words" if "words" in docs.columns else "text"

    def words_of(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                for i, held, of in zip(*[batch.slice(lo, 1000).column(c).to_pylist() for c in ("doc_id", source, "kin")], strict=True):
                    if source == "text":
                        for c in SEPARATORS[1:]:
                            held = held.replace(c, SEPARATORS[0])
                        held = held.split(SEPARATORS[0])
                    words = set(held)
                    words.discard("")
                    yield i, words, of

    def post(batches):
        first, turn = TaskContext.get().partitionId() << 32, 0
        ids, kin, rows, number = [], [], [], {}

        def out():
            sizes = np.array([len(x) for x in rows], np.int32)
            word = np.concatenate(rows)
            order = np.argsort(word, kind="stable")
            place = np.repeat(np.arange(len(rows), dtype=np.int32), sizes)[order]
            ends = np.searchsorted(word[order], np.arange(len(number) + 1))
            lists = [place[lo:hi].tobytes() for lo, hi in zip(ends, ends[1:], strict=False)]
            none = [None] * len(lists)
            columns = ([first + turn] * (1 + len(lists)), [None, *number], [None, *np.diff(ends).tolist()], [np.array(ids, np.int64).tobytes(), *lists], [np.array(kin, np.int64).tobytes(), *none], [sizes.tobytes(), *none])
            types = (pa.int64(), pa.string(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
            return pa.record_batch([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=[f.split()[0] for f in POSTINGS.split(", ")])

        total = 0
        for i, words, of in words_of(batches):
            rows.append(np.array([number.setdefault(w, len(number)) for w in words], np.int32))
            ids.append(i)
            kin.append(of)
            total += len(words)
            if total >= HELD_WORDS:
                yield out()
                ids, kin, rows, number, total, turn = [], [], [], {}, 0, turn + 1
        if ids:
            yield out()

    posted = kept(docs.mapInArrow(post, POSTINGS), "postings")
    shared = posted.where("word is not null").groupBy("word").agg(F.sum("c").alias("c")).where("c > 1").select("word", F.monotonically_increasing_id().alias("id"))
    shared = kept(shared.select("word", F.shiftright("id", 33).alias("task"), F.col("id").bitwiseAND((1 << 33) - 1).alias("place")), "words")
    tasks = 1 + (shared.agg(F.max("task")).first()[0] or 0)
    number = shared.select("word", (F.col("place") * tasks + F.col("task")).cast("int").alias("n"))
    told = posted.where("word is not null").join(number, "word").select("held", "n", "docs", "kin", "sizes")
    told = told.unionByName(posted.where("word is null").select("held", F.lit(None).cast("int").alias("n"), "docs", "kin", "sizes"))

    def assemble(_, part):
        n, blobs = part.column("n").to_pylist(), part.column("docs").to_pylist()
        head = n.index(None)
        ids, kin, sizes = (np.frombuffer(part.column(c)[head].as_py(), t) for c, t in (("docs", np.int64), ("kin", np.int64), ("sizes", np.int32)))
        blobs[head] = b""
        row = np.frombuffer(b"".join(blobs), np.int32)
        word = np.repeat(np.array([x or 0 for x in n], np.int32), [len(b) // 4 for b in blobs])
        order = np.lexsort((word, row))
        word, ends = word[order], np.searchsorted(row[order], np.arange(len(ids) + 1))
        at = [word[lo:hi].tobytes() for lo, hi in zip(ends, ends[1:], strict=False)]
        return pa.table({"doc_id": ids, "kin": kin, "size": sizes, "at": pa.array(at, pa.binary())})

    out = kept(told.groupBy("held").applyInArrow(assemble, "doc_id long, kin long, size int, at binary"), "numbered")
    discard(posted, shared)
    return out


def _squeezed(x: np.ndarray) -> bytes:
    """Whole numbers as their steps, byte by byte of these, by Zstandard; ``_steps`` undoes it."""
    steps = np.diff(x, prepend=x.dtype.type(0))
    return zstandard.ZstdCompressor(level=1).compress(steps.view(np.uint8).reshape(len(x), x.itemsize).T.tobytes())


def _steps(data: bytes, kind: type) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(kind).ravel(), dtype=kind)  # steps wrap as they were taken


def _by_word(block: _Block) -> list[bytes]:
    """A block's words, ends and rows of their lists: a fraction of the bytes that numbers of words take, row by row."""
    order = np.argsort(block.at, kind="stable")
    words, many = np.unique(block.at, return_counts=True)
    return [_squeezed(words.astype(np.int32)), _squeezed(np.cumsum(many).astype(np.int32)), _squeezed(block.row[order].astype(np.int32 if len(block.ids) > 1 << 16 else np.uint16))]


def _by_row(ids: np.ndarray, sizes: np.ndarray, words: bytes, ends: bytes, rows: bytes) -> _Block:
    row = _steps(rows, np.int32 if len(ids) > 1 << 16 else np.uint16)
    at = np.repeat(_steps(words, np.int32), np.diff(_steps(ends, np.int32), prepend=0))
    order = np.argsort(row, kind="stable")
    return _Block(ids, np.ones(len(ids), np.int64), sizes, row[order].astype(np.int64), at[order])


def _reach(bound: np.ndarray) -> np.ndarray:
    """Common words as a share of both sets' words together that a likeness of ``bound`` takes, a little less."""
    return (bound / (1 + bound) * (1 - 1e-5)).astype(np.float32)


def _part(x: _Block, keep: np.ndarray) -> _Block:
    there = keep[x.row]
    return _Block(x.ids[keep], x.copies[keep], x.sizes[keep], (np.cumsum(keep) - 1)[x.row[there]], x.at[there])


def _likest(a: _Block, b: _Block, to_a: np.ndarray, to_b: np.ndarray, k: int):
    """``src, dst, s``: of each row of two different blocks the ``k`` likest of the other's that reach the row's bound, both ways round, ties by id.

    Rows that can't reach a bound with the words the other block has at all are not compared. Where a bound is nothing,
    those without a common word count by their ids.
    """
    _, *sides = _shared(a, b)
    keep = []
    for (row, _), x, mine, y, others in zip(sides, (a, b), (to_a, to_b), (b, a), (to_b, to_a), strict=True):
        keep.append(np.bincount(row, minlength=len(x.ids)) >= np.minimum(_reach(mine), _reach(others).min()) * (x.sizes + y.sizes.min()))
    a, b, to_a, to_b = _part(a, keep[0]), _part(b, keep[1]), to_a[keep[0]], to_b[keep[1]]
    if not len(a.ids) or not len(b.ids):
        return
    reach_a, reach_b, total_a, total_b = _reach(to_a), _reach(to_b), a.sizes.astype(np.float32), b.sizes.astype(np.float32)
    low_a, low_b = np.zeros(len(a.ids), bool), np.zeros(len(b.ids), bool)
    low_a[np.argsort(a.ids, kind="stable")[:k]] = low_b[np.argsort(b.ids, kind="stable")[:k]] = True
    found: tuple[list, list] = ([], [])
    for rows, common in _common(a, b):
        need = np.minimum(reach_a[rows][:, None], reach_b)
        need *= total_a[rows][:, None] + total_b
        np.maximum(need, np.float32(0.5), out=need)
        hits = common >= need
        for left, right in ((to_a[rows] <= 0, low_b), (low_a[rows], to_b <= 0)):
            if left.any() and right.any():
                hits[np.ix_(left, right)] = True
        row, col = np.nonzero(hits)
        both = common[row, col].astype(np.float64)
        row = row + rows.start
        s = both / np.maximum(a.sizes[row].astype(np.int64) + b.sizes[col] - both, 1)
        for out, bound, src, dst in ((found[0], to_a, row, col), (found[1], to_b, col, row)):
            there = s >= bound[src]
            out.append((src[there], dst[there], s[there]))
    for out, x, y in ((found[0], a, b), (found[1], b, a)):
        src, dst, s = (np.concatenate(c) for c in zip(*out, strict=True))
        order = np.lexsort((y.ids[dst], -s, src))
        src, dst, s = src[order], dst[order], s[order]
        first = np.arange(len(src)) - np.searchsorted(src, src) < k
        yield x.ids[src[first]], y.ids[dst[first]], s[first]


def nearest_documents(docs: DataFrame, k: int = 10) -> DataFrame:
    """``src, dst``: of each document the ``k`` documents whose whole word sets are likest, ties by id.

    Blocks are of one language, where ``docs`` has one as ``lang``, and of like sizes: a block's own ``k``-th likest is a bound that few
    rows of other blocks reach. Every two blocks are compared once, for both sides.
    """
    from pyspark.sql.window import Window

    rows = numbered_texts(docs.select("doc_id", "text", _kin(docs)))
    placed = assign_row_ids(rows, ["kin", "size", "doc_id"]).withColumn("block", F.floor(F.col("row_id") / SEARCH_BLOCK))

    def own(key, part):
        part = part.sort_by("row_id").combine_chunks()
        ids, size, blobs = part.column("doc_id").to_numpy(), part.column("size").to_numpy().astype(np.int32), part.column("at").to_pylist()
        held = np.array([len(x) // 4 for x in blobs], np.int32)
        block = _Block(ids, np.ones(len(ids), np.int64), size, np.repeat(np.arange(len(ids)), held), np.frombuffer(b"".join(blobs), np.int32))
        bound, found = np.zeros(len(ids)), []
        for rows, common in _common(block, block):
            s = common.astype(np.float64) / np.maximum(size[rows][:, None].astype(np.int64) + size[None, :] - common, 1)
            s[ids[rows][:, None] == ids] = -1  # a document is no neighbour of its own
            row, col = _first(s, ids, k)
            there = s[row, col] >= 0
            row, col = row[there], col[there]
            found.append((ids[rows][row], ids[col], s[row, col]))
            last = np.flatnonzero(np.bincount(row, minlength=len(s)) == k)
            bound[rows.start + last] = s[row, col][np.searchsorted(row, last, "right") - 1]
        blobs = [x.tobytes() for x in (ids, size, bound, *[np.concatenate(x) for x in zip(*found, strict=True)])]
        blobs[2:2] = _by_word(block)
        return pa.table([pa.array([key[0].as_py()], pa.int64()), *[pa.array([x], pa.binary()) for x in blobs]], names=names)

    names = ["block", "ids", "sizes", "words", "ends", "rows", "bound", "src", "dst", "s"]
    least = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    tasks = lambda blocks: max(least, min(512, 4 * blocks))  # noqa: E731  blocks and their pairs are too few for their work to be dealt out by size
    placed = placed.repartition(tasks(-(-rows.count() // SEARCH_BLOCK)), "block")
    blocks = kept(placed.groupBy("block").applyInArrow(own, "block long, " + ", ".join(f"{c} binary" for c in names[1:])), "blocks", "none")
    discard(rows)
    numbers = sorted(r.block for r in blocks.select("block").collect())
    dealt = blocks.select(*names[:7]).withColumn("other", F.explode(F.array(*[F.lit(b).cast("long") for b in numbers]) if numbers else F.array().cast("array<long>"))).where("block <> other")
    dealt = dealt.withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other"))

    def others(_, part):
        held = sorted(part.to_pylist(), key=lambda r: r["block"])
        sides = [_by_row(np.frombuffer(r["ids"], np.int64), np.frombuffer(r["sizes"], np.int32), r["words"], r["ends"], r["rows"]) for r in held]
        found = list(_likest(*sides, *[np.frombuffer(r["bound"]) for r in held], k))
        src, dst, s = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        return pa.table({"src": src, "dst": dst, "s": s})

    def opened(batches):
        for batch in batches:
            for src, dst, s in zip(*[batch.column(c).to_pylist() for c in ("src", "dst", "s")], strict=True):
                yield pa.record_batch([pa.array(np.frombuffer(src, np.int64)), pa.array(np.frombuffer(dst, np.int64)), pa.array(np.frombuffer(s))], names=["src", "dst", "s"])

    far = dealt.repartition(tasks(len(numbers) * (len(numbers) - 1) // 2), "lo", "hi").groupBy("lo", "hi").applyInArrow(others, "src long, dst long, s double")
    found = kept(far.unionByName(blocks.select("src", "dst", "s").mapInArrow(opened, "src long, dst long, s double")), "likest")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))
    return found.withColumn("n", rank).where(F.col("n") <= k).select("src", "dst")


def top_embeddings(vectors: DataFrame, k: int = 10) -> DataFrame:
    """Directed: the ``k`` vectors of ``vectors(doc_id, vector)`` at the least angle, ties by id."""

    def like(part, first, second):
        x = part.column("vector").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(part.num_rows, -1)
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        return np.round(x[first] @ x[second].T, 9)

    return _nearest(_block_pairs(vectors, "doc_id"), like, k)


def adjacency(edges: DataFrame, ids: DataFrame) -> tuple[DataFrame, list[int]]:
    """0/1 table of ``edges(src, dst)`` over ``ids(doc_id)``, packed to bits, rows and columns in id order."""
    nodes = kept(assign_row_ids(ids.select("doc_id").distinct(), ["doc_id"]), "nodes")
    n = nodes.count()
    ends = edges.join(nodes.select(F.col("doc_id").alias("dst"), F.col("row_id").cast("int").alias("at")), "dst")
    ones = nodes.join(ends.groupBy(F.col("src").alias("doc_id")).agg(F.collect_list("at").alias("at")), "doc_id", "left")
    ones = ones.select("row_id", F.coalesce("at", F.array().cast("array<int>")).alias("at"))
    return kept(packed(ones.repartition(tasks_for(n, n, ones), "row_id"), n), "codes"), [2] * n


def document_network(spark: SparkSession, sf_dir: str, threshold: float = 0.3) -> tuple[DataFrame, list[int]]:
    """Undirected network of all documents by their whole word sets."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return likeness_table(document_words(docs), docs, threshold)


def directed_network(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return adjacency(top_documents(docs), docs)


def embedding_network(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    """Directed network of the embeddings: they carry no clusters, so labels should gain nothing."""
    table = read(spark, sf_dir, "embeddings")
    vectors = table.select(F.col(table.columns[0]).alias("doc_id"), F.col(next(f.name for f in table.schema if f.dataType.typeName() == "array")).alias("vector"))
    return adjacency(top_embeddings(kept(vectors, "vectors")), vectors)


def network_table(spark: SparkSession, sf_dir: str, threshold: float = 0.3) -> tuple[DataFrame, list[int]]:
    """Undirected network of all documents, by their frequent words, packed to bits."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return likeness_table(frequent_words(docs), docs, threshold)


def network(spark: SparkSession, sf_dir: str, threshold: float = 0.3) -> tuple[DataFrame, list[int]]:
    """The same table as lists of codes."""
    codes, cards = network_table(spark, sf_dir, threshold)
    return unpacked(codes, len(cards)), cards


def supplier_threshold(spark: SparkSession, sf_dir: str) -> int:
    """Common orders that about a tenth of the pairs of suppliers reach: mean and 1.3 standard deviations of a Poisson law."""
    line, n = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct(), read(spark, sf_dir, "supplier").count()
    per = line.groupBy("l_orderkey").agg(F.count("*").alias("c")).agg(F.sum(F.col("c") * (F.col("c") - 1))).first()[0] or 0
    mean = per / max(1, n * (n - 1))
    return max(1, int(np.ceil(mean + 1.3 * mean**0.5)))


def supplier_graph(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    return supplier_table(spark, sf_dir, supplier_threshold(spark, sf_dir))


def supplier_links(spark: SparkSession, sf_dir: str, common: int) -> DataFrame:
    """``a, b``, both ways: suppliers that share at least ``common`` orders."""
    line = kept(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct(), "supply")
    a, b = line.select("l_orderkey", F.col("l_suppkey").alias("a")), line.select("l_orderkey", F.col("l_suppkey").alias("b"))
    once = a.join(b, "l_orderkey").where("a < b").groupBy("a", "b").agg(F.count("*").alias("c")).where(F.col("c") >= common).select("a", "b")
    once = kept(once, "supplier-links")
    return once.unionByName(once.select(F.col("b").alias("a"), F.col("a").alias("b")))


def supplier_table(spark: SparkSession, sf_dir: str, common: int) -> tuple[DataFrame, list[int]]:
    """Table of the suppliers that share at least ``common`` orders, packed to bits."""
    pairs = supplier_links(spark, sf_dir, common)
    names = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("a"))
    n = names.count()
    least = names.agg(F.min("a")).first()[0]
    ones = names.join(pairs.groupBy("a").agg(F.collect_list((F.col("b") - least).cast("int")).alias("at")), "a", "left")
    rows = ones.select((F.col("a") - least).alias("row_id"), F.coalesce("at", F.array().cast("array<int>")).alias("at"))
    return kept(packed(rows.repartition(tasks_for(n, n, rows), "row_id"), n), "codes"), [2] * n


def supplier_network(spark: SparkSession, sf_dir: str, common: int) -> tuple[DataFrame, list[int]]:
    """The same table as lists of codes."""
    codes, cards = supplier_table(spark, sf_dir, common)
    return unpacked(codes, len(cards)), cards


def sbm(spark: SparkSession, p0: float, p1: float, k: int, m: int, n: int, seed: int) -> tuple[DataFrame, list[int], DataFrame]:
    from blockpress.operators.models import sample_sbm

    drawn, _ = sample_sbm(spark, p0, p1, k, m, n, seed)
    drawn = kept(drawn, "sbm")
    return drawn.select("row_id", "codes"), [2] * n, drawn.select("row_id", F.col("u").alias("label"))


#: Builder and label sizes (dictionary coder, frequency coder) of each experiment; 0 stands for one label a column.
EXPERIMENTS: dict[str, tuple[Callable, tuple[int, int], tuple[int, int], str]] = {
    "flat": (flat_table, (9, 9), (5, 8), "byte"),
    "flat18": (flat_table_18, (9, 15), (5, 14), "byte"),
    "network": (network, (5, 5), (5, 5), "byte"),
    "network_words": (document_network, (5, 5), (5, 5), "byte"),
    "network_dense": (lambda spark, sf_dir: document_network(spark, sf_dir, 0.2), (5, 5), (5, 5), "byte"),
    "network_directed": (directed_network, (5, 5), (5, 5), "byte"),
    "network_suppliers": (supplier_graph, (5, 5), (5, 5), "byte"),
    "network_embeddings": (embedding_network, (5, 5), (5, 5), "byte"),
    "transactions": (transactions, (3, 0), (3, 0), "byte"),
    "neighbours": (neighbours, (6, 7), (2, 6), "byte"),
    "wide55": (wide_55, (6, 17), (6, 17), "byte"),
    "wide68": (wide_68, (9, 0), (9, 0), "byte"),
    "ratings": (ratings, (2, 0), (8, 8), "byte"),
    "words": (word_presence, (5, 5), (5, 5), "byte"),
}


#: Builders of the same tables packed to bits, where an experiment's own gives lists of codes.
IN_BITS: dict[str, Callable] = {"network": network_table}


def build(spark: SparkSession, sf_dir: str, name: str, shuffled: bool = False, seed: int = 42, bits: bool = False) -> Workload:
    make, k_lz, k_ans, pack = EXPERIMENTS[name]
    codes, cards = (IN_BITS.get(name, make) if bits else make)(spark, sf_dir)
    n = len(cards)
    if shuffled:
        codes = shuffle_rows(codes, seed)
    size = lambda k: (k[0], min(k[1] or n, n))
    return Workload(name, codes, cards, size(k_lz), size(k_ans), pack=pack)


METHODS = ("lz", "lz_c", "ans_table", "ans_column", "latent_lz", "latent_ans")


def code_with(w: Workload, method: str, lat: L.Latents | None = None):
    """The container of one method on one workload."""
    w = replace(w, codes=unpacked(w.codes, w.n))
    one = w.codes.withColumn("u", F.lit(0))
    none, each = np.zeros(w.n, int), np.arange(w.n)
    if method == "lz":
        return compress(one, w.cards, none, "zstd", order="row", pack=w.pack)
    if method == "lz_c":
        return compress(one, w.cards, none, "zstd", order="col", pack=w.pack)
    if method == "ans_table":
        return compress(one, w.cards, none, "rans")
    if method == "ans_column":
        return compress(one, w.cards, each, "rans")
    labelled = w.codes.join(lat.rows, "row_id")
    return compress(labelled, w.cards, lat.columns, "zstd" if method == "latent_lz" else "rans", pack=w.pack)


REPORT = "workload string, method string, k_r int, k_c int, shuffled boolean, pack string, raw_bits double, coded_bits double, rate double, drr double, runs int, drr_sd double"


def report(spark: SparkSession, sf_dir: str, names: list[str], methods=METHODS, runs: int = 5, shuffled: bool = False, fraction: float = 1.0, **spectral) -> DataFrame:
    """The results table: each method's data reduction on each workload, latent ones as means over random starts."""
    rows = []
    for name in names:
        w = build(spark, sf_dir, name, shuffled, bits=True)
        rows += measure(w, methods, runs, shuffled, fraction, **spectral)
    return spark.createDataFrame(rows, REPORT)


def permuted(w: Workload, seed: int = 42) -> Workload:
    """The same table with its rows permuted."""
    return replace(w, codes=shuffle_rows(w.codes, seed))


def labels_of_runs(w: Workload, wanted: list[tuple[int, int]], runs: int, fraction: float = 1.0, n_components: str = "k-1", unit: bool = False, psi: str = "index", init: str = "random", solver: str = "auto") -> tuple[DataFrame, list[list[np.ndarray]]]:
    """``row_id, us, codes`` and, for each pair of label sizes and each run, the column labels.

    A run is one plain start on both sides (``init="random"``), or one with care on both (``k-means||``, best of five).
    """
    if psi == "index":  # codes are their own image
        x = w.codes.select("row_id", F.col("codes").alias("x"))
    else:
        x = kept(image(unpacked(w.codes, w.n), w.cards, psi), "image")
    extra = 0 if n_components == "k-1" else 1
    width = lambda k: max(1, k - 1 + extra)
    d = min(w.n, max(width(k) for pair in wanted for k in pair if k < w.n or k == pair[0]))
    factors = L.spectral_factors(x, w.n, d, solver=solver, fraction=fraction)
    a = F.col("a")
    if unit:
        norm = F.sqrt(F.aggregate("a", F.lit(0.0), lambda s, v: s + v * v))
        a = F.transform("a", lambda v: v / F.greatest(norm, F.lit(1e-300)))
    specs = [(k_r, min(width(k_r), d), 100 + s) for k_r, _ in wanted for s in range(runs)]
    found = starts = None
    if init == "random" and psi == "index" and not unit:
        starts = L.kmeans_starts(factors.rows, specs)
    elif init == "random":
        found = L.kmeans_many(factors.rows.select("row_id", a.alias("a")), specs)
    else:
        rows = kept(factors.rows.select("row_id", a.alias("a")), "factors")
        for j, (k, size, seed) in enumerate(specs):
            one = L.kmeans_rows(rows.select("row_id", F.slice("a", 1, size).alias("a")), k, seed, init).withColumnRenamed("u", f"u{j}")
            found = one if found is None else found.join(one, "row_id")
        found = found.select("row_id", F.array(*[F.col(f"u{j}").cast("int") for j in range(len(specs))]).alias("us"))
    columns = []
    for _, k_c in wanted:
        if k_c >= w.n or k_c <= 1:
            columns.append([np.arange(w.n) if k_c >= w.n else np.zeros(w.n, int)] * runs)
        else:
            columns.append([L.kmeans_small(factors.columns[:, : min(width(k_c), d)], k_c, 100 + s, starts=1 if init == "random" else 5) for s in range(runs)])
    if starts is not None:  # rows are labelled where they are
        return L.labelled(w.codes, factors.basis, starts), columns
    return kept(w.codes.join(found, "row_id").select("row_id", "us", "codes"), "labelled"), columns


def measure(w: Workload, methods=METHODS, runs: int = 5, shuffled: bool = False, fraction: float = 1.0, **spectral) -> list[tuple]:
    """``REPORT`` rows of one workload: all methods and all runs are coded in one pass."""
    m = w.codes.count()
    raw = raw_bits(w.cards, m)
    none, each = (0,) * w.n, tuple(range(w.n))
    flat = {"lz": C.Coding("lz", "zstd", none), "lz_c": C.Coding("lz_c", "zstd", none, order="col"), "ans_table": C.Coding("ans_table", "rans", none), "ans_column": C.Coding("ans_column", "rans", each)}
    latent = [x for x in methods if x.startswith("latent")]
    wanted = [w.k_lz if x == "latent_lz" else w.k_ans for x in latent]
    codings = [flat[x] for x in methods if x in flat]
    rows = w.codes.withColumn("us", F.array().cast("array<int>"))
    if latent:
        rows, columns = labels_of_runs(w, wanted, runs, fraction, **spectral)
        for i, x in enumerate(latent):
            codings += [C.Coding(x, "zstd" if x == "latent_lz" else "rans", tuple(columns[i][s].tolist()), i * runs + s) for s in range(runs)]
    sizes = [sum(s.values()) for s in C.coded_sizes(rows, w.cards, codings, w.pack)]
    out = []
    for x in methods:
        got = np.array([s for s, c in zip(sizes, codings, strict=True) if c.name == x])
        k = wanted[latent.index(x)] if x in latent else (1, 1)
        coded = float(got.mean())
        out.append((w.name, x, int(k[0]), int(k[1]), shuffled, w.pack, raw, coded, coded / raw, 1 - coded / raw, len(got), float((1 - got / raw).std(ddof=1)) if len(got) > 1 else 0.0))
    return out
