"""The full suffix array of a corpus by a distributed difference cover, and the repeats its neighbours show (operator 1).

Every step is rows in Spark: nothing of a corpus-wide step runs in one task or on the driver.

* Sample: the positions ``i`` with ``i % 3`` of 1 or 2, a difference cover modulo three. Distinct triples of
  symbols are sorted by range and named by rank.
* Recurse: the names at 1, 4, 7 ... and those at 2, 5, 8 ... of a text are two texts of the next level. A
  name of level ``k`` stands for ``3**(k + 1)`` bytes; the recursion ends with the first level where all names
  differ or that many bytes are ``length`` or more, so suffixes are in order by that many bytes at least.
* Merge: a remaining suffix (``i % 3 == 0``) is its first symbol and a sampled suffix. It is compared with
  the sampled ones at 1 by (symbol, next rank), with those at 2 by (symbol, symbol, next rank but one): two
  sorts by range, whose running counts add up to each suffix's rank.
* Compare adjacent prefixes: neighbours in rank order that share a hash of their first ``length`` bytes.

``suffix_dedup`` gives the same results from a sparse sample and is what the query runs; the README has what
both cost. Equal texts are one text with its copies counted. Null text: empty; repeated rows repeat each
other's strings; null and repeated ``doc_id`` do no harm; further columns are ignored; no rows: no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockpress.llm.common import slices, stored, text_bytes
from blockpress.sources.storage import discard

LENGTH = 200
#: Positions of a text that one task reads ahead in.
BLOCK = 1 << 16
#: A triple in more than one of this many samples gets its name from a broadcast table, which so has fewer rows than this.
HOT = 4096
AT = ["sid", "path", "i"]


def _text_rows(texts: DataFrame, length: int) -> DataFrame:
    """``(sid, path, i, sym, sym1, sym2, head)`` of every byte: it and the next two (from 1; past the end 0), and a hash of its window or null."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", 1 << 16):
            raw, at = text_bytes(batch.column("text"))
            size = np.diff(at)
            place = np.arange(len(raw)) - np.repeat(at[:-1], size)
            left = np.repeat(at[1:], size) - np.arange(len(raw))
            sym = np.concatenate([raw, [0, 0]]).astype(np.int64) + 1
            data = raw.tobytes()
            head = [hashlib.blake2b(data[k : k + length], digest_size=16).digest() if n >= length else None for k, n in enumerate(left.tolist())]
            cols = [pa.array(np.repeat(batch.column("sid").to_numpy(), size)), pa.array(np.zeros(len(raw), np.int64)), pa.array(place)]
            cols += [pa.array(np.where(left > k, sym[k : k + len(raw)], 0)) for k in range(3)]
            yield pa.record_batch([*cols, pa.array(head, pa.binary())], names=[*AT, "sym", "sym1", "sym2", "head"])

    return texts.select("sid", "text").mapInArrow(emit, "sid long, path long, i long, sym long, sym1 long, sym2 long, head binary")


def _ahead(rows: DataFrame, columns: list[str]) -> DataFrame:
    """``rows`` with each column's values one and two positions on (past the end 0), by blocks with two positions of overlap."""
    own = F.expr(f"i div {BLOCK}")
    both = F.when((F.col("i") % BLOCK < 2) & (F.col("i") >= BLOCK), F.array(own, own - 1)).otherwise(F.array(own))
    w = Window.partitionBy("sid", "path", "block").orderBy("i")
    later = [F.coalesce(F.lead(c, k).over(w), F.lit(0)).alias(f"{c}{k}") for c in columns for k in (1, 2)]
    return rows.withColumn("block", F.explode(both)).select("*", *later).where(own == F.col("block")).drop("block")


def _running(df: DataFrame, keys: list[str], flags: list[str], name: str) -> tuple[DataFrame, dict[str, int]]:
    """``df`` in order of ``keys`` with ``<flag>_before``, the sum of each flag over the rows before, and the sums over all."""
    spark, names = df.sparkSession, [*df.columns, "part", *(f"{f}_before" for f in flags)]
    schema = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in df.schema), "part int", *(f"{f}_before long" for f in flags)])

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, total = TaskContext.get().partitionId(), dict.fromkeys(flags, 0)
        for batch in batches:
            cols = [*batch.columns, pa.array(np.full(batch.num_rows, part, np.int32))]
            for f in flags:
                value = batch.column(batch.schema.get_field_index(f)).to_numpy()
                upto = total[f] + np.cumsum(value)
                cols.append(pa.array(upto - value))
                total[f] = int(upto[-1]) if len(upto) else total[f]
            yield pa.record_batch(cols, names=names)

    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    laid = stored(df.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).mapInArrow(emit, schema), name)
    sums = sorted(laid.groupBy("part").agg(*[F.sum(f).alias(f) for f in flags]).collect())  # a row for each partition
    total, rows = dict.fromkeys(flags, 0), []
    for s in sums:
        rows.append((s["part"], *total.values()))
        total = {f: total[f] + s[f] for f in flags}
    offset = spark.createDataFrame(rows, ", ".join(["part int", *(f"{f}_offset long" for f in flags)]))
    moved = laid.join(F.broadcast(offset), "part")
    out = moved.select(*df.columns, *[(F.col(f"{f}_before") + F.col(f"{f}_offset")).alias(f"{f}_before") for f in flags])
    out._kept_at = laid._kept_at
    return out, total


def _ranks(strings: DataFrame, rows: DataFrame, length: int, level: int) -> DataFrame:
    """``(sid, path, i, rank)``, ranks from 1: suffixes of ``strings(sid, path, i, sym)``; ``rows`` has the next two symbols too.

    Suffixes that agree in the bytes the last level's names stand for may have any order or equal ranks.
    """
    triple = ["sym", "sym1", "sym2"]
    sample = rows.where("i % 3 <> 0").select(*AT, *triple)
    names, total = _running(sample.groupBy(*triple).agg(F.count("*").alias("n")).withColumn("one", F.lit(1).cast("long")), triple, ["one", "n"], f"names{level}")
    names = names.select(*triple, "n", (F.col("one_before") + 1).alias("name"), (F.col("n_before") + 1).alias("least"))
    often = names.where(F.col("n") * HOT > total["n"]).drop("n").withColumn("hot", F.lit(True))
    first = sample.join(F.broadcast(often), triple, "left")
    rest = first.where("hot IS NULL").drop("name", "least", "hot").join(names.where(F.col("n") * HOT <= total["n"]).drop("n"), triple)
    named = stored(first.where("hot").drop("hot").unionByName(rest).select(*AT, "name", "least"), f"named{level}")
    spent = [names, named]
    if total["one"] == total["n"] or 3 ** (level + 1) >= length:
        sampled = named.select(*AT, F.col("least").alias("rank"))
    else:
        inner = named.select("sid", F.expr("path * 2 + i % 3 - 1").alias("path"), F.expr("i div 3").alias("i"), F.col("name").alias("sym"))
        ranked = _ranks(inner, _ahead(inner, ["sym"]), length, level + 1)
        sampled = ranked.select("sid", F.expr("path div 2").alias("path"), F.expr("i * 3 + path % 2 + 1").alias("i"), "rank")
        spent.append(ranked)
    near = stored(_ahead(strings.select(*AT, "sym").join(sampled, AT, "left"), ["sym", "rank"]), f"near{level}")
    zero, other = F.expr("i % 3 = 0").cast("long").alias("zero"), F.expr("i % 3 <> 0").cast("long").alias("other")
    with_one, _ = _running(near.where("i % 3 < 2").select(*AT, "rank", "sym", F.col("rank1").alias("next"), zero, other), ["sym", "next", *AT], ["zero", "other"], f"merge1-{level}")
    with_two, _ = _running(near.where("i % 3 <> 1").select(*AT, "rank", "sym", "sym1", F.col("rank2").alias("next"), zero, other), ["sym", "sym1", "next", *AT], ["zero", "other"], f"merge2-{level}")
    # a remaining suffix: those of its kind before it (from one sort) and the sampled ones of either; a sampled one: its rank and the remaining ones
    ones = with_one.select(*AT, F.expr("if(zero = 1, zero_before + other_before + 1, rank + zero_before)").alias("share"))
    twos = with_two.select(*AT, F.expr("if(zero = 1, other_before, rank + zero_before)").alias("share"))
    out = stored(ones.unionByName(twos).groupBy(*AT).agg(F.sum("share").alias("rank")), f"ranks{level}")
    discard(*spent, near, with_one, with_two)
    return out


def _texts(docs: DataFrame) -> DataFrame:
    """``(sid, text, copies)``: different texts, numbered; rows are told apart by a cryptographic hash first."""
    text = F.coalesce("text", F.lit(""))
    own = docs.select(text.alias("text"), F.sha2(text, 256).alias("sha"))
    each = own.groupBy("sha").agg(F.count("*").alias("copies"), F.first("text").alias("text")).withColumn("one", F.lit(1).cast("long"))
    return _running(each, ["sha"], ["one"], "texts")[0].select("sha", F.col("one_before").alias("sid"), "text", "copies")


def suffix_array(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``(sid, path, i, rank)`` of every byte of the different texts of ``docs(text)``, numbered by ``_texts``; ``path`` is 0."""
    rows = _text_rows(_texts(docs), length).drop("head")
    return _ranks(rows, rows, length, 0)


def repeated_starts(texts: DataFrame, length: int) -> DataFrame:
    """``(sid, i)``: starts of strings of ``length`` bytes of ``texts(sid, text)`` that start twice in them."""
    rows = _text_rows(texts, length)
    ranks = _ranks(rows, rows, length, 0)
    heads = rows.where("head IS NOT NULL").select(*AT, "head").join(ranks, AT).select("sid", "i", "rank", "head")
    parts = max(1, int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Neighbours' equality within a partition; the first and the last row carry their hash out."""
        from pyspark import TaskContext

        part, held = TaskContext.get().partitionId(), None

        def out(sid, i, prev, edge):
            return pa.record_batch([pa.array(sid, pa.int64()), pa.array(i, pa.int64()), pa.array(prev, pa.bool_()), pa.array(edge, pa.binary()), pa.array([part] * len(sid), pa.int32())], names=["sid", "i", "same", "edge", "part"])

        for batch in batches:
            if not batch.num_rows:
                continue
            sid, i, head = (batch.column(c).to_pylist() for c in ("sid", "i", "head"))
            if held is None:
                held = (sid[0], i[0], head[0], False)
                yield out([sid[0]], [i[0]], [False], [head[0]])
                sid, i, head = sid[1:], i[1:], head[1:]
            done: list[tuple] = []
            for s, k, h in zip(sid, i, head, strict=True):
                same = h == held[2]
                done.append((*held[:2], held[3] or same))
                held = (s, k, h, same)
            if done:
                a, b, c = zip(*done, strict=True)
                yield out(a, b, c, [None] * len(a))
        if held is not None:
            yield out([held[0]], [held[1]], [held[3]], [held[2]])

    laid = heads.repartitionByRange(parts, "rank", "sid", "i").sortWithinPartitions("rank", "sid", "i")
    pairs = stored(laid.mapInArrow(emit, "sid long, i long, same boolean, edge binary, part int"), "pairs")
    # two edges a partition, in order: the last of one beside the first of the next
    edges = [(r.part, r.edge) for r in pairs.where("edge IS NOT NULL").select("part", "edge").collect()]
    held: dict[int, list] = {}
    for part, edge in edges:
        held.setdefault(part, []).append(edge)
    order = sorted(held)
    across = [(p, e) for a, b in zip(order, order[1:], strict=False) for e in {bytes(x) for x in held[a]} & {bytes(x) for x in held[b]} for p in (a, b)]
    beyond = texts.sparkSession.createDataFrame(across, "part int, edge binary").distinct().withColumn("across", F.lit(True))
    found = pairs.join(F.broadcast(beyond), ["part", "edge"], "left").where("same OR across")
    return found.select("sid", "i").distinct()


def removal_digests(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """As ``suffix_dedup.removal_digests``, from the full array."""
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    texts = stored(_texts(docs), "texts")
    starts = repeated_starts(texts, length).groupBy("sid").agg(F.collect_list("i").alias("starts"))  # bounded by the text's length
    shas = docs.select("doc_id", F.sha2(F.coalesce("text", F.lit("")), 256).alias("sha"))
    rows = shas.join(texts.join(starts, "sid", "left"), "sha").select("doc_id", "text", "copies", "starts")

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            out = []
            for text, copies, at in zip(batch.column("text").cast(pa.binary()).to_pylist(), batch.column("copies").to_pylist(), batch.column("starts").to_pylist(), strict=True):
                first = np.arange(max(0, len(text) - length + 1)) if copies > 1 else np.array(at or [], np.int64)
                edge = np.zeros(len(text) + 2, np.int64)
                np.add.at(edge, first + 1, 1)
                np.add.at(edge, first + 1 + length, -1)
                gone = np.cumsum(edge)[:-1] > 0  # a leading False
                out.append((len(text), int(gone.sum()), int((gone[1:] & ~gone[:-1]).sum()), hashlib.sha256(np.frombuffer(text, np.uint8)[~gone[1:]].tobytes()).hexdigest()))
            cols = list(zip(*out, strict=True))
            yield pa.record_batch([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3])], names=[c.split()[0] for c in schema.split(", ")])

    return rows.mapInArrow(emit, schema)
