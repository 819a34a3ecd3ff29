"""Measures of coders and of their theory on drawn or given data."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.coders import phrase_lz, rans, zstd
from blockpress.functions import theory as T

PHRASES = "seq_id long, phrase_no int, start long, length long, pointer long"


def phrases(seqs: DataFrame, tie: str = "latest") -> DataFrame:
    """``PHRASES`` of ``seqs(seq_id, codes)``; a sequence is parsed whole in one task, so chunk long ones first."""
    import pyarrow as pa

    def emit(batches):
        for batch in batches:
            rows = []
            for k, codes in zip(batch.column("seq_id").to_pylist(), batch.column("codes").to_pylist(), strict=True):
                rows += [(k, j, p.start, p.length, p.pointer) for j, p in enumerate(phrase_lz.parse(codes or [], tie))]
            cols = list(zip(*rows, strict=True)) or [()] * 5
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=[f.split()[0] for f in PHRASES.split(", ")])

    return seqs.select("seq_id", "codes").mapInArrow(emit, PHRASES)


def match_stats(found: DataFrame, n: int) -> DataFrame:
    """``kind, phrases, symbols, avg_len, max_len``: new symbols, matches in the same columns, and others."""
    kind = F.when(F.col("pointer") < 1, "literal").when(F.pmod(F.col("start") - F.col("pointer"), F.lit(n)) == 0, "aligned").otherwise("scattered")
    return found.groupBy(kind.alias("kind")).agg(F.count("*").alias("phrases"), F.sum("length").alias("symbols"), F.avg("length").alias("avg_len"), F.max("length").alias("max_len"))


def lz_bits(found: DataFrame, n: int, k: int) -> DataFrame:
    """Coded bits of each sequence from its phrases: pointers of one width, lengths in gamma code."""
    from blockpress.functions.bits import elias_gamma_bits

    return found.groupBy("seq_id").agg((F.count("*") * phrase_lz.pointer_bits(n, k) + F.sum(elias_gamma_bits("length"))).cast("long").alias("bits"))


def recovery_failure(runs: DataFrame) -> float:
    """Share of ``runs(err_u, err_v)`` in which some label is wrong."""
    return runs.agg(F.avg(((F.col("err_u") > 0) | (F.col("err_v") > 0)).cast("int"))).first()[0]


def coded_bits(coder: str, seq: np.ndarray, k: int) -> float:
    """Bits of a sequence under a base coder, counts included where they are sent."""
    if coder == "zstd":
        return 8.0 * len(zstd.encode(seq, "bits", k))
    if coder == "lz":
        return float(phrase_lz.encode(seq.tolist(), k)[1])
    counts = np.bincount(seq, minlength=k)
    if coder == "ans":
        return 8.0 * len(rans.encode(seq, *rans.scaled(counts))) + 64.0 * k
    if coder == "ac":
        from blockpress.coders import arith, elias

        return arith.encode(seq.tolist(), counts.tolist())[1] + sum(elias.gamma_bits(int(c) + 1) for c in counts)
    raise ValueError(coder)


def redundancy(coder: str, q, n: int, draws: int = 4, seed: int = 42) -> float:
    """Mean bits beyond the source's entropy, a symbol, as a share of the raw size: by drawing."""
    rng, k = np.random.default_rng(seed), len(q)
    mean = np.mean([coded_bits(coder, rng.choice(k, n, p=q), k) for _ in range(draws)])
    return (mean - n * T.entropy(q)) / (n * np.log2(k))


def worst_redundancy(spark: SparkSession, coder: str, sources: list, sizes: list[int], draws: int = 2) -> DataFrame:
    """``n, redundancy``: the largest over the sources at each size; every cell of the grid is a task of its own."""
    import pandas as pd

    grid = spark.createDataFrame([(i, n) for i in range(len(sources)) for n in sizes], "source int, n long").repartition(len(sources) * len(sizes))

    def run(batches):
        for b in batches:
            yield pd.DataFrame({"n": b.n, "redundancy": [redundancy(coder, sources[s], int(n), draws) for s, n in zip(b.source, b.n, strict=True)]})

    return grid.mapInPandas(run, "n long, redundancy double").groupBy("n").agg(F.max("redundancy").alias("redundancy"))


def aep_deviation(model: T.Model, m: int, n: int, runs: int = 50, seed: int = 42) -> tuple[float, float]:
    """Largest deviation in nats of tiny tables' log-probability from the entropy, and the bound that holds it at t = 3."""
    rng = np.random.default_rng(seed)
    entropy = T.table_entropy(model, m, n)
    worst = 0.0
    for _ in range(runs):
        u, v = rng.choice(len(model.row), m, p=model.row), rng.choice(len(model.col), n, p=model.col)
        table = np.array([[rng.choice(model.q.shape[2], p=model.q[a, b]) for b in v] for a in u])
        worst = max(worst, abs(-T.log_probability(table, model) - entropy) * np.log(2))
    return worst, T.aep_bound(model, m, n, 3.0)


def native_sizes(codes: DataFrame, n: int, where: str) -> DataFrame:
    """``codec, n_bytes``: what Parquet's own encodings make of the codes, one column each."""
    spark = codes.sparkSession
    wide = codes.select(*[F.element_at("codes", j + 1).cast("int").alias(f"c{j}") for j in range(n)])
    rows = []
    jvm = spark.sparkContext._jvm
    for codec in ("none", "snappy", "zstd"):
        path = f"{where}/{codec}"
        wide.write.mode("overwrite").option("compression", codec).parquet(path)
        at = jvm.org.apache.hadoop.fs.Path(path)
        rows.append((codec, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()))
    return spark.createDataFrame(rows, "codec string, n_bytes long")
