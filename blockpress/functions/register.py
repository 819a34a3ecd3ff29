"""Functions for SQL text: measures as Arrow functions, the phrase parser as a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from blockpress.coders import phrase_lz, rans, zstd


def zstd_bits(data: pd.Series) -> pd.Series:
    return data.map(lambda b: None if b is None else 8 * len(zstd.zstandard.ZstdCompressor(level=zstd.LEVEL).compress(b)))


def lz_bits(codes: pd.Series) -> pd.Series:
    return codes.map(lambda c: None if c is None else phrase_lz.encode(list(c), int(max(c, default=0)) + 1)[1])


def rans_bits(codes: pd.Series) -> pd.Series:
    """Coded bits and counts of the frequency coder."""

    def size(c) -> int | None:
        if c is None:
            return None
        x = np.asarray(c, np.int64)
        counts = np.bincount(x, minlength=1)
        return 8 * len(rans.encode(x, *rans.scaled(counts))) + 64 * int((counts > 0).sum())

    return codes.map(size)


def _entropy_of(counts: pd.Series) -> float:
    c = counts[counts > 0].to_numpy(float)
    return float((c * np.log2(c.sum() / c)).sum() / c.sum()) if len(c) else 0.0


def entropy_bits(counts):
    """Entropy in bits of a group's counts, as a grouped aggregate: groups are histograms, so they are small."""
    return pandas_udf(_entropy_of, "double")(counts)


class Bits:
    """Rows ``place, bit`` of a binary value, the highest bit of the first byte first."""

    def eval(self, data):
        for k, byte in enumerate(bytes(data or b"")):
            for j in range(8):
                yield 8 * k + j, byte >> (7 - j) & 1


class LzPhrases:
    """Rows of phrases of one array of codes."""

    def eval(self, codes):
        for j, p in enumerate(phrase_lz.parse(list(codes or []), "earliest")):
            yield j, p.start, p.length, p.pointer


def register_functions(spark: SparkSession) -> None:
    """``zstd_bits(binary)``, ``lz_bits(array)``, ``rans_bits(array)``, ``entropy_bits(count)``, ``lz_phrases(array)``, ``bits(binary)``, and measures as plain SQL functions."""
    spark.udf.register("zstd_bits", pandas_udf(zstd_bits, "long"))
    spark.udf.register("lz_bits", pandas_udf(lz_bits, "long"))
    spark.udf.register("rans_bits", pandas_udf(rans_bits, "long"))
    spark.udf.register("entropy_bits", pandas_udf(_entropy_of, "double"))
    spark.udtf.register("bits", udtf(Bits, returnType="place int, bit int"))
    spark.udtf.register("lz_phrases", udtf(LzPhrases, returnType="phrase_no int, start long, length long, pointer long"))
    sql = {
        "h2(p DOUBLE) RETURNS DOUBLE": "CASE WHEN p <= 0 OR p >= 1 THEN 0D ELSE -p * log2(p) - (1 - p) * log2(1 - p) END",
        "elias_gamma_bits(x BIGINT) RETURNS INT": "2 * length(bin(x)) - 1",
        "elias_delta_bits(x BIGINT) RETURNS INT": "length(bin(x)) + 2 * length(bin(length(bin(x)))) - 2",
        "plain_bits(n BIGINT, k BIGINT) RETURNS BIGINT": "CASE WHEN k <= 1 THEN 0 ELSE n * length(bin(k - 1)) END",
    }
    for head, body in sql.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
