"""Joins that Spark has no operator for, as compositions that shuffle by key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof(left: DataFrame, right: DataFrame, key: str, time: str, carry: list[str]) -> DataFrame:
    """``left`` with the ``carry`` columns of the newest ``right`` row of its key at or before its time.

    One shuffle by key: both sides in one sorted run, the last right row carried forwards. Of right rows
    at one time the one with the greatest carried values counts.
    """
    mine = [c for c in left.columns if c not in (key, time)]
    a = left.select(key, time, F.lit(1).alias("_side"), F.struct(*mine).alias("_l"), F.lit(None).cast(right.select(F.struct(*carry)).schema[0].dataType).alias("_r"))
    b = right.select(key, time, F.lit(0).alias("_side"), F.lit(None).cast(left.select(F.struct(*mine)).schema[0].dataType).alias("_l"), F.struct(*carry).alias("_r"))
    run = Window.partitionBy(key).orderBy(time, "_side", "_r").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_r", F.last("_r", ignorenulls=True).over(run)).where("_side = 1")
    return both.select(key, time, "_l.*", "_r.*")


def interval(left: DataFrame, right: DataFrame, at: Column, lo: Column, hi: Column, width: float, on: Column | None = None) -> DataFrame:
    """Rows with ``lo <= at < hi``: an equi-join on buckets of ``width``, then the exact test.

    A right row goes to each bucket that it touches, so ``width`` should be about as long as intervals are.
    """
    a = left.withColumn("_b", F.floor(at / width))
    b = right.withColumn("_b", F.explode(F.sequence(F.floor(lo / width), F.floor(hi / width))))
    hit = (at >= lo) & (at < hi)
    return a.join(b, "_b").where(hit if on is None else hit & on).drop("_b")


def multiset_equal(a: DataFrame, b: DataFrame) -> bool:
    """Whether two frames hold the same rows as often: one aggregation, no collect of rows."""
    both = a.withColumn("_d", F.lit(1)).unionByName(b.withColumn("_d", F.lit(-1)))
    return both.groupBy(*a.columns).agg(F.sum("_d").alias("_d")).where("_d <> 0").isEmpty()


def per_group(df: DataFrame, key: str, order: list[Column], k: int) -> DataFrame:
    """The first ``k`` rows of each group; Spark keeps ``k`` a task before the shuffle."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(key).orderBy(*order))).where(F.col("rank") <= k)
