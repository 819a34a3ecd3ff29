"""Appending to a compressed table: codes, statistics and containers from a stream.

The codebook and the block model are frozen; symbols the codebook lacks get code -1 and are counted.
Batches go to containers by batch number, so a batch that runs twice replaces itself. Rows later than the
watermark are left out of window statistics, counted, and still go to the containers (``run_windows``).
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.plans.encode import Codebook, encode_table
from blockpress.sources.storage import new_path


def read_stream(spark: SparkSession, path: str, like: DataFrame, files_per_trigger: int | None = 1) -> DataFrame:
    """A folder of Parquet files as a stream with a known schema.

    Files come by their time of writing, which need not be the rows' own order. With a limit an early file that was
    written last brings late rows; without one (None) all files there make one batch, in which nothing is late.
    """
    reader = spark.readStream.schema(like.schema)
    return (reader.option("maxFilesPerTrigger", files_per_trigger) if files_per_trigger else reader).parquet(path)


def coded(stream: DataFrame, book: Codebook, keep: list[str]) -> DataFrame:
    """The stream's rows as codes under the frozen codebook, and how many symbols it lacks."""
    out = encode_table(stream, book, keep)
    return out.withColumn("unseen", F.size(F.filter("codes", lambda x: x < 0)))


def windowed_counts(stream: DataFrame, time: str, width: str, late: str = "0 seconds", slide: str | None = None) -> DataFrame:
    """Rows, unseen symbols and code counts in each time window; rows later than ``late`` do not count."""
    span = F.window(time, width, slide) if slide else F.window(time, width)
    return stream.withWatermark(time, late).groupBy(span.alias("w")).agg(F.count("*").alias("n"), F.sum("unseen").alias("unseen")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "unseen")


def session_counts(stream: DataFrame, time: str, key: str, gap: str, late: str = "0 seconds") -> DataFrame:
    """Sessions of each key: rows that follow within ``gap``."""
    return stream.withWatermark(time, late).groupBy(key, F.session_window(time, gap).alias("w")).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(stream: DataFrame, keys: list[str], time: str, late: str) -> DataFrame:
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all there is, into a table in shared storage."""
    spark = stream.sparkSession
    out, state = new_path(spark, "stream-out"), new_path(spark, "stream-state")
    if mode == "append":
        query = stream.writeStream.outputMode("append").format("parquet").option("checkpointLocation", state).trigger(availableNow=True).start(out)
    else:
        query = stream.writeStream.outputMode(mode).foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(out)).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(out)


def compress_batches(stream: DataFrame, write: Callable[[DataFrame, int], None]) -> None:
    """Hand each micro-batch to ``write`` with its number; the same number may come again."""
    state = new_path(stream.sparkSession, "stream-state")
    stream.writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()


def _batch_tables(spark: SparkSession, root: str, name: str, before: int | None = None) -> DataFrame | None:
    """What batches have written under ``name``, of those before a batch where one is given; None if nothing."""
    at = spark._jvm.org.apache.hadoop.fs.Path(f"{root}/{name}")
    if not at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at):
        return None
    rows = spark.read.option("basePath", f"{root}/{name}").parquet(f"{root}/{name}")
    return rows if before is None else rows.where(F.col("batch") < before)


def run_windows(stream: DataFrame, time: str, width: str, late_seconds: float, slide: str | None = None) -> dict[str, DataFrame]:
    """Run ``stream(time, codes, unseen, ...)`` over all there is, with late rows told apart.

    ``windows(start, end, n, unseen)`` and ``counts(start, end, col_id, code, cnt)`` hold the rows in time, batch
    by batch combined; ``late(batch, n)`` counts the rows more than ``late_seconds`` behind the newest time of
    the batches before; ``rows`` holds all rows, for the container. A batch that runs again writes the same folders
    again and looks at the same earlier batches, so nothing counts twice.
    """
    spark = stream.sparkSession
    root, state = new_path(spark, "stream-windows"), new_path(spark, "stream-state")
    span = F.window(time, width, slide) if slide else F.window(time, width)

    def write(df: DataFrame, k: int) -> None:
        seen = _batch_tables(spark, root, "newest", k)
        newest = seen.agg(F.max("newest")).first()[0] if seen is not None else None  # a row for each batch
        mark = F.lit(None).cast("double") if newest is None else F.lit(newest - late_seconds)
        flagged = df.withColumn("late", F.coalesce(F.unix_micros(time) / 1e6 < mark, F.lit(False)))
        flagged.write.mode("overwrite").parquet(f"{root}/rows/batch={k}")
        rows = spark.read.schema(flagged.schema).parquet(f"{root}/rows/batch={k}")
        live = rows.where("not late").select(span.alias("w"), "codes", "unseen")
        live.groupBy("w").agg(F.count("*").alias("n"), F.sum("unseen").alias("unseen")).write.mode("overwrite").parquet(f"{root}/windows/batch={k}")
        cells = live.select("w", F.posexplode("codes").alias("col_id", "code"))
        cells.groupBy("w", "col_id", "code").agg(F.count("*").alias("cnt")).write.mode("overwrite").parquet(f"{root}/counts/batch={k}")
        rows.agg(F.count_if("late").alias("n")).write.mode("overwrite").parquet(f"{root}/late/batch={k}")
        rows.agg(F.coalesce(F.max(F.unix_micros(time)) / 1e6, F.lit(float("-inf"))).alias("newest")).write.mode("overwrite").parquet(f"{root}/newest/batch={k}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    edge = [F.col("w.start").alias("start"), F.col("w.end").alias("end")]
    windows = _batch_tables(spark, root, "windows").groupBy("w").agg(F.sum("n").alias("n"), F.sum("unseen").alias("unseen"))
    counts = _batch_tables(spark, root, "counts").groupBy("w", "col_id", "code").agg(F.sum("cnt").alias("cnt"))
    return {
        "windows": windows.select(*edge, "n", "unseen"),
        "counts": counts.select(*edge, "col_id", F.col("code").cast("int").alias("code"), "cnt"),
        "late": _batch_tables(spark, root, "late").select(F.col("batch").cast("long").alias("batch"), "n"),
        "rows": _batch_tables(spark, root, "rows").drop("batch"),
    }


def windowed_rates(counts: DataFrame, cards: list[int]) -> DataFrame:
    """``start, entropy, drr``: of each window's ``counts``, the entropy of a row's codes column by column, and the data reduction of the frequency coder with a table for each column and window."""
    from blockpress.operators.entropy import ideal_sizes

    raw = F.array(*[F.lit(float(math.log2(max(k, 1)))) for k in cards])
    sizes = ideal_sizes(counts, ["start", "col_id"]).withColumn("raw", F.col("n") * F.element_at(raw, F.col("col_id") + 1))
    totals = sizes.groupBy("start").agg(F.sum(F.col("code_bits") / F.col("n")).alias("entropy"), F.sum(F.col("code_bits") + F.col("count_bits")).alias("coded"), F.sum("raw").alias("raw"))
    return totals.select("start", "entropy", (1 - F.col("coded") / F.col("raw")).alias("drr"))


def matched(left: DataFrame, right: DataFrame, key: str, time: str, right_time: str, within: str, late: str) -> DataFrame:
    """Two streams joined on a key where the right row's time lies at most ``within`` behind the left one's."""
    a, b = left.withWatermark(time, late), right.withWatermark(right_time, late).withColumnRenamed(key, "_key")
    near = F.expr(f"{right_time} >= {time} AND {right_time} <= {time} + INTERVAL {within}")
    return a.join(b, (F.col(key) == F.col("_key")) & near).drop("_key")


def with_labels(stream: DataFrame, logq, log_row, columns) -> DataFrame:
    """``row_id, u, entropy`` of ``stream(row_id, codes)``: each new row's likeliest label under a frozen block model."""
    from blockpress.operators.codec import row_scores

    return row_scores(stream, logq, log_row, columns)


DRIFT = "key string, n long, divergence double, drifted boolean"


def drift(stream: DataFrame, key: str, code: str, law: dict[int, float], limit: float, least: int = 100) -> DataFrame:
    """Running divergence in bits of each key's codes from a frozen law, flagged beyond ``limit``.

    The state of a key is one count a code; codes outside the law count as one more, of the law's least share.
    """
    import math

    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    codes = sorted(law)
    floor = min(law.values())

    def update(key_, frames, state):
        counts = list(state.get[0]) if state.exists else [0] * (len(codes) + 1)
        for f in frames:
            for c, n in f["code"].value_counts().items():
                counts[codes.index(c) if c in law else -1] += int(n)
        state.update((counts,))
        n = sum(counts)
        shares = [*(law[c] for c in codes), floor]
        gap = sum(c / n * math.log2(c / n / s) for c, s in zip(counts, shares, strict=True) if c)
        yield pd.DataFrame({"key": [str(key_[0])], "n": [n], "divergence": [gap], "drifted": [n >= least and gap > limit]})

    rows = stream.select(F.col(key).cast("string").alias("key"), F.col(code).cast("int").alias("code"))
    return rows.groupBy("key").applyInPandasWithState(update, DRIFT, "counts array<long>", "update", GroupStateTimeout.NoTimeout)


def last_states(stream: DataFrame, key: str) -> DataFrame:
    """Run an update-mode stream over all there is; the newest row of each key."""
    spark = stream.sparkSession
    out, state = new_path(spark, "stream-updates"), new_path(spark, "stream-state")

    def write(df: DataFrame, k: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={k}")

    stream.writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(out)
    return rows.groupBy(key).agg(F.max_by(F.struct(*[c for c in rows.columns if c not in (key, "batch")]), "batch").alias("r")).select(key, "r.*")
