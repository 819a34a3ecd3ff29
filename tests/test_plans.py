"""Plans are what they should be: pruned scans, no Python where expressions do, no single-task windows."""

from pyspark.sql import functions as F

from blockpress.operators import entropy as E
from blockpress.plans import encode as P


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_encoding_reads_only_kept_columns(spark, small):
    df = spark.read.parquet(f"{small}/lineitem.parquet")
    book = P.fit_codebook(df.select("l_quantity", "l_returnflag"))
    text = plan(P.encode_table(df, book, ["l_orderkey"]))
    assert "l_extendedprice" not in text and "l_shipdate" not in text
    assert "Python" not in text and "Exchange" not in text and "Arrow" not in text


def test_histograms_combine_before_the_shuffle(spark, small):
    df = spark.read.parquet(f"{small}/lineitem.parquet").select("l_linenumber", "l_returnflag")
    codes = P.encode_table(df, P.fit_codebook(df)).withColumn("row_id", F.lit(0))
    hist = P.to_long(codes).groupBy("col_id", "code").agg(F.count("*").alias("cnt"))
    text = plan(hist)
    assert text.count("Exchange") == 1 and "partial_count" in text


def test_filters_reach_the_scan(spark, small):
    df = spark.read.parquet(f"{small}/lineitem.parquet").where("l_quantity > 49").select("l_returnflag", "l_linestatus")
    text = plan(E.conditional_entropy(df.withColumnRenamed("l_returnflag", "code").groupBy("l_linestatus", "code").agg(F.count("*").alias("cnt")), ["l_linestatus"]))
    assert "GreaterThan(l_quantity,49" in text


def test_row_numbers_need_no_single_task(spark):
    text = plan(P.assign_row_ids(spark.range(100).select(F.col("id").alias("k")), ["k"]))
    assert "Window" not in text and "SinglePartition" not in text


def test_exact_quantiles_by_counts_near_the_sketches(spark, monkeypatch):
    """Ties, nulls, few values, NaN and stretches that miss: the same as percentile."""
    from pyspark.sql import functions as F

    from blockpress.plans import encode as P

    x = F.xxhash64("id")
    df = spark.range(4001).select((x % 100_000 / 7).alias("a"), F.when(F.col("id") % 5 > 0, F.col("id") % 300 * 0.1).alias("b"), F.when(F.col("id") % 3 == 0, float("nan")).otherwise(x % 1000 * 1.0).alias("c"), (F.col("id") * F.col("id")).alias("d"), F.lit(None).cast("double").alias("e"))
    shares = [0.25, 0.5, 0.75]
    want = [df.agg(F.percentile(F.col(c), F.array(*[F.lit(q) for q in shares]))).first()[0] for c in df.columns]
    around = [df.agg(F.percentile_approx(F.col(c).cast("double"), F.array(*[F.lit(q + e) for q in shares for e in (-0.01, 0.01)]), 10000)).first()[0] for c in df.columns]
    around[3] = [0.0, 1.0] * 3
    assert str(P.exact_quantiles(df, df.columns, shares, around)) == str(want)
    calls = []
    monkeypatch.setattr(F, "percentile", lambda *a: calls.append(a))
    assert [c.kind for c in P.fit_codebook(df.select("a", "b", "d")).columns] == ["Q", "C", "Q"] and not calls
