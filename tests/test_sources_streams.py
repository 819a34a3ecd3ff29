"""Formats in and out, and streams with state."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockpress.operators import joins as J
from blockpress.operators import models
from blockpress.plans import encode as P
from blockpress.sources import readers as R
from blockpress.sources.storage import new_path
from blockpress.streaming import stream as S


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats(spark, small, fmt):
    nation = spark.read.parquet(f"{small}/nation.parquet")
    path = new_path(spark, fmt)
    nation.write.format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(path)
    assert J.multiset_equal(R.read_table(spark, path, fmt, nation.schema), nation)


def test_formats_need_a_schema(spark):
    with pytest.raises(ValueError):
        R.read_table(spark, "nowhere", "csv")


def test_nested_columns(spark, small):
    vectors = spark.read.parquet(f"{small}/embeddings.parquet")
    name = next(f.name for f in vectors.schema if f.dataType.typeName() == "array")
    flat = R.flattened(vectors, {name: 64})
    assert len(flat.columns) == len(vectors.columns) + 63
    events = R.json_fields(spark.read.parquet(f"{small}/events.parquet"), "props", "k int")
    assert events.where("props_k is null").count() == 0 and "props" not in events.columns
    book = P.fit_codebook(flat.drop("label", "vec_id", "id"))
    assert set(book.cards) == {4}  # numbers of many values: quartiles


def test_online_labels(spark):
    from blockpress.functions.theory import symmetric_binary

    m = symmetric_binary(0.1, 0.9, 3)
    codes, v = models.sample_table(spark, m, 90, 60, 4)
    where = new_path(spark, "rows")
    codes.write.parquet(where)
    live = S.read_stream(spark, where, codes)
    got = S.run_to_table(S.with_labels(live, np.log2(m.q), np.log2(m.row), v))
    both = got.withColumnRenamed("u", "found").join(codes.select("row_id", "u"), "row_id")
    assert both.count() == 90 and both.where("u <> found").count() == 0


def test_drift(spark):
    rows = [("steady", k % 2) for k in range(400)] + [("odd", 0) for _ in range(300)] + [("new", 5)] * 3
    df = spark.createDataFrame(rows, "k string, c int")
    where = new_path(spark, "codes")
    df.repartition(3).write.parquet(where)
    out = S.last_states(S.drift(S.read_stream(spark, where, df), "k", "c", {0: 0.5, 1: 0.5}, 0.2), "key")
    got = {r.key: (r.n, round(r.divergence, 3), r.drifted) for r in out.collect()}
    assert got == {"steady": (400, 0.0, False), "odd": (300, 1.0, True), "new": (3, 1.0, False)}


def test_stream_joins_codebook(spark, small):
    events = spark.read.parquet(f"{small}/events.parquet").select("event_id", "event_type")
    where = new_path(spark, "events")
    events.write.parquet(where)
    book = P.fit_codebook(events.select("event_type")).frame(spark).select("code", F.col("value").alias("event_type"))
    live = S.read_stream(spark, where, events).join(F.broadcast(book), "event_type")
    assert S.run_to_table(live).groupBy("code").count().count() == book.count()
