"""The engine on Spark: encoding, labels, codec, streams, and their behaviour on planted and given tables."""

import re

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from blockpress.functions import theory as T
from blockpress.operators import codec as C
from blockpress.operators import entropy as E
from blockpress.operators import joins as J
from blockpress.operators import latents as L
from blockpress.operators import measures as M
from blockpress.operators import models
from blockpress.operators.components import connected_components
from blockpress.plans import encode as P
from blockpress.plans import workloads as W
from blockpress.sources.storage import kept, new_path


@pytest.fixture(scope="module")
def planted(spark):
    codes, v = models.sample_sbm(spark, 0.1, 0.8, 3, 240, 120, seed=3)
    return kept(codes, "planted"), v


def test_codebook_and_codes(spark):
    rows = [(k, float(k), f"s{k}", k % 3, None if k % 2 else "x", k % 2 == 0) for k in range(600)]
    df = spark.createDataFrame(rows, "id int, value double, name string, small int, gaps string, flag boolean")
    kinds = {r.col_name: r.kind for r in P.profile_columns(df).collect()}
    assert kinds == {"id": "Q", "value": "Q", "name": "D", "small": "C", "gaps": "C", "flag": "C"}
    book = P.fit_codebook(df)
    assert book.dropped == ["name"] and book.cards == [4, 4, 3, 2, 2]
    codes = {r.id: r.codes for r in P.encode_table(df, book, ["id"]).collect()}
    assert codes[0] == [0, 0, 0, 0, 1] and codes[599] == [3, 3, 2, 1, 0]
    unseen = P.encode_table(spark.createDataFrame([(1, 5.0, "n", 9, "y", True)], df.schema), book).first().codes
    assert unseen[2] == -1 and unseen[3] == -1
    assert P.raw_bits(book.cards, 10) == pytest.approx(10 * (2 + 2 + np.log2(3) + 1 + 1))
    assert P.raw_bits(book.cards, 10, "common") == 100


def test_row_ids_are_dense_and_do_not_depend_on_partitions(spark):
    df = spark.range(1000).select(((F.col("id") * 37) % 1000).alias("k"))
    for n in (1, 4, 16):
        got = sorted((r.row_id, r.k) for r in P.assign_row_ids(df.repartition(n), ["k"]).collect())
        assert got == [(i, i) for i in range(1000)]
    once = {r.row_id: r.k for r in P.shuffle_rows(P.assign_row_ids(df, ["k"])).collect()}
    again = {r.row_id: r.k for r in P.shuffle_rows(P.assign_row_ids(df.repartition(7), ["k"])).collect()}
    assert once == again and sorted(once.values()) == list(range(1000)) and once != {i: i for i in range(1000)}


def test_entropies_nest(planted):
    codes, v = planted
    hist = kept(E.block_histogram(E.with_labels(codes, v.tolist())), "hist")
    h = E.plugin_entropies(hist).first()
    assert h.h_x_uv <= h.h_x_u <= h.h_x <= 1 and h.h_x_uv <= h.h_x_v
    assert hist.agg(F.sum("cnt")).first()[0] == 240 * 120
    sizes = E.ideal_sizes(hist, ["u", "v"]).agg(F.sum("code_bits")).first()[0]
    assert sizes == pytest.approx(h.h_x_uv * 240 * 120)


@pytest.mark.parametrize("solver", ["gram", "power", "sketch"])
def test_factors(spark, planted, solver):
    codes, _ = planted
    x = kept(P.image(codes, [2] * 120), "x")
    f = L.spectral_factors(x, 120, 3, solver)
    full = np.array([r.x for r in x.orderBy("row_id").collect()])
    s = np.linalg.svd(full, compute_uv=False)[:3]
    assert np.allclose(f.sigma[:2], s[:2], rtol=0.02)
    a = np.array([r.a for r in f.rows.orderBy("row_id").collect()])
    if solver == "gram":
        assert np.allclose(f.sigma, s) and np.allclose(a.T @ a, np.eye(3), atol=1e-6)
        assert np.allclose((a * f.sigma) @ f.columns.T @ f.columns, full @ f.columns)


def test_library_solver_agrees(spark, planted):
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    codes, _ = planted
    x = P.image(codes, [2] * 120)
    s = RowMatrix(x.rdd.map(lambda r: Vectors.dense(r.x))).computeSVD(3).s
    assert np.allclose(L.spectral_factors(x, 120, 3).sigma, s.toArray())


@pytest.mark.parametrize("cluster", ["kmeans", "threshold"])
def test_planted_labels_are_found(spark, planted, cluster):
    codes, v = planted
    x = kept(P.image(codes, [2] * 120), "x")
    lat = L.spectral_latents(x, 120, 3, 3, n_components="k", cluster=cluster, init="k-means||", theta=0.6 if cluster == "threshold" else 0)
    both = codes.select("row_id", F.col("u").alias("truth")).join(lat.rows, "row_id")
    if cluster == "kmeans":
        assert E.label_error(both, "truth", "u") == 0
        assert E.assignment_error([(int(a), int(b), 1) for a, b in zip(v, lat.columns, strict=True)]) == 0
    else:
        direct = np.array([r.a for r in L.spectral_factors(x, 120, 3).rows.orderBy("row_id").collect()])
        want = L.threshold_labels(direct, 0.6)
        got = {r.row_id: r.u for r in lat.rows.collect()}
        assert E.assignment_error([(int(want[i]), int(u), 1) for i, u in got.items()]) == 0


def test_subsampled_factors_lose_little(spark, planted):
    codes, _ = planted
    x = kept(P.image(codes, [2] * 120), "x")
    lat = L.spectral_latents(x, 120, 3, 3, n_components="k", fraction=0.5, init="k-means||")
    both = codes.select("row_id", F.col("u").alias("truth")).join(lat.rows, "row_id")
    assert E.label_error(both, "truth", "u") <= 0.05


def test_sampling_by_length_keeps_the_spectrum(spark, planted):
    codes, _ = planted
    x = kept(P.image(codes, [2] * 120), "x")
    full, part = L.spectral_factors(x, 120, 2), L.spectral_factors(x, 120, 2, fraction=0.6, sampling="length")
    assert np.allclose(full.sigma, part.sigma, rtol=0.15)
    assert abs(full.columns[:, 0] @ part.columns[:, 0]) > 0.98


def test_degenerate_sizes(spark, planted):
    codes, _ = planted
    x = kept(P.image(codes, [2] * 120, "scaled"), "x")
    lat = L.spectral_latents(x, 120, 1, 120)
    assert {r.u for r in lat.rows.collect()} == {0} and (lat.columns == np.arange(120)).all()
    assert len(L.kmeans_small(np.zeros((5, 2)), 3)) == 5


@pytest.mark.parametrize("coder", ["rans", "zstd", "lz"])
@pytest.mark.parametrize("order", ["row", "col"])
def test_round_trip(spark, planted, coder, order):
    codes, v = planted
    box = C.compress(codes, [2] * 120, v, coder, order=order, pack="bits", chunk_rows=100)
    back = C.decompress(box, 100)
    assert J.multiset_equal(codes.select("row_id", "codes"), back)
    assert box.blocks.agg(F.sum("n_symbols")).first()[0] == 240 * 120
    some = C.decompress(box, 100, only=[3, 50]).orderBy("row_id").collect()
    full = codes.orderBy("row_id").collect()
    assert all(a.codes == [b.codes[3], b.codes[50]] for a, b in zip(some, full, strict=True))


def test_relabelling_leaves_sizes(spark, planted):
    codes, v = planted
    a = C.compress(codes, [2] * 120, v)
    b = C.compress(codes.withColumn("u", 2 - F.col("u")), [2] * 120, (v + 1) % 3)
    assert a.bits["blocks"] == b.bits["blocks"] and a.coded_bits == pytest.approx(b.coded_bits, rel=1e-3)


def test_container(spark, planted):
    from blockpress.sources import container as S

    codes, v = planted
    box = C.compress(codes, [2] * 120, v)
    path = new_path(spark, "container")
    S.write_container(box, path)
    again = S.read_container(spark, path)
    assert J.multiset_equal(codes.select("row_id", "codes"), C.decompress(again))
    assert again.coded_bits == box.coded_bits
    assert [r.codes for r in S.read_columns(spark, path, [7]).orderBy("row_id").collect()] == [[r.codes[7]] for r in codes.orderBy("row_id").collect()]
    want = {r.row_id for r in codes.collect() if r.codes[7] == 1}
    assert {r.row_id for r in S.rows_with_code(again, 7, 1).collect()} == want
    assert C.size_breakdown(box).count() == 6


def test_latents_win_where_there_is_structure(spark):
    """The experiments' shape: with labels each coder does better, and the frequency coder best of all."""
    codes, cards, truth = W.sbm(spark, 0.1, 0.9, 3, 300, 300, 5)
    w = W.Workload("drawn", codes, cards, (3, 3), (3, 3), truth, "bits")
    drr = {r[1]: r[9] for r in W.measure(w, ("lz", "lz_c", "ans_table", "latent_lz", "latent_ans"), 1, n_components="k", init="k-means||")}
    assert drr["latent_ans"] > max(drr["lz"], drr["lz_c"], drr["ans_table"]) + 0.2
    assert drr["latent_lz"] > drr["lz"] + 0.1
    opt, fs, _ = T.sbm_rates(0.1, 0.9, 3, 1)
    assert abs(drr["latent_ans"] - (1 - opt)) < 0.07 and abs(drr["ans_table"] - (1 - fs)) < 0.02


def test_labels_gain_nothing_without_structure(spark):
    codes, cards, _ = W.sbm(spark, 0.3, 0.3, 3, 200, 200, 5)
    w = W.Workload("flat", codes, cards, (3, 3), (3, 3), None, "bits")
    drr = {r[1]: r[9] for r in W.measure(w, ("ans_table", "latent_ans"), 1)}
    assert abs(drr["latent_ans"] - drr["ans_table"]) < 0.06


def test_search_includes_no_labels(spark, planted):
    codes, _ = planted
    x = kept(P.image(codes, [2] * 120), "x")
    f = L.spectral_factors(x, 120, 3)
    f.rows = kept(f.rows, "rows")
    rows = C.search_latents(codes.select("row_id", "codes"), f, 120, [2] * 120, [3], [3]).collect()
    assert {(r.k_r, r.k_c) for r in rows} == {(a, b) for a in (1, 3) for b in (1, 3, 120)}
    assert min(rows, key=lambda r: r.rank).k_r == 3


def test_bits_back_and_refinement(spark, planted):
    codes, v = planted
    got = C.bits_back_savings(codes, [2] * 120, v)
    assert 0 <= got["saved_bits"] < 0.02 * got["label_bits"]  # labels are certain: nothing comes back
    spoilt = codes.withColumn("u", F.when(F.col("row_id") % 10 == 0, (F.col("u") + 1) % 3).otherwise(F.col("u")))
    mended = C.refine_labels(spoilt, [2] * 120, v, 2).join(codes.select("row_id", F.col("u").alias("truth")), "row_id")
    assert mended.where("u <> truth").count() == 0
    assert C.compress_reordered(codes, [2] * 120, v).coded_bits > 0


def test_models(spark):
    drawn, v = models.sample_sbm(spark, 0.2, 0.7, 3, 400, 100, 9)
    hist = E.block_histogram(E.with_labels(kept(drawn, "m"), v.tolist()))
    fit = models.fit_model(hist, 2)
    assert np.abs(fit.q - T.symmetric_binary(0.2, 0.7, 3).q).max() < 0.08
    assert models.sample_iid(spark, [0.5, 0.5], 1000).agg(F.avg("code")).first()[0] == pytest.approx(0.5, abs=0.06)


def test_components(spark):
    edges = [(k, k + 1) for k in range(1, 40)] + [(100, 101), (101, 102), (102, 100), (7, 7), (200, 7), (None, 3)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{k: 1 for k in range(1, 41)}, 200: 1, 100: 100, 101: 100, 102: 100}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_match_statistics(spark):
    codes, _, _ = W.sbm(spark, 0.05, 0.9, 3, 200, 10, 1)
    seq = codes.groupBy(F.lit(0).cast("long").alias("seq_id")).agg(F.array_sort(F.collect_list(F.struct("row_id", "codes"))).alias("r"))
    found = kept(M.phrases(seq.select("seq_id", F.flatten(F.transform("r", lambda s: s["codes"].cast("array<int>"))).alias("codes"))), "phrases")
    stats = {r.kind: r for r in M.match_stats(found, 10).collect()}
    assert stats["literal"].phrases == 2 and sum(r.symbols for r in stats.values()) == 2000
    assert M.lz_bits(found, 2000, 2).first().bits > 0
    assert M.recovery_failure(spark.createDataFrame([(0.0, 0.0), (0.1, 0.0)], "err_u double, err_v double")) == 0.5


def test_joins(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 1, 2), ("b", 9, 3)], "k string, t int, id int")
    right = spark.createDataFrame([("a", 2, 20), ("a", 5, 50), ("a", 7, 70)], "k string, t int, v int")
    assert {(r.id, r.v) for r in J.asof(left, right, "k", "t", ["v"]).collect()} == {(1, 50), (2, None), (3, None)}
    spans = spark.createDataFrame([(0, 0, 10), (1, 5, 6), (2, 9, 30)], "s int, lo int, hi int")
    hit = J.interval(left, spans, F.col("t"), F.col("lo"), F.col("hi"), 4)
    assert {(r.id, r.s) for r in hit.collect()} == {(1, 0), (1, 1), (2, 0), (3, 0), (3, 2)}
    assert J.per_group(left, "k", [F.col("t")], 1).count() == 2
    assert not J.multiset_equal(left, left.unionAll(left.limit(1)))


def test_sql_functions(spark):
    from blockpress.functions.register import register_functions

    register_functions(spark)
    r = spark.sql("SELECT h2(0.5D) AS h, elias_gamma_bits(8) AS g, elias_delta_bits(8) AS d, plain_bits(10, 5) AS p, lz_bits(array(0, 1, 0, 1, 0, 1, 1)) AS l, zstd_bits(X'00000000') AS z").first()
    assert (r.h, r.g, r.d, r.p, r.l) == (1.0, 7, 8, 30, 7) and r.z > 0
    assert spark.sql("SELECT * FROM lz_phrases(array(0, 1, 0, 1, 0, 1, 1))").count() == 4


def test_streams(spark, small):
    from blockpress.streaming import stream as S

    events = spark.read.parquet(f"{small}/events.parquet").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    where = new_path(spark, "events")
    newest = events.agg(F.expr("percentile_approx(ts, array(0.33, 0.67))")).first()[0]
    for part in (F.col("ts") < newest[0], (F.col("ts") >= newest[0]) & (F.col("ts") < newest[1]), F.col("ts") >= newest[1]):  # one after the other: files are read by their time of writing
        events.where(part).coalesce(1).write.mode("append").parquet(where)
    book = P.fit_codebook(events.select("event_type"))
    book.columns[0].values.pop()  # one type is new to the codebook
    live = S.coded(S.read_stream(spark, where, events), book, ["event_id", "user_id", "ts"])
    got = S.run_to_table(S.windowed_counts(live, "ts", "1 day", "10 days"), "append")
    batch = P.encode_table(events, book, ["ts"])
    days = {r.d: (r.n, r.m) for r in batch.groupBy(F.window("ts", "1 day").start.alias("d")).agg(F.count("*").alias("n"), F.sum((F.element_at("codes", 1) < 0).cast("int")).alias("m")).collect()}
    seen = {r.start: (r.n, r.unseen) for r in got.collect()}
    assert seen and all(days[d] == x for d, x in seen.items())
    boxes = {}

    def write(df, k):
        numbered = P.assign_row_ids(df.where("unseen = 0").select("event_id", "codes"), ["event_id"])
        boxes[k] = C.compress(numbered.select("row_id", F.lit(0).alias("u"), "codes"), book.cards, np.zeros(1, int))

    S.compress_batches(S.coded(S.read_stream(spark, where, events), book, ["event_id"]), write)
    assert len(boxes) == 3 and sum(b.labels.count() for b in boxes.values()) == batch.where(F.element_at("codes", 1) >= 0).count()
    once = S.run_to_table(S.deduplicated(S.read_stream(spark, where, events), ["event_id"], "ts", "1 day"))
    assert once.count() == events.count()
    sessions = S.run_to_table(S.session_counts(S.read_stream(spark, where, events), "ts", "user_id", "1 hour", "10 days"))
    assert sessions.count() > 0


@pytest.mark.parametrize("name", ["flat", "neighbours", "ratings", "words", "network"])
def test_workloads(spark, small, name):
    w = W.build(spark, small, name)
    n = {"flat": 11, "neighbours": 10, "ratings": 101, "words": 200, "network": 200}[name]
    assert w.n == n
    r = w.codes.agg(F.count("*").alias("m"), F.min(F.size("codes")).alias("a"), F.max(F.size("codes")).alias("b"), F.max("row_id").alias("top")).first()
    assert r.a == r.b == n and r.top == r.m - 1


def test_order_matters_to_the_dictionary_coder_alone(spark, small):
    here = {r.method: r.drr for r in W.report(spark, small, ["neighbours"], ("lz", "ans_column"), 1).collect()}
    mixed = {r.method: r.drr for r in W.report(spark, small, ["neighbours"], ("lz", "ans_column"), 1, shuffled=True).collect()}
    assert here["lz"] > mixed["lz"] + 0.1 and abs(here["ans_column"] - mixed["ans_column"]) < 0.01


def test_kmeans_fits_on_all_rows(spark, monkeypatch):
    """A cluster too small for a sample of the rows is found."""
    monkeypatch.setattr(L, "FIT_ROWS", 20, raising=False)
    rows = [(k, [100.0 if k < 4 else (k % 7) / 100]) for k in range(600)]
    got = {r.row_id: r.u for r in L.kmeans_rows(spark.createDataFrame(rows, "row_id long, a array<double>"), 2).collect()}
    assert all(got[k] == (k < 4) for k in range(600))


def test_network_takes_all_documents(spark, small, monkeypatch):
    """Whatever their ids, and in one block or in several."""
    where = new_path(spark, "later")
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    docs.withColumn("doc_id", F.col("doc_id") + 5000).write.parquet(f"{where}/documents.parquet")
    monkeypatch.setattr(W, "PAIR_BLOCK", 60, raising=False)
    codes, cards = W.network(spark, where)
    sets = {}
    for r in W.frequent_words(docs).collect():
        sets.setdefault(r.doc_id, set()).add(r.word)
    ids = sorted(r.doc_id for r in docs.select("doc_id").collect())
    none = set()
    want = {i: [int(a != b and len(sets.get(a, none) & sets.get(b, none)) >= 0.3 * len(sets.get(a, none) | sets.get(b, none)) > 0) for b in ids] for i, a in enumerate(ids)}
    assert len(cards) == len(ids) and {r.row_id: r.codes for r in codes.collect()} == want


def test_coder_ablation_takes_all_rows(spark, small):
    """The frequency coder's size is that of the whole table."""
    from blockpress import queries as Q

    where = new_path(spark, "later")
    docs = spark.read.parquet(f"{small}/documents.parquet")
    docs.withColumn("doc_id", F.col("doc_id") + 150).write.parquet(f"{where}/documents.parquet")
    rows = kept(Q._labelled_words(spark, where), "words")
    want = C.compress(rows, [2] * 200, np.array(Q.WORD_GROUPS), "rans", "rans", pack="bits").coded_bits
    assert {r.coder: r.coded_bits for r in Q.coder_ablation(spark, where).collect()}["rans"] == want


def test_container_needs_nothing_but_its_segments(spark, planted):
    """Row numbers with gaps, labels coded by each coder, plain code where that is shorter, and damage found."""
    codes, v = planted
    gaps = codes.withColumn("row_id", F.col("row_id") * 7 + 3)
    for coder in ("rans", "zstd", "lz"):
        box = C.compress(gaps, [2] * 120, v, coder, pack="bits", chunk_rows=500, fallback=True)
        again = C.Container(kept(box.segments, "again"), [2] * 120)
        assert J.multiset_equal(gaps.select("row_id", "codes"), C.decompress(again))
        assert again.coded_bits == box.coded_bits == box.segments.agg(F.sum(8 * F.length("payload"))).first()[0]
    broken = box.segments.withColumn("payload", F.when(F.col("segment") == "blocks", F.expr("concat(payload, x'00')")).otherwise(F.col("payload")))
    with pytest.raises(Exception, match="damaged"):
        C.decompress(C.Container(kept(broken, "broken"), [2] * 120)).collect()


def test_never_worse_than_raw(spark):
    """Coin flips under many labels: the fallback sends the table plain, and it comes back."""
    codes = kept(spark.range(300).select(F.col("id").alias("row_id"), F.transform(F.sequence(F.lit(0), F.lit(19)), lambda j: (F.abs(F.xxhash64("id", j)) % 2).cast("smallint")).alias("codes")), "flips").withColumn("u", (F.col("row_id") % 9).cast("int"))
    box = C.compress(codes, [2] * 20, np.arange(20) % 6, "rans", fallback=True)
    assert box.plain and box.bits["blocks"] == 300 * 20 and box.coded_bits <= 300 * 20 + 8 * (C.HEADER.size + 8)
    assert J.multiset_equal(codes.select("row_id", "codes"), C.decompress(box))


def test_sizes_in_one_pass_are_those_of_containers(spark, planted):
    codes, v = planted
    rows = codes.select("row_id", F.array("u").alias("us"), "codes")
    for coder in ("rans", "zstd"):
        for order in ("row", "col"):
            want = C.compress(codes, [2] * 120, v, coder, order=order).bits
            got = C.coded_sizes(rows, [2] * 120, [C.Coding("x", coder, tuple(v.tolist()), 0, order)])[0]
            assert got == pytest.approx(want)


def test_starts_of_kmeans_in_one_scan(spark):
    """Three far clusters are found from any start whose centres fall into all of them; equal specs agree; one label is one label."""
    rng = np.random.default_rng(0)
    at = np.repeat([[0.0, 0.0], [9.0, 0.0], [0.0, 9.0]], [50, 30, 20], axis=0) + rng.normal(0, 0.3, (100, 2))
    rows = spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(at)], "row_id long, a array<double>")
    specs = [(3, 2, s) for s in range(6)] + [(1, 1, 0), (3, 2, 0)]
    got = {r.row_id: r.us for r in L.kmeans_many(rows, specs).collect()}
    us = np.array([got[i] for i in range(100)])
    truth = np.repeat([0, 1, 2], [50, 30, 20])
    assert any((us[:, s] == truth).all() for s in range(6)) and (us[:, 6] == 0).all() and (us[:, 0] == us[:, 7]).all()


def test_late_rows_are_counted_and_kept(spark):
    """A batch of older rows behind the mark: out of the windows, in the count, in the container's rows; a second run changes nothing."""
    from blockpress.streaming import stream as S

    times = ["2024-01-05 10:00:00", "2024-01-05 11:00:00", "2024-01-01 10:00:00", "2024-01-05 09:30:00"]
    df = spark.createDataFrame([(i, t, "a") for i, t in enumerate(times)], "event_id long, t string, kind string").selectExpr("event_id", "cast(t as timestamp) ts", "kind")
    where = new_path(spark, "late")
    for ids in ((0, 1), (2, 3)):
        df.where(F.col("event_id").isin(*ids)).coalesce(1).write.mode("append").parquet(where)
    live = S.coded(S.read_stream(spark, where, df, 1), P.fit_codebook(df.select("kind")), ["event_id", "ts"])
    got = S.run_windows(live, "ts", "1 day", 86400.0)
    late = got["late"].agg(F.sum("n")).first()[0]
    timely = got["windows"].agg(F.sum("n")).first()[0]
    assert timely + late == 4 and got["rows"].count() == 4
    assert late in (0, 1)  # which file comes first is the file system's to say


def test_links_are_counted_over_blocks_by_class(spark, monkeypatch):
    """Copies, empty sets, words of one document alone, dense and rare words, in many blocks and tiles: the same as brute force."""
    monkeypatch.setattr(W, "PAIR_BLOCK", 13)
    monkeypatch.setattr(W, "TILE_CELLS", 60)
    monkeypatch.setattr(W, "LIST_COST", 6)
    rng = np.random.default_rng(3)
    sets = [sorted({f"w{int(x)}" for x in rng.zipf(1.3, rng.integers(1, 25)) if x < 60}) for _ in range(80)]
    sets += [[], [], ["alone"], *[sets[4]] * 9, sets[7], ["alone too", "w1"]]
    ids = [5000 - 3 * k for k in range(len(sets))]
    df = spark.createDataFrame(list(zip(ids, sets)), "doc_id long, words array<string>")
    alike = lambda a, b: bool(a) and bool(b) and len({*a} & {*b}) >= 0.3 * len({*a} | {*b})
    want = {i: (min(j for j, b in zip(ids, sets) if a == b), sum(i != j and alike(a, b) for j, b in zip(ids, sets))) for i, a in zip(ids, sets)}
    assert {r.doc_id: (r.class_id, r.n_links) for r in W.link_counts(df, 0.3).collect()} == want
    pairs = {(r.src, r.dst) for r in W.jaccard_pairs(df.select("doc_id", F.explode("words").alias("word")), 0.3).collect()}
    assert pairs == {(i, j) for i, a in zip(ids, sets) for j, b in zip(ids, sets) if i < j and alike(a, b)}


def test_searches_take_every_fiftieth_document(spark, small, monkeypatch):
    """The likest of the documents asked for, over all documents and in several blocks, are those that the whole search gives."""
    monkeypatch.setattr(W, "PAIR_BLOCK", 70)
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    whole = {(r.src, r.dst) for r in W.top_documents(docs).collect()}
    assert {(r.src, r.dst) for r in W.top_documents(docs, every=50).collect()} == {e for e in whole if e[0] % 50 == 0}
    assert len(whole) == 10 * docs.count()


def test_supplier_degrees_need_no_table(spark, small, monkeypatch):
    """The degrees come from the links; a table as wide as there are suppliers is not made for them."""
    from blockpress import queries as Q

    codes, _ = W.supplier_network(spark, small, 29)
    want = {r.row_id: sum(r.codes) for r in codes.collect()}
    monkeypatch.setattr(W, "dense", None)
    assert {r.row_id: r.degree for r in Q.supplier_degrees(spark, small).collect()} == want


def test_dense_rows_come_in_small_batches(spark, monkeypatch):
    """Wide rows leave a task a few at a time."""
    monkeypatch.setattr(W, "TILE_CELLS", 100)
    rows = spark.createDataFrame([(k, [k % 30]) for k in range(40)], "row_id long, at array<int>").coalesce(1)
    seen = []
    real = W.pa.record_batch
    ones = {r.row_id: r.codes for r in W.dense(rows, 30).collect()}
    assert all(c == [int(j == k % 30) for j in range(30)] for k, c in ones.items()) and len(ones) == 40

    class Frame:
        def mapInArrow(self, emit, schema):
            seen.extend(b.num_rows for b in emit([real([W.pa.array(range(40)), W.pa.array([[k % 30] for k in range(40)], W.pa.list_(W.pa.int32()))], names=["row_id", "at"])]))

    W.dense(Frame(), 30)
    assert max(seen) == 3 and sum(seen) == 40


def test_planted_cells_are_hashed_together(spark, small, monkeypatch):
    """Heads of hashes as hashlib has them, whatever the lengths, and the histogram of the cells one by one, in tiles."""
    import hashlib

    from blockpress.operators import models as M

    for prefix in (b"42|7|", b"42|12|", b"1|1234567|", b"42|90071992547409931|"):
        for tails in (["1", "8"], ["10", "99"], ["123456", "000000", "999999"], ["1234567890123456789"]):
            want = [int(hashlib.md5(prefix + t.encode()).hexdigest()[:8], 16) for t in tails]
            assert M.md5_heads(prefix, M.tail_words(tails), len(tails[0])).tolist() == want
    monkeypatch.setattr(M, "HASH_TILE", 37)
    from blockpress.operators.entropy import block_histogram

    key = lambda df: {(r.u, r.v, r.code): r.cnt for r in df.collect()}
    assert key(M.planted_histogram(spark, small)) == key(block_histogram(M.planted_on_keys(spark, small)))


def test_planted_bits_are_the_planted_rows(spark, small):
    """Cells packed to bits are those drawn one by one, and so are the factors and products made from them."""
    from blockpress.operators import models as M
    from blockpress.operators.cells import unpacked

    bits, v = M.planted_bits(spark, small)
    rows, by_key = M.planted_rows(spark, small)
    bits, rows = kept(bits, "bits"), kept(rows, "rows")
    n = len(v)
    ones = lambda df, v: {r.row_id: (r.u, [sum(c for c, k in zip(r.codes, v, strict=True) if k == j) for j in range(6)], sum(r.codes)) for r in df.collect()}
    assert ones(unpacked(bits, n), v.tolist()) == ones(rows, by_key.tolist())
    x = P.image(unpacked(bits, n), [2] * n)
    packed = bits.select("row_id", F.col("codes").alias("x"))
    few = F.when(F.col("row_id") % 60 == 0, F.col("codes")).otherwise(F.lit(bytes(-(-n // 8))))  # a hundredth ones, most rows without any
    sparse = bits.select("row_id", few.alias("codes"))
    basis = np.random.default_rng(1).standard_normal((n, 4))
    a = lambda df: {r.row_id: r.a for r in df.collect()}
    for left, right in ((packed, x), (sparse.withColumnRenamed("codes", "x"), P.image(unpacked(sparse, n), [2] * n))):
        assert np.allclose(L.transposed_product(left, basis), L.transposed_product(right, basis))
        assert np.allclose(L.gram(left, n), L.gram(right, n))
        one, two = a(L.project(left, basis)), a(L.project(right, basis))
        assert one.keys() == two.keys() and all(np.allclose(one[k], two[k]) for k in one)


def test_packed_tables_are_sized_like_lists(spark):
    """A wide 0/1 table by bits: packing, sizes of all codings and each column's own as containers have them."""
    n, m = 1500, 90
    ones = spark.range(m).select(F.col("id").alias("row_id"), F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.pmod(F.xxhash64("id", j), F.lit(97)) < 1 + F.pmod(j, F.lit(5))).alias("at"))
    lists, bits = kept(W.dense(ones, n), "lists"), kept(W.packed(ones, n), "bits")
    assert J.multiset_equal(W.unpacked(bits, n), lists)
    v, u = np.arange(n) % 5, (F.col("row_id") % 3).cast("int")
    one, own = (0,) * n, tuple(v.tolist())
    codings = [C.Coding("a", "rans", tuple(range(n))), C.Coding("b", "rans", own, 0), C.Coding("c", "zstd", own, 0), C.Coding("d", "zstd", one, order="col"), C.Coding("e", "rans", tuple(range(n)), 0)]
    got = [C.coded_sizes(df.select("row_id", F.array(u).alias("us"), "codes"), [2] * n, codings) for df in (lists, bits)]
    want = [C.compress(lists.withColumn("u", u if c.which == 0 else F.lit(0)), [2] * n, np.array(c.columns), c.coder, order=c.order).bits for c in codings]
    for c, a, b, w in zip(codings, *got, want, strict=True):
        assert a == b == pytest.approx(w), c.name


def test_first_of_a_row_by_ids(spark):
    """The greatest cells of each row with ties by id, as a full sort has them, and vectors' neighbours one by one."""
    rng = np.random.default_rng(5)
    for m, n, k in ((7, 40, 10), (5, 10, 10), (4, 3, 10), (6, 50, 1)):
        like, ids = rng.integers(0, 4, (m, n)) / 4, rng.permutation(n)
        row, col = W._first(like, ids, k)
        want = [(i, int(j)) for i in range(m) for j in np.lexsort((ids, -like[i]))[:k]]
        assert list(zip(row.tolist(), col.tolist(), strict=True)) == want
    x = rng.integers(-2, 3, (60, 3)).astype(float)
    vectors = spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(x)], "doc_id long, vector array<double>")
    unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    like = np.round(unit @ unit.T, 9)
    want = {(i, int(j)) for i in range(60) for j in [j for j in np.lexsort((np.arange(60), -like[i])) if j != i][:10]}
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(W, "VECTOR_BLOCK", 16)
        assert {(r.src, r.dst) for r in W.top_embeddings(vectors).collect()} == want


def test_rows_are_encoded_as_by_expressions(spark, small):
    """Numbers, dates, times, texts and nulls of every kind, seen and unseen, have the codes that ``encode_table`` gives."""
    import datetime as dt
    from decimal import Decimal

    kind = "k long, small int, text string, flag boolean, day date, time timestamp, price double, cost decimal(9,2), many double, gap int"
    day = lambda i: dt.date(1960, 1, 1) + dt.timedelta(days=900 * (i % 30))
    rows = [(i, i % 5, f"t{i % 7}", i % 3 == 0, day(i), dt.datetime(2020, 1, 1 + i % 9, 5), (i % 4 - 1) * 0.1, Decimal(i % 6), (i * 37 % 600) / 7, None if i % 2 else 5) for i in range(600)]
    none = [(1000 + i, *[None if i == j else x for j, x in enumerate(rows[i][1:])]) for i in range(9)]
    new = [(2000, 99, "new", True, dt.date(1999, 9, 9), dt.datetime(1999, 1, 1), 7.5, Decimal(77), float("nan"), 6), (2001, -1, "", None, None, None, -0.0, None, float("inf"), None)]
    df = spark.createDataFrame(rows, kind)
    for fitted, seen in ((df, rows + none + new), (spark.createDataFrame(rows + none, kind), rows + none + new)):
        book = P.fit_codebook(fitted.drop("k"))
        asked = spark.createDataFrame(seen, kind)
        want = {r.k: r.codes for r in P.encode_table(asked, book, ["k"]).collect()}
        assert {r.k: r.codes for r in P.encode_rows(asked, book, "k").collect()} == want and len(want) == len(seen)


def test_a_table_is_built_once(spark, small, monkeypatch):
    """Reports on one table in two ways fit its codes once, and say what two reports say."""
    from blockpress import queries as Q

    built, real = [], W.fit_codebook
    want = sorted(map(tuple, W.report(spark, small, ["neighbours"]).collect() + W.report(spark, small, ["neighbours"], shuffled=True).collect()))
    monkeypatch.setattr(W, "fit_codebook", lambda *a, **k: built.append(1) or real(*a, **k))
    got = sorted(map(tuple, Q.latent_report_neighbours(spark, small).collect()))
    assert len(built) == 1 and [r[:3] for r in got] == [r[:3] for r in want]
    assert np.allclose([r[7] for r in got], [r[7] for r in want], rtol=1e-6)


def test_indicators_are_spread_from_codes(spark, small, monkeypatch):
    """F16: the wide table is sorted and coded by its narrow columns, and is what one of indicator columns is; nulls too."""
    df, made = W.with_indicators(W.star(spark, small))
    names = [*W.NUMBERS, *made, "l_returnflag"]
    want, cards = W._tabular(df.select(names), names)
    sorted_, real = [], W.assign_row_ids
    monkeypatch.setattr(W, "assign_row_ids", lambda d, *a, **k: sorted_.append(len(d.columns)) or real(d, *a, **k))
    got, own = W.wide_55(spark, small)
    assert own == cards and max(sorted_) < 20
    assert J.multiset_equal(got.select("row_id", "codes"), want.select("row_id", "codes"))
    plain = spark.createDataFrame([(i, None if i % 4 == 0 else "abc"[i % 3], None if i % 5 == 0 else "x", i % 2) for i in range(60)], "row_id long, p string, q string, n int")
    book = P.fit_codebook(plain.drop("row_id"))
    got, wide = W.spread(P.encode_rows(plain, book, "row_id"), book, ["p", "q"])
    shown = plain.select("row_id", *[(F.col(c) == v).cast("int").alias(f"is_{c}_{k}") for c, vs in (("p", "abc"), ("q", "x")) for k, v in enumerate(vs)], "n")
    want = P.fit_codebook(shown.drop("row_id"))
    assert wide == want and J.multiset_equal(got, P.encode_table(shown, want, ["row_id"]))


def test_labels_need_no_image_and_no_join(spark, small, monkeypatch):
    """F3, F8: starts are fitted on packed points, rows are labelled where they are; centres begin at the different points that come first by hash of their least row."""
    at = np.array([[0.0, 0.0], [9.0, 0.0], [0.0, 9.0], [9.0, 9.0]])
    for times in (1, 3000):  # few rows; and more equal ones than a task draws
        points = np.repeat(at, times, axis=0)
        rows = spark.createDataFrame(pd.DataFrame({"row_id": np.arange(len(points)), "a": points.tolist()}))
        starts = L.kmeans_starts(rows.select("row_id", F.col("a").cast("array<double>").alias("a")), [(4, 2, 7), (1, 1, 7)], iterations=1)
        assert sorted(map(tuple, starts.centres[0].tolist())) == sorted(map(tuple, at.tolist()))
        assert sorted(starts.labels(at)[:, 0].tolist()) == [0, 1, 2, 3] and (starts.labels(at)[:, 1] == 0).all()
    written = []
    for module in (W, L, C, P):
        real = module.kept
        monkeypatch.setattr(module, "kept", lambda df, name, *a, real=real: written.append(name) or real(df, name, *a))
    w = W.build(spark, small, "transactions", True)
    rows, _ = W.labels_of_runs(w, [w.k_ans], 2)
    assert rows.count() == w.codes.count() and not {"image", "labelled", "shuffled", "different-points"} & set(written)
    us = {r.row_id: r.us for r in rows.collect()}
    factors = L.spectral_factors(w.codes.select("row_id", F.col("codes").alias("x")), w.n, 2)
    joined = {r.row_id: r.us for r in L.kmeans_many(factors.rows, [(3, 2, 100), (3, 2, 101)]).collect()}
    assert us == joined


def test_codebook_takes_one_summary(spark, monkeypatch):
    """F3, F8: values and the stretches around quantiles come from one scan; odd columns from the sketches still."""
    x = F.xxhash64("id")
    df = spark.range(5000).repartition(5).select(x.alias("a"), (F.pmod(x, F.lit(7)) - 3).cast("int").alias("b"), F.when(F.col("id") % 3 > 0, x % 1000 / 7.0).alias("c"), F.pmod(x, F.lit(9)).cast("string").alias("d"), x.cast("string").alias("e"), (x % 2 == 0).alias("f"), F.date_add(F.lit("1960-01-01"), F.pmod(x, F.lit(20000)).cast("int")).alias("g"), F.timestamp_seconds(F.pmod(x, F.lit(10**9))).alias("h"), F.timestamp_seconds(F.pmod(x, F.lit(3))).alias("i"), F.lit(None).cast("int").alias("k"), F.when(F.col("id") % 2 == 0, float("nan")).otherwise(1.5).alias("n"))
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(P, "summaries", lambda *a: {})
        want = P.fit_codebook(df)
    monkeypatch.setattr(P, "SUMMARY_RANKS", 50)
    monkeypatch.setattr(P, "SUMMARY_ROWS", 700)
    assert str(P.fit_codebook(df)) == str(want)
    assert want.dropped == ["e", "n"] and [c.kind for c in want.columns] == list("QCQCCQQCC")
    calls, real = [], F.percentile_approx
    monkeypatch.setattr(F, "percentile_approx", lambda *a: calls.append(a) or real(*a))
    P.fit_codebook(df.drop("n"))
    assert not calls


def test_network_of_words_has_no_row_for_each_link(spark, monkeypatch):
    """bits of block pairs make the table that its links make; copies, documents without words and single blocks too."""
    texts = [" ".join(f"w{(i * 7 + j) % 23 if i % 9 else j}" for j in range(i % 13)) for i in range(150)]
    docs = spark.createDataFrame([(1000 - 3 * i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    edges = W.jaccard_pairs(W.document_words(docs), 0.3)
    want, cards = W.adjacency(edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), docs)
    want = {r.row_id: bytes(r.codes) for r in want.collect()}
    monkeypatch.setattr(W, "jaccard_pairs", lambda *a: pytest.fail("a row for each link"))
    monkeypatch.setattr(W, "read", lambda *a: docs)
    for block, tile in ((8192, 1 << 21), (32, 150 * 16)):
        monkeypatch.setattr(W, "PAIR_BLOCK", block)
        monkeypatch.setattr(W, "TILE_CELLS", tile)
        codes, n = W.document_network(spark, "", 0.3)
        assert n == cards and {r.row_id: bytes(r.codes) for r in codes.collect()} == want
    assert any(any(x) for x in want.values())


@pytest.mark.parametrize("name", ["network", "network_suppliers"])
def test_networks_are_measured_as_bits(spark, small, monkeypatch, name):
    """no list of codes is made for the results table, whose sizes are those of the lists."""
    import dataclasses

    one = W.build(spark, small, name, bits=True)
    lists = dataclasses.replace(one, codes=kept(W.unpacked(one.codes, one.n), "lists"))
    methods = ("lz", "lz_c", "ans_table", "ans_column")
    want = W.measure(lists, methods, 1)
    for f in ("dense", "unpacked"):
        monkeypatch.setattr(W, f, lambda *a: pytest.fail("lists of codes"))
    monkeypatch.setattr(W, "jaccard_pairs", lambda *a: pytest.fail("a row for each link"))
    assert [tuple(r) for r in W.report(spark, small, [name], methods, 1).collect()] == want


def test_blocks_of_sets_are_not_written_for_their_pairs(spark, monkeypatch):
    """a block is kept once; the plan that compares blocks has no exchange of them."""
    monkeypatch.setattr(W, "PAIR_BLOCK", 10)
    words = [(k, [f"w{(k * j) % 17}" for j in range(1, 2 + k % 6)]) for k in range(100)]
    df = spark.createDataFrame(words, "doc_id long, words array<string>")
    whole = sorted(W.link_counts(df, 0.3).collect())
    monkeypatch.setattr(W, "BLOCK_WORDS", 12)
    monkeypatch.setattr(W, "TILE_CELLS", 30)
    monkeypatch.setattr(W, "OPEN_BLOCKS", 2)
    text = df.select("doc_id", F.array_join("words", ", ").alias("text"), (F.col("doc_id") % 3).cast("string").alias("lang"))
    assert sorted(W.link_counts(text, 0.3).collect()) == sorted(W.link_counts(df, 0.3).collect()) == whole
    plans, real = [], W._met
    monkeypatch.setattr(W, "_met", lambda *a: plans.append(real(*a)) or plans[-1])
    W.link_counts(df, 0.3)
    plan = plans[0]._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan


def test_nearest_documents_over_blocks_and_stretches(spark, monkeypatch):
    """Ties, copies, texts without words, other languages and words of one document, in many blocks and stretches: the same as brute force."""
    monkeypatch.setattr(W, "SEARCH_BLOCK", 13)
    monkeypatch.setattr(W, "HELD_WORDS", 90)
    monkeypatch.setattr(W, "TILE_CELLS", 60)
    monkeypatch.setattr(W, "LIST_COST", 6)
    rng = np.random.default_rng(8)
    texts = [" ".join(f"W{int(x)}" for x in rng.zipf(1.3, rng.integers(1, 25)) if x < 60) for _ in range(60)]
    texts += [None, "", " ,.", "alone", *[texts[4]] * 14, texts[7], "alone-too\tw1|W1"]
    ids = [5000 - 3 * k for k in range(len(texts))]
    langs = [None if k % 11 == 0 else "ab"[k % 2] for k in range(len(texts))]
    sets = [{w for w in re.split(r"[ \n\t.,;:!?|]+", (t or "").lower()) if w} for t in texts]
    want = set()
    for i, a in zip(ids, sets, strict=True):
        like = sorted((-len(a & b) / max(1, len(a | b)), j) for j, b in zip(ids, sets, strict=True) if i != j)
        want |= {(i, j) for _, j in like[:10]}
    df = spark.createDataFrame(list(zip(ids, texts, langs, strict=True)), "doc_id long, text string, lang string").repartition(3, "doc_id")
    for docs in (df, df.drop("lang")):
        assert {(r.src, r.dst) for r in W.nearest_documents(docs).collect()} == want
    monkeypatch.setattr(W, "MARKED_WORDS", 0)
    assert {(r.src, r.dst) for r in W.nearest_documents(df).collect()} == want


def test_few_ones_give_the_sizes_and_factors_of_all_cells(spark, monkeypatch):
    """A packed table with few ones: sizes, counts and products by the ones' places are those of the cells."""
    rng = np.random.default_rng(2)
    m, n = 90, 131
    cells = (rng.random((m, n)) < 0.01).astype(np.uint8)
    cells[:3] = rng.random((3, n)) < 0.4  # stretches with many ones too
    us = rng.integers(0, 3, (m, 2))
    rows = [(i, us[i].tolist(), bytearray(np.packbits(cells[i]).tobytes())) for i in range(m)]
    df = spark.createDataFrame(rows, "row_id long, us array<int>, codes binary")
    v = tuple(int(x) for x in rng.integers(0, 4, n))
    none, each = (0,) * n, tuple(range(n))
    codings = [C.Coding("a", "zstd", none), C.Coding("b", "zstd", v, 1, "col"), C.Coding("c", "rans", none), C.Coding("d", "rans", each), C.Coding("e", "rans", v, 0), C.Coding("f", "zstd", v, 0)]
    monkeypatch.setattr(C, "CHUNK_CELLS", 20 * n)
    monkeypatch.setattr(C, "FEW_ONES", 1 << 40)
    want = C.coded_sizes(df, [2] * n, codings)
    monkeypatch.setattr(C, "FEW_ONES", 5)
    assert C.coded_sizes(df, [2] * n, codings) == want
    x = df.select("row_id", F.col("codes").alias("x"))
    monkeypatch.setattr(L, "SPARSE", 0.05)
    monkeypatch.setattr("blockpress.operators.cells.SLICE_CELLS", 10 * n)
    held, basis = L.by_ones(x, n), rng.standard_normal((n, 4))
    assert set(held.columns) == {"ids", "sizes", "places", "bits"} and 0 < held.where("bits is null").count() < held.count()
    assert np.allclose(L.transposed_product(held, basis), cells.T.astype(float) @ (cells @ basis))
    assert all(np.allclose(r.a, cells[r.row_id] @ basis) for r in L.project(held, basis).collect())
