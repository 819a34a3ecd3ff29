"""Further queries: measures of the theory over grids, operators of the relational surface, SQL functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.functions import theory as T
from blockpress.functions.bits import h2
from blockpress.operators import entropy as E
from blockpress.operators import models as M
from blockpress.plans import encode as P
from blockpress.plans import workloads as W
from blockpress.queries import GRID, _labelled_words, _word_histogram, lineitem, measured_chances, query
from blockpress.sources.storage import kept

# preprocessing


@query
def null_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    """NULL as a symbol of its own: documents without a label, coded beside those with one."""
    docs, labels = W.read(spark, sf_dir, "documents").select("doc_id", "lang"), W.read(spark, sf_dir, "labels")
    df = docs.join(labels, "doc_id", "left").select("lang", "quality", "toxic")
    codes = P.encode_table(df.withColumn("row_id", F.lit(0).cast("long")), P.fit_codebook(df), ["row_id"])
    return P.code_counts(codes).select("col_id", "code", "cnt")


@query
def numeric_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Column sums of the four numeric images of order priority, status and part-of-year codes."""
    df = W.read(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderstatus")
    numbered = df.withColumnRenamed("o_orderkey", "row_id")
    book = P.fit_codebook(df.drop("o_orderkey"))
    codes = P.encode_table(numbered, book, ["row_id"])
    weights = [[float((3 * k + 1) % 7) for k in range(c)] for c in book.cards]
    out = None
    for psi in ("index", "scaled", "onehot", "mapping"):
        x = P.image(codes, book.cards, psi, weights)
        one = x.select(F.posexplode("x").alias("col_id", "v")).groupBy("col_id").agg(F.round(F.sum("v"), 4).alias("total")).withColumn("psi", F.lit(psi))
        out = one if out is None else out.unionByName(one)
    return out.select("psi", "col_id", "total")


@query
def raw_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Uncoded size of the line items in kilobytes and megabytes of 1,024."""
    df = lineitem(spark, sf_dir)
    book, m = P.fit_codebook(df), df.count()
    rows = [(unit, P.raw_size(book.cards, m, unit)) for unit in ("KB", "MB")]
    return spark.createDataFrame(rows, "unit string, s double").select("unit", F.round("s", 4).alias("size"))


# entropies


@query
def block_entropy_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of the cells given both labels: block by block, and as cells times the conditional entropy."""
    hist = kept(_word_histogram(spark, sf_dir), "hist")
    blocks = E.ideal_sizes(hist, ["u", "v"]).agg(F.sum("code_bits").alias("b"), F.sum("n").alias("n"))
    return blocks.crossJoin(E.conditional_entropy(hist, ["u", "v"])).select(F.round("b", 3).alias("by_blocks"), F.round(F.col("n") * F.col("entropy"), 3).alias("by_entropy"))


@query
def fitted_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plug-in block laws of the word table under given labels, with the labels' own laws."""
    model = M.fit_model(_word_histogram(spark, sf_dir), 2)
    rows = [(u, v, x, float(p), float(model.row[u]), float(model.col[v])) for (u, v, x), p in np.ndenumerate(model.q)]
    df = spark.createDataFrame(rows, "u int, v int, code int, p double, r double, c double")
    return df.select("u", "v", "code", F.round("p", 6).alias("p"), F.round("r", 6).alias("row_share"), F.round("c", 6).alias("col_share"))


@query
def entropy_aggregate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of the ship month given the return flag, by the grouped aggregate function."""
    from blockpress.functions.register import entropy_bits

    df = lineitem(spark, sf_dir).select("l_returnflag", F.month("l_shipdate").alias("code")).groupBy("l_returnflag", "code").agg(F.count("*").alias("cnt"))
    return df.groupBy("l_returnflag").agg(F.round(entropy_bits("cnt"), 6).alias("entropy"))  # counts, a dozen a group


@query
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The registered functions from SQL text: whole-number codes, plain and frequency-coder sizes, bits as rows."""
    from blockpress.functions.register import register_functions

    register_functions(spark)
    W.read(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).createOrReplaceTempView("orders_each")
    return spark.sql(
        "SELECT n, customers, gamma_bits, delta_bits, plain, ones_of_five FROM (SELECT n, count(*) AS customers, max(elias_gamma_bits(n)) AS gamma_bits, "
        "max(elias_delta_bits(n)) AS delta_bits, max(plain_bits(n, 5)) AS plain FROM orders_each GROUP BY n) CROSS JOIN (SELECT sum(b.bit) AS ones_of_five FROM bits(x'05') AS b)"
    )


# theory over grids


@query
def fano_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits that label estimates leave open, a label: those that take each line number's return flag for its commonest, with their error as measured."""
    flags = lineitem(spark, sf_dir).groupBy(F.col("l_linenumber").alias("line"), "l_returnflag").agg(F.count("*").alias("c"))
    errors = flags.groupBy("line").agg(F.round(1 - F.max("c") / F.sum("c"), 6).alias("err")).collect()  # a row a line number
    rows = [(r.line, r.err, k, T.label_slack(r.err, k)) for r in errors for k in (2, 3, 5, 8)]
    return spark.createDataFrame(rows, "line int, err double, k int, s double").select("line", "err", "k", F.round("s", 6).alias("slack"))


@query
def ideal_rates_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy sandwich, reachable rate and floor of symmetric binary tables under chances measured on the line items, at a label error of a hundredth."""
    rows = []
    for line, p0, p1, k in [(*c, k) for c in measured_chances(spark, sf_dir) for k in (3, 5, 7)]:
        model = T.symmetric_binary(p0, p1, k)
        lo, hi = T.entropy_sandwich(model, 1000, 500, 0.01, 0.01)
        rows.append((line, p0, p1, k, lo, hi, *T.ideal_rate_bounds(model, 1000, 500, 0.01, 0.01), T.n_parameters(k, 2), T.shape_exponent(1000, 500)))
    df = spark.createDataFrame(rows, "line int, p0 double, p1 double, k int, a double, b double, c double, d double, parameters int, e double")
    return df.select("line", "p0", "p1", "k", F.round("a", 6).alias("lower"), F.round("b", 6).alias("upper"), F.round("c", 6).alias("reachable"), F.round("d", 6).alias("floor"), "parameters", F.round("e", 6).alias("alpha"))


@query
def spectral_conditions_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signal, size and noise of symmetric binary tables, whether recovery is promised, and the model's three inequalities."""
    rows = []
    for p0, p1, k, _ in sorted(set((*g[:3], 1.0) for g in GRID)):
        for n in (1000, 100_000):
            c = T.spectral_conditions(T.symmetric_binary(p0, p1, k), [0, 1], 2 * n, n, 0.5, 1.0)
            rows.append((p0, p1, k, n, c["mu"], c["nu"], c["sigma"], c["ok"], *T.sbm_region(p0, p1, 2 * n, n)))
    df = spark.createDataFrame(rows, "p0 double, p1 double, k int, n int, a double, b double, c double, promised boolean, dense boolean, apart boolean, strong boolean")
    return df.select("p0", "p1", "k", "n", F.round("a", 6).alias("mu"), F.round("b", 6).alias("nu"), F.round("c", 6).alias("sigma"), "promised", "dense", "apart", "strong")


@query
def latent_bound_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Upper bound of the latent scheme with the frequency coder, with and without the spectral step, under chances measured on the line items."""
    rows = []
    for line, p0, p1, k in [(*c, k) for c in measured_chances(spark, sf_dir) for k in (3, 5)]:
        for n in (1000, 10_000):
            model = T.symmetric_binary(p0, p1, k)
            rows.append((line, p0, p1, k, n, T.latent_rate_bound(model, n, n, "ans", 0.01), T.latent_rate_bound(model, n, n, "ans", spectral=True)))
    df = spark.createDataFrame(rows, "line int, p0 double, p1 double, k int, n int, a double, b double")
    return df.select("line", "p0", "p1", "k", "n", F.round("a", 6).alias("bound"), F.round("b", 6).alias("spectral_bound"))


@query
def enumerated_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entropy of tiny tables under laws measured on the line items by going over all of them, and what a table tells about its labels."""
    rows = []
    for line, p0, p1 in measured_chances(spark, sf_dir):
        model = T.symmetric_binary(p0, p1, 2)
        rows.append((line, p0, p1, T.table_entropy(model, 2, 2), T.table_label_information(model, 2, 2)))
    df = spark.createDataFrame(rows, "line int, p0 double, p1 double, a double, b double")
    return df.select("line", "p0", "p1", F.round("a", 6).alias("entropy"), F.round("b", 6).alias("information"))


@query
def concentration_constants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Constants of a table's concentration for symmetric binary laws measured on the line items, and the deviation bound at t = 3."""
    rows = []
    for line, p0, p1 in measured_chances(spark, sf_dir):
        model = T.symmetric_binary(p0, p1, 3)
        c = T.aep_constants(model)
        rows.append((line, p0, p1, *(float(c[x]) for x in ("ratio", "m1", "m2", "s", "s1", "s2")), float(T.aep_bound(model, 100, 50, 3.0))))
    df = spark.createDataFrame(rows, "line int, p0 double, p1 double, ratio double, m1 double, m2 double, s double, s1 double, s2 double, bound double")
    return df.select("line", "p0", "p1", *[F.round(c, 5).alias(c) for c in ("ratio", "m1", "m2", "s", "s1", "s2", "bound")])


@query
def equipartition_deviation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest deviation of drawn tiny tables' log-probability from their entropy, under laws measured on the line items: within the bound."""
    from blockpress.operators.measures import aep_deviation

    rows = [(line, p0, p1, *map(float, aep_deviation(T.symmetric_binary(p0, p1, 2), 3, 3, 200))) for line, p0, p1 in measured_chances(spark, sf_dir)]
    return spark.createDataFrame(rows, "line int, p0 double, p1 double, d double, b double").select("line", "p0", "p1", (F.col("d") <= F.col("b")).alias("within"))


@query
def injective_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best one-to-one code of the event types' empirical law, and the bound it cannot pass."""
    law = W.read(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("c")).collect()  # event types
    n = sum(r.c for r in law)
    p = [r.c / n for r in law]
    df = spark.createDataFrame([(T.injective_bound(p), T.shortest_one_to_one(p))], "b double, s double")
    return df.select(F.round("b", 6).alias("bound"), F.round("s", 6).alias("shortest"))


@query
def joint_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Joint law of symbol and labels of symmetric binary models, with chances measured on the line items."""
    rows = [(line, u, v, x, float(p)) for line, p0, p1 in measured_chances(spark, sf_dir) for (u, v, x), p in np.ndenumerate(T.symmetric_binary(p0, p1, 3).law())]
    return spark.createDataFrame(rows, "line int, u int, v int, x int, p double").select("line", "u", "v", "x", F.round("p", 6).alias("p"))


@query
def total_variation_general(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distance between the laws of ship months under each pair of return flag and line status: any alphabet."""
    df = lineitem(spark, sf_dir).groupBy(F.col("l_returnflag").alias("u"), F.col("l_linestatus").alias("v"), F.month("l_shipdate").alias("code")).agg(F.count("*").alias("cnt"))
    return E.tv_distances(df).select("u", "v", "u2", "v2", F.round("tv", 6).alias("tv"))


@query
def finite_state_machine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A run-length machine of two states on each customer's sequence of open and closed orders: code lengths."""
    from blockpress.coders.fsm import FiniteStateEncoder

    # after a zero a zero costs one bit and a one two; after a one the other way about
    machine = FiniteStateEncoder(2, {(0, 0): "0", (1, 0): "10", (0, 1): "10", (1, 1): "0"}, {(0, 0): 0, (1, 0): 1, (0, 1): 0, (1, 1): 1})
    assert machine.is_lossless(6) and not machine.is_degenerate()

    def lengths(batches):
        import pandas as pd

        for b in batches:
            yield pd.DataFrame({"o_custkey": b.o_custkey, "bits": [len(machine.encode(list(x))) for x in b.x]})

    o = W.read(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", (F.col("o_orderstatus") == "O").cast("int").alias("x"))
    seqs = o.groupBy("o_custkey").agg(F.transform(F.array_sort(F.collect_list(F.struct("o_orderkey", "x"))), lambda s: s["x"]).alias("x"))  # a customer's orders
    return seqs.mapInPandas(lengths, "o_custkey long, bits long")


@query
def lz_length_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequences of order priorities whose coded length is not that of their phrases: none."""
    from blockpress.coders import phrase_lz

    o = W.read(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", (F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("x"))
    seqs = o.groupBy("o_custkey").agg(F.transform(F.array_sort(F.collect_list(F.struct("o_orderkey", "x"))), lambda s: s["x"]).alias("codes"))  # a customer's orders

    def both(batches):
        import pandas as pd

        for b in batches:
            rows = []
            for x in map(list, b.codes):
                data, bits, plain = phrase_lz.encode(x, 5)
                by_phrases = phrase_lz.phrase_bits(phrase_lz.parse(x), len(x), 5)
                rows.append(bits == (min(by_phrases, len(x) * 3)) and -(-bits // 8) == len(data) and phrase_lz.decode(data, len(x), 5, plain) == x)
            yield pd.DataFrame({"same": rows})

    return seqs.mapInPandas(both, "same boolean").agg(F.count("*").alias("sequences"), F.count_if(~F.col("same")).alias("different"))


# relational surface


@query
def covariances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lineitem(spark, sf_dir).groupBy("l_returnflag").agg(F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("covariance"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("correlation"))


@query
def commonest_symbols(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most frequent mode symbol of each block: the ship month of each flag and status; ties by the smaller."""
    c = lineitem(spark, sf_dir).groupBy("l_returnflag", "l_linestatus", F.month("l_shipdate").alias("code")).agg(F.count("*").alias("cnt"))
    return c.groupBy("l_returnflag", "l_linestatus").agg(F.max_by("code", F.struct("cnt", -F.col("code"))).cast("long").alias("mode"), F.max("cnt").alias("cnt"))


@query
def range_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user in the hundred hours before each event."""
    e = W.read(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-360_000_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query
def set_intersections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with open and finished orders, with one kind alone, and with either."""
    o = W.read(spark, sf_dir, "orders")
    a, b = o.where("o_orderstatus = 'O'").select("o_custkey"), o.where("o_orderstatus = 'F'").select("o_custkey")
    kinds = (("intersect", a.intersect(b)), ("except", a.subtract(b)), ("union", a.union(b).distinct()), ("intersect_all", a.intersectAll(b)))
    out = None
    for kind, df in kinds:
        one = df.agg(F.count("*").alias("n")).withColumn("kind", F.lit(kind))
        out = one if out is None else out.unionByName(one)
    return out.select("kind", "n")


@query
def calendar_fields(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items by the calendar fields of the wide table, and the mean lag from order to shipment."""
    line, o = lineitem(spark, sf_dir), W.read(spark, sf_dir, "orders")
    both = line.join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    lag = F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))
    parts = (F.year, F.quarter, F.month, F.weekofyear)
    names = ("year", "quarter", "month", "week")
    return both.groupBy(*[f("l_shipdate").cast("long").alias(n) for f, n in zip(parts, names, strict=True)]).agg(F.count("*").alias("n"), F.round(F.avg(lag), 6).alias("lag"))


@query
def json_properties(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.sources.readers import json_fields

    e = json_fields(W.read(spark, sf_dir, "events").select("event_type", "props"), "props", "k int")
    return e.groupBy("event_type").agg(F.count("props_k").alias("n"), F.sum("props_k").cast("long").alias("k"))


@query
def closed_form_entropy_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Binary entropy by the column expression, from the mean chance of a one, with chances measured on the line items."""
    g = spark.createDataFrame([(*c, k) for c in measured_chances(spark, sf_dir) for k in (3, 5, 7)], "line int, p0 double, p1 double, k int")
    return g.select("line", "p0", "p1", "k", F.round(h2((F.col("k") - 1) / F.col("k") * F.col("p0") + F.col("p1") / F.col("k")), 6).alias("h"))
