"""Block histograms, plug-in entropies and ideal code sizes, as grouped aggregations.

Once the histogram ``(u, v, code, cnt)`` exists, everything here costs as many rows as it has.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.functions.bits import elias_gamma_bits, share_bits


def block_histogram(long: DataFrame, row_label: str | Column = "u", col_label: str | Column = "v") -> DataFrame:
    """Counts of each code under each pair of labels. ``long`` has one row a cell, with both labels."""
    u = F.col(row_label) if isinstance(row_label, str) else row_label
    v = F.col(col_label) if isinstance(col_label, str) else col_label
    return long.groupBy(u.alias("u"), v.alias("v"), "code").agg(F.count("*").alias("cnt"))


def with_labels(codes: DataFrame, col_labels: list[int]) -> DataFrame:
    """Cells of ``codes(row_id, u, codes)`` with their labels; column labels are a constant of the plan."""
    v = F.array(*[F.lit(x) for x in col_labels])
    return codes.select("row_id", "u", F.posexplode("codes").alias("col_id", "code")).withColumn("v", F.element_at(v, F.col("col_id") + 1))


def conditional_entropy(hist: DataFrame, given: list[str], symbol: list[str] | None = None, count: str = "cnt") -> DataFrame:
    """One row: entropy of the symbol in bits given the columns named, by empirical counts."""
    symbol = symbol or ["code"]
    cell = hist.groupBy(*given, *symbol).agg(F.sum(count).alias("c"))
    total = F.sum("c").over(Window.partitionBy(*[F.col(g) for g in given])) if given else None
    cell = cell.withColumn("t", total) if given else cell.crossJoin(cell.agg(F.sum("c").alias("t")))
    return cell.agg((F.sum(share_bits("c", "t")) / F.sum("c")).alias("entropy"))


def plugin_entropies(hist: DataFrame) -> DataFrame:
    """H(X), H(X|U), H(X|V), H(X|U,V) by empirical counts, in one row."""
    out = None
    for name, given in (("h_x", []), ("h_x_u", ["u"]), ("h_x_v", ["v"]), ("h_x_uv", ["u", "v"])):
        one = conditional_entropy(hist, given).select(F.col("entropy").alias(name))
        out = one if out is None else out.crossJoin(one)
    return out


def entropy_cube(hist: DataFrame) -> DataFrame:
    """``u, v, gid, n, entropy``: entropy of the codes for each label pair, label, and overall, in one pass."""
    cube = hist.cube("u", "v", "code").agg(F.sum("cnt").alias("c"), F.grouping_id().alias("g")).where("g % 2 = 0")
    t = F.sum("c").over(Window.partitionBy("g", "u", "v"))
    rows = cube.withColumn("t", t)
    return rows.groupBy("u", "v", (F.col("g") / 2).cast("int").alias("gid")).agg(F.sum("c").alias("n"), (F.sum(share_bits("c", "t")) / F.sum("c")).alias("entropy"))


def ideal_sizes(hist: DataFrame, by: list[str], counts_as: str = "long") -> DataFrame:
    """Frequency-coder size of each portion: ideal code bits and the cost of sending its counts."""
    cell = hist.groupBy(*by, "code").agg(F.sum("cnt").alias("c"))
    t = F.sum("c").over(Window.partitionBy(*by))
    send = F.lit(64) if counts_as == "long" else elias_gamma_bits("c")
    rows = cell.withColumn("t", t).withColumn("code_bits", share_bits("c", "t")).withColumn("count_bits", send)
    return rows.groupBy(*by).agg(F.sum("c").alias("n"), F.sum("code_bits").alias("code_bits"), F.sum("count_bits").alias("count_bits"))


def tv_distances(hist: DataFrame) -> DataFrame:
    """``u, v, u2, v2, tv``: total variation between the laws of each two blocks of a histogram, over any symbols."""
    law = hist.withColumn("p", F.col("cnt") / F.sum("cnt").over(Window.partitionBy("u", "v"))).select("u", "v", "code", "p")
    sides = [law.groupBy("u", "v").agg(F.map_from_entries(F.collect_list(F.struct("code", "p"))).alias("p")).select(F.col("u").alias(f"u{e}"), F.col("v").alias(f"v{e}"), F.col("p").alias(f"p{e}")) for e in ("", "2")]
    pairs = sides[0].join(sides[1], (F.col("u") < F.col("u2")) | ((F.col("u") == F.col("u2")) & (F.col("v") < F.col("v2"))))  # a row for each block
    each = F.map_zip_with("p", "p2", lambda k, a, b: F.abs(F.coalesce(a, F.lit(0.0)) - F.coalesce(b, F.lit(0.0))))
    return pairs.select("u", "v", "u2", "v2", (F.aggregate(F.map_values(each), F.lit(0.0), lambda s, x: s + x) / 2).alias("tv"))


def label_sizes(labels: DataFrame, label: str) -> DataFrame:
    """One row: ideal bits of the labels and of their counts."""
    hist = labels.groupBy(F.col(label).alias("code")).agg(F.count("*").alias("cnt")).withColumn("side", F.lit(label))
    return ideal_sizes(hist, ["side"])


def label_error(truth_and_estimate: DataFrame, truth: str, estimate: str) -> float:
    """Share of rows that the best relabelling gets wrong; the contingency table alone reaches the driver."""
    pairs = truth_and_estimate.groupBy(truth, estimate).agg(F.count("*").alias("c")).collect()
    return assignment_error([(r[0], r[1], r.c) for r in pairs])


def assignment_error(pairs: list[tuple]) -> float:
    """As ``label_error``, of (truth, estimate, count)."""
    import numpy as np

    rows, cols = sorted({p[0] for p in pairs}, key=str), sorted({p[1] for p in pairs}, key=str)
    if not pairs:
        return 0.0
    n = max(len(rows), len(cols))
    gain = np.zeros((n, n))
    for t, e, c in pairs:
        gain[rows.index(t), cols.index(e)] += c
    return float(1 - best_assignment(gain) / gain.sum())


def best_assignment(gain) -> float:
    """Most that a one-to-one assignment of rows to columns can gain: shortest augmenting paths."""
    import numpy as np

    cost = gain.max() - gain
    n = len(cost)
    u, v, match = np.zeros(n + 1), np.zeros(n + 1), np.zeros(n + 1, int)
    for i in range(1, n + 1):
        match[0], j0 = i, 0
        least, used, way = np.full(n + 1, np.inf), np.zeros(n + 1, bool), np.zeros(n + 1, int)
        while True:
            used[j0] = True
            i0, free = match[j0], np.flatnonzero(~used)
            slack = cost[i0 - 1, free - 1] - u[i0] - v[free]
            better = slack < least[free]
            least[free[better]] = slack[better]
            way[free[better]] = j0
            j1 = free[np.argmin(least[free])]
            delta = least[j1]
            u[match[used]] += delta
            v[used] -= delta
            least[~used] -= delta
            j0 = j1
            if match[j0] == 0:
                break
        while j0:
            match[j0] = match[way[j0]]
            j0 = way[j0]
    return float(sum(gain[match[j] - 1, j - 1] for j in range(1, n + 1)))


def ngram_entropy(seqs: DataFrame, codes: str, size: int) -> DataFrame:
    """One row: entropy in bits of the windows of ``size`` codes that lie within a row, and per symbol."""
    last = F.size(codes) - size + 1
    at = F.when(last >= 1, F.sequence(F.lit(1), last)).otherwise(F.array().cast("array<int>"))
    grams = seqs.select(F.explode(F.transform(at, lambda i: F.array_join(F.slice(codes, i, size).cast("array<string>"), ","))).alias("code"))
    hist = grams.groupBy("code").agg(F.count("*").alias("cnt"))
    return conditional_entropy(hist, []).select("entropy", (F.col("entropy") / size).alias("per_symbol"))
