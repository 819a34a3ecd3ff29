"""Connected components of an undirected graph by alternating star contractions.

Each round rewires every node to the least node it knows, first from the larger neighbours' side,
then from the smaller ones'; rounds grow with the logarithm of the longest chain. Rounds are cut by
tables in shared storage, so a lost executor costs a task and not the lineage; a round's tables go when
the next one stands.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpress.sources.storage import discard, kept


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges(a, b)`` of longs in; ``(node, component)`` out, the least node of its component.

    Loops and repeated edges do no harm; edges with a null end are ignored; nodes without an edge to
    another node do not appear; no edges: no rows.
    """
    now = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now, print_ = kept(now, "edges"), None
    for _ in range(max_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = kept(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")), "low")
        wide = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        wide = kept(wide, "large-star")
        least = kept(wide.groupBy("u").agg(F.min("v").alias("m")), "low")
        near = wide.join(least, "u")
        after = near.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        after = kept(after, "small-star")
        discard(now, low, wide, least)
        now = after
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen == print_:
            break
        print_ = seen
    else:
        raise RuntimeError("components did not settle")
    stars = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
