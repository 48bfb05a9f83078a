"""Connected components of a link table, by alternating large-star and small-star rounds on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.llm.common import materialise, release

#: Links that one task holds while rounds run; small tables take few tasks, large ones as many as they need.
LINKS_PER_TASK = 250_000


def connected_components(links: DataFrame, max_rounds: int = 40, settle: bool = True) -> DataFrame:
    """node, component (the smallest node reachable) for every node of ``links`` (columns a, b: comparable ids).

    A node with very many links meets them through a partial aggregate and a join that can be split, never in one
    group; each round is written to the shared folder, so a lost executor costs one round. Rounds grow with the logarithm of
    the longest path. With ``settle=False`` it stops after ``max_rounds``: labels are then sound (equal labels are connected) but
    may tell connected nodes apart. Null ids and self links are ignored; no links give no rows.
    """
    edges = materialise(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter(F.col("u") != F.col("v")).distinct())
    before, tasks = None, max(8, edges.count() // LINKS_PER_TASK)
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("_m")).select("u", F.least("u", "_m").alias("m"))
        large = both.filter(F.col("v") > F.col("u")).join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter(F.col("u") != F.col("v"))
        small = large.withColumn("m", F.min("v").over(Window.partitionBy("u")))
        small = small.select(F.inline(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v"))))).filter(F.col("u") != F.col("v")).distinct()
        last, edges = edges, materialise(small.coalesce(tasks))
        release(last)
        now = tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()) if settle else None
        if settle and now == before:
            break
        before = now
    else:
        if settle:
            raise RuntimeError("components did not settle")
    if not settle:
        return edges.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component"))
    heads = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(heads)
