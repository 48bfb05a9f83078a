"""Expert routes of tokens: routing, replay and its baseline, freezing."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def centroids(vectors: DataFrame, dims: int = 64) -> DataFrame:
    """expert, centre: mean vector of each label, computed dimension by dimension with partial aggregation."""
    long = vectors.select(F.col("label").alias("expert"), F.posexplode("embedding").alias("d", "x"))
    means = long.groupBy("expert", "d").agg(F.avg(F.col("x").cast("double")).alias("x"))
    return means.groupBy("expert").agg(F.transform(F.array_sort(F.collect_list(F.struct("d", "x"))), lambda s: s["x"]).alias("centre"))


def route(vectors: DataFrame, experts: DataFrame, k: int = 1, step: int | None = None) -> DataFrame:
    """vec_id, expert, place (from 1): the k experts of largest inner product; ``step`` rounds the centres to 1/step first.

    The expert table is a handful of rows by configuration and is broadcast.
    """
    centre = F.col("centre") if step is None else F.transform("centre", lambda x: F.round(x * step) / step)
    e = experts.select("expert", centre.alias("centre"))
    s = vectors.select("vec_id", "embedding").crossJoin(F.broadcast(e))
    s = s.withColumn("score", F.round(F.aggregate(F.zip_with("embedding", "centre", lambda a, b: a * b), F.lit(0.0), lambda acc, x: acc + x), 9))
    w = Window.partitionBy("vec_id").orderBy(F.desc("score"), "expert")
    return s.withColumn("place", F.row_number().over(w)).filter(F.col("place") <= k).select("vec_id", "expert", "place")


def replay(tokens: DataFrame, recorded: DataFrame) -> DataFrame:
    """The actor takes the recorded experts: a join on the token, nothing is routed anew."""
    return tokens.join(recorded, "vec_id")


def mismatch(recorded: DataFrame, again: DataFrame) -> DataFrame:
    """Tokens whose first expert differs."""
    b = again.select("vec_id", F.col("expert").alias("again"), "place")
    return recorded.join(b, ["vec_id", "place"]).filter("place = 1").agg(F.count("*").alias("n_tokens"), F.sum((F.col("expert") != F.col("again")).cast("long")).alias("n_changed"))


def update(experts: DataFrame, gradient: float, freeze: bool) -> DataFrame:
    """Router weights after a step: untouched when frozen, whether or not routes are replayed."""
    return experts if freeze else experts.withColumn("centre", F.transform("centre", lambda x: x - gradient * x))
