"""The prompt pool: deduplication of equal texts and a stable draw. Near duplicates are among the optional operators (``prompt_neardup``)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def dedup(docs: DataFrame, level: str = "exact") -> DataFrame:
    """prompt_id (the smallest id of equal texts) and n_copies; one partial aggregation by digest, no text is shuffled."""
    text = {"exact": F.col("text"), "normalised": F.trim(F.lower("text"))}[level]
    return docs.select("doc_id", F.md5(text).alias("_d")).groupBy("_d").agg(F.min("doc_id").alias("prompt_id"), F.count("*").alias("n_copies")).drop("_d")


def draw(prompts: DataFrame, n: int, seed: int) -> DataFrame:
    """n prompts in the order of a seeded digest: the same on any partitioning and engine. The sort is a bounded top-n."""
    order = F.md5(F.concat(F.lit(f"{seed}:"), F.col("prompt_id").cast("string")))
    top = prompts.withColumn("_o", order).orderBy("_o", "prompt_id").limit(n)
    return top.withColumn("place", F.row_number().over(Window.orderBy("_o", "prompt_id"))).drop("_o")  # n rows
