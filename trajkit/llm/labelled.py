"""The bounded sample of labelled rows that the classifiers learn from."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Labelled rows that a classifier learns from at most; the choice is by a hash of the id.
SAMPLE_ROWS = 8000


def fold(doc_id, parts: int):
    """crc32 of the id as text, modulo ``parts``."""
    return F.pmod(F.crc32(doc_id.cast("string")), F.lit(parts))


def training_rows(docs: DataFrame, labels: DataFrame, column: str, parts: int, held_out: int, rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, text, label of at most ``rows`` labelled documents outside the held-out fold.

    Labels other than 0 and 1, null ids and repeated ids with different labels are left out. The label table is cut to
    ``rows`` before the join, so the broadcast side is bounded by that parameter. Where rows repeat an id, the least of their
    texts stands for it, so the result is bounded as well.
    """
    own = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(column).cast("int").alias("label")).filter("doc_id is not null and label in (0, 1)")
    own = own.filter(fold(F.col("doc_id"), parts) != held_out).groupBy("doc_id").agg(F.min("label").alias("label"), F.max("label").alias("_high")).filter("label = _high").drop("_high")
    own = own.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    return texts.join(F.broadcast(own), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text")).select("doc_id", "text", "label")


def one_row_per_text(rows: DataFrame) -> DataFrame:
    """Copies of a text teach once."""
    w = Window.partitionBy(F.md5("text"), "label").orderBy("doc_id")
    return rows.withColumn("_k", F.row_number().over(w)).filter("_k = 1").drop("_k")
