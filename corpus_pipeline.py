"""The corpus pipeline: stages over documents, each written as Parquet and read again as the next one's input.

All stages but the last return the columns of ``documents``. Toxic documents go; one document of each group of near
copies stays; secrets are masked; sources are mixed to target weights, whole documents repeated as often as the mix takes
them; the result is packed.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trajkit.llm import curve_packing, secret_scan, shingle_join, toxicity_grammar, weighted_mixing
from trajkit.llm.common import shared_folder


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the grammar scores at 0.3 or more go. Its stems are learned from the labels of ``sf_dir``."""
    return toxicity_grammar.drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by a shingle similarity of 0.75 stays: the smallest doc_id."""
    return shingle_join.keep_one(docs)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked in the text; no document goes."""
    return secret_scan.redacted(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: the whole epochs of its source, and once more if it is drawn.

    Rows are found again by id, source and size, nulls included; repeated rows get the same number of copies.
    """
    key = ["doc_id", "source", "_size"]
    taken = weighted_mixing.mix(docs.select("doc_id", "source", "text"), boundary="nearest").withColumnRenamed("size", "_size")
    taken = taken.filter("copies > 0").groupBy(*key).agg(F.max("copies").alias("_copies")).select(*[F.col(c).alias(f"_k_{c}") for c in key], "_copies")
    sized = docs.withColumn("_size", weighted_mixing.word_count(F.col("text")))
    same = [sized[c].eqNullSafe(taken[f"_k_{c}"]) for c in key]
    return sized.join(taken, same).withColumn("_n", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents, repeats included, in sequences of at most 2048 ids."""
    return curve_packing.pack(docs)


STAGES = [
    ("toxicity", toxicity),
    ("n-gram jaccard join", near_duplicates),
    ("secret scans", secrets),
    ("mixing sources to target weights", mixing),
    ("packing", packing),
]

#: Model scores and encoded ids can't be expressed in SQL; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order on the documents of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        path = f"{shared_folder(spark).rstrip('/')}/pipeline/{uuid.uuid4().hex}"
        out.write.option("compression", "zstd").parquet(path)
        docs = spark.read.parquet(path)
    return docs
