"""Exact length histogram of encoded documents, with suffix sums that answer questions for every context limit."""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.llm.common import materialise, pieces
from trajkit.llm.tokens_bpe import encoder, parts

#: Lengths are prefix-summed in ranges of this many, so that no window spans the whole histogram.
RANGE = 64


def encoded_lengths(docs: DataFrame, extra_ids: int = 1, json_file: str = "byte_bpe_50k.json") -> DataFrame:
    """n_tokens, n_docs: documents by encoded length, counted within each task first, then added up.

    The length counts ``extra_ids`` for the end marker. Null or empty text has that length alone.
    """

    def count(batches):
        encode, found = encoder(json_file), Counter()
        for batch in pieces(batches):
            found.update(sum(len(encode(p)) for p in parts(x.as_py() or "")) + extra_ids for x in batch.column(0))
        yield pa.RecordBatch.from_pydict({"n_tokens": pa.array(list(found), pa.int64()), "n_docs": pa.array(list(found.values()), pa.int64())})

    return docs.select("text").mapInArrow(count, "n_tokens long, n_docs long").groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))


def with_sums(histogram: DataFrame) -> DataFrame:
    """Adds, for each length L taken as a context limit: docs_longer, tokens_longer (suffix sums over lengths > L),
    docs_upto, tokens_upto, truncated_tokens = sum(min(length, L)), lost_tokens and the share of documents kept whole.

    Two levels: sums by range of lengths, then within a range.
    """
    h = histogram.withColumn("_range", F.floor(F.col("n_tokens") / RANGE)).withColumn("_tokens", F.col("n_tokens") * F.col("n_docs"))
    totals = h.groupBy("_range").agg(F.sum("n_docs").alias("_d"), F.sum("_tokens").alias("_t"))
    after = Window.orderBy(F.col("_range").desc()).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    totals = totals.select(
        "_range", F.coalesce(F.sum("_d").over(after), F.lit(0)).alias("_d_after"), F.coalesce(F.sum("_t").over(after), F.lit(0)).alias("_t_after"),
        F.sum("_d").over(whole).alias("_docs"), F.sum("_t").over(whole).alias("_all"),
    )
    inside = Window.partitionBy("_range").orderBy(F.col("n_tokens").desc()).rowsBetween(Window.unboundedPreceding, -1)
    h = h.join(totals, "_range")
    h = h.withColumn("docs_longer", F.col("_d_after") + F.coalesce(F.sum("n_docs").over(inside), F.lit(0)))
    h = h.withColumn("tokens_longer", F.col("_t_after") + F.coalesce(F.sum("_tokens").over(inside), F.lit(0)))
    return h.select(
        "n_tokens", "n_docs", (F.col("_docs") - F.col("docs_longer")).alias("docs_upto"), "docs_longer",
        (F.col("_all") - F.col("tokens_longer")).alias("tokens_upto"), "tokens_longer",
        (F.col("_all") - F.col("tokens_longer") + F.col("n_tokens") * F.col("docs_longer")).alias("truncated_tokens"),
        (F.col("tokens_longer") - F.col("n_tokens") * F.col("docs_longer")).alias("lost_tokens"),
        F.round((F.col("_docs") - F.col("docs_longer")) / F.col("_docs"), 6).alias("share_whole"),
    )


def token_counts(docs: DataFrame, extra_ids: int = 1) -> DataFrame:
    """One row per encoded length that occurs, ascending in meaning: totals, cumulated counts and truncated totals.

    Empty table: no rows. Null text: an empty document. Repeated rows count each. Other columns are ignored. The texts are
    encoded once: the histogram, which the sums read twice, is written to the shared folder first.
    """
    return with_sums(materialise(encoded_lengths(docs, extra_ids)))


def for_limits(sums: DataFrame, limits: list[int]) -> DataFrame:
    """The same answers for context limits that aren't lengths of the table: each takes the next shorter length's sums."""
    spark = sums.sparkSession
    asked = spark.createDataFrame([(int(x),) for x in limits], "context_limit long")
    base = sums.agg(F.sum("n_docs").alias("_docs"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("_all"))
    near = asked.join(sums, F.col("n_tokens") <= F.col("context_limit"), "left").groupBy("context_limit").agg(F.max_by(F.struct("docs_upto", "tokens_upto"), "n_tokens").alias("s"))
    near = near.crossJoin(F.broadcast(base))  # one row of totals
    upto, tokens = F.coalesce(F.col("s.docs_upto"), F.lit(0)), F.coalesce(F.col("s.tokens_upto"), F.lit(0))
    return near.select("context_limit", upto.alias("docs_upto"), (F.col("_docs") - upto).alias("docs_longer"), (tokens + F.col("context_limit") * (F.col("_docs") - upto)).alias("truncated_tokens"))


def quantiles(sums: DataFrame, shares: list[float]) -> DataFrame:
    """share, n_tokens: the smallest length that at least this share of the documents doesn't exceed."""
    asked = sums.sparkSession.createDataFrame([(float(x),) for x in shares], "share double")
    return asked.join(sums, F.col("docs_upto") >= F.col("share") * (F.col("docs_upto") + F.col("docs_longer"))).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))
