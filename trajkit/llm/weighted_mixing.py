"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

Each document gets the key ``-ln(u) / w`` with ``u`` drawn from a hash of its id and ``w`` its
quality weight, so a good document tends to come early. Within a source the documents are
ordered by that key and their sizes are prefix-summed to the source's budget: complete epochs
first, then a fractional selection by key order.

No source is ever sorted in one task. Keys fall into ``BUCKETS`` monotone key ranges per
source; sums per (source, range) find the range that holds the budget's edge, and only the
documents of that one range are ordered exactly.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit.llm.common import WORD_PATTERN, materialise

#: Source weights in code point order, repeating, and the cap as a multiple of a source's size.
SOURCE_WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
BUCKETS = 4096
#: Above this many sources the target table is joined by shuffle on a salted key, not broadcast.
BROADCAST_SOURCES = 20_000
SALTS = 64


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def quality_weight(text: Column, size: Column) -> Column:
    """1 for clean prose, down to 1/5 where each word carries a symbol of [#*$%&|<>]."""
    symbols = F.coalesce(F.regexp_count(text, F.lit(r"[#*$%&|<>]")), F.lit(0))
    return F.lit(1.0) / (1.0 + 4.0 * F.least(F.lit(1.0), symbols / F.greatest(size, F.lit(1))))


def exponential_key(doc_id: Column, weight: Column) -> Column:
    """-ln(u)/weight; u is uniform in (0, 1) from 48 bits of md5(doc_id)."""
    bits = F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, 12), 16, 10).cast("double")
    return -F.log((bits + 0.5) / float(1 << 48)) / weight


def source_targets(sized: DataFrame) -> DataFrame:
    """source, source_size, target: weights 5, 2, 1 repeating in code point order (null last), shares of all sizes,
    capped at 3 times a source's size with the excess reshared by weight until none is above (water-filling).

    Works on one row per source; the only un-partitioned windows of this module are over these aggregates.
    """
    by = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    rank = F.row_number().over(Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))) - 1
    weights = F.array(*[F.lit(w) for w in SOURCE_WEIGHTS])
    by = by.withColumn("weight", F.get(weights, F.pmod(rank, F.lit(len(SOURCE_WEIGHTS))).cast("int")))
    by = by.withColumn("cap", F.col("source_size") * MAX_EPOCHS)
    # Sources reach their cap in the order of cap/weight; the level is the one at which the budget is spent.
    before = Window.orderBy(F.col("cap") / F.col("weight"), "weight", F.col("source").isNull(), F.col("source").cast("binary"))
    done = before.rowsBetween(Window.unboundedPreceding, -1)
    rest = before.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    total = F.sum("source_size").over(Window.partitionBy())
    level = (total - F.coalesce(F.sum("cap").over(done), F.lit(0))) / F.sum("weight").over(rest)
    by = by.withColumn("level", level).withColumn("total", total)
    # The first source whose cap lies above its level fixes the level of all later ones.
    by = by.withColumn("open", F.col("cap") > F.col("level") * F.col("weight"))
    final = F.first(F.when(F.col("open"), F.col("level")), ignorenulls=True).over(before.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    by = by.withColumn("final", final)
    target = F.when(F.col("final").isNull(), F.col("cap").cast("double")).otherwise(F.least(F.col("cap").cast("double"), F.col("final") * F.col("weight")))
    return by.select("source", "source_size", F.round(target, 6).alias("target"))


def _with_source(df: DataFrame, table: DataFrame, few: bool) -> DataFrame:
    """Join on source, null included: broadcast when the number of sources was checked, else salted against a hot source."""
    left = df.withColumn("_s", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n")))
    right = table.withColumn("_s", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))).drop("source")
    if few:
        return left.join(F.broadcast(right), "_s", "left").drop("_s")
    left = left.withColumn("_salt", F.pmod(F.xxhash64("_row"), F.lit(SALTS)))
    right = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return left.join(right, ["_s", "_salt"], "left").drop("_s", "_salt")


def mix(docs: DataFrame, boundary: str = "cut", weight: Column | None = None) -> DataFrame:
    """doc_id, size, source_size, target, taken, and ``copies`` (whole copies taken) for every row of ``docs``.

    ``boundary``: what happens to the document at the edge of a source's budget. "cut" takes its leading words
    so that the source meets its target to the word; "nearest" takes it whole iff that brings the sum closer.

    Null text: size 0, nothing taken. Null source: a source of its own, last. Null doc_id: kept, keyed as the
    empty string. Repeated rows are separate documents with equal keys. Empty table: empty result. Other columns
    are ignored. Reruns agree: keys depend on doc_id alone.
    """
    if boundary not in ("cut", "nearest"):
        raise ValueError(boundary)
    size = word_count(F.col("text"))
    base = docs.select("doc_id", "source", size.alias("size"), (weight if weight is not None else quality_weight(F.col("text"), size)).alias("_w"))
    base = base.withColumn("_key", exponential_key(F.col("doc_id"), F.col("_w"))).withColumn("_row", F.monotonically_increasing_id())
    base = base.withColumn("_bucket", F.least(F.floor((1.0 - F.exp(-F.col("_key"))) * BUCKETS), F.lit(BUCKETS - 1)).cast("int")).drop("_w")
    base = materialise(base)  # the texts are scanned once
    targets = materialise(source_targets(base))
    few = targets.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    # Budget left for the fractional epoch, and the key range in which it ends.
    sums = base.groupBy("source", "_bucket").agg(F.sum("size").alias("_sum"))
    w = Window.partitionBy("source").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("_before", F.coalesce(F.sum("_sum").over(w), F.lit(0)))
    sums = sums.withColumn("_row", F.col("_bucket"))
    t = targets.withColumn("_epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0))
    t = t.withColumn("_rest", F.round(F.col("target")).cast("long") - F.col("_epochs") * F.col("source_size"))
    edge = _with_source(sums, t.select("source", "_rest"), few).filter((F.col("_before") < F.col("_rest")) & (F.col("_before") + F.col("_sum") >= F.col("_rest")))
    edge = edge.select("source", F.col("_bucket").alias("_edge"), F.col("_before"))
    t = t.withColumn("_row", F.xxhash64("source"))
    table = _with_source(t, edge, few).drop("_row")
    out = _with_source(base, table, few)
    at_edge = F.col("_bucket") == F.coalesce(F.col("_edge"), F.lit(-1))
    # Only rows of the edge range are ordered; the others meet in small windows keyed by their own row.
    exact = out.filter(at_edge)
    order = Window.partitionBy("source", "_bucket").orderBy("_key", "doc_id", "size", "_row").rowsBetween(Window.unboundedPreceding, -1)
    exact = exact.withColumn("_left", F.col("_rest") - F.col("_before") - F.coalesce(F.sum("size").over(order), F.lit(0)))
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("_left")))
    if boundary == "nearest":
        part = F.when(2 * part >= F.col("size"), F.col("size")).otherwise(0)
    exact = exact.withColumn("_part", part).drop("_left")
    rest = out.filter(~at_edge).withColumn("_part", F.when(F.col("_bucket") < F.coalesce(F.col("_edge"), F.lit(0)), F.col("size")).otherwise(F.lit(0)))
    both = rest.unionByName(exact)
    return both.select(
        "doc_id", "size", "source_size", "target", (F.col("_epochs") * F.col("size") + F.col("_part")).cast("long").alias("taken"),
        (F.col("_epochs") + F.when((F.col("_part") == F.col("size")) & (F.col("size") > 0), 1).otherwise(0)).cast("int").alias("copies"), "source",
    )
