"""Experiences by reference: heavy columns are written where they arise, light rows travel, ranks reload what they are assigned."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.ranking import global_rank, with_range

NODES = 100


def build(docs: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """experience_id, group, reward, length, node and the heavy payload."""
    e = docs.select(F.col("doc_id").alias("experience_id"), F.col("source").alias("group_key"), F.length("text").cast("long").alias("length"), F.pmod("doc_id", F.lit(NODES)).cast("int").alias("node"), F.col("text").alias("payload"))
    if labels is not None:
        e = e.join(labels.select(F.col("doc_id").alias("experience_id"), F.col("quality").cast("double").alias("reward")), "experience_id", "left")
    return e


def reference() -> object:
    return F.struct(F.col("node").alias("node"), F.col("experience_id").alias("payload_id"), F.md5("payload").alias("digest"))


def light(experiences: DataFrame) -> DataFrame:
    """The row that travels: the payload is replaced by its reference."""
    return experiences.withColumn("ref", reference()).drop("payload")


def offload(experiences: DataFrame, store: str) -> DataFrame:
    """Writes payloads partitioned by producing node, without a shuffle, and returns the light rows."""
    experiences.select("node", F.col("experience_id").alias("payload_id"), F.md5("payload").alias("digest"), "payload").write.mode("overwrite").partitionBy("node").parquet(store)
    return light(experiences)


def reload(light_rows: DataFrame, store: str, rank: int | None = None) -> DataFrame:
    """Light rows of one rank (or all) with their payloads; the join prunes to the nodes that the references name."""
    rows = light_rows if rank is None else light_rows.filter(F.col("rank_id") == rank)
    payload = light_rows.sparkSession.read.parquet(store).select(F.col("node").cast("int").alias("node"), "payload_id", "digest", "payload")
    keyed = rows.withColumn("payload_id", F.col("ref.payload_id")).withColumn("digest", F.col("ref.digest"))
    return keyed.join(payload, ["node", "payload_id", "digest"]).drop("payload_id", "digest", "ref")


def gather_cost(experiences: DataFrame, reference_bytes: int = 48) -> DataFrame:
    """Bytes that pass one controller: all payloads if it gathers, references if it doesn't."""
    return experiences.agg(F.sum(F.octet_length("payload")).alias("gathered_bytes"), (F.count("*") * reference_bytes).alias("reference_bytes"))


def transfer(assigned: DataFrame, places: DataFrame, ranks: int) -> DataFrame:
    """Local and moved bytes by region, nation and node: a payload is local if its rank lives on its node's place."""
    moved = F.when(F.pmod("node", F.lit(ranks)) == F.col("rank_id"), 0).otherwise(F.col("length"))
    return assigned.withColumn("moved", moved).join(F.broadcast(places), "node").rollup("region", "nation", "node").agg(F.sum("length").alias("bytes"), F.sum("moved").alias("moved"))


def assign(light_rows: DataFrame, ranks: int, how: str = "serpentine", keep_groups: bool = False, window: list[str] | None = None) -> DataFrame:
    """Adds rank_id. serpentine: sorted by length, to and fro; lpt: longest first to the least loaded rank; round_robin; hash; prefix: in the order of ids, equal shares of cumulated length.

    ``keep_groups`` assigns whole groups by their total length. lpt runs per ``window`` on (id, length) rows only.
    """
    if keep_groups:
        g = light_rows.groupBy("group_key").agg(F.sum("length").alias("length")).withColumnRenamed("group_key", "experience_id")
        out = assign(g, ranks, how).select(F.col("experience_id").alias("group_key"), "rank_id")
        return light_rows.join(out, "group_key")  # one row a group, which grows with the data
    if how == "hash":
        return light_rows.withColumn("rank_id", F.pmod(F.conv(F.substring(F.md5(F.col("experience_id").cast("string")), 1, 8), 16, 10).cast("long"), F.lit(ranks)))
    if how == "round_robin":
        return global_rank(light_rows, F.col("experience_id"), []).withColumn("rank_id", F.pmod(F.col("rank") - 1, F.lit(ranks))).drop("rank")
    if how == "serpentine":
        k = F.pmod(F.col("rank") - 1, F.lit(2 * ranks))
        return global_rank(light_rows, F.col("length"), ["experience_id"], descending=True).withColumn("rank_id", F.when(k < ranks, k).otherwise(2 * ranks - 1 - k)).drop("rank")
    if how == "prefix":
        parts = with_range(light_rows, F.col("experience_id"))
        sums = parts.groupBy("_part").agg(F.sum("length").alias("_s"))
        shift = F.coalesce(F.sum("_s").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a range
        sums = sums.select("_part", shift.alias("_shift")).crossJoin(sums.agg(F.sum("_s").alias("_total")))
        inside = F.coalesce(F.sum("length").over(Window.partitionBy("_part").orderBy("experience_id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        share = F.floor((F.col("_shift") + inside) * ranks / F.greatest("_total", F.lit(1)))
        return parts.join(F.broadcast(sums), "_part").withColumn("rank_id", F.least(share, F.lit(ranks - 1).cast("long"))).drop("_part", "_shift", "_total")
    if how == "lpt":

        def place(pdf):
            pdf = pdf.sort_values(["length", "experience_id"], ascending=[False, True])
            load, out = [(0, r) for r in range(ranks)], []
            for n in pdf["length"]:
                w, r = heapq.heappop(load)
                out.append(r)
                heapq.heappush(load, (w + int(n), r))
            return pdf.assign(rank_id=out)[["experience_id", "rank_id"]]

        keys = window or [F.lit(0).alias("_w")]
        part = light_rows.select("experience_id", "length", *(window or [])).groupBy(*keys).applyInPandas(place, "experience_id long, rank_id long")
        return light_rows.join(part, "experience_id")
    raise ValueError(how)


def audit(light_rows: DataFrame, payloads: DataFrame) -> DataFrame:
    """Counts of dangling references, unreferenced payloads and duplicate payloads."""
    refs, have = light_rows.select(F.col("ref.payload_id").alias("payload_id")), payloads.select("payload_id")
    a = refs.join(have, "payload_id", "left_anti").agg(F.count("*").alias("dangling"))
    b = have.join(refs, "payload_id", "left_anti").agg(F.count("*").alias("unreferenced"))
    c = have.groupBy("payload_id").count().filter("count > 1").agg(F.count("*").alias("duplicated"))
    return a.crossJoin(b).crossJoin(c)  # one row each


def memory(assigned: DataFrame, reference_bytes: int = 48) -> DataFrame:
    """Peak bytes at the controller with and without gathering, and at the fullest rank."""
    per = assigned.groupBy("rank_id").agg(F.sum("length").alias("bytes"), F.count("*").alias("n"))
    return per.agg(F.sum("bytes").alias("controller_gather"), (F.sum("n") * reference_bytes).alias("controller_refs"), F.max("bytes").alias("rank_peak"))
