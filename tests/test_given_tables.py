"""Queries whose rows come from the given tables."""

import pytest
from pyspark.sql import functions as F

from trajkit import workloads
from trajkit.catalog import QUERIES
from trajkit.session import materialise


@pytest.mark.parametrize("name", ["m_ratio", "offload_trade", "shard_bytes", "wl_footprint_ratio", "segment_edge"])
def test_reads_a_given_table(spark, small, name):
    assert any(small in f for f in QUERIES[name](spark, small).inputFiles())

def test_written_results_leave_no_shuffle(spark):
    kept = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses()
    before = kept.size()
    got = materialise(spark.range(1000).repartition(4).groupBy((F.col("id") % 7).alias("k")).count())
    assert kept.size() <= before and got.count() == 7


def test_pieces_that_share_an_id_give_the_first(spark):
    from trajkit.queries.capture import _vocabulary

    turns = spark.createDataFrame([(1, 0, "user", "lesleréan"), (0, 1, "user", "word dotaas"), (2, 0, "user", "dotaas")], "conv_id long, turn long, role string, text string")
    assert {(r["piece"], r["n"]) for r in _vocabulary(turns).filter("id = 1817749225").collect()} == {("dotaas", 3)}
    assert {r["piece"] for r in _vocabulary(turns.withColumn("conv_id", -F.col("conv_id"))).filter("id = 1817749225").collect()} == {"dotaas"}
    assert {r["piece"] for r in _vocabulary(turns.filter("conv_id > 0")).filter("id = 1817749225").collect()} == {"lesleréan"}


def test_log_is_replayed_whole(spark, small):
    got = {(r["rollout_id"], r["turn"], r["pos"]) for r in QUERIES["scan_pysource"](spark, small).collect()}
    talk = workloads.table(spark, small, "conversations").filter("role = 'assistant'").collect()
    assert got == {(r["conv_id"], r["turn"], i) for r in talk for i in range(len((r["text"] or "").split()))}
