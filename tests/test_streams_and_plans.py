"""Streams against their batch twins, plan shapes, and properties on the smallest tables."""

import inspect
import os
import pkgutil
from datetime import datetime, timedelta

import pandas as pd
import trajkit
from pyspark.sql import functions as F

from trajkit import capture, experience, joins, losses, ranking, scheduling, streaming, worlds, workloads
from trajkit.catalog import QUERIES


def test_stream_of_groups_equals_batch(spark, small):
    batch = {r["group_id"] for r in scheduling.group_times(workloads.lifecycle(spark, small), 4).collect()}
    assert {r["group_id"] for r in QUERIES["stream_groups"](spark, small).collect()} == batch


def test_streamed_rows_stay_in_files(spark, small):
    got = QUERIES["stream_dedup"](spark, small)
    assert got.inputFiles()  # a memory table on the driver has none
    events = workloads.table(spark, small, "events").select("event_id")
    assert sorted(r["rollout_id"] for r in got.collect()) == sorted(r["event_id"] for r in events.collect())


def test_neighbouring_groups_share_a_state(spark, tmp_path):
    day = lambda k: datetime(2024, 1, 1) + timedelta(days=k)
    files = [
        [(0, day(0), False), (0, day(0), False), (1, day(0), False), (2, day(0), False), (3, day(0), True), (9, day(0), False), (9, day(0), False)],
        [(1, day(1), False), (0, day(1), False), (3, day(1), False), (9, day(1), True)],  # late members of closed groups emit nothing
        [(40, day(30), False)],
        [(40, day(31), False)],
        [(2, day(31), False)],  # the first member of group 2 has timed out
    ]
    for k, rows in enumerate(files):
        path = str(tmp_path / f"{k}.parquet")
        pd.DataFrame(rows, columns=["group_id", "at", "failed"]).astype({"at": "datetime64[us]"}).to_parquet(path)
        os.utime(path, (1000 + k, 1000 + k))
    stream = streaming.source(spark, str(tmp_path), "group_id long, at timestamp_ntz, failed boolean").withColumn("at", F.col("at").cast("timestamp"))
    q = streaming.group_completion(stream, 2, span=4).writeStream.format("memory").queryName("shared_state").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    got = sorted((r["group_id"], r["n_rollouts"], r["finished"], r["state"]) for r in spark.table("shared_state").collect())
    us = lambda k: 1704067200000000 + k * 86400000000
    assert got == [(0, 2, us(0), "complete"), (1, 2, us(1), "complete"), (3, 0, us(0), "failed"), (9, 2, us(0), "complete"), (40, 2, us(31), "complete")]
    assert q.recentProgress[0]["stateOperators"][0]["numRowsTotal"] == 2  # five groups in two spans


def test_payloads_survive_the_store(spark, small, tmp_path):
    e = experience.build(workloads.table(spark, small, "documents"))
    back = experience.reload(experience.offload(e, str(tmp_path)), str(tmp_path)).select(*e.columns)
    assert e.exceptAll(back).count() == 0 == back.exceptAll(e).count()


def test_light_rows_carry_no_payload(spark, small):
    plan = experience.assign(experience.light(experience.build(workloads.table(spark, small, "documents"))), 4)
    assert "payload" not in plan.columns and "text" not in plan.columns


def test_filters_and_columns_reach_the_scan(spark, small):
    df = workloads.table(spark, small, "lineitem").filter("l_quantity < 10").groupBy("l_suppkey").count()
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), LessThan(l_quantity,10.0)]" in plan and "l_comment" not in plan


def test_masks_and_ranges_are_inverse(spark, small):
    t = workloads.action_tokens(spark, small).withColumn("m", F.col("mixed_action").cast("int"))
    back = capture.mask_from_ranges(capture.ranges_from_mask(t))
    own = t.filter("m = 1").select("rollout_id", "pos")
    assert own.exceptAll(back).count() == 0 == back.exceptAll(own).count()


def test_keeping_everything_makes_one_segment(spark, small):
    r = worlds.requests(worlds.turns(spark, small))
    assert capture.segment(r).filter("segment_seq > 0").count() == 0


def test_global_rank_equals_a_sorted_list(spark):
    df = spark.createDataFrame([(i, (i * 7919) % 101) for i in range(500)], "id long, k long")
    got = {r["id"]: r["rank"] for r in ranking.global_rank(df, F.col("k"), ["id"]).collect()}
    assert got == {i: n + 1 for n, (_, i) in enumerate(sorted(((i * 7919) % 101, i) for i in range(500)))}


def test_versions_at_refits(spark):
    at = spark.createDataFrame([(9,), (10,), (19,), (20,)], "t long")
    refits = spark.createDataFrame([(0, 0), (10, 1), (20, 2)], "since long, version long")
    for f in (joins.as_of, joins.as_of_few):
        assert [r["version"] for r in f(at, refits, "t", "since", ["version"]).orderBy("t").collect()] == [0, 1, 1, 2]


def test_streaming_is_never_slower_with_enough_workers(spark, small):
    life = workloads.lifecycle(spark, small)
    grid = [{"name": m, "workers": 5000, "batch": 8, "queue": 10_000, "train_us": 1, "mode": m} for m in ("streaming", "barrier")]
    span = {r["name"]: r["makespan_s"] for r in scheduling.simulate(life, grid).collect()}
    assert span["streaming"] <= span["barrier"]


def test_no_localcheckpoint_and_no_optional_imports():
    for m in pkgutil.walk_packages(trajkit.__path__, "trajkit."):
        if ".llm" in m.name:
            continue
        source = inspect.getsource(__import__(m.name, fromlist=["x"]))
        assert ".localCheckpoint(" not in source and "trajkit.llm" not in source


def test_empty_window_has_no_loss(spark):
    t = spark.createDataFrame([], "rollout_id long, l double, m int")
    assert losses.window_token_mean(t).first()["loss"] is None
