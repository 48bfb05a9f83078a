"""Sequences of any length and discount, ranks of long keys, sets of any size, pools by events: against plain Python."""

import math

import pytest
from pyspark.sql import functions as F

from trajkit import advantages, joins, policy, ranking, scheduling


def long_trace(spark, n):
    return spark.range(n).select(F.lit(1).cast("long").alias("rollout_id"), F.col("id").alias("pos"), (F.col("id") % 7 / 3.0).alias("r"), (F.col("id") % 5 / 4.0).alias("v"))


@pytest.mark.parametrize("gamma,lam,n", [(0.5, 1.0, 100_000), (0.9, 0.9, 9_000), (1.0, 0.95, 30_000), (1.0, 1.0, 2_000), (0.0, 0.9, 50), (0.999, 0.999, 100_000)])
def test_sums_over_long_sequences(spark, gamma, lam, n):
    r, v = [k % 7 / 3.0 for k in range(n)], [k % 5 / 4.0 for k in range(n)]
    ret, adv = [0.0] * (n + 1), [0.0] * (n + 1)
    for t in range(n - 1, -1, -1):
        ret[t] = r[t] + gamma * ret[t + 1]
        adv[t] = r[t] + gamma * (v[t + 1] if t + 1 < n else 0.0) - v[t] + gamma * lam * adv[t + 1]
    t = long_trace(spark, n)
    for got, want in ((advantages.returns(t, gamma).select("pos", "ret"), ret), (advantages.gae(t, gamma, lam).select("pos", "adv"), adv), (advantages.gae_chunked(t, gamma, lam).select("pos", "adv"), adv)):
        assert all(math.isclose(x, want[p], rel_tol=1e-9, abs_tol=1e-9) for p, x in got.collect())


def test_returns_count_steps_by_position(spark):
    t = spark.createDataFrame([(1, 0, 1.0), (1, 3, 1.0), (1, 5000, 1.0)], "rollout_id long, pos long, r double")
    got = {x["pos"]: x["ret"] for x in advantages.returns(t, 0.5).collect()}
    assert got == {5000: 1.0, 3: 1.0, 0: 1.125}


def test_ranks_of_long_keys(spark):
    keys = [2**60 + k for k in (3, 1, 2)] + [None, -(2**60)]
    df = spark.createDataFrame([(i, k) for i, k in enumerate(keys)], "i long, k long")
    rank = lambda d: {x["k"]: x["rank"] for x in ranking.global_rank(df, F.col("k"), ["i"], descending=d).collect()}
    assert rank(False) == {None: 1, -(2**60): 2, 2**60 + 1: 3, 2**60 + 2: 4, 2**60 + 3: 5}
    assert rank(True) == {None: 1, 2**60 + 3: 2, 2**60 + 2: 3, 2**60 + 1: 4, -(2**60): 5}


def test_nucleus_of_many_equal_tokens(spark):
    n = 200_000
    p = spark.range(n).select(F.col("id").alias("token_id"), F.lit(-math.log(n)).alias("logp"))
    got = policy.nucleus(p, 0.9)
    size, low, total = got.agg(F.count("*"), F.max("token_id"), F.sum("p")).first()
    assert abs(size - 180_000) <= 1 and low == size - 1 and total == pytest.approx(1.0)
    few = spark.createDataFrame([(1, math.log(0.5)), (2, math.log(0.2)), (3, math.log(0.2)), (4, math.log(0.1))], "token_id long, logp double")
    assert {x["token_id"] for x in policy.nucleus(few, 0.6).collect()} == {1, 2}


def test_as_of_without_keys(spark, monkeypatch):
    monkeypatch.setattr(ranking, "RANGE_ROWS", 10)
    left, right = spark.range(0, 300, 3).select(F.col("id").alias("at")), spark.createDataFrame([(k * k, k) for k in range(3, 17)], "since long, v long")
    want = {a: max((k for k in range(3, 17) if k * k <= a), default=None) for a in range(0, 300, 3)}
    for out in (joins.as_of(left, right, "at", "since", ["v"]), joins.as_of_few(left, right, "at", "since", ["v"]), joins.as_of_few(left, right, "at", "since", ["v"], limit=3)):
        assert {x["at"]: x["v"] for x in out.collect()} == want
    assert joins.as_of_few(left, right.limit(0), "at", "since", ["v"]).filter("v is null").count() == 100


def test_pool_updates_when_groups_end():
    ends = lambda mode, jobs, workers=2, batch=1, queue=9: scheduling.pool_run(jobs, workers, batch, queue, 1.0, mode)["steps"]
    jobs = [(1, 600.0), (2, 60.0), (3, 60.0)]
    assert ends("streaming", jobs) == [61.0, 121.0, 601.0]
    assert ends("barrier", jobs) == [601.0, 662.0, 723.0]
    assert ends("one_step", jobs) == [601.0, 661.0, 721.0]
    assert ends("streaming", [(k, 10.0) for k in range(4)], workers=4, batch=2) == [11.0, 12.0]
    assert ends("streaming", [(1, 5.0), (1, 7.0), (2, 1.0)], workers=1, batch=2, queue=1) == [14.0]
