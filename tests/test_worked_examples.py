"""Worked examples with numbers derived by hand, and properties that must hold."""

import pytest
from pyspark.sql import functions as F

from trajkit import advantages, capture, correction, experience, groups, losses, measures, parallel, policy, registry, scheduling, wire, worlds


def rollouts(spark, rewards, group=1):
    return spark.createDataFrame([(group, i, float(r)) for i, r in enumerate(rewards)], "group_id long, rollout_id long, reward double")


def column(df, name="adv"):
    return [r[name] for r in df.orderBy("rollout_id").collect()]


def test_window_mean_does_not_depend_on_cuts(spark):
    t = spark.createDataFrame([(1, 1.0), (1, 2.0), (1, 3.0), (2, 10.0)], "rollout_id long, l double").withColumn("m", F.lit(1))
    assert losses.window_token_mean(t).first()["loss"] == 4
    assert losses.mean_of_means(t, ["rollout_id"]).first()["loss"] == 6
    assert {r["loss"] for r in losses.invariance(t, [(1, 1), (2, 1), (3, 2)]).collect()} == {4.0}


def test_rejected_tokens_stay_in_the_denominator(spark):
    t = spark.createDataFrame([(1.0, 1.0), (2.0, 1.0), (3.0, 1.0), (10.0, 0.0)], "x double, w double").withColumn("m", F.lit(1)).withColumn("l", F.col("w") * F.col("x"))
    assert losses.window_token_mean(t).first()["loss"] == 1.5
    assert losses.accepted_only(t).first()["loss"] == 2.0
    assert losses.window_token_mean(t.filter("m = 0")).first()["loss"] is None


def test_estimators(spark):
    r = rollouts(spark, [1, 0, 0, 0])
    assert column(advantages.group_mean(r)) == [0.75, -0.25, -0.25, -0.25]
    assert column(advantages.leave_one_out(r)) == pytest.approx([1, -1 / 3, -1 / 3, -1 / 3])
    assert column(advantages.group_relative(r, eps=0.0)) == pytest.approx([1.5, -0.5, -0.5, -0.5])
    assert column(advantages.group_relative(r, ddof=0, eps=0.0)) == pytest.approx([1.7320508, -0.5773503, -0.5773503, -0.5773503])
    assert column(advantages.group_relative(rollouts(spark, [1, 1, 1, 1]))) == [0, 0, 0, 0]
    assert column(advantages.leave_one_out(rollouts(spark, [1]))) == [0]
    assert groups.drop_degenerate(rollouts(spark, [1, 1])).count() == 0


def test_registered_estimators_are_checked(spark):
    @registry.register("advantage", "test_bad")
    def bad(r):
        return r.withColumn("adv", F.lit(float("inf")))

    assert registry.checked_advantage("group_mean", rollouts(spark, [1, 0])).count() == 2
    with pytest.raises(ValueError):
        registry.checked_advantage("test_bad", rollouts(spark, [1, 0]))
    with pytest.raises(KeyError):
        registry.get("advantage", "nothing")


def test_gae_and_its_chunked_form(spark):
    t = spark.createDataFrame([(1, 0, 0.0, 0.5), (1, 1, 0.0, 0.5), (1, 2, 1.0, 0.5)], "rollout_id long, pos long, r double, v double")
    a = lambda lam: [r["adv"] for r in advantages.gae(t, 1.0, lam).orderBy("pos").collect()]
    assert a(1.0) == pytest.approx([0.5, 0.5, 0.5])
    assert a(0.0) == pytest.approx([0, 0, 0.5])
    d = spark.createDataFrame([(1, i, float(i + 1), 0.0) for i in range(3)], "rollout_id long, pos long, r double, v double")
    for chunk in (1, 2, 5):
        assert [r["adv"] for r in advantages.gae_chunked(d, 0.9, 1.0, chunk).orderBy("pos").collect()] == pytest.approx([5.23, 4.7, 3.0])


def test_weights_and_gates(spark):
    import math

    t = spark.createDataFrame([(1, 0, p, math.log(x), 0.0) for p, x in enumerate([0.5, 1.0, 4.0])], "rollout_id long, segment_seq long, pos long, o double, b double").withColumn("m", F.lit(1))
    w = lambda df: [r["w"] for r in df.orderBy("pos").collect()]
    assert w(correction.token_truncate(t)) == pytest.approx([0.5, 1, 2])
    assert w(correction.token_mask(t)) == pytest.approx([0.5, 1, 0])
    same = t.withColumn("o", F.lit(math.log(1.1)))
    assert set(w(correction.seq_gate(same, 0.8, 1.2))) == {1.0}
    assert set(w(correction.seq_gate(same, 0.8, 1.2, "prod"))) == {0.0}
    with pytest.raises(ValueError):
        correction.check(True, "none")
    with pytest.raises(ValueError):
        correction.seq_truncate(t.withColumn("version", F.col("pos")), check_versions=True)


def test_rewards_count_once(spark):
    r = spark.createDataFrame([(1, 1, 1.0), (1, 2, 0.0)], "group_id long, rollout_id long, reward double")
    s = spark.createDataFrame([(1, 0), (1, 1), (2, 0)], "rollout_id long, segment_seq long")
    got = groups.segment_counted_stats(r, s).first()
    assert (got["by_rollout"], got["by_segment"]) == (0.5, pytest.approx(2 / 3))


def requests(spark, rows):
    return spark.createDataFrame([(1, i, [(x[0], x[1:]) for x in m], r) for i, (m, r) in enumerate(rows)], "rollout_id long, request_seq long, messages array<struct<role:string,content:string>>, reply string")


def test_segments_of_a_rewritten_history(spark):
    r = requests(spark, [(["u0"], "1"), (["u0", "assistant1", "u2"], "3"), (["s", "u4"], "5"), (["s", "u4", "assistant5", "u6"], "7")])
    r = r.withColumn("messages", F.transform("messages", lambda m: F.struct(F.when(m["content"].startswith("ssistant"), "assistant").otherwise(m["role"]).alias("role"), F.regexp_replace(m["content"], "ssistant", "").alias("content"))))
    assert [x["segment_seq"] for x in capture.segment(r).orderBy("request_seq").collect()] == [0, 0, 1, 1]
    s = capture.assemble(capture.segment(r)).collect()
    assert sum(len(x["action_ranges"]) for x in s) == 4
    for x in s:
        for a in x["action_ranges"]:
            assert all(x["action_mask"][a["lo"] : a["hi"]])


def test_dialects_agree(spark):
    r = requests(spark, [(["sx", "uy"], "z")]).withColumn("messages", F.transform("messages", lambda m: F.struct(F.when(m["role"] == "s", "system").otherwise("user").alias("role"), m["content"].alias("content"))))
    a, b = wire.normalise(wire.to_completions(r)), wire.normalise(wire.to_messages(r))
    assert a.collect() == b.collect()
    assert wire.route_url("http://h/s/", wire.COMPLETIONS) != wire.route_url("http://h/s/", wire.MESSAGES)


def test_batches_by_completion(spark):
    g = spark.createDataFrame([(3, 1), (1, 2), (4, 3), (5, 5)], "group_id long, finished long").withColumn("dispatched", F.col("group_id"))
    got = {r["group_id"]: r["batch"] for r in scheduling.streaming(g, 2).collect()}
    assert got == {3: 0, 1: 0, 4: 1, 5: 1}


def test_assignment_by_length(spark):
    e = spark.createDataFrame([(i, n, 0) for i, n in enumerate([9, 7, 6, 5, 4, 3])], "experience_id long, length long, node int")
    load = lambda how: sorted(r["l"] for r in experience.assign(e, 2, how).groupBy("rank_id").agg(F.sum("length").alias("l")).collect())
    assert load("lpt") == [17, 17] and load("serpentine") == [16, 18] and load("round_robin") == [15, 19]


def test_published_arithmetic(spark):
    one = spark.range(1)
    v = lambda c: one.select(c).first()[0]
    assert round(v(measures.throughput(F.lit(880000), F.lit(119.4), F.lit(16)))) == 461
    assert round(v(measures.throughput(F.lit(880000), F.lit(109.5), F.lit(16)))) == 502
    assert round(v(measures.ratio(F.lit(329.0), F.lit(64.0))), 2) == 5.14
    assert round(100 * v(measures.saved(F.lit(64.7), F.lit(46.4))), 1) == 28.3
    r = rollouts(spark, [1, 0, 0, 0])
    assert measures.pass_at(r, 2).first()["unbiased"] == pytest.approx(0.5)


def test_plans_are_checked():
    parallel.Plan(8, dp=8, ep=8, experts=128, serving_tp=8, serving_world=8).validate()
    with pytest.raises(ValueError):
        parallel.Plan(8, tp=2, dp=8).validate()
    with pytest.raises(ValueError):
        parallel.Plan(8, dp=8, ep=8, experts=10).validate()


def test_versions_are_published_in_order_and_once(spark, tmp_path):
    p, path = spark.createDataFrame([(1, 0.5)], "token_id long, theta double"), str(tmp_path)
    assert policy.publish(p, 0, path) and not policy.publish(p, 0, path)
    with pytest.raises(ValueError):
        policy.publish(p, 2, path)
    assert policy.published(spark, path) == [0]


def test_sessions_capture_what_agents_send(spark):
    def agent(ctx):
        ctx.chat([{"role": "user", "content": ctx.label}])
        return 1.0

    p = spark.createDataFrame([(1, [("user", "a b")], "l m")], "rollout_id long, messages array<struct<role:string,content:string>>, label string")
    row = worlds.run_sessions(p, agent).first()
    assert (row["reply"], row["reward"]) == ("m l", 1.0)
