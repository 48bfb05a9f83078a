"""Groups of multi-turn rollouts through the whole step: segments, grades, gate and truncation, context shards, replayed routes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit import advantages, capture, correction, grading, groups, losses, parallel, policy, routing, worlds
from trajkit.ranking import global_rank
from trajkit.session import materialise

SAMPLES, CP, EXPERTS, EP = 4, 8, 10, (2, 5, 10)


def rewards(turns: DataFrame, requests: DataFrame) -> DataFrame:
    """group_id, rollout_id, reward of complete groups: the mean token F1 of replies against the turn before each; a rollout without replies has 0."""
    grade = grading.token_f1(F.col("reply"), F.try_element_at("messages", F.lit(-1))["content"])
    graded = requests.select("rollout_id", grade.alias("g")).groupBy("rollout_id").agg(F.avg("g").alias("reward"))
    r = turns.groupBy("rollout_id").agg(F.max("turn").alias("completed_at")).withColumn("group_id", F.floor(F.col("rollout_id") / SAMPLES))
    return groups.complete(r.join(graded, "rollout_id", "left").fillna(0.0, ["reward"]), SAMPLES)


def sequences(requests: DataFrame) -> DataFrame:
    """rollout_id, segment_seq, pos, length, token_id, m: every token of every segment; replies are actions, all other turns observations."""
    s = capture.assemble(capture.segment(requests))
    t = s.select("rollout_id", "segment_seq", F.size("token_ids").alias("length"), F.posexplode(F.arrays_zip("token_ids", "action_mask")).alias("pos", "x"))
    return t.select("rollout_id", "segment_seq", F.col("pos").cast("long").alias("pos"), "length", F.col("x.token_ids").alias("token_id"), F.col("x.action_mask").cast("int").alias("m"))


def scored(turns: DataFrame, behaviour: DataFrame, actor: DataFrame, low: float = 0.99, high: float = 1.01) -> DataFrame:
    """The tokens of all complete groups with both log-probabilities, advantage, weight by gate and truncation, and loss."""
    requests = materialise(worlds.requests(turns))
    adv = advantages.group_relative(rewards(turns, requests)).select("group_id", "rollout_id", "reward", "adv")
    t = groups.fan_out(adv, sequences(requests))
    t = policy.score(policy.score(t, behaviour, "b"), actor, "o").withColumn("c", F.col("o"))
    return correction.gate_truncate(t, low, high).withColumn("l", losses.contribution(losses.surrogate("clip")))


def routed(tokens: DataFrame, vectors: DataFrame, step: int = 64, broadcast_rows: int = 2_000_000) -> tuple[DataFrame, DataFrame]:
    """Recorded and anew routed experts of every token, which stands at the vector of its id modulo their number.

    The route is recorded on the vectors once; the actor replays it by a join. ``step`` is the precision of a router that doesn't replay.
    """
    n, centres = max(1, vectors.count()), routing.centroids(vectors)
    place = global_rank(vectors.select("vec_id"), F.col("vec_id"), [], "k").withColumn("k", F.col("k") - 1)
    own, again = (materialise(place.join(routing.route(vectors, centres, step=s), "vec_id").select(F.col("k").alias("vec_id"), "expert", "place")) for s in (None, step))
    near = lambda df: F.broadcast(df) if n <= broadcast_rows else df
    at = tokens.withColumn("vec_id", F.pmod("token_id", F.lit(n)))
    return routing.replay(at, near(own)), routing.replay(at, near(again))


def step(turns: DataFrame, behaviour: DataFrame, actor: DataFrame, vectors: DataFrame) -> DataFrame:
    """One row: sizes, rejected action tokens, the loss whole and over context shards, tokens whose expert replay keeps, load and overflow of expert ranks."""
    t = materialise(scored(turns, behaviour, actor))
    out = t.agg(
        F.countDistinct("group_id").alias("n_groups"), F.countDistinct("rollout_id").alias("n_rollouts"), F.countDistinct("rollout_id", "segment_seq").alias("n_segments"), F.count("*").alias("n_tokens"),
        F.sum("m").cast("long").alias("n_actions"), F.sum((F.col("m") * (F.col("w") == 0).cast("int"))).cast("long").alias("n_rejected"), F.max("length").alias("longest"),
    )
    cut = losses.partial_sums(parallel.context_shards(t, CP), ["cp_rank"]).agg((F.sum("num") / F.sum("den")).alias("sharded"))
    out = out.crossJoin(losses.window_token_mean(t).select("loss")).crossJoin(cut)
    own, again = routed(t.select("rollout_id", "segment_seq", "pos", "token_id"), vectors)
    own = materialise(own)
    changed = again.groupBy("vec_id").agg(F.count("*").alias("n"), F.first("expert").alias("again")).join(own.groupBy("vec_id").agg(F.first("expert").alias("expert")), "vec_id")
    out = out.crossJoin(own.agg(F.count("*").alias("n_replayed"))).crossJoin(changed.agg(F.sum(F.col("n") * (F.col("again") != F.col("expert")).cast("long")).alias("n_changed")))
    for ep in EP:
        load = parallel.expert_dispatch(own, ep, EXPERTS)
        out = out.crossJoin(load.agg(F.max("n_tokens").alias(f"ep{ep}_most"), F.sum("overflow").alias(f"ep{ep}_overflow")))
    return out  # one row each
