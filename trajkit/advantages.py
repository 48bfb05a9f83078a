"""Advantage estimators on rollout rewards, and token-level ones on traces.

A rollout's reward enters once, whatever the number of its segments. Where a group's rewards are all
equal, or it has one rollout only, group-relative values are 0. Rollouts without a reward make null results.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit.registry import register

EPS = 1e-6


def _group():
    return Window.partitionBy("group_id")


@register("advantage", "raw")
def raw(rollouts: DataFrame, reward: str = "reward") -> DataFrame:
    return rollouts.withColumn("adv", F.col(reward))


@register("advantage", "batch_mean")
def batch_mean(rollouts: DataFrame, reward: str = "reward") -> DataFrame:
    mean = rollouts.agg(F.avg(reward).alias("_mean"))  # one row
    return rollouts.crossJoin(F.broadcast(mean)).withColumn("adv", F.col(reward) - F.col("_mean")).drop("_mean")


@register("advantage", "group_mean")
def group_mean(rollouts: DataFrame, whiten: bool = False, reward: str = "reward", eps: float = EPS) -> DataFrame:
    out = rollouts.withColumn("adv", F.col(reward) - F.avg(reward).over(_group()))
    return whitened(out, eps) if whiten else out


def whitened(df: DataFrame, eps: float = EPS, value: str = "adv") -> DataFrame:
    """(x - mean) / (std + eps) over the whole window of rows: two numbers are gathered, then broadcast."""
    s = df.agg(F.avg(value).alias("_mean"), F.stddev_samp(value).alias("_std"))
    return df.crossJoin(F.broadcast(s)).withColumn(value, (F.col(value) - F.col("_mean")) / (F.col("_std") + eps)).drop("_mean", "_std")


@register("advantage", "leave_one_out")
def leave_one_out(rollouts: DataFrame, reward: str = "reward") -> DataFrame:
    n, total = F.count(reward).over(_group()), F.sum(reward).over(_group())
    return rollouts.withColumn("adv", F.when(n < 2, 0.0).otherwise(F.col(reward) - F.try_divide(total - F.col(reward), n - 1)))


@register("advantage", "group_relative")
def group_relative(rollouts: DataFrame, ddof: int = 1, eps: float = EPS, reward: str = "reward") -> DataFrame:
    mean, spread = F.avg(reward).over(_group()), F.max(reward).over(_group()) - F.min(reward).over(_group())
    std = (F.stddev_samp(reward) if ddof else F.stddev_pop(reward)).over(_group())
    return rollouts.withColumn("adv", F.when(spread == 0, 0.0).otherwise((F.col(reward) - mean) / (std + eps)))


@register("advantage", "group_relative_unscaled")
def group_relative_unscaled(rollouts: DataFrame, reward: str = "reward") -> DataFrame:
    """The centred reward without division by a spread; meant for the constant-length normaliser."""
    return rollouts.withColumn("adv", F.col(reward) - F.avg(reward).over(_group()))


def token_rewards(trace: DataFrame, beta: float, reward: str = "reward", by: list[str] | None = None) -> DataFrame:
    """r: the reward on the last action token of the rollout (or of each segment), less beta times the token's kl."""
    last = F.max("pos").over(Window.partitionBy(*(by or ["rollout_id"])))
    return trace.withColumn("r", F.when(F.col("pos") == last, F.col(reward)).otherwise(0.0) - beta * F.col("kl"))


def _reach(g: float) -> int:
    """So many steps that g to their power is about 1e-260: scaled sums stay finite over them, and what lies beyond adds nothing."""
    return 1 << 62 if g >= 1.0 else max(1, int(600 / -math.log(g)))


def discounted(df: DataFrame, value: Column, g: float, by: list[str], name: str, gaps: bool = False) -> DataFrame:
    """Adds ``name``: the sum of ``value`` from each row of a sequence on, discounted by ``g`` a step; any g and length, by window sums alone.

    Steps are counted from the end, in runs of at most ``_reach(g)``. Within a run the sum of g**-k * value, scaled back by
    g**k, gives every term a weight of at most 1; the last sum of the run behind it comes in by one product. With ``gaps`` a step
    is a difference of ``pos``, else a row.
    """
    back = Window.partitionBy(*by).orderBy(F.desc("pos"))
    if g >= 1.0 or g <= 0.0:
        return df.withColumn(name, F.sum(value).over(back.rowsBetween(Window.unboundedPreceding, 0)) if g >= 1.0 else value)
    k = F.max("pos").over(Window.partitionBy(*by)) - F.col("pos") if gaps else F.row_number().over(back) - 1
    reach, power = _reach(g), lambda x: F.pow(F.lit(g), x)
    df = df.withColumn("_x", value).withColumn("_k", k.cast("long")).withColumn("_run", F.floor(F.col("_k") / reach))
    own = F.sum(F.col("_x") * power(-(F.col("_k") % reach))).over(Window.partitionBy(*by, "_run").orderBy("_k").rowsBetween(Window.unboundedPreceding, 0))
    df = df.withColumn("_own", own * power(F.col("_k") % reach))
    ends = F.when(F.lead("_run").over(back) > F.col("_run"), F.struct(F.col("_k").alias("k"), F.col("_own").alias("sum")))
    df = df.withColumn("_end", ends).withColumn("_end", F.last("_end", ignorenulls=True).over(back.rowsBetween(Window.unboundedPreceding, -1)))
    return df.withColumn(name, F.col("_own") + F.coalesce(power(F.col("_k") - F.col("_end.k")) * F.col("_end.sum"), F.lit(0.0))).drop("_x", "_k", "_run", "_own", "_end")


def returns(trace: DataFrame, gamma: float, by: list[str] | None = None) -> DataFrame:
    """ret: the sum of r from each token on, discounted by the distance in ``pos``."""
    return discounted(trace, F.col("r"), gamma, by or ["rollout_id"], "ret", gaps=True)


def reinforce_pp(trace: DataFrame, gamma: float = 1.0, beta: float = 0.0, eps: float = EPS, across_segments: bool = True) -> DataFrame:
    """Token returns of the penalised reward, whitened over all action tokens of the window."""
    by = ["rollout_id"] if across_segments else ["rollout_id", "segment_seq"]
    out = returns(token_rewards(trace, beta, by=by), gamma, by).withColumn("adv", F.col("ret"))
    s = out.filter("m = 1").agg(F.avg("adv").alias("_mean"), F.stddev_pop("adv").alias("_std"))
    return out.crossJoin(F.broadcast(s)).withColumn("adv", (F.col("adv") - F.col("_mean")) / (F.col("_std") + eps)).drop("_mean", "_std", "r", "ret")


def _differences(trace: DataFrame, gamma: float, by: list[str]) -> Column:
    """The temporal difference r + gamma * (value of the next token, 0 after the last) - v."""
    w = Window.partitionBy(*by).orderBy("pos")
    return F.col("r") + gamma * F.coalesce(F.lead("v").over(w), F.lit(0.0)) - F.col("v")


def gae(trace: DataFrame, gamma: float = 1.0, lam: float = 0.95, by: list[str] | None = None) -> DataFrame:
    """adv and ret per token from r and v: temporal differences discounted by gamma * lam; linear in the length of a sequence."""
    by = by or ["rollout_id"]
    d = trace.select(*by, "pos", "r", "v").withColumn("_d", _differences(trace, gamma, by))
    return discounted(d, F.col("_d"), gamma * lam, by, "adv").select(*by, "pos", "adv", (F.col("adv") + F.col("v")).alias("ret"))


def gae_chunked(trace: DataFrame, gamma: float = 1.0, lam: float = 0.95, chunk: int = 4096) -> DataFrame:
    """The same with a sequence's chunks summed in separate tasks: each chunk is an affine map of what follows it.

    A chunk of n tokens passes (gamma * lam)**n of its successor's first value on. Only one row per chunk meets in the second step.
    """
    g = gamma * lam
    chunk = min(chunk, _reach(g)) if g > 0 else chunk
    d = trace.withColumn("d", _differences(trace, gamma, ["rollout_id"])).withColumn("chunk", F.floor(F.col("pos") / chunk))
    d = discounted(d, F.col("d"), g, ["rollout_id", "chunk"], "_a")
    per = d.groupBy("rollout_id", "chunk").agg(F.min_by("_a", "pos").alias("first"), F.count("*").alias("n"), F.max("pos").alias("_last"))
    seq = per.groupBy("rollout_id").agg(F.reverse(F.array_sort(F.collect_list(F.struct("chunk", "first", "n")))).alias("c"))
    step = lambda acc, x: F.struct((x["first"] + F.pow(F.lit(g), x["n"]) * acc["carry"]).alias("carry"), F.concat(acc["out"], F.array(F.struct(x["chunk"].alias("chunk"), acc["carry"].alias("after")))).alias("out"))
    zero = F.struct(F.lit(0.0).alias("carry"), F.array().cast("array<struct<chunk:bigint,after:double>>").alias("out"))
    after = seq.select("rollout_id", F.inline(F.aggregate("c", zero, step, lambda a: a["out"])))
    out = d.join(after.join(per.select("rollout_id", "chunk", "_last"), ["rollout_id", "chunk"]), ["rollout_id", "chunk"])
    return out.select("rollout_id", "pos", (F.col("_a") + F.pow(F.lit(g), F.col("_last") + 1 - F.col("pos")) * F.col("after")).alias("adv"))
