"""Cost and accuracy measures; each counts what it says over one step, run or pair of runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def rewards(rollouts: DataFrame) -> DataFrame:
    """Mean reward once per rollout; mean and share of zero of the within-group spread."""
    g = rollouts.groupBy("group_id").agg(F.sum("reward").alias("s"), F.count("reward").alias("n"), F.stddev_samp("reward").alias("sd"), (F.max("reward") - F.min("reward")).alias("spread"))
    return g.agg((F.sum("s") / F.sum("n")).alias("reward_mean"), F.avg("sd").alias("within_group_std"), F.avg((F.col("spread") == 0).cast("double")).alias("zero_share"), F.count("*").alias("n_groups"))


def lengths(per_rollout: DataFrame, cap: int, exact: bool = True) -> DataFrame:
    """Mean, median, 95th percentile and maximum of ``length``; share at or over the cap. At scale use exact=False."""
    p = F.percentile if exact else (lambda c, q: F.percentile_approx(c, q, 10_000))
    return per_rollout.agg(F.avg("length").alias("mean"), p("length", F.lit(0.5)).alias("p50"), p("length", F.lit(0.95)).alias("p95"), F.max("length").alias("longest"), F.avg((F.col("length") >= cap).cast("double")).alias("truncated"))


def pass_at(rollouts: DataFrame, n: int, reward: str = "reward") -> DataFrame:
    """group_id, any_correct, unbiased: 1 - C(N-c, n)/C(N, n) as a product, for groups of at least n rollouts."""
    g = rollouts.groupBy("group_id").agg(F.count(reward).alias("n_all"), F.sum(reward).cast("long").alias("n_right")).filter(F.col("n_all") >= n)
    wrong = F.col("n_all") - F.col("n_right")
    miss = F.aggregate(F.sequence(F.lit(0), F.lit(n - 1)), F.lit(1.0), lambda acc, i: acc * F.greatest(wrong - i, F.lit(0)) / (F.col("n_all") - i))
    return g.select("group_id", "n_all", "n_right", (F.col("n_right") > 0).alias("any_correct"), (1.0 - miss).alias("unbiased"))


def stages(log: DataFrame) -> DataFrame:
    """Mean seconds of each stage and its share of the total, from rows (step, stage, seconds)."""
    total = F.sum("seconds").over(Window.partitionBy())
    return log.groupBy("stage").agg(F.avg("seconds").alias("mean_s"), F.sum("seconds").alias("seconds")).withColumn("share", F.col("seconds") / total)


def step_time(steps: DataFrame, first: int = 2, last: int = 10, ddof: int = 1) -> DataFrame:
    """Mean and deviation over runs of each run's mean step time over steps first..last; step 1 is warm-up."""
    per = steps.filter(F.col("step").between(first, last)).groupBy("run").agg(F.avg("seconds").alias("mean"))
    return per.agg(F.avg("mean").alias("step_s"), (F.stddev_samp("mean") if ddof else F.stddev_pop("mean")).alias("step_std"), F.count("*").alias("n_runs"))


def throughput(tokens: Column, seconds: Column, devices: Column) -> Column:
    return tokens / seconds / devices


def ratio(a: Column, b: Column) -> Column:
    return F.try_divide(a, b)


def saved(baseline: Column, enabled: Column) -> Column:
    """Share of the baseline that the feature saves; negative where it costs."""
    return F.try_divide(baseline - enabled, baseline)


def retained(trace: DataFrame, by: tuple[str, ...] = ("rollout_id", "segment_seq")) -> DataFrame:
    """Share of sequences, and of action tokens, that a gate keeps."""
    s = trace.groupBy(*by).agg(F.max((F.col("w") > 0).cast("int")).alias("keep"), F.sum("m").alias("n"))
    return s.agg(F.avg("keep").alias("by_sequence"), (F.sum(F.col("keep") * F.col("n")) / F.sum("n")).alias("by_token"), F.count("*").alias("n_sequences"))


def correction_report(trace: DataFrame, cap: float = 2.0, clip: float = 0.2) -> DataFrame:
    """How far sampling and training policies are apart, what truncation cuts off, and the effective sample size."""
    rho, q = F.exp(F.col("o") - F.col("b")), F.exp(F.col("c") - F.col("o"))
    t = trace.select(rho.alias("rho"), F.least(rho, F.lit(cap)).alias("w"), (F.col("o") - F.col("b")).alias("gap"), q.alias("q"))
    return t.agg(
        F.count("*").alias("n_tokens"), F.round(F.avg("rho"), 6).alias("rho_mean"), F.round(F.max("rho"), 6).alias("rho_max"), F.round(F.avg((F.col("rho") > cap).cast("double")), 6).alias("truncated"),
        F.round(F.avg(F.col("rho") - F.col("w")), 6).alias("bias"), F.round(-F.avg("gap"), 6).alias("kl_k1"), F.round(F.sum("w") * F.sum("w") / F.sum(F.col("w") * F.col("w")), 6).alias("ess"),
        F.round(F.avg((F.abs(F.col("q") - 1) > clip).cast("double")), 6).alias("clipped"),
    )


def alignment(pairs: DataFrame) -> DataFrame:
    """Numerical consistency of two log-probability columns b and o: largest and mean distance, and correlation."""
    d = F.abs(F.col("o") - F.col("b"))
    return pairs.agg(F.count("*").alias("n"), F.max(d).alias("max_gap"), F.avg(d).alias("mean_gap"), F.corr("o", "b").alias("correlation"))


def imbalance(assigned: DataFrame, rank: str = "rank_id", length: str = "length") -> DataFrame:
    """Largest over mean rank load, and the share of padding if each rank pads to its longest item."""
    r = assigned.groupBy(rank).agg(F.sum(length).alias("load"), F.max(length).alias("top"), F.count("*").alias("n"))
    return r.agg((F.max("load") / F.avg("load")).alias("imbalance"), (1 - F.sum("load") / F.sum(F.col("top") * F.col("n"))).alias("padding_waste"), F.max("load").alias("slowest"))


def reprefill(requests: DataFrame, seconds_per_token: float = 1e-4, base_seconds: float = 0.05) -> DataFrame:
    """Uncached prompt tokens, hit rate and a modelled latency: a fixed cost a request and a cost per uncached token."""
    miss = F.sum(F.col("prompt_tokens") - F.col("hit_tokens"))
    return requests.agg(F.sum("prompt_tokens").alias("prompt_tokens"), F.sum("hit_tokens").alias("hit_tokens"), miss.alias("uncached"), (F.sum("hit_tokens") / F.sum("prompt_tokens")).alias("hit_rate"), (base_seconds * F.count("*") + seconds_per_token * miss).alias("latency_s"))


def offload_tradeoff(params, bytes_per_state: int = 8, bandwidth: float = 25e9, base_seconds=200.0, base_gb=60.0) -> dict:
    """For numbers or columns: memory that moving two optimizer moments to the host frees on a device, and the transfer time that it adds a step."""
    state = params * bytes_per_state
    return {"saved_gb": state / 1e9, "saved_share": state / 1e9 / base_gb, "added_s": 2 * state / bandwidth, "added_share": 2 * state / bandwidth / base_seconds}
