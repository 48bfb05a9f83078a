"""Parallel plans, and checks that sharded computations equal unsharded ones."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Plan:
    """Training sizes must multiply to the world; experts must divide over expert ranks; serving is sized on its own."""

    world: int
    tp: int = 1
    cp: int = 1
    dp: int = 1
    ep: int = 1
    experts: int = 1
    serving_tp: int = 1
    serving_dp: int = 1
    serving_world: int = 1
    max_batched_tokens: int = 8192
    speculative_tokens: int = 0
    routing_replay: bool = False
    freeze_router: bool = False
    offload_optimizer: bool = False

    def validate(self) -> "Plan":
        if self.tp * self.cp * self.dp != self.world:
            raise ValueError("tp * cp * dp must equal the training world")
        if self.experts % self.ep or (self.cp * self.dp) % self.ep and self.ep % (self.cp * self.dp):
            raise ValueError("experts must divide over ep, and ep must fit the data ranks")
        if self.serving_tp * self.serving_dp != self.serving_world:
            raise ValueError("serving tp * dp must equal the serving world")
        if min(self.max_batched_tokens, 1) < 1 or self.speculative_tokens < 0:
            raise ValueError("token budget must be positive, speculation not negative")
        return self


def tensor_shards(vectors: DataFrame, tp: int, dims: int = 64) -> DataFrame:
    """vec_id, sharded, whole: squared norms as a sum of partial products over tp slices, and at once."""
    width = dims // tp
    dot = lambda x: F.aggregate(F.transform(x, lambda v: v.cast("double") * v), F.lit(0.0), lambda acc, v: acc + v)
    parts = sum((dot(F.slice("embedding", k * width + 1, width)) for k in range(1, tp)), dot(F.slice("embedding", 1, width)))
    return vectors.select("vec_id", parts.alias("sharded"), dot(F.col("embedding")).alias("whole"))


def context_shards(trace: DataFrame, cp: int) -> DataFrame:
    """cp_rank of each token: sequences cut into cp equal chunks."""
    return trace.withColumn("cp_rank", F.floor(F.col("pos") * cp / F.col("length")))


def expert_dispatch(routes: DataFrame, ep: int, n_experts: int, capacity: float = 1.25) -> DataFrame:
    """Tokens, share and overflow of each expert rank; experts are dealt to ranks in blocks."""
    per = n_experts // ep
    load = routes.withColumn("ep_rank", F.floor(F.col("expert") / per)).groupBy("ep_rank").agg(F.count("*").alias("n_tokens"))
    total = routes.agg(F.count("*").alias("_all"))
    cap = F.ceil(F.col("_all") * capacity / ep)
    return load.crossJoin(F.broadcast(total)).select("ep_rank", "n_tokens", cap.alias("capacity"), F.greatest(F.lit(0), F.col("n_tokens") - cap).alias("overflow"))


def shard_bytes(params: DataFrame, plan: Plan, bytes_per_param: int = 2) -> DataFrame:
    """rank, bytes of fully sharded parameters, from one row with their number ``params``: the remainder goes to the first ranks."""
    n = plan.dp * plan.cp
    ranks = params.select("params", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("rank"))
    return ranks.select("rank", ((F.expr(f"params div {n}") + (F.col("rank") < F.col("params") % n).cast("long")) * bytes_per_param).alias("bytes"))
