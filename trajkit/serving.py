"""Serving accounting: speculation, prefix caches, engine choice, token-budget batches, retention over refits."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit import tokens
from trajkit.policy import uniform


def speculate(trace: DataFrame, ks: list[int], greedy: bool = False) -> DataFrame:
    """Per k and rollout: target passes with k drafted tokens a pass, from columns target and draft (log-probabilities).

    A pass keeps the drafted tokens before the first refused one and adds one token of the target; the next pass drafts again right
    behind it. A token is refused if its u exceeds target/draft, or, ``greedy``, if it isn't the target's likeliest (column best).
    Whatever came before, a refused token ends the pass that it falls in, so runs between refused tokens are counted on their own.
    """
    if greedy:
        ok = F.col("token_id") == F.col("best")
    else:
        ok = uniform(F.lit("spec"), F.col("rollout_id"), F.col("pos")) <= F.least(F.lit(1.0), F.exp(F.col("target") - F.col("draft")))
    bad = (~ok).cast("long")
    w = Window.partitionBy("rollout_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    t = trace.select("rollout_id", bad.alias("_bad"), F.coalesce(F.sum(bad).over(w), F.lit(0)).alias("_run"))
    runs = t.groupBy("rollout_id", "_run").agg(F.count("*").alias("_n"), F.max("_bad").alias("_ended"))
    runs = runs.withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks]))).withColumn("_passes", F.ceil(F.col("_n") / (F.col("k") + 1)))
    # The last pass of a rollout may end inside its draft, without a token of the target.
    own = F.when(F.col("_ended") == 1, F.col("_passes")).otherwise(F.floor(F.col("_n") / (F.col("k") + 1)))
    return runs.groupBy("k", "rollout_id").agg(F.sum("_n").alias("n_tokens"), F.sum("_passes").alias("passes"), F.sum(F.col("_n") - own).alias("accepted"))


def blocks(requests: DataFrame, size: int = 16, by: tuple[str, ...] = ()) -> DataFrame:
    """rollout_id, request_seq, block, chain, tokens (and ``by``): chained digests of the rendered prompt's full blocks."""
    t = requests.select(*by, "rollout_id", "request_seq", tokens.render(F.col("messages")).alias("t"))
    n = F.floor(F.size("t") / size).cast("int")
    parts = F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.slice("t", (i - 1) * size + 1, F.lit(size)), " "))
    link = lambda acc, p: F.concat(acc, F.array(F.md5(F.concat(F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit("")), p))))
    t = t.withColumn("prompt_tokens", F.size("t").cast("long")).filter(n >= 0).withColumn("c", F.when(n > 0, F.aggregate(parts, F.array().cast("array<string>"), link)).otherwise(F.array().cast("array<string>")))
    return t.select(*by, "rollout_id", "request_seq", "prompt_tokens", F.posexplode_outer("c").alias("block", "chain"))


def route_requests(requests: DataFrame, engines: int, how: str = "session") -> DataFrame:
    """engine of each request: session keeps a rollout on one; round_robin and random don't."""
    hashed = lambda *p: F.pmod(F.conv(F.substring(F.md5(F.concat_ws(":", *[x.cast("string") for x in p])), 1, 8), 16, 10).cast("long"), F.lit(engines))
    e = {"session": hashed(F.col("rollout_id")), "round_robin": F.pmod(F.col("rollout_id") + F.col("request_seq"), F.lit(engines)), "random": hashed(F.col("rollout_id"), F.col("request_seq"))}[how]
    return requests.withColumn("engine", e)


def prefix_cache(requests: DataFrame, engines: int = 4, how: str = "session", size: int = 16, ttl: int | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """rollout_id, request_seq, prompt_tokens, hit_tokens: a block hits if its chain was seen on that engine by an earlier request.

    Requests are ordered by (request_seq, rollout_id): all first turns, then all second turns. Nothing is evicted unless ``ttl`` is
    set: then a chain leaves an engine on which none of the ttl turns before used it. Each value of ``by`` has caches of its own.
    """
    b = route_requests(blocks(requests, size, by), engines, how)
    # The block of a shared system prompt is in all requests: what remains of it after the partial aggregate is one row a turn.
    place = [*by, "engine", "chain"]
    used = b.filter("chain is not null").groupBy(*place, "request_seq").agg(F.min("rollout_id").alias("_first"))
    used = used.withColumn("_before", F.lag("request_seq").over(Window.partitionBy(*place).orderBy("request_seq")))
    b = b.join(used, [*place, "request_seq"], "left")
    kept = F.col("_before").isNotNull() if ttl is None else F.col("_before") >= F.col("request_seq") - ttl
    hit = (F.col("_first") < F.col("rollout_id")) | F.coalesce(kept, F.lit(False))
    b = b.withColumn("_hit", F.when(hit, size).otherwise(0))
    return b.groupBy(*by, "rollout_id", "request_seq").agg(F.max("prompt_tokens").alias("prompt_tokens"), F.sum("_hit").cast("long").alias("hit_tokens"))


def pack(requests: DataFrame, budget: int, max_seqs: int, key: str = "engine") -> DataFrame:
    """batch of each request: next fit under a token budget and a sequence limit, per engine; light rows only."""

    def fit(pdf):
        pdf, used, n, batch, out = pdf.sort_values(["request_seq", "rollout_id"]), 0, 0, 0, []
        for t in pdf["prompt_tokens"]:
            if n and (used + t > budget or n >= max_seqs):
                used, n, batch = 0, 0, batch + 1
            used, n = used + t, n + 1
            out.append(batch)
        return pdf.assign(batch=out)

    light = requests.select(key, "rollout_id", "request_seq", "prompt_tokens")
    return light.groupBy(key).applyInPandas(fit, f"{key} long, rollout_id long, request_seq long, prompt_tokens long, batch long")


def retained(versioned: DataFrame) -> DataFrame:
    """Prefix tokens kept at refits by retained requests, and those that a restart would compute again."""
    w = Window.partitionBy("rollout_id").orderBy("pos")
    jump = F.col("version") != F.lag("version").over(w)
    t = versioned.withColumn("_jump", F.coalesce(jump, F.lit(False)))
    return t.groupBy("rollout_id").agg(F.sum(F.when(F.col("_jump"), F.col("pos")).otherwise(0)).alias("kept_prefix"), F.sum(F.col("_jump").cast("long")).alias("refits_seen"))
