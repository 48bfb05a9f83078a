"""A tabular softmax policy: one logit a token and version, estimated on documents; sampling, scoring and publishing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trajkit import tokens
from trajkit.ranking import global_rank, with_range
from trajkit.session import materialise

ALPHA, VERSIONS = 0.1, 4


def corpus_tokens(docs: DataFrame) -> DataFrame:
    """doc_id, pos, token_id of all documents' words."""
    t = docs.select("doc_id", F.posexplode(tokens.split(F.col("text"))).alias("pos", "piece"))
    return t.select("doc_id", F.col("pos").cast("long").alias("pos"), tokens.token_id(F.col("piece")).alias("token_id"))


def fit(docs: DataFrame, version: int, alpha: float = ALPHA, versions: int = VERSIONS) -> DataFrame:
    """token_id, n, logp of version k, from documents with doc_id mod versions <= k; ``unseen`` rows use other_logp.

    The vocabulary is the distinct tokens of that slice and one place for all others. Counts are aggregated before the shuffle.
    """
    slice_ = docs.filter(F.pmod("doc_id", F.lit(versions)) <= version)
    counts = slice_.select(F.explode(tokens.split(F.col("text"))).alias("p")).groupBy(tokens.token_id(F.col("p")).alias("token_id")).agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("_all"), F.count("*").alias("_types"))
    norm = F.log(F.col("_all") + alpha * (F.col("_types") + 1))
    return counts.crossJoin(F.broadcast(total)).select("token_id", "n", (F.log(F.col("n") + alpha) - norm).alias("logp"), (F.log(F.lit(alpha)) - norm).alias("other_logp"))


def fit_bigram(docs: DataFrame, version: int, backoff: float = 0.4, alpha: float = ALPHA, versions: int = VERSIONS, unigram: DataFrame | None = None) -> DataFrame:
    """prev, token_id, n, p: interpolation of the bigram share with the unigram probability (``unigram``: a written ``fit`` of that version).

    Pairs are made inside each document's row, so only their counts are shuffled.
    """
    ids = docs.filter(F.pmod("doc_id", F.lit(versions)) <= version).select(F.transform(tokens.split(F.col("text")), tokens.token_id).alias("_i"))
    n = F.greatest(F.size("_i") - 1, F.lit(0))
    step = F.arrays_zip(F.slice("_i", F.lit(1), n).alias("prev"), F.slice("_i", F.lit(2), n).alias("token_id"))
    both = ids.select(F.inline(step)).groupBy("prev", "token_id").agg(F.count("*").alias("n"))
    first = both.groupBy("prev").agg(F.sum("n").alias("_n"))
    uni = (fit(docs, version, alpha, versions) if unigram is None else unigram).select("token_id", F.exp("logp").alias("_u"))
    return both.join(first, "prev").join(uni, "token_id").select("prev", "token_id", "n", ((1 - backoff) * F.col("n") / F.col("_n") + backoff * F.col("_u")).alias("p"))


def score_bigram(trace: DataFrame, bigram: DataFrame, unigram: DataFrame, name: str = "target", backoff: float = 0.4) -> DataFrame:
    """Adds each token's log-probability after the token before it in its rollout, and ``best``, the likeliest token there.

    Pairs that were not seen have the unigram's share alone; after an unseen or no token the unigram holds whole.
    """
    t = trace.withColumn("prev", F.lag("token_id").over(Window.partitionBy("rollout_id").orderBy("pos")))
    t = score(t, unigram, "_u")
    first = unigram.orderBy(F.desc("logp"), "token_id").limit(1).select(F.col("token_id").alias("_top"), (backoff * F.exp("logp")).alias("_top_p"))
    after = bigram.groupBy("prev").agg(F.max_by("token_id", F.struct(F.round("p", 12), -F.col("token_id"))).alias("_next"), F.max("p").alias("_next_p"))
    t = t.join(bigram.select("prev", "token_id", F.col("p").alias("_p")), ["prev", "token_id"], "left").join(after, "prev", "left").crossJoin(F.broadcast(first))
    known = F.col("_next").isNotNull()
    logp = F.when(F.col("_p").isNotNull(), F.log("_p")).when(known, F.log(F.lit(backoff)) + F.col("_u")).otherwise(F.col("_u"))
    best = F.when(known & (F.col("_next_p") >= F.col("_top_p")), F.col("_next")).otherwise(F.col("_top"))
    return t.withColumn(name, logp).withColumn("best", best).drop("prev", "_u", "_p", "_next", "_next_p", "_top", "_top_p")


def score(trace: DataFrame, policy: DataFrame, name: str = "o", broadcast_rows: int = 2_000_000) -> DataFrame:
    """Adds the log-probability of each token under ``policy``; tokens it lacks get its unseen mass.

    The table is broadcast only when its checked size allows it; beyond that the join shuffles on token_id.
    """
    small = policy.limit(broadcast_rows + 1).count() <= broadcast_rows
    table = policy.select("token_id", F.col("logp").alias("_l"))
    other = policy.select(F.col("other_logp").alias("_o")).limit(1)
    out = trace.join(F.broadcast(table) if small else table, "token_id", "left").crossJoin(F.broadcast(other))
    return out.withColumn(name, F.coalesce("_l", "_o")).drop("_l", "_o")


def temper(policy: DataFrame, tau: float) -> DataFrame:
    """logp of the policy at temperature tau, renormalised with the maximum taken out."""
    top = policy.agg((F.max("logp") / tau).alias("_top"))
    p = policy.crossJoin(F.broadcast(top)).withColumn("_x", F.exp(F.col("logp") / tau - F.col("_top")))
    z = p.agg(F.sum("_x").alias("_z"))
    return p.crossJoin(F.broadcast(z)).select("token_id", F.log(F.col("_x") / F.col("_z")).alias("logp"))


def top_k(policy: DataFrame, k: int) -> DataFrame:
    """The k likeliest tokens (ties by id), renormalised. A bounded top-n, so what follows works on k rows."""
    best = policy.orderBy(F.desc("logp"), "token_id").limit(k).select("token_id", F.exp("logp").alias("p"))
    return best.withColumn("p", F.col("p") / F.sum("p").over(Window.partitionBy()))


def nucleus(policy: DataFrame, top_p: float) -> DataFrame:
    """The smallest set of likeliest tokens (ties by id) with mass of at least top_p, renormalised, over a policy of any size.

    Masses are summed by distinct probability first, and one row tells where the set ends; only tokens of that one probability are
    ranked by id.
    """
    if top_p >= 1.0:
        return policy.select("token_id", F.exp("logp").alias("p"))
    each = policy.groupBy("logp").agg((F.count("*") * F.exp("logp")).alias("_mass"))
    each = with_range(each, -F.col("logp"))
    sums = each.groupBy("_part").agg(F.sum("_mass").alias("_s"))
    before = F.coalesce(F.sum("_s").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))  # one row a range
    inside = F.coalesce(F.sum("_mass").over(Window.partitionBy("_part").orderBy(F.desc("logp")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    each = each.join(F.broadcast(sums.select("_part", before.alias("_b"))), "_part").withColumn("_before", F.col("_b") + inside)
    edge = each.filter(F.col("_before") < top_p).agg(F.min_by(F.struct("logp", "_before"), "logp").alias("e")).first()["e"]
    if edge is None:
        return policy.select("token_id", F.exp("logp").alias("p"))
    last = global_rank(policy.filter(F.col("logp") == F.lit(edge["logp"])), F.col("token_id"), [])
    last = last.filter(F.lit(edge["_before"]) + (F.col("rank") - 1) * F.exp("logp") < top_p)
    kept = policy.filter(F.col("logp") > F.lit(edge["logp"])).select("token_id", F.exp("logp").alias("p")).unionByName(last.select("token_id", F.exp("logp").alias("p")))
    return kept.crossJoin(F.broadcast(kept.agg(F.sum("p").alias("_all")))).select("token_id", (F.col("p") / F.col("_all")).alias("p"))


def uniform(*parts: Column) -> Column:
    """A reproducible number in (0, 1) from the parts' digest: the same on any engine and partitioning."""
    return (F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("double") + 0.5) / 4294967296.0


def sample(prompts: DataFrame, dist: DataFrame, n: int, max_tokens: int, seed: int) -> DataFrame:
    """rollout_id (prompt_id * n + sample), pos, token_id by inverse distribution over a bounded table (token_id, p)."""
    w = Window.orderBy(F.desc("p"), "token_id")
    cdf = dist.select("token_id", (F.sum("p").over(w) - F.col("p")).alias("_lo"), F.sum("p").over(w).alias("_hi"), F.row_number().over(w).alias("_k"), F.count("*").over(Window.partitionBy()).alias("_n"))
    cdf = cdf.withColumn("_hi", F.when(F.col("_k") == F.col("_n"), F.lit(2.0)).otherwise(F.col("_hi")))  # rounding never loses a draw
    r = prompts.select("prompt_id", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("s")).select("prompt_id", (F.col("prompt_id") * n + F.col("s")).alias("rollout_id"))
    d = r.select("prompt_id", "rollout_id", F.explode(F.sequence(F.lit(0), F.lit(max_tokens - 1))).alias("pos")).withColumn("_u", uniform(F.lit(seed), F.col("rollout_id"), F.col("pos")))
    return d.join(F.broadcast(cdf), (F.col("_u") >= F.col("_lo")) & (F.col("_u") < F.col("_hi"))).select("prompt_id", "rollout_id", F.col("pos").cast("long").alias("pos"), "token_id")


def pieces(docs: DataFrame) -> DataFrame:
    """token_id, piece: a word of each token of all documents, the smallest where ids collide."""
    p = docs.select(F.explode(tokens.split(F.col("text"))).alias("piece")).distinct()
    return p.groupBy(tokens.token_id(F.col("piece")).alias("token_id")).agg(F.min("piece").alias("piece"))


def sample_whole(draws: DataFrame, policy: DataFrame, seed: int, by: list[str], task_rows: int = 250_000, buckets: int = 1 << 20, carry: tuple[str, ...] = ()) -> DataFrame:
    """Adds token_id, and the policy's columns in ``carry``, to each row of ``draws`` by inverse distribution over a policy (token_id, logp) of any size.

    Probabilities become whole numbers of 2^-50, so intervals meet exactly and each entry can be drawn. Their running sums follow
    token_id, in ranges ranked on their own and shifted by the sums before them; draws meet intervals in equal buckets of mass, by an
    equi-join. ``by`` names the columns that, with the seed, make a row's number. The policy is read three times: pass a written one.
    """
    x = policy.select("token_id", *carry, F.greatest(F.lit(1), F.round(F.exp("logp") * float(1 << 50))).cast("long").alias("_w"))
    size, total = x.agg(F.count("*"), F.coalesce(F.sum("_w"), F.lit(0))).first()
    parts = max(8, -(-size // task_rows))
    x = x.withColumn("_part", F.floor(F.col("token_id") * parts / float(1 << 32)))
    sums = x.groupBy("_part").agg(F.sum("_w").alias("_s"))
    before = F.coalesce(F.sum("_s").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a range
    sums = sums.select("_part", before.alias("_before"))
    width = max(1, -(-total // max(1, min(size, buckets))))
    hi = F.col("_before") + F.sum("_w").over(Window.partitionBy("_part").orderBy("token_id"))
    spans = x.join(F.broadcast(sums), "_part").withColumn("_hi", hi).select("token_id", *carry, (F.col("_hi") - F.col("_w")).alias("_lo"), "_hi")
    whole = lambda c: F.expr(f"{c} div {width}")  # noqa: E731  exact on longs
    spans = spans.withColumn("_b", F.explode(F.sequence(whole("_lo"), whole("(_hi - 1)"))))
    digits = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in by])), 1, 13), 16, 10).cast("long")
    at = F.least(F.floor(digits * (total / float(1 << 52))), F.lit(max(0, total - 1)))
    d = draws.withColumn("_at", at)
    return d.join(spans, whole("_at") == F.col("_b")).filter("_at >= _lo and _at < _hi").select(*draws.columns, "token_id", *carry)


def cap(lengths: DataFrame, context: int, response: int) -> DataFrame:
    """kept: tokens left of a response under both caps; truncated: whether any were cut."""
    kept = F.greatest(F.lit(0), F.least(F.col("n_tokens"), F.lit(response), F.lit(context) - F.col("prompt_tokens")))
    return lengths.withColumn("kept", kept).withColumn("truncated", F.col("n_tokens") > F.col("kept"))


def publish(theta: DataFrame, version: int, path: str) -> bool:
    """Writes one version as a partition and then its marker; an existing version is left as it is (False), so a replay publishes once."""
    spark = theta.sparkSession
    if version in published(spark, path):
        return False
    if version and version - 1 not in published(spark, path):
        raise ValueError("versions are published in order")
    theta.withColumn("version", F.lit(version)).write.mode("overwrite").parquet(f"{path}/theta/version={version}")
    spark.range(1).select(F.lit(version).alias("version")).write.mode("overwrite").parquet(f"{path}/marker/v={version}")
    return True


def published(spark: SparkSession, path: str) -> list[int]:
    from pyspark.errors import AnalysisException

    try:
        return sorted(r[0] for r in spark.read.schema("version int").parquet(f"{path}/marker/*").distinct().collect())
    except AnalysisException:
        return []


def load(spark: SparkSession, path: str, version: int) -> DataFrame:
    return spark.read.parquet(f"{path}/theta/version={version}").drop("version")


def serve_precision(policy: DataFrame, digits: int) -> DataFrame:
    """The serving side's log-probabilities: rounded, which is where training and inference part."""
    return policy.withColumn("logp", F.round("logp", digits)).withColumn("other_logp", F.round("other_logp", digits))


def fit_once(docs: DataFrame, version: int, **how) -> DataFrame:
    return materialise(fit(docs, version, **how))
