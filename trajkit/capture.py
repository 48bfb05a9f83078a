"""Capture of exchanges as token-exact segments.

Requests are records of what an agent sent; engine tokens are what the serving engine returned. A request continues
the current segment iff its messages extend the recorded history (the previous request and its reply) and the rendered
stream keeps its prefix; otherwise it opens a segment. All steps share one partitioning by rollout.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit import tokens



def _by():
    return Window.partitionBy("rollout_id").orderBy("request_seq")


def engine_tokens(requests: DataFrame, logp=None, version: Column | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """rollout_id, request_seq, pos, token_id, b, version: the reply's tokens as the engine returned them, with the request's columns in ``carry``."""
    t = requests.select("rollout_id", "request_seq", *carry, F.posexplode(tokens.split(F.col("reply"))).alias("pos", "piece"))
    return t.select("rollout_id", "request_seq", *carry, F.col("pos").cast("long").alias("pos"), tokens.token_id(F.col("piece")).alias("token_id"), (logp or F.lit(-1.0)).alias("b"), (version if version is not None else F.lit(0)).alias("version"))


def record(requests: DataFrame, engine: DataFrame) -> DataFrame:
    """Action tokens with their context: joined on the exchange; the engine's ids are taken as they are."""
    return requests.select("rollout_id", "request_seq", F.size(tokens.render(F.col("messages"))).alias("context_tokens")).join(engine, ["rollout_id", "request_seq"])


def retokenise_drift(requests: DataFrame, engine: DataFrame, scheme: str = "char_bigram") -> DataFrame:
    """Share of engine tokens that a trace rebuilt from reply text with another scheme would place differently."""
    again = requests.select("rollout_id", "request_seq", F.posexplode(tokens.split(F.col("reply"), scheme)).alias("pos", "piece"))
    again = again.select("rollout_id", "request_seq", F.col("pos").cast("long").alias("pos"), tokens.token_id(F.col("piece")).alias("again"))
    both = engine.join(again, ["rollout_id", "request_seq", "pos"], "left")
    return both.groupBy("rollout_id").agg(F.count("*").alias("n_tokens"), F.sum((~F.col("token_id").eqNullSafe(F.col("again"))).cast("long")).alias("n_moved"))


def contract_violations(trace: DataFrame, engine: DataFrame) -> DataFrame:
    """Positions with m = 1 whose id the engine didn't return there."""
    return trace.filter("m = 1").join(engine.select("rollout_id", "request_seq", "pos", "token_id"), ["rollout_id", "request_seq", "pos", "token_id"], "left_anti")


def history_extends(requests: DataFrame) -> DataFrame:
    """extends: the messages start with the previous request's messages and its reply. The first request of a rollout extends nothing."""
    reply = F.struct(F.lit("assistant").alias("role"), F.col("reply").alias("content"))
    seen = F.lag(F.concat("messages", F.array(reply))).over(_by())
    return requests.withColumn("_seen", seen).withColumn("extends", F.col("_seen").isNotNull() & (F.slice("messages", F.lit(1), F.greatest(F.size("_seen"), F.lit(1))) == F.col("_seen"))).drop("_seen")


def history_extends_by_digest(requests: DataFrame) -> DataFrame:
    """The same from chained digests: d_k = md5(d_(k-1), message_k). What is compared and carried is a digest per message, not its text."""
    reply = F.struct(F.lit("assistant").alias("role"), F.col("reply").alias("content"))
    link = lambda acc, m: F.concat(acc, F.array(F.md5(F.concat_ws("\x1f", F.coalesce(F.try_element_at(acc, F.lit(-1)), F.lit("")), m["role"], m["content"]))))
    chain = F.aggregate(F.concat("messages", F.array(reply)), F.array(F.lit("")), link)
    r = requests.withColumn("_chain", chain)
    r = r.withColumn("_last", F.lag(F.element_at("_chain", -1)).over(_by())).withColumn("_n", F.lag(F.size("_chain")).over(_by()))
    return r.withColumn("extends", F.coalesce((F.col("_n") < F.size("_chain")) & (F.get("_chain", F.col("_n") - 1) == F.col("_last")), F.lit(False))).drop("_chain", "_last", "_n")


def prefix_kept(requests: DataFrame, template: str = "marked") -> DataFrame:
    """prefix_kept: the rendered stream starts with the previous rendered stream and its reply, rendered as that template does."""
    reply = F.struct(F.lit("assistant").alias("role"), F.col("reply").alias("content"))
    r = requests.withColumn("_now", tokens.render(F.col("messages"), template)).withColumn("_next", tokens.render(F.concat("messages", F.array(reply)), template))
    r = r.withColumn("_seen", F.lag("_next").over(_by()))
    return r.withColumn("prefix_kept", F.col("_seen").isNotNull() & (F.slice("_now", F.lit(1), F.greatest(F.size("_seen"), F.lit(1))) == F.col("_seen"))).drop("_now", "_next", "_seen")


def segment(requests: DataFrame, template: str = "marked", check: str = "both") -> DataFrame:
    """Adds segment_seq from 0. check: both (the rule), history, prefix, never (one segment), always (one per request).

    A retry of the same request, a shorter or an edited history opens a segment; an empty reply or a tool-only turn continues
    if it extends; rollouts without requests have no segments.
    """
    first = F.row_number().over(_by()) == 1
    if check == "never":
        return requests.withColumn("segment_seq", F.lit(0).cast("long"))
    if check == "always":
        return requests.withColumn("segment_seq", (F.row_number().over(_by()) - 1).cast("long"))
    r = requests
    goes_on = F.lit(True)
    if check in ("both", "history"):
        r, goes_on = history_extends(r), goes_on & F.col("extends")
    if check in ("both", "prefix"):
        r, goes_on = prefix_kept(r, template), goes_on & F.col("prefix_kept")
    opens = F.when(first, 0).when(goes_on, 0).otherwise(1)
    return r.withColumn("_open", opens).withColumn("segment_seq", F.sum("_open").over(_by().rowsBetween(Window.unboundedPreceding, 0)).cast("long")).drop("_open", "extends", "prefix_kept")


def assemble(segmented: DataFrame, template: str = "marked") -> DataFrame:
    """One row per segment: token_ids, action_mask and action_ranges.

    The last request of a segment renders the whole context once; its earlier replies are inside it. Ranges are computed from
    running lengths: each request's context length is where its sampled tokens start.
    """
    ids = lambda pieces: F.transform(pieces, tokens.token_id)
    extra = 0 if template == "plain" else 1
    r = segmented.withColumn("_lo", F.size(tokens.render(F.col("messages"), template)) + extra).withColumn("_n", F.size(tokens.split(F.col("reply"))))
    s = r.groupBy("rollout_id", "segment_seq").agg(
        F.array_sort(F.collect_list(F.struct(F.col("_lo").alias("lo"), (F.col("_lo") + F.col("_n")).alias("hi")))).alias("action_ranges"),
        F.max_by(F.struct("messages", "reply"), "request_seq").alias("last"), F.count("*").alias("n_requests"),
    )
    reply = F.struct(F.lit("assistant").alias("role"), F.col("last.reply").alias("content"))
    s = s.withColumn("token_ids", ids(tokens.render(F.concat("last.messages", F.array(reply)), template)))
    mask = F.transform("token_ids", lambda _, i: F.exists("action_ranges", lambda x: (x["lo"] <= i) & (i < x["hi"])))
    return s.withColumn("action_mask", mask).drop("last")


def ranges_from_mask(trace: DataFrame) -> DataFrame:
    """(rollout_id, lo, hi) of maximal runs of action tokens, by gaps and islands."""
    island = F.col("pos") - F.row_number().over(Window.partitionBy("rollout_id").orderBy("pos"))
    return trace.filter("m = 1").withColumn("_i", island).groupBy("rollout_id", "_i").agg(F.min("pos").alias("lo"), (F.max("pos") + 1).alias("hi")).drop("_i")


def mask_from_ranges(ranges: DataFrame) -> DataFrame:
    return ranges.select("rollout_id", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("pos"))
