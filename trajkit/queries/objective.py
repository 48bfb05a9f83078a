"""Groups, estimators, corrections and losses on orders and lineitem (volume fixtures)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from trajkit import advantages, batches, correction, critic, groups, losses, measures, prompts, update, workloads
from trajkit.registered import query
from trajkit.oracles import FIRST, ROLLOUTS, TOKENS, TRACE

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)


def four(spark, sf):
    return groups.take_samples(workloads.rollouts(spark, sf), 4)


def live(spark, sf):
    return advantages.group_relative(groups.drop_degenerate(four(spark, sf)))


def trace(spark, sf):
    """Action tokens of the surviving rollouts with their advantages; the light side is broadcast by the planner when small."""
    t = groups.fan_out(live(spark, sf).select("rollout_id", "group_id", "adv", "reward", "reward_c"), workloads.action_tokens(spark, sf))
    return t.withColumn("length", F.count("*").over(Window.partitionBy("rollout_id")))


# ---- groups ----------------------------------------------------------------------------------

query("group_assemble", f"WITH {ROLLOUTS} SELECT group_id, count(*) AS n_rollouts, count(reward) AS n_graded, epoch_us(max(completed_at)) AS done_us, count(reward) >= 4 AS complete FROM rollouts GROUP BY group_id")(
    lambda s, d: groups.assemble(workloads.rollouts(s, d), 4).select("group_id", "n_rollouts", "n_graded", F.unix_micros(F.col("completed_at").cast("timestamp")).alias("done_us"), "complete")
)
query("group_complete", f"WITH {ROLLOUTS} SELECT group_id, rollout_id FROM rollouts WHERE group_id IN (SELECT group_id FROM rollouts GROUP BY 1 HAVING count(*) >= 4)")(
    lambda s, d: groups.complete(workloads.rollouts(s, d), 4).select("group_id", "rollout_id")
)
query("group_first_n", f"WITH {FIRST} SELECT group_id, rollout_id, sample::INTEGER AS sample, reward FROM four")(lambda s, d: four(s, d).select("group_id", "rollout_id", "sample", "reward"))
query("group_stats", f"WITH {ROLLOUTS} SELECT group_id, count(*) AS n, round(avg(reward), 6) AS mean, round(stddev_samp(reward), 6) AS std, min(reward) AS low, max(reward) AS high FROM rollouts GROUP BY 1")(
    lambda s, d: groups.stats(workloads.rollouts(s, d)).select("group_id", "n", r6("mean"), r6("std"), "low", "high")
)
query("dyn_filter", f"WITH {FIRST} SELECT group_id, rollout_id, reward FROM live")(lambda s, d: groups.drop_degenerate(four(s, d)).select("group_id", "rollout_id", "reward"))
query("backfill", f"""WITH {FIRST}, k AS (SELECT group_id, row_number() OVER (ORDER BY done, group_id) AS rank FROM gs WHERE spread > 0) SELECT group_id, rank, (rank - 1) // 32 AS batch FROM k""")(
    lambda s, d: groups.backfill(four(s, d), 32)
)
query("backfill_off", f"""WITH {FIRST}, k AS (SELECT group_id, spread, row_number() OVER (ORDER BY done, group_id) AS rank FROM gs) SELECT (rank - 1) // 32 AS batch, count(*) AS n_groups FROM k WHERE spread > 0 GROUP BY 1""")(
    lambda s, d: groups.backfill(four(s, d), 32, fill=False).groupBy("batch").agg(F.count("*").alias("n_groups"))
)
query("filter_whole", f"WITH {FIRST} SELECT group_id, rollout_id FROM four WHERE group_id NOT IN (SELECT group_id FROM four WHERE gate_hint = '1-URGENT')")(
    lambda s, d: groups.filter_whole(four(s, d), F.col("gate_hint") != "1-URGENT").select("group_id", "rollout_id")
)
query("overlong", f"""WITH {TOKENS}, n AS (SELECT rollout_id, count(*) AS length FROM tok GROUP BY 1)
SELECT rollout_id, length, length > 6 AS masked, CASE WHEN length <= 4 THEN 0.0 WHEN length > 6 THEN -1.0 ELSE -(length - 4) / 2.0 END::DOUBLE AS penalty FROM n""")(
    lambda s, d: groups.overlong(workloads.action_tokens(s, d).groupBy("rollout_id").agg(F.count("*").alias("length")), 6, 2)
)


def _lengths(s, d):
    return trace(s, d).groupBy("rollout_id", "group_id").agg(F.count("*").alias("length")).withColumn("rank_id", F.pmod("group_id", F.lit(8)))


query("mb_fixed", f"WITH {TRACE}, n AS (SELECT rollout_id, group_id % 8 AS rank_id FROM trace GROUP BY ALL) SELECT rollout_id, rank_id, (row_number() OVER (PARTITION BY rank_id ORDER BY rollout_id) - 1) // 4 AS microbatch_id FROM n")(
    lambda s, d: batches.microbatch(_lengths(s, d), "fixed", size=4).select("rollout_id", "rank_id", "microbatch_id")
)
query("mb_budget", f"""WITH {TRACE}, n AS (SELECT rollout_id, group_id % 8 AS rank_id, count(*) AS length FROM trace GROUP BY ALL)
SELECT rollout_id, rank_id, (coalesce(sum(length) OVER (PARTITION BY rank_id ORDER BY rollout_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) // 64)::BIGINT AS microbatch_id FROM n""")(
    lambda s, d: batches.microbatch(_lengths(s, d), "budget", budget=64).select("rollout_id", "rank_id", "microbatch_id")
)
query("mb_next_fit")(lambda s, d: batches.microbatch(_lengths(s, d), "next_fit", budget=64).select("rollout_id", "rank_id", "microbatch_id", "length"))
query("prompt_dedup", "SELECT min(doc_id) AS prompt_id, count(*) AS n_copies FROM documents GROUP BY md5(text)")(lambda s, d: prompts.dedup(workloads.table(s, d, "documents"), "exact").select("prompt_id", "n_copies"))
query("prompt_dedup_normalised", "SELECT min(doc_id) AS prompt_id, count(*) AS n_copies FROM documents GROUP BY md5(trim(lower(text)))")(
    lambda s, d: prompts.dedup(workloads.table(s, d, "documents"), "normalised").select("prompt_id", "n_copies")
)
query("prompt_draw", """WITH p AS (SELECT min(doc_id) AS prompt_id FROM documents GROUP BY md5(text)), o AS (SELECT prompt_id, row_number() OVER (ORDER BY md5('7:' || prompt_id), prompt_id) AS place FROM p)
SELECT prompt_id, place::INTEGER AS place FROM o WHERE place <= 2000""")(lambda s, d: prompts.draw(prompts.dedup(workloads.table(s, d, "documents"), "exact"), 2000, 7).select("prompt_id", "place"))

# ---- advantages ------------------------------------------------------------------------------

_ADV = "SELECT rollout_id, group_id, round({}, 6) AS adv FROM four JOIN gs USING (group_id)"


def _adv(name, expr, fn, tail=""):
    query(name, f"WITH {FIRST}{tail} {_ADV.format(expr)}")(lambda s, d: fn(four(s, d)).select("rollout_id", "group_id", r6(F.col("adv") + 0.0, "adv")))


_adv("adv_raw", "reward", advantages.raw)
_adv("adv_batch_mean", "reward - (SELECT avg(reward) FROM four)", advantages.batch_mean)
_adv("adv_group_mean", "reward - mu", advantages.group_mean)
_adv("adv_group_mean_whiten", "(reward - mu - (SELECT avg(x) FROM c)) / ((SELECT stddev_samp(x) FROM c) + 1e-6)", lambda r: advantages.group_mean(r, whiten=True), ", c AS (SELECT reward - mu AS x FROM four JOIN gs USING (group_id))")
_adv("adv_rloo", "reward - (total - reward) / (n - 1)", advantages.leave_one_out)
_adv("adv_grpo", "CASE WHEN spread = 0 THEN 0 ELSE (reward - mu) / (sd + 1e-6) END", advantages.group_relative)
_adv("adv_grpo_pop", "CASE WHEN spread = 0 THEN 0 ELSE (reward - mu) / (sp + 1e-6) END", lambda r: advantages.group_relative(r, ddof=0))
_adv("adv_dr_grpo", "reward - mu", advantages.group_relative_unscaled)

_RPP = f"""WITH {TRACE}, x AS (SELECT *, CASE WHEN pos = length - 1 THEN reward ELSE 0 END - 0.01 * (o - b) AS r FROM trace),
y AS (SELECT *, (SELECT sum(z.r) FROM x z WHERE z.rollout_id = x.rollout_id AND z.pos >= x.pos) AS ret FROM x)"""


@query("adv_reinforce_pp", _RPP + " SELECT rollout_id, pos, round((ret - (SELECT avg(ret) FROM y)) / ((SELECT stddev_pop(ret) FROM y) + 1e-6), 6) AS adv FROM y")
def adv_reinforce_pp(s, d):
    return advantages.reinforce_pp(trace(s, d).withColumn("kl", F.col("o") - F.col("b")), beta=0.01).select("rollout_id", "pos", r6("adv"))


_GAE = f"""WITH RECURSIVE {TRACE}, x AS (SELECT rollout_id, pos, length, CASE WHEN pos = length - 1 THEN reward ELSE 0 END AS r, (pos + 1) / (2.0::DOUBLE * length) AS v FROM trace),
dl AS (SELECT *, r + 0.99 * coalesce(lead(v) OVER (PARTITION BY rollout_id ORDER BY pos), 0) - v AS delta FROM x),
g AS (SELECT rollout_id, pos, v, delta AS a FROM dl WHERE pos = length - 1 UNION ALL SELECT dl.rollout_id, dl.pos, dl.v, dl.delta + 0.99 * 0.95 * g.a FROM g JOIN dl ON dl.rollout_id = g.rollout_id AND dl.pos = g.pos - 1)"""


def _gae_input(s, d):
    return trace(s, d).withColumn("r", F.when(F.col("pos") == F.col("length") - 1, F.col("reward")).otherwise(0.0)).withColumn("v", (F.col("pos") + 1) / (2.0 * F.col("length")))


query("adv_gae", _GAE + " SELECT rollout_id, pos, round(a::DOUBLE, 6) AS adv FROM g")(lambda s, d: advantages.gae(_gae_input(s, d), 0.99, 0.95).select("rollout_id", "pos", r6("adv")))
query("adv_gae_returns", _GAE + " SELECT rollout_id, pos, round((a + v)::DOUBLE, 6) AS ret FROM g")(lambda s, d: advantages.gae(_gae_input(s, d), 0.99, 0.95).select("rollout_id", "pos", r6("ret")))
query("adv_gae_chunked", _GAE + " SELECT rollout_id, pos, round(a::DOUBLE, 6) AS adv FROM g")(lambda s, d: advantages.gae_chunked(_gae_input(s, d), 0.99, 0.95, chunk=3).select("rollout_id", "pos", r6("adv")))

_RET = f"WITH {TRACE}, x AS (SELECT *, pow(0.9::DOUBLE, length - 1 - pos) * reward AS ret FROM trace), bk AS (SELECT least(pos, 3) AS pos_bucket, least(length, 6) AS len_bucket, avg(ret) AS value, count(*) AS n FROM x GROUP BY ALL)"


def _with_returns(s, d):
    return trace(s, d).withColumn("ret", F.pow(F.lit(0.9), F.col("length") - 1 - F.col("pos")) * F.col("reward"))


query("critic_value", _RET + " SELECT pos_bucket, len_bucket, round(value, 6) AS value, n FROM bk")(lambda s, d: critic.fit(_with_returns(s, d)).select("pos_bucket", "len_bucket", r6("value"), "n"))


@query("critic_loss", _RET + """, z AS (SELECT ret, value AS v, 0.9 * value AS old FROM x JOIN bk ON pos_bucket = least(pos, 3) AND len_bucket = least(length, 6))
SELECT 'plain' AS kind, round(avg(0.5 * (v - ret) ** 2), 6) AS value_loss FROM z
UNION ALL SELECT 'clipped', round(avg(0.5 * greatest((v - ret) ** 2, (greatest(least(v, old + 0.02), old - 0.02) - ret) ** 2)), 6) FROM z""")
def critic_loss(s, d):
    t = _with_returns(s, d)
    t = critic.score(t, critic.fit(t)).withColumn("v_old", 0.9 * F.col("v"))
    a, b = critic.value_loss(t), critic.value_loss(t, 0.02)
    return a.select(F.lit("plain").alias("kind"), r6("value_loss")).unionByName(b.select(F.lit("clipped").alias("kind"), r6("value_loss")))


@query("adv_segments", f"""WITH {TRACE}, e AS (SELECT *, max(pos) OVER (PARTITION BY rollout_id, segment_seq) AS last FROM trace)
SELECT rollout_id, round(sum(pow(0.9::DOUBLE, length - 1 - pos) * reward), 6) AS across, round(sum(pow(0.9::DOUBLE, last - pos) * reward), 6) AS restarted FROM e GROUP BY 1""")
def adv_segments(s, d):
    t = trace(s, d).withColumn("kl", F.lit(0.0))
    out = None
    for name, by in (("across", ["rollout_id"]), ("restarted", ["rollout_id", "segment_seq"])):
        part = advantages.returns(advantages.token_rewards(t, 0.0, by=by), 0.9, by).groupBy("rollout_id").agg(F.round(F.sum("ret"), 6).alias(name))
        out = part if out is None else out.join(part, "rollout_id")
    return out


@query("adv_edge", f"""WITH {ROLLOUTS}, g AS (SELECT group_id, rollout_id, CASE WHEN gate_hint = '5-LOW' THEN NULL ELSE reward END AS reward FROM rollouts),
k AS (SELECT group_id, count(*) AS n, count(reward) AS c, max(reward) - min(reward) AS spread FROM g GROUP BY 1)
SELECT CASE WHEN c < n THEN 'incomplete' WHEN n = 1 THEN 'singleton' WHEN spread = 0 THEN 'equal' ELSE 'mixed' END AS kind, count(*) AS n_groups,
  sum(CASE WHEN c = n AND n > 1 AND spread > 0 THEN 1 ELSE 0 END)::BIGINT AS n_active FROM k GROUP BY 1""")
def adv_edge(s, d):
    r = workloads.rollouts(s, d).withColumn("reward", F.when(F.col("gate_hint") != "5-LOW", F.col("reward")))
    r = advantages.group_relative(r).withColumn("rloo", F.col("adv"))
    r = advantages.leave_one_out(r.drop("adv"))
    g = r.groupBy("group_id").agg(F.count("*").alias("n"), F.count("reward").alias("c"), (F.max("reward") - F.min("reward")).alias("spread"), F.max(F.abs("rloo")).alias("top"))
    whole = F.col("c") == F.col("n")
    kind = F.when(~whole, "incomplete").when(F.col("n") == 1, "singleton").when(F.col("spread") == 0, "equal").otherwise("mixed")
    return g.groupBy(kind.alias("kind")).agg(F.count("*").alias("n_groups"), F.sum((whole & (F.col("top") > 0)).cast("long")).alias("n_active"))


# ---- correction ------------------------------------------------------------------------------


def _weights(name, expr, fn, tail=""):
    query(name, f"WITH {TRACE}{tail} SELECT rollout_id, pos, round({expr}, 6) AS w FROM trace ORDER BY 1, 2" if not tail else f"WITH {TRACE}{tail} SELECT rollout_id, pos, round({expr}, 6) AS w FROM q")(
        lambda s, d: fn(trace(s, d)).select("rollout_id", "pos", r6("w"))
    )


_SEQ = ", q AS (SELECT trace.*, lr, ls FROM trace JOIN (SELECT rollout_id, segment_seq, avg(o - b) AS lr, sum(o - b) AS ls FROM trace GROUP BY ALL) USING (rollout_id, segment_seq))"
query("logp_present", f"WITH {TRACE} SELECT rollout_id, pos FROM trace WHERE b IS NULL")(lambda s, d: correction.attach(trace(s, d)).select("rollout_id", "pos"))
_weights("corr_tis", "least(exp(o - b), 2)", correction.token_truncate)
_weights("corr_mask", "CASE WHEN exp(o - b) BETWEEN 0.5 AND 2 THEN exp(o - b) ELSE 0 END", correction.token_mask)
_weights("corr_seq_gate", "CASE WHEN exp(lr) BETWEEN 0.8 AND 1.2 THEN 1 ELSE 0 END::DOUBLE", lambda t: correction.seq_gate(t, 0.8, 1.2), _SEQ)
_weights("corr_seq_prod", "CASE WHEN exp(ls) BETWEEN 0.8 AND 1.2 THEN 1 ELSE 0 END::DOUBLE", lambda t: correction.seq_gate(t, 0.8, 1.2, "prod"), _SEQ)
_weights("corr_gate_tis", "CASE WHEN exp(lr) BETWEEN 0.8 AND 1.2 THEN least(exp(o - b), 2) ELSE 0 END", lambda t: correction.gate_truncate(t, 0.8, 1.2), _SEQ)
_weights("corr_seq_tis", "least(exp(sr), 2)", correction.seq_truncate, ", q AS (SELECT trace.*, sr FROM trace JOIN (SELECT rollout_id, sum(o - b) AS sr FROM trace GROUP BY ALL) USING (rollout_id))")
query("corr_report", f"""WITH {TRACE}, x AS (SELECT exp(o - b) AS rho, least(exp(o - b), 2) AS w, o - b AS gap, exp(c - o) AS q, adv FROM trace)
SELECT count(*) AS n_tokens, round(avg(rho), 6) AS rho_mean, round(max(rho), 6) AS rho_max, round(avg(CASE WHEN rho > 2 THEN 1.0 ELSE 0.0 END), 6) AS truncated, round(avg(rho - w), 6) AS bias,
 round(-avg(gap), 6) AS kl_k1, round(sum(w) * sum(w) / sum(w * w), 6) AS ess, round(avg(CASE WHEN abs(q - 1) > 0.2 THEN 1.0 ELSE 0.0 END), 6) AS clipped FROM x""")(lambda s, d: measures.correction_report(trace(s, d)))


@query("gate_retained", f"""WITH {TRACE}, q AS (SELECT rollout_id, segment_seq, exp(avg(o - b)) BETWEEN 0.8 AND 1.2 AS keep, count(*) AS n FROM trace GROUP BY ALL)
SELECT round(avg(keep::INT), 6) AS by_sequence, round(sum(CASE WHEN keep THEN n ELSE 0 END) / sum(n), 6) AS by_token, count(*) AS n_sequences FROM q""")
def gate_retained(s, d):
    return measures.retained(correction.seq_gate(trace(s, d), 0.8, 1.2)).select(r6("by_sequence"), r6("by_token"), "n_sequences")


@query("version_mix", f"""WITH {TRACE}, v AS (SELECT rollout_id, datediff('day', DATE '1992-01-01', sampled_at::DATE) // 30 AS version FROM trace)
SELECT n_versions, count(*) AS n_rollouts FROM (SELECT rollout_id, count(DISTINCT version) AS n_versions FROM v GROUP BY 1) GROUP BY 1""")
def version_mix(s, d):
    t = trace(s, d).withColumn("version", F.floor(F.datediff(F.to_date("sampled_at"), F.lit("1992-01-01").cast("date")) / 30))
    return correction.version_mix(t).groupBy("n_versions").agg(F.count("*").alias("n_rollouts"))


# ---- losses ----------------------------------------------------------------------------------


def _loss(s, d):
    return trace(s, d).withColumn("w", F.lit(1.0)).withColumn("l", -F.col("adv"))


@query("loss_window", f"WITH {TRACE} SELECT round(sum(-adv) + 0.0, 6) AS num, count(*) AS den, round(sum(-adv) / count(*), 6) AS loss FROM trace")
def loss_window(s, d):
    return losses.window_token_mean(_loss(s, d)).select(r6(F.col("num") + 0.0, "num"), "den", r6("loss"))


query("loss_mb_mean", f"WITH {TRACE} SELECT round(avg(x), 6) AS loss FROM (SELECT avg(-adv) AS x FROM trace GROUP BY rollout_id)")(lambda s, d: losses.mean_of_means(_loss(s, d), ["rollout_id"]).select(r6("loss")))
query("loss_seq_mean", f"WITH {TRACE} SELECT round(avg(x), 6) AS loss FROM (SELECT avg(-adv) AS x FROM trace GROUP BY rollout_id, segment_seq)")(
    lambda s, d: losses.mean_of_means(_loss(s, d), ["rollout_id", "segment_seq"]).select(r6("loss"))
)
query("loss_rank_mean", f"WITH {TRACE} SELECT round(avg(x), 6) AS loss FROM (SELECT avg(-adv) AS x FROM trace GROUP BY group_id % 8)")(
    lambda s, d: losses.mean_of_means(_loss(s, d).withColumn("rank_id", F.pmod("group_id", F.lit(8))), ["rank_id"]).select(r6("loss"))
)
query("loss_const", f"WITH {TRACE} SELECT round(sum(-adv) / (count(DISTINCT rollout_id) * 8.0), 6) AS loss FROM trace")(lambda s, d: losses.constant_length(_loss(s, d), 8).select(r6("loss")))
query("loss_accepted", f"WITH {TRACE}, x AS (SELECT adv, CASE WHEN exp(o - b) BETWEEN 0.8 AND 1.25 THEN exp(o - b) ELSE 0 END AS w FROM trace) SELECT round(sum(-w * adv) / sum(CASE WHEN w > 0 THEN 1 ELSE 0 END), 6) AS loss FROM x")(
    lambda s, d: losses.accepted_only(correction.token_mask(trace(s, d), 0.8, 1.25).withColumn("l", -F.col("w") * F.col("adv"))).select(r6("loss"))
)
_SPLITS = [(1, 1), (2, 3), (8, 5), (4, 16)]
query("loss_invariance", f"WITH {TRACE} " + " UNION ALL ".join(
    f"SELECT {r} AS ranks, {m} AS microbatches, (SELECT round(sum(-adv) / count(*), 6) FROM trace) AS loss, (SELECT round(avg(x), 6) FROM (SELECT avg(-adv) AS x FROM trace GROUP BY rollout_id % {r}, (rollout_id // {r}) % {m})) AS mean_of_means" for r, m in _SPLITS
))(lambda s, d: losses.invariance(_loss(s, d), _SPLITS).select("ranks", "microbatches", r6("loss"), r6("mean_of_means")))


def _surrogate(name, expr, **how):
    query(name, f"WITH {TRACE}, x AS (SELECT *, exp(c - o) AS q FROM trace) SELECT round(avg({expr}), 6) AS loss FROM x")(
        lambda s, d: losses.window_token_mean(trace(s, d).withColumn("l", losses.surrogate(**how))).select(r6("loss"))
    )


_surrogate("loss_plain", "-q * adv", kind="plain")
_surrogate("loss_clip", "-least(q * adv, greatest(least(q, 1.2), 0.8) * adv)", kind="clip")
_surrogate("loss_clip_asym", "-least(q * adv, greatest(least(q, 1.28), 0.8) * adv)", kind="clip", high=0.28)
_surrogate("loss_dual", "-CASE WHEN adv < 0 THEN greatest(least(q * adv, greatest(least(q, 1.2), 0.8) * adv), 1.1 * adv) ELSE least(q * adv, greatest(least(q, 1.2), 0.8) * adv) END", kind="dual", dual=1.1)


@query("loss_total", f"""WITH {TRACE}, x AS (SELECT *, exp(c - o) AS q, least(exp(o - b), 2) AS w FROM trace)
SELECT round(avg(w * -least(q * adv, greatest(least(q, 1.2), 0.8) * adv) + 0.05 * (exp(-(o - b)) - 1 + (o - b)) - 0.01 * (-c)), 6) AS loss FROM x""")
def loss_total(s, d):
    t = correction.token_truncate(trace(s, d)).withColumn("ref", F.col("b"))
    return losses.window_token_mean(t.withColumn("l", losses.contribution(losses.surrogate("clip"), 0.05, 0.01, losses.kl("k3"), -F.col("c")))).select(r6("loss"))


@query("ratio_base", f"""WITH {TRACE}, x AS (SELECT *, exp(c - o) AS q, exp(c - b) AS p, least(exp(o - b), 2) AS w FROM trace)
SELECT round(avg(w * -least(q * adv, greatest(least(q, 1.2), 0.8) * adv)), 6) AS actor, round(avg(-least(p * adv, greatest(least(p, 1.2), 0.8) * adv)), 6) AS behaviour FROM x""")
def ratio_base(s, d):
    t = correction.token_truncate(trace(s, d))
    a, b = t.withColumn("l", F.col("w") * losses.surrogate("clip")), t.withColumn("l", losses.surrogate("clip", base="behaviour"))
    return losses.window_token_mean(a).select(r6("loss", "actor")).crossJoin(losses.window_token_mean(b).select(r6("loss", "behaviour")))


_PART_POLICY = "pol AS (SELECT p_partkey AS token_id, p_retailprice / 1000 AS theta FROM part), z AS (SELECT token_id, theta, theta - (SELECT max(theta) + ln(sum(exp(theta - (SELECT max(theta) FROM pol)))) FROM pol) AS logp FROM pol)"
_GRAD = f"""WITH {TRACE}, {_PART_POLICY}, k AS (SELECT token_id, CASE WHEN (adv >= 0 AND exp(c - o) <= 1.2) OR (adv < 0 AND exp(c - o) >= 0.8) THEN -least(exp(o - b), 2) * exp(c - o) * adv ELSE 0 END AS k FROM trace),
own AS (SELECT token_id, sum(k) AS k FROM k GROUP BY 1), g AS (SELECT z.token_id, theta, (coalesce(own.k, 0) - exp(logp) * (SELECT sum(k) FROM k)) / (SELECT count(*) FROM k) AS grad FROM z LEFT JOIN own USING (token_id))"""


def part_policy(s, d):
    return update.softmax(workloads.table(s, d, "part").select(F.col("p_partkey").alias("token_id"), (F.col("p_retailprice") / 1000).alias("theta")))


def _gradient(s, d):
    return update.gradient(update.coefficients(correction.token_truncate(trace(s, d))), part_policy(s, d))


query("grad", _GRAD + " SELECT token_id, round(grad * 1000 + 0.0, 6) AS grad_milli FROM g")(lambda s, d: _gradient(s, d).select("token_id", r6(F.col("grad") * 1000 + 0.0, "grad_milli")))


@query("adam_step", _GRAD + """, n AS (SELECT sqrt(sum(grad * grad)) AS norm FROM g), h AS (SELECT token_id, theta, grad * least(1.0, 0.01 / ((SELECT norm FROM n) + 1e-12)) AS g FROM g)
SELECT token_id, round(theta - 0.01 * ((0.1 * g) / (1 - 0.9::DOUBLE)) / (sqrt((0.001 * g * g) / (1 - 0.999::DOUBLE)) + 1e-8), 5) AS theta FROM h""")
def adam_step(s, d):
    state = part_policy(s, d).select("token_id", "theta", F.lit(0.0).alias("mean"), F.lit(0.0).alias("var"))
    return update.adam(state, _gradient(s, d), 1, clip=0.01).select("token_id", F.round("theta", 5).alias("theta"))


@query("reward_bias", f"""WITH {TRACE}, k AS (SELECT rollout_id, count(DISTINCT segment_seq) AS k FROM trace GROUP BY 1)
SELECT group_id, round(sum(reward * k) / sum(k), 6) AS by_segment, round(avg(reward), 6) AS by_rollout FROM live JOIN k USING (rollout_id) GROUP BY 1""")
def reward_bias(s, d):
    return groups.segment_counted_stats(live(s, d), workloads.action_tokens(s, d)).select("group_id", r6("by_segment"), r6("by_rollout"))


@query("reward_once", f"""WITH {TRACE}, sg AS (SELECT rollout_id, segment_seq, count(*) AS n_tokens FROM trace GROUP BY ALL)
SELECT sg.rollout_id, segment_seq, n_tokens, round(adv, 6) AS adv FROM sg JOIN live USING (rollout_id)""")
def reward_once(s, d):
    seg = workloads.action_tokens(s, d).groupBy("rollout_id", "segment_seq").agg(F.count("*").alias("n_tokens"))
    return groups.fan_out(live(s, d).select("rollout_id", "adv"), seg).select("rollout_id", "segment_seq", "n_tokens", r6("adv"))


# ---- masks and versions: the same with context tokens in the trace ------------------------------


def masked(s, d):
    """The trace with its context tokens: only actions carry loss, weight and gradient; versions change within a rollout."""
    t = trace(s, d).withColumn("m", F.col("mixed_action").cast("int"))
    return t.withColumn("version", F.floor(F.datediff(F.to_date("sampled_at"), F.lit("1992-01-01").cast("date")) / 30))


_MASKED = f"WITH {TRACE}, mt AS (SELECT *, mixed_action::INT AS m, datediff('day', DATE '1992-01-01', sampled_at::DATE) // 30 AS version, exp(c - o) AS q, exp(o - b) AS rho FROM trace)"
_CLIP = "least(q * adv, greatest(least(q, 1.2), 0.8) * adv)"


@query("loss_masked", _MASKED + f"""SELECT round(sum(m * least(rho, 2) * -{_CLIP}), 6) AS num, sum(m)::BIGINT AS den, round(sum(m * least(rho, 2) * -{_CLIP}) / sum(m), 6) AS loss, count(*) AS n_tokens FROM mt""")
def loss_masked(s, d):
    """Context tokens are in the window and in neither sum."""
    t = correction.token_truncate(masked(s, d)).withColumn("l", F.col("w") * losses.surrogate("clip"))
    return losses.window_token_mean(t).select(r6("num"), "den", r6("loss")).crossJoin(t.agg(F.count("*").alias("n_tokens")))


@query("loss_masked_means", _MASKED + """SELECT 'sequence' AS over, round(avg(x), 6) AS loss FROM (SELECT sum(m * -q * adv) / sum(m) AS x FROM mt GROUP BY rollout_id, segment_seq HAVING sum(m) > 0)
UNION ALL SELECT 'rank', round(avg(x), 6) FROM (SELECT sum(m * -q * adv) / sum(m) AS x FROM mt GROUP BY group_id % 8 HAVING sum(m) > 0)
UNION ALL SELECT 'window', round(sum(m * -q * adv) / sum(m), 6) FROM mt""")
def loss_masked_means(s, d):
    """Means of means weigh a token by the company it keeps; the window mean does not."""
    t = masked(s, d).withColumn("w", F.lit(1.0)).withColumn("l", losses.surrogate("plain")).withColumn("rank_id", F.pmod("group_id", F.lit(8)))
    named = lambda df, name: df.select(F.lit(name).alias("over"), r6("loss"))
    out = named(losses.mean_of_means(t, ["rollout_id", "segment_seq"]), "sequence").unionByName(named(losses.mean_of_means(t, ["rank_id"]), "rank"))
    return out.unionByName(named(losses.window_token_mean(t), "window"))


query("loss_masked_invariance", _MASKED + " " + " UNION ALL ".join(
    f"SELECT {r} AS ranks, {k} AS microbatches, (SELECT round(sum(m * -q * adv) / sum(m), 6) FROM mt) AS loss, (SELECT round(avg(x), 6) FROM (SELECT sum(m * -q * adv) / sum(m) AS x FROM mt GROUP BY rollout_id % {r}, (rollout_id // {r}) % {k} HAVING sum(m) > 0)) AS mean_of_means"
    for r, k in _SPLITS
))(lambda s, d: losses.invariance(masked(s, d).withColumn("w", F.lit(1.0)).withColumn("l", losses.surrogate("plain")), _SPLITS).select("ranks", "microbatches", r6("loss"), r6("mean_of_means")))


@query("gate_masked", _MASKED + """, sq AS (SELECT rollout_id, segment_seq, exp(avg(o - b) FILTER (m = 1)) AS g, sum(m) AS n FROM mt GROUP BY ALL HAVING sum(m) > 0)
SELECT rollout_id, segment_seq, n::BIGINT AS n_actions, g BETWEEN 0.8 AND 1.2 AS kept FROM sq""")
def gate_masked(s, d):
    """The gate's ratio is over action tokens alone; a segment without any has none."""
    t = correction.seq_gate(masked(s, d), 0.8, 1.2).filter("m = 1")
    return t.groupBy("rollout_id", "segment_seq").agg(F.count("*").alias("n_actions"), (F.max("w") == 1).alias("kept"))


@query("corr_seq_tis_versions", _MASKED + """, one AS (SELECT rollout_id FROM mt GROUP BY 1 HAVING count(DISTINCT version) = 1), sq AS (SELECT rollout_id, least(exp(sum(o - b) FILTER (m = 1)), 2) AS w, sum(m) AS n FROM mt JOIN one USING (rollout_id) GROUP BY 1)
SELECT rollout_id, round(w, 6) AS w, n::BIGINT AS n_actions FROM sq WHERE n > 0""")
def corr_seq_tis_versions(s, d):
    """Rollouts of a single version may take one weight a sequence; the rule refuses any others."""
    t = masked(s, d)
    t = t.join(correction.version_mix(t).filter("n_versions = 1").select("rollout_id"), "rollout_id", "left_semi")
    return correction.seq_truncate(t).filter("m = 1").groupBy("rollout_id").agg(F.round(F.max("w"), 6).alias("w"), F.count("*").alias("n_actions"))


query("grad_masked", _GRAD.replace("FROM trace)", "FROM trace WHERE mixed_action)") + " SELECT token_id, round(grad * 1000 + 0.0, 6) AS grad_milli FROM g")(
    lambda s, d: update.gradient(update.coefficients(correction.token_truncate(masked(s, d))), part_policy(s, d)).select("token_id", r6(F.col("grad") * 1000 + 0.0, "grad_milli"))
)
