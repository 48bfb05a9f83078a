"""Measures over steps, runs and pairs of runs."""

from __future__ import annotations

import os

from pyspark.sql import functions as F

from trajkit import capture, correction, footprint, groups, losses, measures, policy, update, workloads
from trajkit.registered import query
from trajkit.oracles import FIRST, TRACE
from trajkit.queries.capture import _SET, AGENTS, COMPACTED, HEX, REQ, WORDS, agents
from trajkit.queries.objective import _GRAD, four, part_policy, trace
from trajkit.queries.policies import ENGINE, fit_sql
from trajkit.queries.serving import _CENT, _route_sql

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
query("m_reward", f"WITH {FIRST} SELECT round(avg(reward), 6) AS reward_mean, count(DISTINCT group_id) AS n_groups FROM four")(lambda s, d: measures.rewards(four(s, d)).select(r6("reward_mean"), "n_groups"))
query("m_group_var", f"WITH {FIRST} SELECT round(avg(sd), 6) AS within_group_std, round(avg(CASE WHEN spread = 0 THEN 1.0 ELSE 0.0 END), 6) AS zero_share FROM gs")(lambda s, d: measures.rewards(four(s, d)).select(r6("within_group_std"), r6("zero_share")))
query("m_lengths", f"WITH {TRACE}, n AS (SELECT rollout_id, count(*) AS n FROM trace GROUP BY 1) SELECT round(avg(n), 6) AS mean, quantile_cont(n, 0.5)::DOUBLE AS p50, quantile_cont(n, 0.95)::DOUBLE AS p95, max(n) AS longest, round(avg(CASE WHEN n >= 6 THEN 1.0 ELSE 0.0 END), 6) AS truncated FROM n")(
    lambda s, d: measures.lengths(trace(s, d).groupBy("rollout_id").agg(F.count("*").alias("length")), 6).select(r6("mean"), "p50", "p95", "longest", r6("truncated"))
)
query("m_pass_at", """WITH g AS (SELECT o_custkey AS group_id, count(*) AS n_all, sum(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END)::BIGINT AS n_right FROM orders GROUP BY 1 HAVING count(*) >= 2)
SELECT *, n_right > 0 AS any_correct, round(1 - ((n_all - n_right) * greatest(n_all - n_right - 1, 0))::DOUBLE / (n_all * (n_all - 1)), 6) AS unbiased FROM g""")(
    lambda s, d: measures.pass_at(workloads.rollouts(s, d), 2).select("group_id", "n_all", "n_right", "any_correct", r6("unbiased"))
)
query("m_stages", "SELECT event_type AS stage, round(avg(value), 6) AS mean_s, round(sum(value) / (SELECT sum(value) FROM events), 6) AS share FROM events GROUP BY 1")(
    lambda s, d: measures.stages(workloads.table(s, d, "events").select(F.col("event_type").alias("stage"), F.col("value").alias("seconds"))).select("stage", r6("mean_s"), r6("share"))
)
_STEPS = "st AS (SELECT event_id % 3 AS run, event_id // 3 % 20 + 1 AS step, value AS seconds FROM events), pr AS (SELECT run, avg(seconds) AS m FROM st WHERE step BETWEEN 2 AND 10 GROUP BY 1)"


def _steps(s, d):
    """All events as steps of three runs; a run counts its steps from 1 to 20 again and again."""
    e = workloads.table(s, d, "events")
    return e.select((F.col("event_id") % 3).alias("run"), (F.floor(F.col("event_id") / 3) % 20 + 1).alias("step"), F.col("value").alias("seconds"))


query("m_step_time", f"WITH {_STEPS} SELECT round(avg(m), 6) AS step_s, round(stddev_samp(m), 6) AS step_std, count(*) AS n_runs FROM pr")(lambda s, d: measures.step_time(_steps(s, d)).select(r6("step_s"), r6("step_std"), "n_runs"))
query("m_throughput", f"WITH {_STEPS} SELECT round(880000 / avg(m) / 16, 6) AS tokens_per_device_s FROM pr")(lambda s, d: measures.step_time(_steps(s, d)).select(r6(measures.throughput(F.lit(880000), F.col("step_s"), F.lit(16)), "tokens_per_device_s")))
_RUNS = "SELECT coalesce(event_type, 'unnamed') AS name, sum(round(value * 1e6)::BIGINT) FILTER (WHERE event_id % 2 = 1) / count(value) FILTER (WHERE event_id % 2 = 1) AS a, sum(round(value * 1e6)::BIGINT) FILTER (WHERE event_id % 2 = 0) / count(value) FILTER (WHERE event_id % 2 = 0) AS b FROM events GROUP BY 1"


@query("m_ratio", f"SELECT name, round(a / nullif(b, 0), 6) AS ratio, round((b - a) / nullif(b, 0), 6) AS saved FROM ({_RUNS})")
def m_ratio(s, d):
    """Mean time of each stage in one run (odd events) against the baseline's (even events), summed in whole microseconds."""
    e = workloads.table(s, d, "events").select(F.coalesce("event_type", F.lit("unnamed")).alias("name"), F.pmod("event_id", F.lit(2)).alias("run"), F.round(F.col("value") * 1e6).cast("long").alias("us"))
    mean = lambda k: F.try_divide(F.sum(F.when(F.col("run") == k, F.col("us"))), F.count(F.when(F.col("run") == k, F.col("us"))))
    pairs = e.groupBy("name").agg(mean(1).alias("a"), mean(0).alias("b"))
    return pairs.select("name", r6(measures.ratio(F.col("a"), F.col("b")), "ratio"), r6(measures.saved(F.col("b"), F.col("a")), "saved"))


_LINES = r"""WITH l AS (SELECT source AS path, unnest(string_split(text, chr(10))) AS line FROM documents)
SELECT path, count(*) AS lines, sum(CASE WHEN regexp_matches(line, '^\s*$') OR regexp_matches(line, '(?i)license') THEN 0 ELSE 1 END)::BIGINT AS code_lines FROM l GROUP BY 1"""


def _lines(s, d):
    each = workloads.table(s, d, "documents").select(F.col("source").alias("path"), F.explode(F.split("text", "\n")).alias("line"))
    return each.groupBy("path").agg(F.count("*").alias("lines"), F.sum((~F.col("line").rlike(r"^\s*$") & ~F.col("line").rlike("(?i)license")).cast("long")).alias("code_lines"))


@query("wl_footprint_ratio", f"SELECT f.path AS name, round(100 * own.n / nullif(f.code_lines, 0))::BIGINT AS percent FROM ({_LINES}) f, (SELECT min(path) AS path, arg_min(code_lines, path) AS n FROM ({_LINES})) own WHERE f.path IS DISTINCT FROM own.path")
def wl_footprint_ratio(s, d):
    """Code lines of the first source by name, in percent of each other source's."""
    f = _lines(s, d)
    own = f.agg(F.min("path").alias("_path"), F.min_by("code_lines", "path").alias("_n"))
    peers = f.crossJoin(F.broadcast(own)).filter(~F.col("path").eqNullSafe(F.col("_path")))
    return peers.select(F.col("path").alias("name"), F.round(F.try_divide(100 * F.col("_n"), F.col("code_lines"))).cast("long").alias("percent"))


query("footprint", _LINES)(_lines)
query("footprint_own")(lambda s, d: footprint.count(s, [os.path.dirname(os.path.dirname(os.path.abspath(__file__)))]))


_CAPPED = _GRAD.replace("FROM trace)", "FROM trace WHERE pos < least(4, 7 - group_id % 8))")


@query("wl_group_step", f"""{_CAPPED}, cp AS (SELECT *, pos < least(4, 7 - group_id % 8) AS kept FROM trace), n AS (SELECT sqrt(sum(grad * grad)) AS norm FROM g),
mv AS (SELECT 0.01 * g / (abs(g) + 1e-8) AS step FROM (SELECT grad * least(1.0, 1 / (norm + 1e-12)) AS g FROM g, n))
SELECT count(*) AS n_tokens, count(DISTINCT rollout_id) AS n_rollouts, (SELECT count(DISTINCT rollout_id) FROM cp WHERE NOT kept) AS n_truncated,
 round(sum(least(exp(o - b), 2) * -least(exp(c - o) * adv, greatest(least(exp(c - o), 1.2), 0.8) * adv)) / count(*), 6) AS loss, round(sum(least(exp(o - b), 2) * -least(exp(c - o) * adv, greatest(least(exp(c - o), 1.2), 0.8) * adv)) / count(*), 6) AS by_microbatch,
 (SELECT count(*) FROM mv WHERE step > 1e-9) AS n_down, (SELECT count(*) FROM mv WHERE step < -1e-9) AS n_up, (SELECT round(max(abs(step)), 6) FROM mv) AS largest_move FROM cp WHERE kept""")
def wl_group_step(s, d):
    """The step at volume: first four samples of each prompt, a context of eight tokens of which a response takes four at most,
    truncated weights, microbatches of one rollout without packing, Adam on the policy of parts.

    A prompt has 1 + group mod 8 tokens; one that fills the context leaves no response.
    """
    t = trace(s, d).withColumn("n_tokens", F.col("length")).withColumn("prompt_tokens", 1 + F.pmod("group_id", F.lit(8)))
    t = policy.cap(t, 8, 4)
    cut = t.filter("truncated").agg(F.countDistinct("rollout_id").alias("n_truncated"))
    t = correction.token_truncate(t.filter("pos < kept")).withColumn("l", losses.contribution(losses.surrogate("clip")))
    parts = losses.partial_sums(t, ["rollout_id"]).agg(r6(F.sum("num") / F.sum("den"), "by_microbatch"))
    out = t.agg(F.count("*").alias("n_tokens"), F.countDistinct("rollout_id").alias("n_rollouts")).crossJoin(losses.window_token_mean(t).select(r6("loss"))).crossJoin(parts).crossJoin(cut)
    pol = part_policy(s, d)
    state = pol.select("token_id", "theta", F.lit(0.0).alias("mean"), F.lit(0.0).alias("var"))
    after = update.adam(state, update.gradient(update.coefficients(t), pol), 1).select("token_id", F.col("theta").alias("after"))
    move = F.col("after") - F.col("theta")
    n = lambda c: F.sum(c.cast("long"))
    moved = pol.join(after, "token_id").agg(n(move < -1e-9).alias("n_down"), n(move > 1e-9).alias("n_up"), r6(F.max(F.abs(move)), "largest_move"))
    return out.crossJoin(moved)  # one row each


@query("wl_grid", f"WITH {TRACE}, m AS (SELECT trace.*, reward - mu AS dr, least(exp(o - b), 2) AS w FROM trace JOIN gs USING (group_id)) "
       + " UNION ALL ".join(f"SELECT '{e}' AS estimator, '{n}' AS normaliser, '{c}' AS correction, round({x}, 6) AS loss FROM {f}"
                            for e, a in (("relative", "adv"), ("unscaled", "dr")) for c, w in (("none", "1"), ("truncate", "w"))
                            for n, x, f in (("window", f"sum(-{w} * {a}) / count(*)", "m"), ("sequence", "avg(x)", f"(SELECT avg(-{w} * {a}) AS x FROM m GROUP BY rollout_id)"), ("constant", f"sum(-{w} * {a}) / (count(DISTINCT rollout_id) * 8.0)", "m"))))
def wl_grid(s, d):
    """Estimator by normaliser by correction on one window."""
    t = correction.token_truncate(trace(s, d))
    own = groups.stats(four(s, d)).select("group_id", F.col("mean").alias("mu"))
    t, out = t.join(own, "group_id").withColumn("dr", F.col("reward") - F.col("mu")), None
    for e, a in (("relative", "adv"), ("unscaled", "dr")):
        for c, w in (("none", F.lit(1.0)), ("truncate", F.col("w"))):
            x = t.withColumn("l", -w * F.col(a))
            for n, df in (("window", losses.window_token_mean(x)), ("sequence", losses.mean_of_means(x, ["rollout_id"])), ("constant", losses.constant_length(x, 8))):
                part = df.select(F.lit(e).alias("estimator"), F.lit(n).alias("normaliser"), F.lit(c).alias("correction"), r6("loss"))
                out = part if out is None else out.unionByName(part)
    return out


@query("wl_compaction", f"""WITH {REQ}, {COMPACTED}, rq AS (SELECT policy, req.* FROM req, (VALUES ('keep_all'), ('last_k'), ('summary'), ('drop_tool')) AS a(policy)),
ml AS (SELECT policy, rollout_id, request_seq, any_value(reply) AS reply, list(role || ':' || content ORDER BY turn) FILTER (role IS NOT NULL) AS ms, coalesce(sum(len({WORDS.format('content')}) + 2), 0) AS prompt FROM (SELECT rq.policy, rq.rollout_id, rq.request_seq, reply, cm.turn, role, content FROM rq LEFT JOIN cm USING (policy, rollout_id, request_seq)) GROUP BY ALL),
nx AS (SELECT *, list_concat(coalesce(ms, []), ['assistant:' || reply]) AS after, len({WORDS.format('reply')}) AS words FROM ml),
lg AS (SELECT *, lag(after) OVER (PARTITION BY policy, rollout_id ORDER BY request_seq) AS seen FROM nx),
sg AS (SELECT *, sum(CASE WHEN seen IS NULL OR coalesce(ms, [])[1:len(seen)] = seen THEN 0 ELSE 1 END) OVER (PARTITION BY policy, rollout_id ORDER BY request_seq) AS seg FROM lg),
gr AS (SELECT policy, rollout_id, seg, count(*) AS n_requests, max_by(prompt + words + 2, request_seq) AS n_tokens, sum(words) AS n_actions FROM sg GROUP BY ALL)
SELECT policy, sum(n_requests)::BIGINT AS n_requests, count(*) AS n_segments, sum(n_tokens)::BIGINT AS n_tokens, sum(n_actions)::BIGINT AS n_actions, sum(n_actions)::BIGINT AS n_sampled FROM gr GROUP BY 1""")
def wl_compaction(s, d):
    """Segments, stored tokens and action tokens under each agent's way with its context; the actions are those sampled, however often context was rewritten."""
    r, out = agents(s, d), None
    for p in AGENTS:
        own = r.filter(F.col("policy") == p)
        seg = capture.assemble(capture.segment(own)).agg(
            F.sum("n_requests").alias("n_requests"), F.count("*").alias("n_segments"), F.sum(F.size("token_ids")).alias("n_tokens"),
            F.sum(F.size(F.filter("action_mask", lambda m: m))).alias("n_actions"),
        )
        part = seg.crossJoin(capture.engine_tokens(own).agg(F.count("*").alias("n_sampled"))).withColumn("policy", F.lit(p))  # one row each
        out = part if out is None else out.unionByName(part)
    return out


_EP = ", ".join(f"(SELECT max(n) FROM ep{k}) AS ep{k}_most, (SELECT sum(greatest(0, n - ceil((SELECT count(*) FROM tr) * 1.25 / {k})))::BIGINT FROM ep{k}) AS ep{k}_overflow" for k in (2, 5, 10))
_F1 = f"coalesce(2.0 * len(list_intersect({_SET.format('reply')}, {_SET.format('content')})) / nullif(len({_SET.format('reply')}) + len({_SET.format('content')}), 0), 0)"


@query("wl_multiturn", f"""WITH {REQ}, {COMPACTED}, {ENGINE}, {fit_sql(3)}, {_CENT}, {_route_sql()}, {_route_sql(64, 'sv')},
f1 AS (SELECT rollout_id, avg({_F1}) AS reward FROM req JOIN mk USING (rollout_id, request_seq) WHERE back = 1 GROUP BY 1),
rw AS (SELECT rollout_id, rollout_id // 4 AS g, coalesce(reward, 0) AS reward, count(*) OVER (PARTITION BY rollout_id // 4) AS n FROM (SELECT DISTINCT rollout_id FROM conv) LEFT JOIN f1 USING (rollout_id)),
av AS (SELECT rollout_id, g, CASE WHEN max(reward) OVER q = min(reward) OVER q THEN 0 ELSE (reward - avg(reward) OVER q) / (stddev_samp(reward) OVER q + 1e-6) END AS adv FROM rw WHERE n >= 4 WINDOW q AS (PARTITION BY g)),
ac AS (SELECT rollout_id, adv, coalesce(pol3.logp, other3.o) AS lo, coalesce(round(pol3.logp, 1), round(other3.o, 1)) AS lb FROM eng JOIN av USING (rollout_id) LEFT JOIN pol3 USING (token_id), other3),
gt AS (SELECT *, exp(avg(lo - lb) OVER (PARTITION BY rollout_id)) BETWEEN 0.99 AND 1.01 AS pass FROM ac),
ls AS (SELECT count(*) AS n_actions, sum(CASE WHEN pass THEN 0 ELSE 1 END)::BIGINT AS n_rejected, round(sum(CASE WHEN pass THEN -least(exp(lo - lb), 2) * adv ELSE 0 END) / count(*), 6) AS loss FROM gt),
mq AS (SELECT rollout_id, max(turn) AS final FROM req GROUP BY 1),
tk AS (SELECT rollout_id, g, {HEX.format('p')} % (SELECT count(*) FROM embeddings) AS k FROM (SELECT rollout_id, g, unnest(list_concat(list_concat(['<|' || role || '|>'], {WORDS.format('content')}), ['<|end|>'])) AS p FROM conv JOIN mq USING (rollout_id) JOIN av USING (rollout_id) WHERE turn <= final)),
pl AS (SELECT vec_id, row_number() OVER (ORDER BY vec_id) - 1 AS k FROM embeddings),
tr AS (SELECT tk.*, rt.expert, sv.expert AS anew FROM tk JOIN pl USING (k) JOIN rt ON rt.vec_id = pl.vec_id AND rt.place = 1 JOIN sv ON sv.vec_id = pl.vec_id AND sv.place = 1),
""" + ", ".join(f"ep{k} AS (SELECT expert // {10 // k} AS r, count(*) AS n FROM tr GROUP BY 1)" for k in (2, 5, 10)) + f"""
SELECT count(DISTINCT g) AS n_groups, count(DISTINCT rollout_id) AS n_rollouts, count(DISTINCT rollout_id) AS n_segments, count(*) AS n_tokens, n_actions, n_rejected, (SELECT max(n) FROM (SELECT count(*) AS n FROM tr GROUP BY rollout_id)) AS longest,
 loss, loss AS sharded, count(*) AS n_replayed, sum(CASE WHEN expert <> anew THEN 1 ELSE 0 END)::BIGINT AS n_changed, {_EP} FROM tr, ls GROUP BY n_actions, n_rejected, loss""")
def wl_multiturn(s, d):
    """The whole step on all complete groups of conversations: sampled at serving precision, gated and truncated, sharded, routes replayed."""
    from trajkit import multiturn, worlds

    actor = policy.fit_once(workloads.table(s, d, "documents"), 3)
    out = multiturn.step(worlds.turns(s, d), policy.serve_precision(actor, 1), actor, workloads.table(s, d, "embeddings"))
    return out.withColumns({"loss": r6("loss"), "sharded": r6("sharded")})


@query("train_loop")
def train_loop(s, d, cfg=None):
    """Three steps of the whole loop, each passage asked for and its own text the label; the log has one row a step."""
    from trajkit import pipeline

    turn = lambda k, role: F.struct(F.lit(k).alias("turn"), F.lit(role).alias("role"))
    turns = workloads.table(s, d, "benchmark").select(F.col("item_id").alias("prompt_id"), F.inline(F.array(turn(0, "user"), turn(1, "assistant"))), F.col("text").alias("content"))
    return pipeline.train(s, turns, workloads.table(s, d, "documents"), 3, cfg or pipeline.Config())[0]


@query("wl_full_path")
def wl_full_path(s, d, cfg=None):
    """Rollout, refit and update end to end on all turns of all conversations: the policy after two steps against the first, in rows and in movement."""
    from trajkit import pipeline, worlds
    from trajkit.session import materialise

    docs = workloads.table(s, d, "documents")
    start = materialise(pipeline.start(docs))
    _, last = pipeline.train(s, worlds.turns(s, d).withColumnRenamed("rollout_id", "prompt_id"), docs, 2, cfg or pipeline.Config(), first=start)
    first = start.select("token_id", F.col("theta").alias("before"))
    return last.join(first, "token_id").agg(F.count("*").alias("n_entries"), F.sum((F.abs(F.col("theta") - F.col("before")) > 1e-9).cast("long")).alias("n_moved"), r6(F.max(F.abs(F.col("theta") - F.col("before"))), "largest_move"))
