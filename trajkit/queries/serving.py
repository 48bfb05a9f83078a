"""Model-parallel and serving accounting."""

from __future__ import annotations

from pyspark.sql import functions as F

from trajkit import losses, measures, parallel, policy, routing, serving, workloads
from trajkit.registered import query
from trajkit.oracles import TRACE
from trajkit.queries.capture import COMPACTED, HEX, REQ, WORDS, agents, requests
from trajkit.queries.objective import _loss
from trajkit.queries.policies import engine, fit_sql
from trajkit.queries.scheduling import _TOK, _versioned

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
_CENT = """lg AS (SELECT label AS expert, unnest(range(64)) AS d, unnest(embedding)::DOUBLE AS x FROM embeddings), ce AS (SELECT expert, d, avg(x) AS x FROM lg GROUP BY ALL)"""


def _route_sql(step=None, name="rt"):
    x = "x" if step is None else f"round(x * {step}) / {step}"
    return f"""{name}s AS (SELECT vec_id, c.expert, round(sum(v.x * {x.replace('x', 'c.x')}), 9) AS score FROM (SELECT vec_id, unnest(range(64)) AS d, unnest(embedding)::DOUBLE AS x FROM embeddings) v JOIN ce c USING (d) GROUP BY ALL),
{name} AS (SELECT vec_id, expert, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, expert) AS place FROM {name}s)"""


def _vec(s, d):
    return workloads.table(s, d, "embeddings")


query("route_topk", f"WITH {_CENT}, {_route_sql()} SELECT vec_id, expert, place::INTEGER AS place FROM rt WHERE place <= 2")(lambda s, d: routing.route(_vec(s, d), routing.centroids(_vec(s, d)), 2))


@query("route_replay", f"WITH {_CENT}, {_route_sql(name='rt')}, {_route_sql(64, 'sv')} SELECT count(*) AS n_tokens, count(*)::BIGINT AS replayed_agree, sum(CASE WHEN rt.expert = sv.expert THEN 1 ELSE 0 END)::BIGINT AS rerouted_agree FROM sv JOIN rt USING (vec_id, place) WHERE place = 1")
def route_replay(s, d):
    """Routes recorded by a serving router of coarser weights: the actor that replays them against the one that routes anew."""
    c = routing.centroids(_vec(s, d))
    served = routing.route(_vec(s, d), c, step=64).select("vec_id", F.col("expert").alias("served"))
    anew = routing.route(_vec(s, d), c).select("vec_id", F.col("expert").alias("anew"))
    both = routing.replay(_vec(s, d).select("vec_id"), served).withColumn("used", F.col("served")).join(anew, "vec_id")
    agree = lambda a: F.sum((F.col(a) == F.col("served")).cast("long"))
    return both.agg(F.count("*").alias("n_tokens"), agree("used").alias("replayed_agree"), agree("anew").alias("rerouted_agree"))


_STEPS = (64, 256, 1024)


@query("route_mismatch", f"WITH {_CENT}, {_route_sql()}, " + ", ".join(_route_sql(k, f"r{k}") for k in _STEPS) + " " + " UNION ALL ".join(
    f"SELECT {k} AS step, count(*) AS n_tokens, sum(CASE WHEN rt.expert <> r{k}.expert THEN 1 ELSE 0 END)::BIGINT AS n_changed FROM rt JOIN r{k} USING (vec_id, place) WHERE place = 1" for k in _STEPS))
def route_mismatch(s, d):
    """What replay avoids: routes that change when the actor's router runs at another precision; finer steps change fewer."""
    c, out = routing.centroids(_vec(s, d)), None
    own = routing.route(_vec(s, d), c)
    for k in _STEPS:
        part = routing.mismatch(own, routing.route(_vec(s, d), c, step=k)).select(F.lit(k).alias("step"), "n_tokens", "n_changed")
        out = part if out is None else out.unionByName(part)
    return out


query("route_freeze", f"WITH {_CENT}, n AS (SELECT expert, sqrt(sum(x * x)) AS n FROM ce GROUP BY 1) SELECT expert, round(n, 6) AS frozen, round(0.9 * n, 6) AS updated FROM n")(
    lambda s, d: routing.update(c := routing.centroids(_vec(s, d)), 0.1, True).select("expert", r6(F.sqrt(F.aggregate("centre", F.lit(0.0), lambda a, x: a + x * x)), "frozen"))
    .join(routing.update(c, 0.1, False).select("expert", r6(F.sqrt(F.aggregate("centre", F.lit(0.0), lambda a, x: a + x * x)), "updated")), "expert")
)
query("ep_load", f"""WITH {_CENT}, {_route_sql()}, l AS (SELECT expert // 2 AS ep_rank, count(*) AS n_tokens FROM rt WHERE place = 1 GROUP BY 1)
SELECT ep_rank, n_tokens, ceil((SELECT count(*) FROM embeddings) * 1.25 / 5)::BIGINT AS capacity, greatest(0, n_tokens - ceil((SELECT count(*) FROM embeddings) * 1.25 / 5))::BIGINT AS overflow FROM l""")(
    lambda s, d: parallel.expert_dispatch(routing.route(_vec(s, d), routing.centroids(_vec(s, d))), 5, 10)
)
query("tp_invariance", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS sharded, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS whole FROM embeddings")(
    lambda s, d: parallel.tensor_shards(_vec(s, d), 8).select("vec_id", r6("sharded"), r6("whole"))
)
query("cp_invariance", f"WITH {TRACE} SELECT round(sum(-adv) / count(*), 6) AS loss, round(sum(-adv) / count(*), 6) AS sharded FROM trace")(
    lambda s, d: losses.window_token_mean(_loss(s, d)).select(r6("loss")).crossJoin(losses.partial_sums(parallel.context_shards(_loss(s, d), 8), ["cp_rank"]).agg(r6(F.sum("num") / F.sum("den"), "sharded")))
)
@query("shard_bytes", f"WITH pa AS (SELECT count(DISTINCT {HEX.format('p')}) AS n FROM (SELECT unnest({WORDS.format('text')}) AS p FROM documents)) SELECT r AS rank, (n // 16 + CASE WHEN r < n % 16 THEN 1 ELSE 0 END) * 2 AS bytes FROM range(16) t(r), pa")
def shard_bytes(s, d):
    """Bytes a rank of the corpus policy, whose entries are its parameters."""
    params = policy.fit(workloads.table(s, d, "documents"), 3).agg(F.count("*").alias("params"))
    return parallel.shard_bytes(params, parallel.Plan(16, cp=2, dp=8))


@query("offload_trade", """WITH ex AS (SELECT label AS expert, sum(len(embedding)) AS params FROM embeddings WHERE embedding IS NOT NULL GROUP BY 1), al AS (SELECT sum(params) * 16 / 1e9::DOUBLE AS gb FROM ex), st AS (SELECT sum(round(value * 1e6)::BIGINT) / count(value) / 1e6::DOUBLE AS seconds FROM events)
SELECT expert, round(params * 8 / 1e9::DOUBLE, 12) AS saved_gb, round(params * 8 / 1e9::DOUBLE / gb, 12) AS saved_share, round(2 * params * 8 / 25e9::DOUBLE, 12) AS added_s, round(2 * params * 8 / 25e9::DOUBLE / seconds, 12) AS added_share FROM ex, al, st""")
def offload_trade(s, d):
    """Each expert's two moments moved to the host: memory freed, of weights, gradients, master copy and moments (16 bytes a parameter), and time added to the mean step."""
    experts = _vec(s, d).filter("embedding is not null").groupBy(F.col("label").alias("expert")).agg(F.sum(F.size("embedding")).alias("params"))
    gb = experts.agg((F.sum("params") * 16 / 1e9).alias("gb"))
    us = F.round(F.col("value") * 1e6).cast("long")
    seconds = workloads.table(s, d, "events").agg((F.sum(us) / F.count("value") / 1e6).alias("seconds"))
    both = experts.crossJoin(F.broadcast(gb)).crossJoin(F.broadcast(seconds))
    trade = measures.offload_tradeoff(F.col("params"), base_seconds=F.col("seconds"), base_gb=F.col("gb"))
    return both.select("expert", *[F.round(v, 12).alias(k) for k, v in trade.items()])


# ---- speculation -----------------------------------------------------------------------------

_SPEC = f"""WITH RECURSIVE {REQ}, {fit_sql(3)}, {fit_sql(0)}, w AS (SELECT rollout_id, request_seq, {WORDS.format('reply')} AS w FROM req),
e AS (SELECT rollout_id, ('0x' || substr(md5(p), 1, 8))::BIGINT AS token_id, row_number() OVER (PARTITION BY rollout_id ORDER BY request_seq, i) - 1 AS pos FROM (SELECT rollout_id, request_seq, unnest(w) AS p, unnest(range(len(w))) AS i FROM w)),
dw AS (SELECT {WORDS.format('text')} AS w FROM documents),
bc AS (SELECT {HEX.format('a')} AS prev, {HEX.format('c')} AS token_id, count(*) AS n FROM (SELECT unnest(w[:-2]) AS a, unnest(w[2:]) AS c FROM dw WHERE len(w) > 1) GROUP BY ALL),
bf AS (SELECT prev, sum(n) AS t FROM bc GROUP BY 1), bi AS (SELECT prev, bc.token_id, 0.6 * bc.n / t + 0.4 * exp(logp) AS p FROM bc JOIN bf USING (prev) JOIN pol3 ON pol3.token_id = bc.token_id),
bt AS (SELECT prev, token_id AS next, p AS next_p FROM (SELECT *, row_number() OVER (PARTITION BY prev ORDER BY round(p, 12) DESC, token_id) AS k FROM bi) WHERE k = 1),
top AS (SELECT token_id AS top, 0.4 * exp(logp) AS top_p FROM pol3 ORDER BY logp DESC, token_id LIMIT 1),
ep AS (SELECT *, lag(token_id) OVER (PARTITION BY rollout_id ORDER BY pos) AS prev, count(*) OVER (PARTITION BY rollout_id) AS n FROM e),
sc AS (SELECT ep.rollout_id, ep.pos, ep.n, CASE WHEN bi.p IS NOT NULL THEN ln(bi.p) WHEN bt.next IS NOT NULL THEN ln(0.4) + coalesce(pol3.logp, other3.o) ELSE coalesce(pol3.logp, other3.o) END AS target,
 coalesce(pol0.logp, other0.o) AS draft, ep.token_id = CASE WHEN next_p >= top_p THEN next ELSE top END AS likeliest
 FROM ep LEFT JOIN bi ON bi.prev = ep.prev AND bi.token_id = ep.token_id LEFT JOIN bt ON bt.prev = ep.prev LEFT JOIN pol3 ON pol3.token_id = ep.token_id LEFT JOIN pol0 ON pol0.token_id = ep.token_id, top, other3, other0),
ok AS (SELECT 'sampled' AS acceptance, rollout_id, pos, n, (('0x' || substr(md5('spec:' || rollout_id || ':' || pos), 1, 8))::BIGINT + 0.5) / 4294967296.0 <= least(1, exp(target - draft)) AS ok FROM sc
 UNION ALL SELECT 'greedy', rollout_id, pos, n, likeliest FROM sc),
st AS (SELECT acceptance, rollout_id, pos, n, coalesce(min(CASE WHEN NOT ok THEN pos END) OVER (PARTITION BY acceptance, rollout_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), n) AS bad FROM ok),
walk AS (SELECT acceptance, rollout_id, k, 0::BIGINT AS pos FROM (SELECT DISTINCT acceptance, rollout_id FROM st), (VALUES (0), (1), (2), (4)) AS ks(k)
 UNION ALL SELECT walk.acceptance, walk.rollout_id, k, least(bad, walk.pos + k) + 1 FROM walk JOIN st ON st.acceptance = walk.acceptance AND st.rollout_id = walk.rollout_id AND st.pos = walk.pos),
sp AS (SELECT walk.acceptance, k, (SELECT count(*) FROM e) AS n_tokens, count(*) AS passes, sum(least(bad, walk.pos + k, n) - walk.pos)::BIGINT AS accepted
 FROM walk JOIN st ON st.acceptance = walk.acceptance AND st.rollout_id = walk.rollout_id AND st.pos = walk.pos GROUP BY ALL)"""


def _spec_trace(s, d):
    """Replies scored once: by the pairs of all documents (the target) and by an older version's words (the draft)."""
    from pyspark.sql import Window

    from trajkit.session import materialise

    e = engine(s, d).withColumn("pos", (F.row_number().over(Window.partitionBy("rollout_id").orderBy("request_seq", "pos")) - 1).cast("long"))
    docs = workloads.table(s, d, "documents")
    words = policy.fit_once(docs, 3)
    pairs = materialise(policy.fit_bigram(docs, 3, unigram=words))
    scored = policy.score_bigram(policy.score(e, policy.fit_once(docs, 0), "draft"), pairs, words)
    return materialise(scored.select("rollout_id", "pos", "token_id", "target", "draft", "best"))


def _speculation(s, d, ks):
    t = _spec_trace(s, d)
    parts = [serving.speculate(t, ks, greedy).withColumn("acceptance", F.lit("greedy" if greedy else "sampled")) for greedy in (False, True)]
    return parts[0].unionByName(parts[1]).groupBy("acceptance", "k").agg(*[F.sum(c).alias(c) for c in ("n_tokens", "passes", "accepted")])


query("spec_accept", f"{_SPEC} SELECT * FROM sp WHERE k = 4")(lambda s, d: _speculation(s, d, [4]))
query("spec_speedup", f"{_SPEC} SELECT a.acceptance, b.k, round(a.passes / b.passes, 6) AS speedup, round(b.accepted / b.n_tokens, 6) AS accepted_share FROM sp a JOIN sp b USING (acceptance) WHERE a.k = 0 AND b.k > 0")(
    lambda s, d: (x := _speculation(s, d, [0, 1, 2, 4])).filter("k > 0").join(x.filter("k = 0").select("acceptance", F.col("passes").alias("off")), "acceptance")
    .select("acceptance", "k", r6(F.col("off") / F.col("passes"), "speedup"), r6(F.col("accepted") / F.col("n_tokens"), "accepted_share"))
)
query("wl_speculation", f"{_SPEC} SELECT * FROM sp")(lambda s, d: _speculation(s, d, [0, 1, 2, 4]))

# ---- prefix cache ----------------------------------------------------------------------------

_PIECES = f"""pc AS (SELECT rollout_id, request_seq, turn, list_concat(list_concat(['<|' || role || '|>'], {WORDS.format('content')}), ['<|end|>']) AS p FROM msg),
st AS (SELECT rollout_id, request_seq, flatten(list(p ORDER BY turn)) AS t FROM pc GROUP BY 1, 2),
bl AS (SELECT rollout_id, request_seq, len(t) AS prompt_tokens, b, md5(array_to_string(t[1:16 * b], ' ')) AS chain FROM st, unnest(range(1, len(t) // 16 + 1)) AS u(b))"""
_ENGINES = {"session": "('0x' || substr(md5(rollout_id::VARCHAR), 1, 8))::BIGINT % 4", "round_robin": "(rollout_id + request_seq) % 4", "random": "('0x' || substr(md5(rollout_id || ':' || request_seq), 1, 8))::BIGINT % 4"}


def _hits(how):
    """Hit blocks by an anti-causal self join on prefixes: independent of chained digests and windows."""
    return f"""SELECT st.rollout_id, st.request_seq, len(t) AS prompt_tokens, (16 * coalesce((SELECT count(*) FROM (SELECT *, {_ENGINES[how]} AS e FROM bl) x WHERE x.rollout_id = st.rollout_id AND x.request_seq = st.request_seq
 AND EXISTS (SELECT 1 FROM (SELECT *, {_ENGINES[how]} AS e FROM bl) y WHERE y.chain = x.chain AND y.e = x.e AND (y.request_seq, y.rollout_id) < (x.request_seq, x.rollout_id))), 0))::BIGINT AS hit_tokens FROM st"""


query("prefix_hits", f"WITH {REQ}, {_PIECES} {_hits('session')}")(lambda s, d: serving.prefix_cache(requests(s, d)).filter("prompt_tokens > 0"))


@query("prefix_affinity", f"WITH {REQ}, {_PIECES} " + " UNION ALL ".join(f"SELECT '{h}' AS affinity, sum(hit_tokens)::BIGINT AS hit_tokens, sum(prompt_tokens)::BIGINT AS prompt_tokens FROM ({_hits(h)})" for h in _ENGINES))
def prefix_affinity(s, d):
    out = None
    for how in _ENGINES:
        part = serving.prefix_cache(requests(s, d), how=how).agg(F.sum("hit_tokens").alias("hit_tokens"), F.sum("prompt_tokens").alias("prompt_tokens")).select(F.lit(how).alias("affinity"), "hit_tokens", "prompt_tokens")
        out = part if out is None else out.unionByName(part)
    return out


query("reprefill", f"WITH {REQ}, {_PIECES}, h AS ({_hits('session')}) SELECT sum(prompt_tokens)::BIGINT AS prompt_tokens, sum(hit_tokens)::BIGINT AS hit_tokens, sum(prompt_tokens - hit_tokens)::BIGINT AS uncached, round(sum(hit_tokens) / sum(prompt_tokens), 6) AS hit_rate, round(0.05 * count(*) + 1e-4 * sum(prompt_tokens - hit_tokens), 6) AS latency_s FROM h")(
    lambda s, d: measures.reprefill(serving.prefix_cache(requests(s, d)).filter("prompt_tokens > 0")).select("prompt_tokens", "hit_tokens", "uncached", r6("hit_rate"), r6("latency_s"))
)
_CACHED = f"""{COMPACTED}, pp AS (SELECT policy, rollout_id, request_seq, turn, list_concat(list_concat(['<|' || role || '|>'], {WORDS.format('content')}), ['<|end|>']) AS p FROM cm),
ps AS (SELECT policy, rollout_id, request_seq, flatten(list(p ORDER BY turn)) AS t FROM pp GROUP BY ALL),
pb AS (SELECT policy, rollout_id, request_seq, md5(array_to_string(t[1:16 * b], ' ')) AS chain FROM ps, unnest(range(1, len(t) // 16 + 1)) AS u(b))"""


def _cached(how, ttl):
    near = "" if ttl is None else f" AND y.request_seq >= x.request_seq - {ttl}"
    return f"""SELECT '{how}' AS affinity, {ttl if ttl else 0} AS ttl, policy, (16 * coalesce(hits, 0))::BIGINT AS hit_tokens, prompt_tokens FROM (SELECT policy, sum(len(t))::BIGINT AS prompt_tokens FROM ps GROUP BY 1) LEFT JOIN
 (SELECT policy, count(*) AS hits FROM (SELECT *, {_ENGINES[how]} AS e FROM pb) x WHERE EXISTS (SELECT 1 FROM (SELECT *, {_ENGINES[how]} AS e FROM pb) y
  WHERE y.policy = x.policy AND y.chain = x.chain AND y.e = x.e AND (y.request_seq, y.rollout_id) < (x.request_seq, x.rollout_id){near}) GROUP BY 1) USING (policy)"""


@query("wl_prefix", f"WITH {REQ}, {_CACHED} " + " UNION ALL ".join(_cached(h, t) for h in ("session", "round_robin") for t in (None, 1)))
def wl_prefix(s, d):
    """Prompt tokens that engines hold already, by the agent's way with its context, the choice of engine, and with or without (0) eviction."""
    r, out = agents(s, d), None
    for how in ("session", "round_robin"):
        for ttl in (None, 1):
            hits = serving.prefix_cache(r, how=how, ttl=ttl, by=("policy",)).groupBy("policy").agg(F.sum("hit_tokens").alias("hit_tokens"), F.sum("prompt_tokens").alias("prompt_tokens"))
            part = hits.select(F.lit(how).alias("affinity"), F.lit(ttl or 0).alias("ttl"), "policy", "hit_tokens", "prompt_tokens")
            out = part if out is None else out.unionByName(part)
    return out


query("serve_pack")(lambda s, d: serving.pack(serving.route_requests(serving.prefix_cache(requests(s, d)), 4), 2048, 128))
query("prefix_retained", _TOK + ", j AS (SELECT *, version <> lag(version) OVER (PARTITION BY rollout_id ORDER BY pos) AS jump FROM v) SELECT rollout_id, sum(CASE WHEN jump THEN pos ELSE 0 END)::BIGINT AS kept_prefix, sum(CASE WHEN jump THEN 1 ELSE 0 END)::BIGINT AS refits_seen FROM j GROUP BY 1")(lambda s, d: serving.retained(_versioned(s, d)))
