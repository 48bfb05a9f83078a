"""The tabular policy on documents and conversations."""

from __future__ import annotations

from pyspark.sql import functions as F

from trajkit import capture, correction, losses, measures, policy, workloads
from trajkit.registered import query
from trajkit.queries.capture import HEX, REQ, WORDS, requests

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)


def fit_sql(v):
    """Version v of the policy as CTEs: cnt{v}, pol{v}, other{v}."""
    return f"""cnt{v} AS (SELECT {HEX.format('p')} AS token_id, count(*) AS n FROM (SELECT unnest({WORDS.format('text')}) AS p FROM documents WHERE doc_id % 4 <= {v}) GROUP BY 1),
tot{v} AS (SELECT ln(sum(n) + 0.1 * (count(*) + 1)) AS z FROM cnt{v}), pol{v} AS (SELECT token_id, n, ln(n + 0.1) - z AS logp FROM cnt{v}, tot{v}), other{v} AS (SELECT ln(0.1) - z AS o FROM tot{v})"""


ENGINE = f"""eng AS (SELECT rollout_id, {HEX.format('p')} AS token_id FROM (SELECT rollout_id, unnest({WORDS.format('reply')}) AS p FROM req))"""


def _docs(s, d):
    return workloads.table(s, d, "documents")


def engine(s, d):
    return capture.engine_tokens(requests(s, d)).select("rollout_id", "request_seq", "pos", "token_id").withColumn("m", F.lit(1))


query("policy_fit", f"WITH {fit_sql(3)} SELECT token_id, n, round(logp, 6) AS logp FROM pol3")(lambda s, d: policy.fit_once(_docs(s, d), 3).select("token_id", "n", r6("logp")))
query("policy_bigram", f"""WITH {fit_sql(0)}, w AS (SELECT doc_id, {WORDS.format('text')} AS w FROM documents WHERE doc_id % 4 <= 0),
b AS (SELECT {HEX.format('a')} AS prev, {HEX.format('c')} AS token_id, count(*) AS n FROM (SELECT unnest(w[:-2]) AS a, unnest(w[2:]) AS c FROM w WHERE len(w) > 1) GROUP BY ALL),
f AS (SELECT prev, sum(n) AS t FROM b GROUP BY 1) SELECT prev, b.token_id, b.n, round(0.6 * b.n / t + 0.4 * exp(logp), 6) AS p FROM b JOIN f USING (prev) JOIN pol0 ON pol0.token_id = b.token_id""")(
    lambda s, d: policy.fit_bigram(_docs(s, d), 0).select("prev", "token_id", "n", r6("p"))
)
query("policy_score", f"WITH {REQ}, {ENGINE}, {fit_sql(3)} SELECT rollout_id, count(*) AS n_tokens, round(sum(coalesce(logp, o)), 5) AS logp FROM eng LEFT JOIN pol3 USING (token_id), other3 GROUP BY 1")(
    lambda s, d: policy.score(engine(s, d), policy.fit_once(_docs(s, d), 3)).groupBy("rollout_id").agg(F.count("*").alias("n_tokens"), F.round(F.sum("o"), 5).alias("logp"))
)
query("sample_temp", f"WITH {fit_sql(0)}, z AS (SELECT sum(exp(logp / 0.7)) AS z FROM pol0) SELECT token_id, round(logp / 0.7 - ln(z), 6) AS logp FROM pol0, z")(lambda s, d: policy.temper(policy.fit_once(_docs(s, d), 0), 0.7).select("token_id", r6("logp")))
query("sample_topk", f"WITH {fit_sql(0)}, k AS (SELECT token_id, exp(logp) AS p FROM pol0 ORDER BY logp DESC, token_id LIMIT 50) SELECT token_id, round(p / (SELECT sum(p) FROM k), 6) AS p FROM k")(
    lambda s, d: policy.top_k(policy.fit_once(_docs(s, d), 0), 50).select("token_id", r6("p"))
)
_NUC = """k AS (SELECT token_id, exp(logp) AS p FROM pol0), c AS (SELECT *, coalesce(sum(p) OVER (ORDER BY p DESC, token_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS b FROM k), h AS (SELECT token_id, p FROM c WHERE b < 0.3)"""
query("sample_topp", f"WITH {fit_sql(0)}, {_NUC} SELECT token_id, round(p / (SELECT sum(p) FROM h), 6) AS p FROM h")(lambda s, d: policy.nucleus(policy.fit_once(_docs(s, d), 0), 0.3).select("token_id", r6("p")))


@query("sample_draw", f"""WITH {fit_sql(0)}, k AS (SELECT token_id, exp(logp) AS p FROM pol0 ORDER BY logp DESC, token_id LIMIT 50), n AS (SELECT token_id, p / (SELECT sum(p) FROM k) AS p FROM k),
c AS (SELECT token_id, sum(p) OVER (ORDER BY p DESC, token_id) AS hi FROM n), r AS (SELECT item_id * 4 + s AS rollout_id, pos FROM benchmark, unnest(range(4)) AS a(s), unnest(range(8)) AS b(pos)),
u AS (SELECT rollout_id, pos, (('0x' || substr(md5('5:' || rollout_id || ':' || pos), 1, 8))::BIGINT + 0.5) / 4294967296.0 AS u FROM r)
SELECT rollout_id, pos, (SELECT token_id FROM c WHERE hi > u ORDER BY hi LIMIT 1) AS token_id FROM u""")
def sample_draw(s, d):
    prompts = workloads.table(s, d, "benchmark").select(F.col("item_id").alias("prompt_id"))
    return policy.sample(prompts, policy.top_k(policy.fit_once(_docs(s, d), 0), 50), 4, 8, 5).select("rollout_id", "pos", "token_id")


query("cap_lengths", f"""WITH {REQ}, p AS (SELECT rollout_id, request_seq, sum(len({WORDS.format('content')}) + 2) AS prompt FROM msg GROUP BY 1, 2), x AS (SELECT r.rollout_id, r.request_seq, len({WORDS.format('reply')}) AS n, coalesce(prompt, 0) AS prompt FROM req r LEFT JOIN p USING (rollout_id, request_seq))
SELECT rollout_id, request_seq, greatest(0, least(n, 128, 256 - prompt))::BIGINT AS kept, n > greatest(0, least(n, 128, 256 - prompt)) AS truncated FROM x""")(
    lambda s, d: policy.cap(_sizes(s, d), 256, 128).select("rollout_id", "request_seq", F.col("kept").cast("long").alias("kept"), "truncated")
)


def _sizes(s, d):
    from trajkit import tokens

    return requests(s, d).select("rollout_id", "request_seq", F.size(tokens.render(F.col("messages"))).alias("prompt_tokens"), F.size(tokens.split(F.col("reply"))).alias("n_tokens"))


@query("policy_versions", f"WITH {', '.join(fit_sql(v) for v in range(4))} " + " UNION ALL ".join(f"SELECT {v} AS version, count(*) AS n_types, sum(n)::BIGINT AS n_tokens, round(max(logp), 6) AS top FROM pol{v}" for v in range(4)))
def policy_versions(s, d):
    """Published one after the other and read back: a version is a partition, its marker makes it visible."""
    import uuid

    from trajkit.session import shared_folder

    path, out = f"{shared_folder(s)}/versions/{uuid.uuid4().hex}", None
    for v in range(policy.VERSIONS):
        policy.publish(policy.fit_once(_docs(s, d), v), v, path)
    for v in policy.published(s, path):
        part = policy.load(s, path, v).agg(F.count("*").alias("n_types"), F.sum("n").alias("n_tokens"), r6(F.max("logp"), "top")).select(F.lit(v).alias("version"), "n_types", "n_tokens", "top")
        out = part if out is None else out.unionByName(part)
    return out


def gap_trace(s, d, behaviour, actor):
    t = policy.score(engine(s, d), behaviour, "b")
    return policy.score(t, actor, "o")


_GAP = f"WITH {REQ}, {ENGINE}, {fit_sql(3)}, g AS (SELECT rollout_id, coalesce(logp, o) AS o, round(coalesce(logp, o), 2) AS b FROM eng LEFT JOIN pol3 USING (token_id), other3)"
query("mismatch_gap", _GAP + " SELECT rollout_id, round(avg(abs(o - b)), 6) AS mean_gap, round(max(abs(o - b)), 6) AS max_gap FROM g GROUP BY 1")(
    lambda s, d: gap_trace(s, d, policy.serve_precision(policy.fit_once(_docs(s, d), 3), 2), policy.fit_once(_docs(s, d), 3)).groupBy("rollout_id").agg(r6(F.avg(F.abs(F.col("o") - F.col("b"))), "mean_gap"), r6(F.max(F.abs(F.col("o") - F.col("b"))), "max_gap"))
)
_KL = f"WITH {REQ}, {ENGINE}, {fit_sql(3)}, {fit_sql(0)}, g AS (SELECT rollout_id, coalesce(pol3.logp, other3.o) - coalesce(pol0.logp, other0.o) AS d FROM eng LEFT JOIN pol3 USING (token_id) LEFT JOIN pol0 USING (token_id), other3, other0)"
for _kind, _expr in (("k1", "d"), ("k2", "0.5 * d * d"), ("k3", "exp(-d) - 1 + d")):
    query(f"kl_{_kind}", _KL + f" SELECT rollout_id, round(avg({_expr}), 6) AS kl FROM g GROUP BY 1")(
        lambda s, d, kind=_kind: gap_trace(s, d, policy.fit_once(_docs(s, d), 0), policy.fit_once(_docs(s, d), 3)).withColumnRenamed("b", "ref").withColumn("kl", losses.kl(kind)).groupBy("rollout_id").agg(r6(F.avg("kl"), "kl"))
    )

_ALIGN = _GAP + " SELECT count(*) AS n, round(max(abs(o - b)), 6) AS max_gap, round(avg(abs(o - b)), 6) AS mean_gap, round(corr(o, b), 6) AS correlation FROM g"
query("alignment", _ALIGN)(lambda s, d: measures.alignment(gap_trace(s, d, policy.serve_precision(policy.fit_once(_docs(s, d), 3), 2), policy.fit_once(_docs(s, d), 3))).select("n", r6("max_gap"), r6("mean_gap"), r6("correlation")))

_GATE = [("far", 0, None, 0.999, 1.001), ("rounded", 3, 2, 0.999, 1.001), ("wide", 0, None, 0.8, 1.2), ("near", 2, None, 0.99, 1.01)]


def _gate_sql():
    parts = []
    for name, v, digits, lo, hi in _GATE:
        b = f"coalesce(p.logp, other{v}.o)"
        b = f"round({b}, {digits})" if digits is not None else b
        parts.append(f"SELECT '{name}' AS setting, count(*) AS n_rollouts, sum(CASE WHEN r BETWEEN {lo} AND {hi} THEN 1 ELSE 0 END)::BIGINT AS kept FROM (SELECT rollout_id, exp(avg(coalesce(pol3.logp, other3.o) - {b})) AS r FROM eng LEFT JOIN pol3 USING (token_id) LEFT JOIN pol{v} p ON p.token_id = eng.token_id, {', '.join(dict.fromkeys(['other3', f'other{v}']))} GROUP BY 1)")
    return f"WITH {REQ}, {ENGINE}, {', '.join(fit_sql(v) for v in (0, 2, 3))} " + " UNION ALL ".join(parts)


@query("wl_gate_extremes", _gate_sql())
def wl_gate_extremes(s, d):
    """The consistency gate at both extremes and between: far policies keep nothing, serving precision keeps all."""
    fits, out = {v: policy.fit_once(_docs(s, d), v) for v in (0, 2, 3)}, None
    for name, v, digits, lo, hi in _GATE:
        b = fits[v] if digits is None else policy.serve_precision(fits[v], digits)
        t = correction.seq_gate(gap_trace(s, d, b, fits[3]), lo, hi, by=("rollout_id",))
        part = t.groupBy("rollout_id").agg(F.max("w").alias("w")).agg(F.count("*").alias("n_rollouts"), F.sum("w").cast("long").alias("kept")).select(F.lit(name).alias("setting"), "n_rollouts", "kept")
        out = part if out is None else out.unionByName(part)
    return out
