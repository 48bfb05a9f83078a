"""Experiences by reference, assignment to ranks, and their baselines."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from trajkit import batches, experience, measures, workloads
from trajkit.registered import query
from trajkit.session import shared_folder

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
RANKS = 8


def built(s, d):
    return experience.build(workloads.table(s, d, "documents"))


def light(s, d):
    return built(s, d).drop("payload")


query("exp_build", "SELECT doc_id AS experience_id, source AS group_key, len(text) AS length, (doc_id % 100)::INTEGER AS node, quality::DOUBLE AS reward FROM documents LEFT JOIN labels USING (doc_id)")(
    lambda s, d: experience.build(workloads.table(s, d, "documents"), workloads.table(s, d, "labels")).select("experience_id", "group_key", "length", "node", "reward")
)
query("exp_light", "SELECT doc_id AS experience_id, len(text) AS length, (doc_id % 100)::INTEGER AS node, md5(text) AS digest FROM documents")(
    lambda s, d: experience.light(built(s, d)).select("experience_id", "length", "node", F.col("ref.digest").alias("digest"))
)


@query("exp_roundtrip", "SELECT doc_id AS experience_id, md5(text) AS payload_md5 FROM documents")
def exp_roundtrip(s, d):
    """Offloaded, then reloaded by reference: every payload comes back as it was."""
    store = f"{shared_folder(s)}/store/{uuid.uuid4().hex}"
    return experience.reload(experience.offload(built(s, d), store), store).select("experience_id", F.md5("payload").alias("payload_md5"))


query("store_bytes", "SELECT sum(strlen(text))::BIGINT AS gathered_bytes, count(*) * 48 AS reference_bytes FROM documents")(lambda s, d: experience.gather_cost(built(s, d)))
_SNAKE = "o AS (SELECT doc_id AS experience_id, source AS group_key, len(text) AS length, doc_id % 100 AS node, row_number() OVER (ORDER BY len(text) DESC, doc_id) - 1 AS k FROM documents), sn AS (SELECT *, CASE WHEN k % 16 < 8 THEN k % 16 ELSE 15 - k % 16 END AS rank_id FROM o)"
query("assign_snake", f"WITH {_SNAKE} SELECT experience_id, rank_id FROM sn")(lambda s, d: experience.assign(light(s, d), RANKS).select("experience_id", "rank_id"))
query("assign_rr", "SELECT doc_id AS experience_id, (row_number() OVER (ORDER BY doc_id) - 1) % 8 AS rank_id FROM documents")(lambda s, d: experience.assign(light(s, d), RANKS, "round_robin").select("experience_id", "rank_id"))
query("assign_hash", "SELECT doc_id AS experience_id, ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 8 AS rank_id FROM documents")(lambda s, d: experience.assign(light(s, d), RANKS, "hash").select("experience_id", "rank_id"))
query("assign_prefix", """WITH k AS (SELECT doc_id AS experience_id, len(text) AS n, coalesce(sum(len(text)) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM documents)
SELECT experience_id, least(7, floor(before * 8 / (SELECT sum(n) FROM k)))::BIGINT AS rank_id FROM k""")(
    lambda s, d: experience.assign(light(s, d), RANKS, "prefix").select("experience_id", "rank_id")
)
query("assign_lpt")(lambda s, d: experience.assign(light(s, d), RANKS, "lpt", window=["node"]).select("experience_id", "rank_id", "length"))
query("assign_groups", """WITH g AS (SELECT source AS group_key, sum(len(text)) AS n FROM documents GROUP BY 1), k AS (SELECT group_key, row_number() OVER (ORDER BY n DESC, group_key) - 1 AS k FROM g)
SELECT doc_id AS experience_id, CASE WHEN k % 16 < 8 THEN k % 16 ELSE 15 - k % 16 END AS rank_id FROM documents JOIN k ON source = group_key""")(lambda s, d: experience.assign(light(s, d), RANKS, keep_groups=True).select("experience_id", "rank_id"))
query("assign_quality", f"WITH {_SNAKE}, r AS (SELECT rank_id, sum(length) AS l, max(length) AS t, count(*) AS n FROM sn GROUP BY 1) SELECT round(max(l) / avg(l), 6) AS imbalance, round(1 - sum(l) / sum(t * n), 6) AS padding_waste, max(l)::BIGINT AS slowest FROM r")(
    lambda s, d: measures.imbalance(experience.assign(light(s, d), RANKS)).select(r6("imbalance"), r6("padding_waste"), "slowest")
)


def _places(s, d):
    nat, reg = workloads.table(s, d, "nation"), workloads.table(s, d, "region")
    n = nat.join(reg, nat.n_regionkey == reg.r_regionkey).select(F.col("n_nationkey"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
    return s.range(experience.NODES).select(F.col("id").cast("int").alias("node"), (F.col("id") % 25).cast("int").alias("n_nationkey")).join(n, "n_nationkey").drop("n_nationkey")


query("store_transfer", f"""WITH {_SNAKE}, p AS (SELECT sn.*, n_name AS nation, r_name AS region, CASE WHEN node % 8 = rank_id THEN 0 ELSE length END AS moved FROM sn JOIN nation ON n_nationkey = node % 25 JOIN region ON r_regionkey = n_regionkey)
SELECT coalesce(region, '*') AS region, coalesce(nation, '*') AS nation, coalesce(node, -1)::BIGINT AS node, sum(length)::BIGINT AS bytes, sum(moved)::BIGINT AS moved FROM p GROUP BY ROLLUP (region, nation, node)""")(
    lambda s, d: experience.transfer(experience.assign(light(s, d), RANKS), _places(s, d), RANKS).select(F.coalesce("region", F.lit("*")).alias("region"), F.coalesce("nation", F.lit("*")).alias("nation"), F.coalesce(F.col("node").cast("long"), F.lit(-1)).alias("node"), "bytes", "moved")
)
query("store_audit", "SELECT (SELECT count(*) FROM documents WHERE doc_id % 7 = 0) AS dangling, (SELECT count(*) FROM documents WHERE doc_id % 11 = 0 AND doc_id % 7 <> 0) AS unreferenced, 0::BIGINT AS duplicated")(
    lambda s, d: experience.audit(experience.light(built(s, d)).filter("experience_id % 11 <> 0 OR experience_id % 7 = 0"), light(s, d).filter("experience_id % 7 <> 0").select(F.col("experience_id").alias("payload_id")))
)
query("store_memory", f"WITH {_SNAKE}, r AS (SELECT rank_id, sum(length) AS l, count(*) AS n FROM sn GROUP BY 1) SELECT sum(l)::BIGINT AS controller_gather, (sum(n) * 48)::BIGINT AS controller_refs, max(l)::BIGINT AS rank_peak FROM r")(lambda s, d: experience.memory(experience.assign(light(s, d), RANKS)))
_HOWS = ("hash", "round_robin", "serpentine")


def _heavy(s, d, name):
    """Experiences whose payload is a page, a vector or a document; a vector's length is its bytes."""
    t = workloads.table(s, d, name)
    if name == "pages":
        t = t.select(F.col("page_id").alias("doc_id"), F.lit(name).alias("source"), F.col("html").alias("text"))
    if name == "embeddings":
        e = experience.build(t.select(F.col("vec_id").alias("doc_id"), F.lit(name).alias("source"), F.concat_ws(" ", F.col("embedding").cast("array<string>")).alias("text")))
        return e.drop("length").join(t.select(F.col("vec_id").alias("experience_id"), (4 * F.size("embedding")).cast("long").alias("length")), "experience_id")
    return experience.build(t)


@query("wl_visual_store", """WITH e AS (SELECT 'pages' AS payload, page_id AS id, len(html) AS n FROM pages UNION ALL SELECT 'documents', doc_id, len(text) FROM documents UNION ALL SELECT 'embeddings', vec_id, 4 * len(embedding) FROM embeddings),
o AS (SELECT *, row_number() OVER (PARTITION BY payload ORDER BY id) - 1 AS i, row_number() OVER (PARTITION BY payload ORDER BY n DESC, id) - 1 AS k FROM e),
r AS (SELECT payload, 'hash' AS how, ('0x' || substr(md5(id::VARCHAR), 1, 8))::BIGINT % 8 AS rank, n FROM o UNION ALL SELECT payload, 'round_robin', i % 8, n FROM o UNION ALL SELECT payload, 'serpentine', CASE WHEN k % 16 < 8 THEN k % 16 ELSE 15 - k % 16 END, n FROM o),
l AS (SELECT payload, how, rank, sum(n) AS l, count(*) AS c FROM r GROUP BY ALL)
SELECT payload, how, sum(c)::BIGINT AS n_reloaded, sum(l)::BIGINT AS controller_gather, (48 * sum(c))::BIGINT AS controller_refs, max(l)::BIGINT AS rank_peak, round(max(l) / avg(l), 6) AS imbalance FROM l GROUP BY ALL""")
def wl_visual_store(s, d):
    """Heavy payloads written by their nodes, light rows assigned to ranks by three rules, payloads reloaded and held against their digests:
    what passes the controller, the fullest rank, and how far it lies above the mean."""
    out = None
    for name in ("pages", "documents", "embeddings"):
        store = f"{shared_folder(s)}/store/{uuid.uuid4().hex}"
        rows = experience.offload(_heavy(s, d, name), store).withColumn("digest_sent", F.col("ref.digest"))
        for how in _HOWS:
            a = experience.assign(rows, RANKS, how)
            back = experience.reload(a, store).agg(F.sum((F.md5("payload") == F.col("digest_sent")).cast("long")).alias("n_reloaded"))
            part = back.crossJoin(experience.memory(a)).crossJoin(measures.imbalance(a).select(r6("imbalance"))).withColumn("payload", F.lit(name)).withColumn("how", F.lit(how))  # one row each
            out = part if out is None else out.unionByName(part)
    return out


@query("attn_mask", """WITH t AS (SELECT l_orderkey AS rollout_id, count(*) AS n FROM lineitem GROUP BY 1), b AS (SELECT *, rollout_id // 64 AS batch FROM t)
SELECT rollout_id, max(n) OVER (PARTITION BY batch) AS padded_length, n AS n_attended, max(n) OVER (PARTITION BY batch) - n AS padding FROM b""")
def attn_mask(s, d):
    seg = workloads.action_tokens(s, d).groupBy("rollout_id").agg(F.collect_list("token_id").alias("token_ids")).withColumn("microbatch_id", F.floor(F.col("rollout_id") / 64))
    p = batches.pad_batch(seg)
    on = F.size(F.filter("attention", lambda x: x)).cast("long")
    return p.select("rollout_id", F.size("padded").cast("long").alias("padded_length"), on.alias("n_attended"), (F.size("padded") - on).alias("padding"))
