"""The driver's queries for this subpackage: op1 to op10 over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trajkit.llm import block_topk, curve_packing, length_histogram, mil_quality, mincut_extract, quality_cascade, secret_scan, shingle_join, toxicity_grammar, weighted_mixing


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_block_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return block_topk.top_k(table(spark, sf_dir, "embeddings"))


def op2_hilbert_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curve_packing.pack(table(spark, sf_dir, "documents"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_cascade.quality_rules(table(spark, sf_dir, "documents")).drop("failed_rule")


def op4_toxicity_grammar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_grammar.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def op6_attention_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mil_quality.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return length_histogram.token_counts(table(spark, sf_dir, "documents"))


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shingle_join.jaccard_components(table(spark, sf_dir, "documents"))


def prompt_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shingle_join.near_duplicates(table(spark, sf_dir, "documents"))


def op9_mincut_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mincut_extract.extract(table(spark, sf_dir, "pages"))


def op10_weighted_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted_mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", F.col("size").cast("long").alias("size"), F.col("source_size").cast("long").alias("source_size"), "target", "taken")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_block_topk": op1_block_topk,
    "op2_hilbert_packing": op2_hilbert_packing,
    "op3_quality_rules": op3_quality_rules,
    "op4_toxicity_grammar": op4_toxicity_grammar,
    "op5_secret_scan": op5_secret_scan,
    "op6_attention_quality": op6_attention_quality,
    "op7_token_counts": op7_token_counts,
    "op8_jaccard_join": op8_jaccard_join,
    "op9_mincut_extract": op9_mincut_extract,
    "op10_weighted_mixing": op10_weighted_mixing,
    "prompt_neardup": prompt_neardup,
}

ORACLES: dict[str, str] = {
    "op1_block_topk": r"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS w FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.w, c.w), lambda z: z[1] * z[2]))::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id)
SELECT query_id, rank::INTEGER AS rank, vec_id, score
FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p) WHERE rank <= 5
""",
    "op3_quality_rules": r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
lines AS (SELECT doc_id, rn, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS rn FROM d)
          WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines, count(*) AS n_lines FROM lines GROUP BY doc_id),
win AS (SELECT doc_id, i, w[i] || chr(32) || w[i+1] || chr(32) || w[i+2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
again AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM again) GROUP BY doc_id),
c AS (SELECT d.doc_id, text, CAST(len(w) AS BIGINT) AS n_words, CAST(len(array_to_string(w, '')) AS BIGINT) AS word_chars,
             CAST(len(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(n_dup_lines, 0) AS BIGINT) AS n_dup_lines,
             coalesce(n_lines, 0) AS n_lines, CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words
      FROM d LEFT JOIN dup USING (doc_id) LEFT JOIN rep USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
       NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words OR word_chars < 2 * n_words OR word_chars > 20 * n_words OR 2 * n_symbols > n_words OR 2 * n_dup_lines > n_lines
            OR len(regexp_replace(text, '[^A-Z]', '', 'g')) > len(regexp_replace(text, '[^a-z]', '', 'g'))) AS kept
FROM c
""",
    "op8_jaccard_join": r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT doc_id, array_to_string(w[i:i+4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w WHERE len(w) >= 5)
      UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM w WHERE len(w) BETWEEN 1 AND 4),
s AS (SELECT DISTINCT doc_id, g FROM g),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM c JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 75 * (a.n + b.n - c)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id, doc_id AS root FROM documents UNION SELECT e.y, r.root FROM r JOIN e ON r.doc_id = e.x)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.component_id FROM documents d LEFT JOIN n USING (doc_id)
JOIN (SELECT doc_id, min(root) AS component_id FROM r GROUP BY doc_id) m ON m.doc_id = d.doc_id
""",
    "op10_weighted_mixing": r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
                  len(regexp_replace(coalesce(text, ''), '[^#*$%&|<>]', '', 'g')) AS sym, ('0x' || md5(doc_id::VARCHAR)[1:12])::BIGINT AS bits FROM documents),
k AS (SELECT *, -ln((bits + 0.5) / 281474976710656.0) / (1.0 / (1.0 + 4.0 * least(1.0, sym::DOUBLE / greatest(size, 1)))) AS key FROM d),
s AS (SELECT source, sum(size)::DOUBLE AS ss, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS rk FROM d GROUP BY source),
w AS (SELECT source, ss, [5, 2, 1][(rk % 3 + 1)::INT] AS wt, (SELECT sum(ss) FROM s) AS total FROM s),
-- the water level: the only candidate at which the capped and the open sources spend the budget exactly
lv AS (SELECT max(lam) AS lam FROM (
         SELECT (a.total - coalesce((SELECT sum(3 * b.ss) FROM w b WHERE 3 * b.ss / b.wt < 3 * a.ss / a.wt), 0)) / (SELECT sum(b.wt) FROM w b WHERE 3 * b.ss / b.wt >= 3 * a.ss / a.wt) AS lam,
                3 * a.ss / a.wt AS top, coalesce((SELECT max(3 * b.ss / b.wt) FROM w b WHERE 3 * b.ss / b.wt < 3 * a.ss / a.wt), 0) AS low FROM w a)
       WHERE lam <= top AND lam >= low),
t AS (SELECT source, ss, round(least(3 * ss, lam * wt), 6) AS target FROM w, lv),
f AS (SELECT *, CASE WHEN ss > 0 THEN floor(target / ss) ELSE 0 END AS ep FROM t),
m AS (SELECT k.doc_id, k.size, f.ss, f.target, f.ep, round(f.target) - f.ep * f.ss - coalesce(sum(k.size) OVER (PARTITION BY k.source ORDER BY key, k.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS room
      FROM k JOIN f ON k.source IS NOT DISTINCT FROM f.source)
SELECT doc_id, size::BIGINT AS size, ss::BIGINT AS source_size, target, (ep * size + greatest(0, least(size, room)))::BIGINT AS taken FROM m
""",
}
