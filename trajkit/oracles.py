"""Shared text of the DuckDB oracles: the fixtures as common table expressions over the raw tables."""

ROLLOUTS = """rollouts AS (SELECT o_custkey AS group_id, o_orderkey AS rollout_id, o_orderdate AS completed_at,
  CASE WHEN o_orderstatus = 'F' THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS reward, o_totalprice / 1e5 AS reward_c, o_orderpriority AS gate_hint FROM orders)"""
FIRST = (
    ROLLOUTS
    + """, four AS (SELECT * EXCLUDE (gn) FROM (SELECT *, row_number() OVER (PARTITION BY group_id ORDER BY completed_at, rollout_id) AS sample,
  count(*) OVER (PARTITION BY group_id) AS gn FROM rollouts) WHERE sample <= 4 AND gn >= 4),
gs AS (SELECT group_id, avg(reward) AS mu, stddev_samp(reward) AS sd, stddev_pop(reward) AS sp, sum(reward) AS total, count(*) AS n, max(reward) - min(reward) AS spread, max(completed_at) AS done FROM four GROUP BY group_id),
live AS (SELECT f.*, mu, sd, (reward - mu) / (sd + 1e-6) AS adv FROM four f JOIN gs USING (group_id) WHERE spread > 0)"""
)
TOKENS = """tok AS (SELECT l_orderkey AS rollout_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount) - 1 AS pos,
  l_partkey AS token_id, l_returnflag <> 'N' AS mixed_action, -(1 + 10 * l_discount) AS b, -(1 + 10 * l_discount) + (l_tax - 0.04) * 20.0 AS o,
  -(1 + 10 * l_discount) + (l_tax - 0.04) * 20.0 + (l_quantity - 25) / 100 AS c, l_suppkey AS node, l_shipdate AS sampled_at FROM lineitem)"""
TRACE = FIRST + ", " + TOKENS + ", trace AS (SELECT tok.*, pos // 3 AS segment_seq, group_id, adv, reward, reward_c, count(*) OVER (PARTITION BY rollout_id) AS length FROM tok JOIN live USING (rollout_id))"
