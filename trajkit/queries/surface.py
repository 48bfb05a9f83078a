"""Operators, sources and functions around the methods."""

import uuid

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from trajkit import sources, tokens, workloads
from trajkit.registered import query
from trajkit.session import shared_folder

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
t = workloads.table
col = F.col


def _path(s, name):
    return f"{shared_folder(s)}/surface/{name}-{uuid.uuid4().hex}"


query("scan_parquet", "SELECT l_suppkey, count(*) AS n, round(min(l_discount + 0.0), 6) AS low FROM lineitem WHERE l_quantity < 10 GROUP BY 1")(lambda s, d: t(s, d, "lineitem").filter("l_quantity < 10").groupBy("l_suppkey").agg(F.count("*").alias("n"), r6(F.min(col("l_discount") + 0.0), "low")))
for _kind in ("json", "csv", "orc"):
    query(f"scan_{_kind}", "SELECT s_suppkey, s_name, s_nationkey FROM supplier")(lambda s, d, k=_kind: sources.round_trip(t(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey"), k, _path(s, k)))
query("scan_text", "SELECT line, count(*) AS n FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM benchmark) GROUP BY 1")(lambda s, d: sources.round_trip(t(s, d, "benchmark").select(F.explode(F.split("text", "\n")).alias("value")), "text", _path(s, "text")).groupBy(col("value").alias("line")).agg(F.count("*").alias("n")))


@query("scan_binary")
def scan_binary(s, d):
    p = _path(s, "bin")
    sources.write(t(s, d, "benchmark").select("text"), "text", p)
    return sources.read(s, "binaryFile", p).select("length", F.md5("content").alias("digest"))


@query("scan_pysource", r"SELECT conv_id AS rollout_id, turn, (i - 1)::INTEGER AS pos, ('0x' || substr(md5(w[i]), 1, 8))::BIGINT AS token_id FROM (SELECT conv_id, turn, w, unnest(range(1, len(w) + 1)) AS i FROM (SELECT conv_id, turn, regexp_extract_all(text, '[^\t\n\x0B\f\r ]+') AS w FROM conversations WHERE role = 'assistant'))")
def scan_pysource(s, d):
    """The replies of all conversations logged in the shared folder and replayed by a source written in Python."""
    p = _path(s, "log")
    replies = t(s, d, "conversations").filter("role = 'assistant'")
    sources.write_log(replies.select(col("conv_id").alias("rollout_id"), "turn", F.transform(tokens.split(col("text")), tokens.token_id).alias("token_ids")), p)
    s.dataSource.register(sources.EngineLog)
    return s.read.format("engine_log").load(p)


@query("sink_roundtrip", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def sink_roundtrip(s, d):
    p = _path(s, "parts")
    n = t(s, d, "nation")
    sources.write(n, "parquet", p, by=["n_regionkey"])
    return sources.read(s, "parquet", p, n.schema).select("n_nationkey", "n_name", "n_regionkey")


query("filter_pred", "SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1e5 AND 3e5 AND o_orderstatus IS NOT DISTINCT FROM 'F'")(
    lambda s, d: t(s, d, "orders").filter(col("o_orderpriority").isin("1-URGENT", "2-HIGH") & col("o_totalprice").between(1e5, 3e5) & col("o_orderstatus").eqNullSafe("F")).select("o_orderkey")
)


def _join(name, how, sql_how, hint=None):
    @query(name, f"SELECT c_custkey, count(o_orderkey) AS n FROM customer {sql_how} JOIN (SELECT * FROM orders WHERE o_totalprice > 2e5) o ON c_custkey = o_custkey GROUP BY 1")
    def run(s, d):
        o = t(s, d, "orders").filter("o_totalprice > 2e5").select("o_custkey", "o_orderkey")
        return t(s, d, "customer").join(o.hint(hint) if hint else o, col("c_custkey") == col("o_custkey"), how).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


_join("join_inner", "inner", "INNER")
_join("join_left", "left", "LEFT")
_join("join_full", "full", "FULL")
_join("join_broadcast", "inner", "INNER", "broadcast")
_join("join_merge", "inner", "INNER", "merge")
_join("join_hash", "inner", "INNER", "shuffle_hash")
query("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: t(s, d, "customer").join(t(s, d, "orders"), col("c_custkey") == col("o_custkey"), "left_semi").select("c_custkey"))
query("join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(lambda s, d: t(s, d, "orders").join(t(s, d, "lineitem"), col("o_orderkey") == col("l_orderkey"), "left_anti").select("o_orderkey"))
query("join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")(
    lambda s, d: t(s, d, "nation").alias("a").join(t(s, d, "nation").alias("b"), (col("a.n_regionkey") == col("b.n_regionkey")) & (col("a.n_nationkey") < col("b.n_nationkey"))).select(col("a.n_nationkey").alias("a"), col("b.n_nationkey").alias("b"))
)


@query("join_range", "SELECT p_partkey, k AS band FROM part JOIN range(30) b(k) ON p_retailprice >= k * 75 AND p_retailprice < k * 75 + 75")
def join_range(s, d):
    from trajkit.joins import range_join

    bands = s.range(30).select(col("id").alias("band"), (col("id") * 75.0).alias("lo"), (col("id") * 75.0 + 75).alias("hi"))
    return range_join(t(s, d, "part").select("p_partkey", "p_retailprice"), bands, col("p_retailprice"), col("lo"), col("hi"), 100.0).select("p_partkey", "band")


query("agg_basic", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 4) AS q, round(avg(l_tax), 6) AS tax FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"), r6(F.avg("l_tax"), "tax")))
query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS nodes FROM lineitem GROUP BY 1")(lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("nodes")))
query("agg_filter", "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS done FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").groupBy("o_orderpriority").agg(F.count_if(col("o_orderstatus") == "F").alias("done")))
query("agg_bool", "SELECT o_custkey, bool_and(o_totalprice > 5e4) AS all_big, bool_or(o_totalprice > 4e5) AS any_big FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.bool_and(col("o_totalprice") > 5e4).alias("all_big"), F.bool_or(col("o_totalprice") > 4e5).alias("any_big")))
query("agg_maxby", "SELECT o_custkey, arg_max(o_orderkey, struct_pack(a := o_totalprice, b := o_orderkey)) AS best FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best")))
query("agg_corr", "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem")(lambda s, d: t(s, d, "lineitem").agg(r6(F.corr("l_quantity", "l_extendedprice"), "r")))
for _name, _sql, _fn in (("rollup", "ROLLUP", "rollup"), ("cube", "CUBE", "cube")):
    query(f"agg_{_name}", f"SELECT coalesce(l_returnflag, '*') AS f, coalesce(l_linestatus, '*') AS st, count(*) AS n FROM lineitem GROUP BY {_sql} (l_returnflag, l_linestatus)")(
        lambda s, d, fn=_fn: getattr(t(s, d, "lineitem"), fn)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("f"), F.coalesce("l_linestatus", F.lit("*")).alias("st"), "n")
    )
query("agg_gsets", "SELECT coalesce(l_returnflag, '*') AS f, coalesce(l_linestatus, '*') AS st, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")(
    lambda s, d: t(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n")).select(F.coalesce("l_returnflag", F.lit("*")).alias("f"), F.coalesce("l_linestatus", F.lit("*")).alias("st"), "n")
)
query("agg_pivot", "SELECT l_returnflag, sum(CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END)::BIGINT AS f, sum(CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END)::BIGINT AS o FROM lineitem GROUP BY 1")(
    lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))
)


@query("sketches", "SELECT count(DISTINCT l_partkey) AS exact_distinct, count(l_extendedprice) AS exact_n, true AS distinct_within, true AS median_within, true AS merged_within FROM lineitem")
def sketches(s, d):
    """Sketches against exact answers in two passes: distinct tokens within 5 %, medians (whole, and merged from a sketch a line status) within 2 % of rank."""
    lines = t(s, d, "lineitem")
    price = col("l_extendedprice").cast("double")
    whole = lines.agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("est"), F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double(price), F.lit(0.5)).alias("mid"))
    each = lines.groupBy("l_linestatus").agg(F.kll_sketch_agg_double(price).alias("k"))
    merged = each.agg(F.kll_sketch_get_quantile_double(F.kll_merge_agg_double("k"), F.lit(0.5)).alias("mid2"))
    x = lines.crossJoin(F.broadcast(whole)).crossJoin(F.broadcast(merged))  # one row each
    near = lambda q: (F.avg((price < col(q)).cast("double")) <= 0.52) & (F.avg((price <= col(q)).cast("double")) >= 0.48)
    n = F.countDistinct("l_partkey")
    return x.agg(n.alias("exact_distinct"), F.count("l_extendedprice").alias("exact_n"), (F.abs(F.max("est") - n) <= 0.05 * n).alias("distinct_within"), near("mid").alias("median_within"), near("mid2").alias("merged_within"))


_W = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)"
query("win_rank", f"SELECT o_orderkey, rank() {_W} AS r, dense_rank() {_W} AS dr, ntile(4) {_W} AS q, round(percent_rank() {_W}, 6) AS pr, coalesce(lag(o_orderkey) {_W}, -1) AS before FROM orders")(lambda s, d: _ranks(t(s, d, "orders")))


def _ranks(o):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return o.select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("q"), r6(F.percent_rank().over(w), "pr"), F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"))


query("win_frames", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 3) AS sliding, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS near FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over((w := Window.partitionBy("o_custkey").orderBy("o_orderkey")).rowsBetween(-2, 0)), 3).alias("sliding"), F.count("*").over(w.rangeBetween(-1000, 0)).alias("near"))
)
query("topk_global", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey"))
query("topk_group", f"SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() {_W} AS k FROM orders) WHERE k <= 2")(lambda s, d: t(s, d, "orders").withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).filter("k <= 2").select("o_custkey", "o_orderkey"))
_A, _B = "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity < 5", "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 45"


def _two(s, d):
    l = t(s, d, "lineitem")
    return l.filter("l_quantity < 5").select(col("l_suppkey").alias("k")), l.filter("l_quantity > 45").select(col("l_suppkey").alias("k"))


for _name, _sql, _fn in (("union", "UNION ALL", "union"), ("intersect", "INTERSECT", "intersect"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll"), ("intersect_all", "INTERSECT ALL", "intersectAll")):
    query(f"set_{_name}", f"SELECT k, count(*) AS n FROM ({_A} {_sql} {_B}) GROUP BY 1")(lambda s, d, fn=_fn: getattr(*(lambda p: (p[0], fn))(_two(s, d)))(_two(s, d)[1]).groupBy("k").agg(F.count("*").alias("n")))
query("fn_string", "SELECT c_custkey, md5(c_name) AS digest, upper(c_mktsegment) AS up, levenshtein(c_name, c_mktsegment) AS far, regexp_extract(c_name, '([0-9]+)', 1) AS num FROM customer")(
    lambda s, d: t(s, d, "customer").select("c_custkey", F.md5("c_name").alias("digest"), F.upper("c_mktsegment").alias("up"), F.levenshtein("c_name", "c_mktsegment").cast("long").alias("far"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("num"))
)
query("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS ln, round(exp(p_size / 50.0), 6) AS e, greatest(p_size, 10) AS g, round(pow(p_size, 0.5), 6) AS root FROM part")(
    lambda s, d: t(s, d, "part").select("p_partkey", r6(F.log("p_retailprice"), "ln"), r6(F.exp(col("p_size") / 50.0), "e"), F.greatest("p_size", F.lit(10)).alias("g"), r6(F.pow("p_size", F.lit(0.5)), "root"))
)
query("fn_date", "SELECT o_orderkey, epoch_us(date_trunc('month', o_orderdate)) AS month_us, extract(dow FROM o_orderdate)::BIGINT + 1 AS dow FROM orders")(
    lambda s, d: t(s, d, "orders").select("o_orderkey", F.unix_micros(F.date_trunc("month", col("o_orderdate").cast("timestamp"))).alias("month_us"), F.dayofweek("o_orderdate").cast("long").alias("dow"))
)
query("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 5) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")(
    lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x), 5).alias("total"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))
)
query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
query("fn_map", "SELECT n_regionkey, count(*) AS n FROM nation GROUP BY 1")(lambda s, d: t(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).select("n_regionkey", F.size(F.map_keys("m")).cast("long").alias("n")))


@query("udf_scalar", "SELECT p_partkey, p_size * 2 + 1 AS x FROM part")
def udf_scalar(s, d):
    return t(s, d, "part").select("p_partkey", F.pandas_udf(_twice, "int")("p_size").alias("x"))


def _twice(v: pd.Series) -> pd.Series:
    return v * 2 + 1


def _spread(v: pd.Series) -> float:
    return float(v.max() - v.min())


query("udf_agg", "SELECT o_custkey, round(max(o_totalprice) - min(o_totalprice), 6) AS spread FROM orders GROUP BY 1")(lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(r6(F.pandas_udf(_spread, "double")("o_totalprice"), "spread")))
query("udf_grouped_map")(lambda s, d: t(s, d, "orders").select("o_custkey", "o_totalprice").groupBy("o_custkey").applyInPandas(lambda p: p.nlargest(1, "o_totalprice"), "o_custkey long, o_totalprice double"))


@query("udf_table", "SELECT item_id, unnest(range(3)) AS i FROM benchmark")
def udf_table(s, d):
    @F.udtf(returnType="i long")
    class Upto:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    s.udtf.register("trajkit_upto", Upto)
    t(s, d, "benchmark").createOrReplaceTempView("trajkit_benchmark")
    return s.sql("SELECT item_id, i FROM trajkit_benchmark, LATERAL trajkit_upto(3)")


@query("sql_surface", "SELECT o_custkey AS group_id, round(avg(CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE 0.0 END), 6) AS mean FROM orders GROUP BY 1 HAVING count(*) >= 4")
def sql_surface(s, d):
    """The same estimators in SQL over a view, with a named argument."""
    workloads.rollouts(s, d).createOrReplaceTempView("trajkit_rollouts")
    return s.sql("SELECT group_id, round(avg(reward), 6) AS mean FROM trajkit_rollouts GROUP BY group_id HAVING count(*) >= :n", args={"n": 4})
