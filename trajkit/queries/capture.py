"""Capture, compaction, worlds and graders on conversations and documents."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from trajkit import capture, grading, tokens, wire, workloads, worlds
from trajkit.registered import query

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
WORDS = r"regexp_extract_all({}, '[^\t\n\x0B\f\r ]+')"
REQ = r"""conv AS (SELECT conv_id AS rollout_id, turn, role, text AS content FROM conversations),
req AS (SELECT rollout_id, turn, row_number() OVER (PARTITION BY rollout_id ORDER BY turn) - 1 AS request_seq, content AS reply FROM conv WHERE role = 'assistant'),
msg AS (SELECT r.rollout_id, r.request_seq, c.turn, c.role, c.content FROM req r JOIN conv c ON c.rollout_id = r.rollout_id AND c.turn < r.turn)"""
HEX = "('0x' || substr(md5({}), 1, 8))::BIGINT"


def requests(s, d):
    return worlds.requests(worlds.turns(s, d))


def _digest(df):
    text = F.array_join(F.transform("messages", lambda m: F.concat_ws(":", m["role"], m["content"])), "|")
    return df.select("rollout_id", "request_seq", F.size("messages").cast("long").alias("n_messages"), F.md5(text).alias("messages_md5"), F.md5("reply").alias("reply_md5"))


_WIRE = f"WITH {REQ} SELECT r.rollout_id, r.request_seq, count(m.turn) AS n_messages, md5(coalesce(string_agg(m.role || ':' || m.content, '|' ORDER BY m.turn), '')) AS messages_md5, md5(r.reply) AS reply_md5 FROM req r LEFT JOIN msg m USING (rollout_id, request_seq) GROUP BY r.rollout_id, r.request_seq, r.reply"
query("wire_completions", _WIRE)(lambda s, d: _digest(wire.normalise(wire.to_completions(requests(s, d)))))
query("wire_messages", _WIRE)(lambda s, d: _digest(wire.normalise(wire.to_messages(requests(s, d)))))


@query("wire_parity", "SELECT 0::BIGINT AS rollout_id, 0::BIGINT AS request_seq WHERE false")
def wire_parity(s, d):
    r = requests(s, d)
    a, b = _digest(wire.normalise(wire.to_completions(r))), _digest(wire.normalise(wire.to_messages(r)))
    return a.exceptAll(b).unionByName(b.exceptAll(a)).select("rollout_id", "request_seq")


_RENDER = f"""WITH {REQ}, p AS (SELECT rollout_id, request_seq, turn, '<|' || role || '|>' || CASE WHEN len({WORDS.format('content')}) > 0 THEN ' ' || array_to_string({WORDS.format('content')}, ' ') ELSE '' END || ' <|end|>' AS t,
  len({WORDS.format('content')}) AS n FROM msg)"""
query("render_once", _RENDER + " SELECT rollout_id, request_seq, (sum(n) + 2 * count(*))::BIGINT AS n_tokens, md5(string_agg(t, ' ' ORDER BY turn)) AS stream_md5 FROM p GROUP BY 1, 2")(
    lambda s, d: requests(s, d).select("rollout_id", "request_seq", tokens.render(F.col("messages")).alias("t")).filter("size(t) > 0").select("rollout_id", "request_seq", F.size("t").cast("long").alias("n_tokens"), F.md5(F.array_join("t", " ")).alias("stream_md5"))
)
query("render_drift", _RENDER + " SELECT rollout_id, request_seq, (sum(n) + 2 * count(*))::BIGINT AS once, (sum(n) + 2 * count(*) + 2)::BIGINT AS twice, 2::BIGINT AS extra FROM p GROUP BY 1, 2")(
    lambda s, d: tokens.render_twice_drift(requests(s, d).filter("size(messages) > 0")).select("rollout_id", "request_seq", *[F.col(c).cast("long").alias(c) for c in ("once", "twice", "extra")])
)


def _vocabulary(turns):
    """Each id with the first piece that has it, by conversation, turn and place, and its count; pieces that share an id are one entry."""
    each = turns.select("conv_id", "turn", F.posexplode(tokens.encode(F.col("text"))).alias("pos", "t"))
    firsts = each.groupBy("t.piece").agg(F.first("t.id").alias("id"), F.min(F.struct("conv_id", "turn", "pos")).alias("at"), F.count("*").alias("n"))
    return firsts.groupBy("id").agg(F.min_by("piece", "at").alias("piece"), F.sum("n").alias("n"))


query("encode_tokens", f"SELECT id, any_value(piece) AS piece, count(*) AS n FROM (SELECT {HEX.format('piece')} AS id, piece FROM (SELECT unnest({WORDS.format('text')}) AS piece FROM conversations)) GROUP BY id")(
    lambda s, d: _vocabulary(workloads.table(s, d, "conversations"))
)
_ENGINE = f"""eng AS (SELECT rollout_id, request_seq, i - 1 AS pos, {HEX.format('piece')} AS token_id, piece FROM
 (SELECT rollout_id, request_seq, unnest(range(1, len(w) + 1)) AS i, unnest(w) AS piece FROM (SELECT rollout_id, request_seq, {WORDS.format('reply')} AS w FROM req)))"""
query("capture_trace", f"""WITH {REQ}, {_ENGINE}, ctx AS (SELECT rollout_id, request_seq, sum(len({WORDS.format('content')}) + 2)::BIGINT AS c FROM msg GROUP BY 1, 2)
SELECT rollout_id, request_seq, coalesce(max(c), 0)::BIGINT AS context_tokens, count(*) AS n_actions, sum(token_id)::BIGINT AS id_sum FROM eng LEFT JOIN ctx USING (rollout_id, request_seq) GROUP BY 1, 2""")(
    lambda s, d: capture.record(r := requests(s, d), capture.engine_tokens(r)).groupBy("rollout_id", "request_seq").agg(F.max("context_tokens").cast("long").alias("context_tokens"), F.count("*").alias("n_actions"), F.sum("token_id").alias("id_sum"))
)


@query("retoken_drift", f"""WITH {REQ}, {_ENGINE}, bi AS (SELECT rollout_id, request_seq, row_number() OVER (PARTITION BY rollout_id, request_seq ORDER BY pos, k) - 1 AS pos, {HEX.format('substr(piece, k, 2)')} AS again
  FROM (SELECT rollout_id, request_seq, pos, piece, unnest(range(1, len(piece) + 1, 2)) AS k FROM eng))
SELECT rollout_id, count(*) AS n_tokens, sum(CASE WHEN again = token_id THEN 0 ELSE 1 END)::BIGINT AS n_moved FROM eng LEFT JOIN bi USING (rollout_id, request_seq, pos) GROUP BY 1""")
def retoken_drift(s, d):
    r = requests(s, d)
    return capture.retokenise_drift(r, capture.engine_tokens(r))


def _contract(s, d, corrupt):
    r = requests(s, d)
    engine = capture.engine_tokens(r)
    trace = engine.withColumn("m", F.lit(1))
    if corrupt:
        trace = trace.withColumn("token_id", F.when((F.col("pos") * 31 + F.col("request_seq") * 7 + F.col("rollout_id")) % 97 == 0, -1 - F.col("token_id")).otherwise(F.col("token_id")))
    return capture.contract_violations(trace, engine).select("rollout_id", "request_seq", "pos", "token_id")


query("contract_ok", "SELECT 0::BIGINT AS rollout_id, 0::BIGINT AS request_seq, 0::BIGINT AS pos, 0::BIGINT AS token_id WHERE false")(lambda s, d: _contract(s, d, False))
query("contract_bad", f"WITH {REQ}, {_ENGINE} SELECT rollout_id, request_seq, pos, -1 - token_id AS token_id FROM eng WHERE (pos * 31 + request_seq * 7 + rollout_id) % 97 = 0")(lambda s, d: _contract(s, d, True))

#: Requests under a policy that keeps the last two messages: the context as one string a request.
_LAST = f"""WITH {REQ}, m2 AS (SELECT *, row_number() OVER (PARTITION BY rollout_id, request_seq ORDER BY turn DESC) AS back FROM msg),
ctx AS (SELECT r.rollout_id, r.request_seq, r.reply, coalesce(string_agg(m.role || ':' || m.content, '|' ORDER BY m.turn) FILTER (WHERE back <= {{k}}), '') AS c FROM req r LEFT JOIN m2 m USING (rollout_id, request_seq) GROUP BY ALL),
x AS (SELECT *, lag(CASE WHEN c = '' THEN '' ELSE c || '|' END || 'assistant:' || reply) OVER (PARTITION BY rollout_id ORDER BY request_seq) AS seen FROM ctx),
y AS (SELECT *, coalesce(c = seen OR starts_with(c, seen || '|'), false) AS extends FROM x)"""


def _policies(s, d):
    r = requests(s, d)
    return {"keep_all": r, "last_k": worlds.compact(r, "last_k", k=2)}


@query("compact_history", " UNION ALL ".join(f"SELECT * FROM ({_LAST.format(k=k)} SELECT '{n}' AS policy, rollout_id, request_seq, extends FROM y)" for n, k in (("keep_all", 999), ("last_k", 2))))
def compact_history(s, d):
    parts = [capture.history_extends(r).select(F.lit(n).alias("policy"), "rollout_id", "request_seq", "extends") for n, r in _policies(s, d).items()]
    return parts[0].unionByName(parts[1])


query("compact_digest", _LAST.format(k=2) + " SELECT rollout_id, request_seq, extends FROM y")(lambda s, d: capture.history_extends_by_digest(_policies(s, d)["last_k"]).select("rollout_id", "request_seq", "extends"))


@query("compact_prefix", f"""WITH {REQ} SELECT rollout_id, request_seq, request_seq > 0 AS marked,
  coalesce(lag(len({WORDS.format('reply')})) OVER (PARTITION BY rollout_id ORDER BY request_seq) <= 1, false) AS history_dropping FROM req""")
def compact_prefix(s, d):
    r = requests(s, d)
    a = capture.prefix_kept(r, "marked").select("rollout_id", "request_seq", F.col("prefix_kept").alias("marked"))
    b = capture.prefix_kept(r, "history_dropping").select("rollout_id", "request_seq", F.col("prefix_kept").alias("history_dropping"))
    return a.join(b, ["rollout_id", "request_seq"])


@query("segments", " UNION ALL ".join(
    f"SELECT * FROM ({_LAST.format(k=k)} SELECT '{n}' AS policy, rollout_id, request_seq, (sum(CASE WHEN extends OR request_seq = 0 THEN 0 ELSE 1 END) OVER (PARTITION BY rollout_id ORDER BY request_seq))::BIGINT AS segment_seq FROM y)" for n, k in (("keep_all", 999), ("last_k", 2))))
def segments(s, d):
    parts = [capture.segment(r).select(F.lit(n).alias("policy"), "rollout_id", "request_seq", "segment_seq") for n, r in _policies(s, d).items()]
    return parts[0].unionByName(parts[1])


@query("segment_ablation", f"""{_LAST.format(k=2)}, n AS (SELECT count(*) AS requests, count(DISTINCT rollout_id) AS rollouts, sum(CASE WHEN NOT extends AND request_seq > 0 THEN 1 ELSE 0 END) AS breaks FROM y)
SELECT 'both' AS rule, (rollouts + breaks)::BIGINT AS n_segments FROM n UNION ALL SELECT 'history', (rollouts + breaks)::BIGINT FROM n UNION ALL SELECT 'prefix', (rollouts + breaks)::BIGINT FROM n
UNION ALL SELECT 'never', rollouts FROM n UNION ALL SELECT 'always', requests FROM n""")
def segment_ablation(s, d):
    r, out = _policies(s, d)["last_k"], None
    for rule in ("both", "history", "prefix", "never", "always"):
        part = capture.segment(r, check=rule).groupBy("rollout_id", "segment_seq").agg(F.count("*").alias("k")).agg(F.count("*").alias("n_segments")).select(F.lit(rule).alias("rule"), "n_segments")
        out = part if out is None else out.unionByName(part)
    return out


@query("segment_tokens", f"""WITH {REQ}, lastq AS (SELECT rollout_id, max(request_seq) AS request_seq, count(*) AS n_requests FROM req GROUP BY 1),
ctx AS (SELECT m.rollout_id, sum(len({WORDS.format('content')}) + 2) AS n FROM msg m JOIN lastq USING (rollout_id, request_seq) GROUP BY 1),
act AS (SELECT rollout_id, sum(len({WORDS.format('reply')})) AS a FROM req GROUP BY 1),
fin AS (SELECT rollout_id, len({WORDS.format('reply')}) + 2 AS f FROM req JOIN lastq USING (rollout_id, request_seq))
SELECT rollout_id, 0::BIGINT AS segment_seq, n_requests, (coalesce(n, 0) + f)::BIGINT AS n_tokens, a::BIGINT AS n_actions FROM lastq LEFT JOIN ctx USING (rollout_id) JOIN act USING (rollout_id) JOIN fin USING (rollout_id)""")
def segment_tokens(s, d):
    seg = capture.assemble(capture.segment(requests(s, d)))
    return seg.select("rollout_id", "segment_seq", "n_requests", F.size("token_ids").cast("long").alias("n_tokens"), F.size(F.filter("action_mask", lambda m: m)).cast("long").alias("n_actions"))


query("action_ranges", """WITH t AS (SELECT l_orderkey AS rollout_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount) - 1 AS pos, l_returnflag <> 'N' AS m FROM lineitem),
e AS (SELECT *, coalesce(lag(m) OVER (PARTITION BY rollout_id ORDER BY pos), false) AS before FROM t), g AS (SELECT *, sum(CASE WHEN m AND NOT before THEN 1 ELSE 0 END) OVER (PARTITION BY rollout_id ORDER BY pos) AS k FROM e)
SELECT rollout_id, min(pos) AS lo, max(pos) + 1 AS hi FROM g WHERE m GROUP BY rollout_id, k""")(lambda s, d: capture.ranges_from_mask(workloads.action_tokens(s, d).withColumn("m", F.col("mixed_action").cast("int"))))

_POLICY = {"keep_all": 999, "last_k": 2, "summary": 2}


@query("compact_policy", f"""WITH {REQ}, n AS (SELECT r.rollout_id, r.request_seq, count(m.turn) AS n FROM req r LEFT JOIN msg m USING (rollout_id, request_seq) GROUP BY 1, 2)
SELECT 'keep_all' AS policy, sum(n)::BIGINT AS n_messages FROM n UNION ALL SELECT 'last_k', sum(least(n, 2))::BIGINT FROM n UNION ALL SELECT 'summary', sum(CASE WHEN n > 2 THEN 3 ELSE n END)::BIGINT FROM n
UNION ALL SELECT 'drop_tool', sum(n)::BIGINT FROM n""")
def compact_policy(s, d):
    r, out = requests(s, d), None
    for p in ("keep_all", "last_k", "summary", "drop_tool"):
        part = worlds.compact(r, p).agg(F.sum(F.size("messages")).alias("n_messages")).select(F.lit(p).alias("policy"), "n_messages")
        out = part if out is None else out.unionByName(part)
    return out


AGENTS = ("keep_all", "last_k", "summary", "drop_tool")
#: Messages of each request under each agent's policy: the whole list, the last two, a note of the others before the last two, no tool messages.
COMPACTED = r"""mk AS (SELECT *, row_number() OVER (PARTITION BY rollout_id, request_seq ORDER BY turn DESC) AS back FROM msg),
cm AS (SELECT 'keep_all' AS policy, rollout_id, request_seq, turn, role, content FROM mk UNION ALL SELECT 'drop_tool', rollout_id, request_seq, turn, role, content FROM mk WHERE role <> 'tool'
 UNION ALL SELECT 'last_k', rollout_id, request_seq, turn, role, content FROM mk WHERE back <= 2 UNION ALL SELECT 'summary', rollout_id, request_seq, turn, role, content FROM mk WHERE back <= 2
 UNION ALL SELECT 'summary', rollout_id, request_seq, -1, 'system', string_agg(array_to_string(regexp_split_to_array(content, '\s+')[1:5], ' '), ' ' ORDER BY turn) FROM mk WHERE back > 2 GROUP BY 2, 3)"""


def agents(s, d):
    """Requests of the same conversations under each way of an agent with its context."""
    r, out = requests(s, d), None
    for p in AGENTS:
        part = worlds.compact(r, p).withColumn("policy", F.lit(p))
        out = part if out is None else out.unionByName(part)
    return out


def edges(r):
    """Requests with special cases, by conversation: retries, edited turns, shortened histories, empty replies, histories replaced by a system message."""
    case, k, m = F.pmod("rollout_id", F.lit(5)), F.col("request_seq"), F.col("messages")
    r = r.withColumn("_cut", F.max(F.when(k == 1, F.size("messages"))).over(Window.partitionBy("rollout_id")))
    message = lambda role, content: F.struct(role.alias("role"), content.alias("content"))
    edited = F.transform(m, lambda x, i: message(x["role"], F.when(i == 0, F.concat_ws(" ", x["content"], k.cast("string"))).otherwise(x["content"])))
    shorter = F.slice(m, F.lit(2), F.greatest(F.size(m) - 1, F.lit(0)))
    muted = F.transform(m, lambda x: message(x["role"], F.when(x["role"] == "assistant", "").otherwise(x["content"])))
    replaced = F.concat(F.array(message(F.lit("system"), F.lit("s"))), F.slice(m, F.greatest(F.col("_cut"), F.lit(1)), F.size(m)))
    changed = F.when(case == 3, muted).when(k == 0, m).when(case == 1, edited).when(case == 2, shorter).when(case == 4, replaced).otherwise(m)
    r = r.withColumn("messages", changed).withColumn("reply", F.when(case == 3, "").otherwise(F.col("reply"))).drop("_cut")
    sent = r.withColumn("_i", F.explode(F.when(case == 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))))
    return sent.withColumn("request_seq", F.when(case == 0, 2 * k + F.col("_i")).otherwise(k)).drop("_i")


@query("segment_edge", f"""WITH {REQ}, li AS (SELECT rollout_id, request_seq AS k, rollout_id % 5 AS c, any_value(reply) AS reply, coalesce(list(msg.role || chr(31) || msg.content ORDER BY msg.turn) FILTER (WHERE msg.turn IS NOT NULL), []::VARCHAR[]) AS ms
  FROM req LEFT JOIN msg USING (rollout_id, request_seq) GROUP BY 1, 2),
ct AS (SELECT *, max(CASE WHEN k = 1 THEN len(ms) END) OVER (PARTITION BY rollout_id) AS cut FROM li),
ed AS (SELECT rollout_id, CASE WHEN c = 0 THEN 2 * k + i ELSE k END AS request_seq, CASE WHEN c = 3 THEN '' ELSE reply END AS reply, CASE
  WHEN c = 3 THEN list_transform(ms, lambda x: CASE WHEN starts_with(x, 'assistant' || chr(31)) THEN 'assistant' || chr(31) ELSE x END) WHEN k = 0 THEN ms
  WHEN c = 1 THEN list_concat([ms[1] || ' ' || k], ms[2:]) WHEN c = 2 THEN ms[2:] WHEN c = 4 THEN list_concat(['system' || chr(31) || 's'], ms[cut:]) ELSE ms END AS ms
  FROM ct, range(2) t(i) WHERE c = 0 OR i = 0),
se AS (SELECT *, row_number() OVER w AS nth, list_append(lag(ms) OVER w, 'assistant' || chr(31) || lag(reply) OVER w) AS seen FROM ed WINDOW w AS (PARTITION BY rollout_id ORDER BY request_seq))
SELECT rollout_id, request_seq, (sum(CASE WHEN nth = 1 OR ms[1:len(seen)] = seen THEN 0 ELSE 1 END) OVER (PARTITION BY rollout_id ORDER BY request_seq))::INTEGER AS segment_seq FROM se""")
def segment_edge(s, d):
    return capture.segment(edges(requests(s, d))).select("rollout_id", "request_seq", F.col("segment_seq").cast("int").alias("segment_seq"))


# ---- worlds ----------------------------------------------------------------------------------

_OVERLAP = """len(list_intersect(list_distinct(regexp_extract_all(lower({a}), '[^\\t\\n\\x0B\\f\\r ]+')), list_distinct(regexp_extract_all(lower({l}), '[^\\t\\n\\x0B\\f\\r ]+'))))
 / len(list_distinct(regexp_extract_all(lower({l}), '[^\\t\\n\\x0B\\f\\r ]+')))"""
_PAIRS = """pr AS (SELECT u.conv_id AS rollout_id, row_number() OVER (PARTITION BY u.conv_id ORDER BY u.turn) - 1 AS t, u.text AS label, a.text AS action, count(*) OVER (PARTITION BY u.conv_id) AS n
 FROM conversations u JOIN conversations a ON a.conv_id = u.conv_id AND a.turn = u.turn + 1 AND u.role = 'user' AND a.role = 'assistant')"""


def _tool(s, d):
    return worlds.tool_states(worlds.turns(s, d)), worlds.ToolDialogue(worlds.overlap, 4)


@query("world_step", f"WITH {_PAIRS} SELECT rollout_id AS state_id, round({_OVERLAP.format(a='action', l='label')}, 6) AS reward, {_OVERLAP.format(a='action', l='label')} >= 0.2 OR n <= 1 AS terminated FROM pr WHERE t = 0")
def world_step(s, d):
    states, world = _tool(s, d)
    return worlds.step(worlds.scripted(states), world).select("state_id", r6("reward"), "terminated")


@query("world_single", f"WITH {_PAIRS} SELECT rollout_id AS state_id, CASE WHEN {_OVERLAP.format(a='action', l='label')} >= 0.2 THEN 1.0 ELSE 0.0 END::DOUBLE AS reward, true AS terminated FROM pr WHERE t = n - 1")
def world_single(s, d):
    states = worlds.tool_states(worlds.turns(s, d)).withColumn("action", F.element_at("script", -1)["assistant"]).withColumn("label", F.element_at("script", -1)["user"])
    return worlds.step(states, worlds.SingleAnswer(lambda a, b: (worlds.overlap(a, b) >= 0.2).cast("double"))).select("state_id", "reward", "terminated")


@query("world_multi", f"""WITH {_PAIRS}, g AS (SELECT rollout_id, t, n, {_OVERLAP.format(a='action', l='label')} AS reward FROM pr), e AS (SELECT *, reward >= 0.2 OR t + 1 >= least(n, 4) AS done FROM g)
SELECT rollout_id AS state_id, t, round(reward, 6) AS reward FROM e QUALIFY done AND row_number() OVER (PARTITION BY rollout_id, done ORDER BY t) = 1""")
def world_multi(s, d):
    states, world = _tool(s, d)
    return worlds.run_world(states, world, worlds.scripted, 4).select("state_id", "t", r6("reward"))


@query("world_visual", "SELECT v.vec_id AS state_id, page_id, len(html) AS payload_chars FROM embeddings v JOIN pages ON page_id = vec_id % (SELECT count(*) FROM pages)")
def world_visual(s, d):
    """Each state points at a screenshot stand-in; the payload is joined by reference when it is looked at."""
    n = workloads.table(s, d, "pages").agg(F.count("*").alias("_n"))
    states = workloads.table(s, d, "embeddings").select(F.col("vec_id").alias("state_id")).crossJoin(F.broadcast(n)).withColumn("page_id", F.pmod("state_id", "_n")).drop("_n")
    return states.join(workloads.table(s, d, "pages").select("page_id", F.length("html").cast("long").alias("payload_chars")), "page_id").select("state_id", "page_id", "payload_chars")


def _graded(name, fn, sql, action="action"):
    query(name, f"WITH {_PAIRS} SELECT rollout_id, t, round({sql}, 6) AS reward FROM pr")(lambda s, d: _pairs(s, d).select("rollout_id", "t", r6(fn(F.col("action"), F.col("label")), "reward")))


def _pairs(s, d):
    p = worlds.tool_states(worlds.turns(s, d)).select(F.col("state_id").alias("rollout_id"), F.posexplode("script").alias("t", "p"))
    return p.select("rollout_id", F.col("t").cast("long").alias("t"), F.col("p.assistant").alias("action"), F.col("p.user").alias("label"))


_CLEAN = "trim(regexp_replace(lower({}), '[^a-z0-9]+', ' ', 'g'))"
_SET = "list_distinct(list_filter(string_split(" + _CLEAN + ", ' '), lambda w: w <> ''))"
_graded("grade_exact", grading.exact, "CASE WHEN action = label THEN 1.0 ELSE 0.0 END::DOUBLE")
_graded("grade_normalised", grading.normalised, f"CASE WHEN {_CLEAN.format('action')} = {_CLEAN.format('label')} THEN 1.0 ELSE 0.0 END::DOUBLE")
_graded("grade_number", grading.number, "CASE WHEN regexp_extract_all(action, '-?[0-9]+(?:\\.[0-9]+)?')[-1]::DOUBLE = regexp_extract_all(label, '-?[0-9]+(?:\\.[0-9]+)?')[-1]::DOUBLE THEN 1.0 ELSE 0.0 END::DOUBLE")
_graded("grade_f1", grading.token_f1, f"coalesce(2.0 * len(list_intersect({_SET.format('action')}, {_SET.format('label')})) / nullif(len({_SET.format('action')}) + len({_SET.format('label')}), 0), 0)")
query("grade_contains", "SELECT item_id, count(*) AS n_documents FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY 1")(
    lambda s, d: workloads.table(s, d, "documents").join(workloads.table(s, d, "benchmark").select("item_id", F.col("text").alias("label")), grading.contains(F.col("text"), F.col("label")) == 1.0).groupBy("item_id").agg(F.count("*").alias("n_documents"))
)
query("grade_label", "SELECT doc_id, greatest(0, quality - toxic)::DOUBLE AS reward FROM labels")(lambda s, d: workloads.table(s, d, "labels").select("doc_id", grading.label_lookup(F.col("quality"), F.col("toxic")).alias("reward")))
query("grade_udf")(lambda s, d: _pairs(s, d).select("rollout_id", "t", grading.from_python(lambda a, b: float(a[:1].lower() == b[:1].lower()))("action", "label").alias("reward")))


def echo_agent(ctx):
    """Calls the model once a user message, growing its context."""
    messages = []
    for m in ctx.prompt:
        messages.append(m)
        if m["role"] == "user":
            messages.append({"role": "assistant", "content": ctx.chat(messages)})
    return float(len(messages) > 2)


def _prompts(s, d):
    turns = worlds.turns(s, d).filter("role <> 'assistant'")
    return turns.groupBy("rollout_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "content"))).alias("m")).select("rollout_id", F.transform("m", lambda x: F.struct(x["role"].alias("role"), x["content"].alias("content"))).alias("messages"), F.lit("").alias("label"))


query("user_driven")(lambda s, d: _digest(worlds.run_sessions(_prompts(s, d), echo_agent)))


@query("style_parity", "SELECT 0::BIGINT AS rollout_id, 0::BIGINT AS request_seq, ''::VARCHAR AS token_md5 WHERE false")
def style_parity(s, d):
    """Traces of the agent-driven run against the same requests built by the framework: no row may differ."""
    logged = worlds.run_sessions(_prompts(s, d), echo_agent)
    own = logged.select("rollout_id", "request_seq", F.concat("messages", F.array(F.struct(F.lit("assistant").alias("role"), F.col("reply").alias("content")))).alias("all"))
    driven = own.select("rollout_id", "request_seq", F.md5(F.array_join(tokens.render(F.col("all")), " ")).alias("token_md5"))
    turns_out = own.withColumn("k", F.row_number().over(Window.partitionBy("rollout_id").orderBy(F.desc("request_seq")))).filter("k = 1")
    turns_out = turns_out.select("rollout_id", F.posexplode("all").alias("turn", "m")).select("rollout_id", "turn", F.col("m.role").alias("role"), F.col("m.content").alias("content"))
    framed = worlds.requests(turns_out).select("rollout_id", "request_seq", F.md5(F.array_join(tokens.render(F.concat("messages", F.array(F.struct(F.lit("assistant").alias("role"), F.col("reply").alias("content"))))), " ")).alias("token_md5"))
    return driven.exceptAll(framed).unionByName(framed.exceptAll(driven))
