"""Agents and worlds: requests under context policies, step worlds, and sessions that agents drive themselves."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trajkit import workloads
from trajkit.session import materialise


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("rollout_id"), "turn", "role", F.col("text").alias("content"))


def requests(turns_df: DataFrame) -> DataFrame:
    """One request per assistant turn: all earlier turns as messages, that turn as the reply.

    The messages are one sorted array per conversation, sliced per request; no turn is joined with another.
    """
    whole = turns_df.groupBy("rollout_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "content"))).alias("all"))
    at = F.filter(F.transform("all", lambda m, i: F.when(m["role"] == "assistant", i)), lambda i: i.isNotNull())
    r = whole.select("rollout_id", "all", F.posexplode(at).alias("request_seq", "at"))
    messages = F.transform(F.slice("all", F.lit(1), F.col("at")), lambda m: F.struct(m["role"].alias("role"), m["content"].alias("content")))
    return r.select("rollout_id", F.col("request_seq").cast("long").alias("request_seq"), messages.alias("messages"), F.get("all", F.col("at"))["content"].alias("reply"))


def compact(requests_df: DataFrame, policy: str = "keep_all", k: int = 2, w: int = 5) -> DataFrame:
    """An agent's own context policy: keep_all, last_k messages, summary (first w words of the dropped ones as one system message), drop_tool."""
    m = F.col("messages")
    if policy == "keep_all":
        return requests_df
    if policy == "drop_tool":
        return requests_df.withColumn("messages", F.filter(m, lambda x: x["role"] != "tool"))
    tail = F.slice(m, F.greatest(F.size(m) - k + 1, F.lit(1)), F.lit(k))
    if policy == "last_k":
        return requests_df.withColumn("messages", F.when(F.size(m) <= k, m).otherwise(tail))
    if policy == "summary":
        dropped = F.slice(m, F.lit(1), F.greatest(F.size(m) - k, F.lit(0)))
        text = F.array_join(F.transform(dropped, lambda x: F.array_join(F.slice(F.split(x["content"], r"\s+"), 1, w), " ")), " ")
        note = F.struct(F.lit("system").alias("role"), text.alias("content"))
        return requests_df.withColumn("messages", F.when(F.size(m) <= k, m).otherwise(F.concat(F.array(note), tail)))
    raise ValueError(policy)


# ---- worlds that the framework drives --------------------------------------------------------


class World:
    """A transition on a frame of live states (state_id, action, label, t): adds reward, terminated, observation."""

    def transition(self, states: DataFrame) -> DataFrame:
        raise NotImplementedError


class SingleAnswer(World):
    """One answer, graded, and the end."""

    def __init__(self, grader):
        self.grader = grader

    def transition(self, states: DataFrame) -> DataFrame:
        return states.withColumn("reward", self.grader(F.col("action"), F.col("label"))).withColumn("terminated", F.lit(True)).withColumn("observation", F.lit(""))


class ToolDialogue(World):
    """Scripted observations come back after each action; the dialogue ends when the grader is content, the script ends, or max_turns is reached."""

    def __init__(self, grader, max_turns: int, good: float = 0.2):
        self.grader, self.max_turns, self.good = grader, max_turns, good

    def transition(self, states: DataFrame) -> DataFrame:
        reward = self.grader(F.col("action"), F.col("label"))
        done = (reward >= self.good) | (F.col("t") + 1 >= self.max_turns) | (F.col("t") + 1 >= F.size("script"))
        return states.withColumn("reward", reward).withColumn("terminated", done).withColumn("observation", F.coalesce(F.get("script", (F.col("t") + 1).cast("int"))["user"], F.lit("")))


def step(states: DataFrame, world: World) -> DataFrame:
    return world.transition(states)


def run_world(states: DataFrame, world: World, act, max_steps: int) -> DataFrame:
    """Steps all live states together until they end; each step is written to the shared folder, so lineage stays flat.

    States that are still live after ``max_steps`` come with the others, not terminated.
    """
    done, live = None, states
    for _ in range(max_steps):
        out = materialise(step(act(live), world))
        ended = out.filter("terminated")
        done = ended if done is None else done.unionByName(ended)
        live = out.filter("not terminated").withColumn("t", F.col("t") + 1).select(*states.columns)
        if not live.limit(1).count():
            return done
    return done if done is None else done.unionByName(out.filter("not terminated"))


def tool_states(turns_df: DataFrame) -> DataFrame:
    """state_id, t, script of (user, assistant) pairs in order, for scripted dialogues."""
    t = turns_df.filter("role <> 'system'").withColumn("pair", F.floor(F.row_number().over(Window.partitionBy("rollout_id").orderBy("turn")).cast("long") / 2 - 0.5))
    pair = t.groupBy("rollout_id", "pair").agg(F.max(F.when(F.col("role") == "user", F.col("content"))).alias("user"), F.max(F.when(F.col("role") == "assistant", F.col("content"))).alias("assistant"))
    return pair.filter("assistant is not null").groupBy(F.col("rollout_id").alias("state_id")).agg(F.array_sort(F.collect_list(F.struct("pair", "user", "assistant"))).alias("script")).withColumn("t", F.lit(0).cast("long"))


def scripted(live: DataFrame) -> DataFrame:
    """The policy of the fixture: the logged assistant turn is the action, the turn before it the label."""
    now = F.get("script", F.col("t").cast("int"))
    return live.withColumn("action", now["assistant"]).withColumn("label", now["user"])


# ---- agents that drive themselves ------------------------------------------------------------


def run_sessions(prompts: DataFrame, agent, call=None) -> DataFrame:
    """Each prompt (rollout_id, messages, label) is given to ``agent(context)``, which makes its own calls and returns a reward.

    ``context.chat(messages)`` answers through ``call`` (a plain function, here a stand-in for a serving engine) and records the exchange:
    what comes out are captured requests, and the reward once per rollout.
    """
    answer = call or (lambda messages: " ".join(reversed(messages[-1]["content"].split()[:4])))

    def drive(frames):
        import pandas as pd

        class Context:
            def __init__(self, row):
                self.prompt, self.label, self.seen = [dict(m) for m in (x.asDict() if hasattr(x, "asDict") else x for x in row.messages)], row.label, []

            def chat(self, messages):
                reply = answer(messages)
                self.seen.append(([dict(m) for m in messages], reply))
                return reply

        for frame in frames:
            rows = []
            for row in frame.itertuples():
                ctx = Context(row)
                reward = float(agent(ctx))
                rows += [(row.rollout_id, i, m, r, reward) for i, (m, r) in enumerate(ctx.seen)]
            yield pd.DataFrame(rows, columns=["rollout_id", "request_seq", "messages", "reply", "reward"])

    return prompts.mapInPandas(drive, "rollout_id long, request_seq long, messages array<struct<role:string,content:string>>, reply string, reward double")


def overlap(action: Column, label: Column) -> Column:
    """Distinct lower-cased words of the label that the action holds, as a share."""
    words = lambda c: F.array_distinct(F.filter(F.split(F.lower(F.coalesce(c, F.lit(""))), r"[\t\n\x0B\f\r ]+"), lambda w: w != ""))
    return F.coalesce(F.try_divide(F.size(F.array_intersect(words(action), words(label))), F.size(words(label))), F.lit(0.0))
