"""Two wire dialects of chat requests, brought to one canonical request."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trajkit.schemas import MESSAGE

COMPLETIONS, MESSAGES = "completions", "messages"
_IDS = [T.StructField("rollout_id", T.LongType()), T.StructField("request_seq", T.LongType())]
#: System text is a message of the list; the reply is one string.
COMPLETIONS_SCHEMA = T.StructType([*_IDS, T.StructField("messages", T.ArrayType(MESSAGE)), T.StructField("reply", T.StringType()), T.StructField("max_tokens", T.IntegerType())])
#: System text is a field of its own; the reply is a list of typed blocks.
_BLOCK = T.StructType([T.StructField("type", T.StringType()), T.StructField("text", T.StringType())])
MESSAGES_SCHEMA = T.StructType([*_IDS, T.StructField("system", T.StringType()), T.StructField("messages", T.ArrayType(MESSAGE)), T.StructField("content", T.ArrayType(_BLOCK)), T.StructField("max_tokens", T.IntegerType())])


def to_completions(requests: DataFrame) -> DataFrame:
    return requests.select(F.lit(COMPLETIONS).alias("dialect"), F.to_json(F.struct("rollout_id", "request_seq", "messages", "reply", F.lit(1024).alias("max_tokens"))).alias("raw"))


def to_messages(requests: DataFrame) -> DataFrame:
    system = F.array_join(F.transform(F.filter("messages", lambda m: m["role"] == "system"), lambda m: m["content"]), "\n")
    has = F.exists("messages", lambda m: m["role"] == "system")
    rest = F.filter("messages", lambda m: m["role"] != "system")
    block = F.struct(F.lit("text").alias("type"), F.col("reply").alias("text"))
    return requests.select(F.lit(MESSAGES).alias("dialect"), F.to_json(F.struct("rollout_id", "request_seq", F.when(has, system).alias("system"), rest.alias("messages"), F.array(block).alias("content"), F.lit(1024).alias("max_tokens"))).alias("raw"))


def parse_completions(raw: Column) -> Column:
    """Canonical struct: rollout_id, request_seq, messages, reply. Malformed JSON gives nulls."""
    r = F.from_json(raw, COMPLETIONS_SCHEMA)
    return F.struct(r["rollout_id"].alias("rollout_id"), r["request_seq"].alias("request_seq"), r["messages"].alias("messages"), r["reply"].alias("reply"))


def parse_messages(raw: Column) -> Column:
    r = F.from_json(raw, MESSAGES_SCHEMA)
    system = F.struct(F.lit("system").alias("role"), r["system"].alias("content"))
    messages = F.when(r["system"].isNotNull(), F.concat(F.array(system), r["messages"])).otherwise(r["messages"])
    text = F.array_join(F.transform(F.filter(r["content"], lambda b: b["type"] == "text"), lambda b: b["text"]), "")
    return F.struct(r["rollout_id"].alias("rollout_id"), r["request_seq"].alias("request_seq"), messages.alias("messages"), text.alias("reply"))


def normalise(logs: DataFrame) -> DataFrame:
    """Rows (dialect, raw) to canonical requests; no shuffle, and an unknown dialect gives nulls."""
    r = F.when(F.col("dialect") == COMPLETIONS, parse_completions(F.col("raw"))).when(F.col("dialect") == MESSAGES, parse_messages(F.col("raw")))
    return logs.select(r.alias("r")).select("r.*")


def route_url(root: str, dialect: str) -> str:
    """Where a client of the dialect must point: one adds its own version path to the session root, the other expects it there."""
    root = root.rstrip("/")
    return f"{root}/v1" if dialect == COMPLETIONS else root
