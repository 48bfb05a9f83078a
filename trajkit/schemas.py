"""Explicit schemas of the data model; nothing is inferred from data."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

MESSAGE = T.StructType([T.StructField("role", T.StringType()), T.StructField("content", T.StringType())])
PROMPT = T.StructType([T.StructField("prompt_id", T.LongType()), T.StructField("messages", T.ArrayType(MESSAGE)), T.StructField("label", T.StringType())])
ROLLOUT = T.StructType(
    [T.StructField("rollout_id", T.LongType()), T.StructField("group_id", T.LongType()), T.StructField("reward", T.DoubleType()), T.StructField("completed_at", T.TimestampType())]
)
SAMPLING = T.StructType([T.StructField("max_tokens", T.IntegerType()), T.StructField("temperature", T.DoubleType()), T.StructField("top_p", T.DoubleType())])
REQUEST = T.StructType(
    [T.StructField("rollout_id", T.LongType()), T.StructField("request_seq", T.LongType()), T.StructField("messages", T.ArrayType(MESSAGE)), T.StructField("reply", T.StringType())]
)
SPAN = T.StructType([T.StructField("lo", T.IntegerType()), T.StructField("hi", T.IntegerType())])
SEGMENT = T.StructType(
    [
        T.StructField("rollout_id", T.LongType()), T.StructField("segment_seq", T.LongType()), T.StructField("token_ids", T.ArrayType(T.LongType())),
        T.StructField("action_mask", T.ArrayType(T.BooleanType())), T.StructField("action_ranges", T.ArrayType(SPAN)),
        T.StructField("behaviour_logp", T.ArrayType(T.DoubleType())), T.StructField("policy_version", T.ArrayType(T.IntegerType())),
    ]
)
REFERENCE = T.StructType([T.StructField("node", T.IntegerType()), T.StructField("payload_id", T.LongType()), T.StructField("digest", T.StringType())])


def validate(df: DataFrame, schema: T.StructType) -> DataFrame:
    """The frame itself if it has every field of ``schema`` with that type; fails before any job runs otherwise."""
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name}: {have.get(f.name, 'missing')}" for f in schema if have.get(f.name) != f.dataType]
    if wrong:
        raise TypeError("schema mismatch: " + ", ".join(wrong))
    return df
