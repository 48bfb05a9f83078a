"""Stable token ids, and rendering of messages to one token stream."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Role markers of the ``marked`` template.
OPEN, CLOSE = "<|{}|>", "<|end|>"
SPACE = r"[\t\n\x0B\f\r ]+"


def token_id(piece: Column) -> Column:
    """The first 8 hex digits of md5 as a number: the same in any engine."""
    return F.conv(F.substring(F.md5(piece), 1, 8), 16, 10).cast("long")


def split(text: Column, scheme: str = "whitespace") -> Column:
    words = F.filter(F.split(F.coalesce(text, F.lit("")), SPACE), lambda w: w != "")
    if scheme == "whitespace":
        return words
    if scheme == "char_bigram":
        return F.flatten(F.transform(words, lambda w: F.transform(F.sequence(F.lit(1), F.length(w), F.lit(2)), lambda i: F.substring(w, i, F.lit(2)))))
    if scheme == "greedy_vocab":
        # Longest match from a fixed set of endings: a word gives its stem and, where there is one, its ending.
        ends = r"^(.+?)(ing|tion|ment|keit|heit|lich|eaux|mente|ción|ed|er|en)$"
        cut = lambda w: F.when(w.rlike(ends), F.array(F.regexp_extract(w, ends, 1), F.regexp_extract(w, ends, 2))).otherwise(F.array(w))
        return F.flatten(F.transform(words, cut))
    raise ValueError(scheme)


def encode(text: Column, scheme: str = "whitespace") -> Column:
    """Array of (id, piece)."""
    return F.transform(split(text, scheme), lambda p: F.struct(token_id(p).alias("id"), p.alias("piece")))


def render(messages: Column, template: str = "marked") -> Column:
    """Pieces of a whole conversation. ``plain``: words only; ``marked``: role markers around each message;
    ``history_dropping``: marked, but of earlier assistant turns only the first word is kept once a later user turn exists."""
    if template == "plain":
        return F.flatten(F.transform(messages, lambda m: split(m["content"])))
    around = lambda m, words: F.concat(F.array(F.format_string("<|%s|>", m["role"])), words, F.array(F.lit(CLOSE)))
    if template == "marked":
        return F.flatten(F.transform(messages, lambda m: around(m, split(m["content"]))))
    if template == "history_dropping":
        n = F.size(messages)
        old = lambda m, i: (m["role"] == "assistant") & (i < n - 1)
        return F.flatten(F.transform(messages, lambda m, i: around(m, F.when(old(m, i), F.slice(split(m["content"]), 1, 1)).otherwise(split(m["content"])))))
    raise ValueError(template)


def render_twice_drift(requests: DataFrame) -> DataFrame:
    """Extra marker tokens if a framework-rendered text were rendered again as the content of one user message."""
    once = F.size(render(F.col("messages")))
    twice = F.size(render(F.array(F.struct(F.lit("user").alias("role"), F.array_join(render(F.col("messages")), " ").alias("content")))))
    return requests.select("rollout_id", "request_seq", once.alias("once"), twice.alias("twice"), (twice - once).alias("extra"))
