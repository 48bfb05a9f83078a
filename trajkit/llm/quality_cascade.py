r"""Quality rules as a short-circuit cascade, in DataFrame functions only.

A sample estimates each rule's cost (timed) and the share of documents that it rejects; the rules then
run in the order of rejection per cost, in one CASE chain that stops at the first rule that
rejects. The order changes the work, never the verdict.

Counts that the contract asks for are computed once per text: words by one split, repeated three-word windows from
window hashes, whose places are sorted only where a hash repeats, repeated lines from the text's lines. What no count needs
is computed behind the order.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trajkit.llm.common import WORD_PATTERN, materialise, release

#: The base rules' thresholds.
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
#: Ids of the sample that orders the cascade, the first by hash; times that a cost is measured.
SAMPLE_ROWS, TIMES = 2000, 1
SPACE = "[\\x20\\x09-\\x0D]+"
#: Fixed value: the symbols that are counted.
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """``rejects``: a boolean Column over the counted columns and ``text``; ``cost``: the features whose cost it pays."""

    name: str
    rejects: Column
    features: tuple[str, ...]


def rules() -> list[Rule]:
    """The library's rules over columns n_words, word_chars, n_symbols, n_dup_lines, n_lines, n_repeat_words, text."""
    n = F.col("n_words")
    return [
        Rule("too_short", n < MIN_WORDS, ("n_words",)),
        Rule("repeated_windows", 100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * n, ("n_words", "n_repeat_words")),
        Rule("word_length", (F.col("word_chars") < 2 * n) | (F.col("word_chars") > 20 * n), ("n_words", "word_chars")),
        Rule("symbols", F.col("n_symbols") > n / 2, ("n_words", "n_symbols")),
        Rule("repeated_lines", 2 * F.col("n_dup_lines") > F.col("n_lines"), ("n_dup_lines",)),
        Rule("shouting", F.regexp_count("text", F.lit("[A-Z]")) > F.regexp_count("text", F.lit("[a-z]")), ("letters",)),
    ]


def word_array(text: Column) -> Column:
    """Words in order; splitting can leave an empty string at either end only."""
    return F.filter(F.split(text, SPACE), lambda w: w != "")


def line_array(text: Column) -> Column:
    """The lines that hold a word."""
    return F.filter(F.split(text, "\n"), lambda line: F.btrim(line, F.lit(" \t\x0b\x0c\r")) != "")


def n_symbols(text: Column) -> Column:
    return F.length(text) - F.length(F.translate(text, SYMBOLS, ""))


def bound(value: Column, use) -> Column:
    """``use`` of ``value`` with the value computed once: lambdas re-evaluate outer expressions for each element, but not their own arguments."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def repeat_words(words: Column) -> Column:
    """Words inside 3-word windows that occur at least twice in the text.

    Window hashes are plain longs. Only where one repeats they are sorted with their places; the places of windows with an
    equal neighbour are sorted, and each covers three words less what the next one covers.
    """

    def windows(h: Column) -> Column:
        return F.transform(F.slice(h, 1, F.size(h) - 2), lambda x, i: F.xxhash64(x, F.get(h, i + 1), F.get(h, i + 2)))

    def count(hashes: Column) -> Column:
        placed = lambda: F.sort_array(F.transform(hashes, lambda x, i: F.struct(x.alias("h"), i.alias("p"))))
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0)).otherwise(bound(placed(), covered))

    word_hashes = F.transform(words, lambda w: F.xxhash64(w))
    return bound(word_hashes, lambda h: F.when(F.size(h) < 4, F.lit(0)).otherwise(bound(windows(h), count)))


def covered(ordered: Column) -> Column:
    """Words covered by the windows that have an equal neighbour in ``ordered`` (structs of hash and place)."""
    equal = F.filter(ordered, lambda s, k: (s["h"] == F.coalesce(F.get(ordered, k - 1)["h"], F.bitwise_not(s["h"]))) | (s["h"] == F.coalesce(F.get(ordered, k + 1)["h"], F.bitwise_not(s["h"]))))
    places = F.sort_array(F.transform(equal, lambda s: s["p"]))
    return F.aggregate(places, F.struct(F.lit(0).alias("sum"), F.lit(-3).alias("last")), lambda a, p: F.struct((a["sum"] + F.least(F.lit(3), p - a["last"])).alias("sum"), p.alias("last")), lambda a: a["sum"])


def counted(docs: DataFrame) -> DataFrame:
    """doc_id, text and the counts; each expensive array is built in a projection of its own, so that it is built once."""
    df = docs.select(F.col("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    both = bound(line_array(F.col("text")), lambda x: F.struct(F.size(x).alias("all"), F.size(F.array_distinct(x)).alias("distinct")))
    df = df.withColumn("_lines", both).withColumn("_words", word_array(F.col("text")))
    return df.select(
        "doc_id", "text", F.size("_words").cast("long").alias("n_words"), n_symbols(F.col("text")).cast("long").alias("n_symbols"),
        F.length(F.array_join("_words", "")).cast("long").alias("word_chars"),
        F.col("_lines.all").cast("long").alias("n_lines"), (F.col("_lines.all") - F.col("_lines.distinct")).cast("long").alias("n_dup_lines"),
        repeat_words(F.col("_words")).cast("long").alias("n_repeat_words"),
    )


def features(text: Column) -> dict[str, Column]:
    """Each feature from the text alone, for timing and for filters that compute none before its turn."""
    words = word_array(text)
    return {
        "n_words": F.size(words), "n_symbols": n_symbols(text), "word_chars": F.length(F.array_join(words, "")), "n_repeat_words": repeat_words(words),
        "n_dup_lines": bound(line_array(text), lambda x: F.struct(F.size(x).alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).alias("n_dup_lines"))),
        "letters": F.struct(F.regexp_count(text, F.lit("[A-Z]")).alias("upper"), F.regexp_count(text, F.lit("[a-z]")).alias("lower")),
    }


def feature_costs(sample: DataFrame) -> dict[str, float]:
    """Seconds that each feature takes on the sample, beyond reading it; the least of a few runs."""

    def seconds(column: Column) -> float:
        found = []
        for _ in range(TIMES):
            start = time.perf_counter()
            sample.select(F.hash(column).alias("h")).agg(F.bit_xor("h")).collect()
            found.append(time.perf_counter() - start)
        return min(found)

    reading = seconds(F.col("text"))
    return {name: max(1e-3, seconds(column) - reading) for name, column in features(F.col("text")).items()}


def cascade_order(sample: DataFrame, found: list[Rule] | None = None, costs: dict[str, float] | None = None) -> list[Rule]:
    """The rules by rejection per cost on the sample: one small aggregate and one row a timing reach the driver.

    Greedy: after a rule is placed, the others are judged on what it lets pass, and features already paid for cost nothing.
    With an empty sample the given order stays. ``costs``: seconds by feature, measured if not given.
    """
    found, costs = found or rules(), costs or feature_costs(sample)
    rejected = counted(sample).select(*[F.coalesce(r.rejects, F.lit(False)).cast("int").alias(r.name) for r in found])
    seen = [tuple(row) for row in rejected.groupBy(*[r.name for r in found]).count().collect()]  # at most 2**rules rows
    order, left, paid = [], list(found), set()
    while left:
        alive = [row for row in seen if not any(row[found.index(r)] for r in order)]
        total = sum(row[-1] for row in alive) or 1

        def value(r: Rule) -> float:
            cost = sum(costs[f] for f in r.features if f not in paid) or 1e-3
            return sum(row[-1] for row in alive if row[found.index(r)]) / total / cost

        best = max(left, key=lambda r: (value(r), -found.index(r)))
        order.append(best)
        left.remove(best)
        paid.update(best.features)
    return order


def sample_of(docs: DataFrame) -> DataFrame:
    """doc_id, text of the SAMPLE_ROWS ids that come first by hash, written once; the same on every run. Rows that repeat an id count once."""
    key = F.xxhash64("doc_id")
    last = docs.select(key.alias("k")).distinct().orderBy("k").limit(SAMPLE_ROWS).agg(F.max("k")).first()[0]
    rows = docs.filter(key <= F.lit(last)).groupBy("doc_id").agg(F.min("text").alias("text"))
    return materialise(rows.select("doc_id", F.coalesce("text", F.lit("")).alias("text")))


def ordered_rules(docs: DataFrame) -> list[Rule]:
    sample = sample_of(docs)
    order = cascade_order(sample)
    release(sample)
    return order


def verdict(order: list[Rule]) -> Column:
    """Name of the first rule that rejects, or null; later rules aren't evaluated."""
    out = F.when(order[0].rejects, F.lit(order[0].name))
    for r in order[1:]:
        out = out.when(r.rejects, F.lit(r.name))
    return out


def quality_rules(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, failed_rule.

    Null text: an empty document, which the base rules reject. Repeated rows are judged alike. A null doc_id is kept
    as null. Empty table: no rows. Other columns are ignored.
    """
    order = ordered_rules(docs)
    df = counted(docs)
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    failed = verdict(order)
    return df.select(
        F.col("doc_id").cast("long").alias("doc_id"), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base.alias("base_failed"), (~base & failed.isNull()).alias("kept"), failed.alias("failed_rule"),
    )


def filter_quality(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that pass, with their own columns; cheap rules come first and costly counts are skipped once one rejects."""
    order = ordered_rules(docs)
    f = features(F.coalesce(F.col("text"), F.lit("")))
    n = f["n_words"]
    direct = {
        "too_short": n < MIN_WORDS, "repeated_windows": 100 * f["n_repeat_words"] > MAX_REPEAT_PERCENT * n,
        "word_length": (f["word_chars"] < 2 * n) | (f["word_chars"] > 20 * n), "symbols": f["n_symbols"] > n / 2,
        "repeated_lines": bound(f["n_dup_lines"], lambda x: 2 * x["n_dup_lines"] > x["n_lines"]), "shouting": f["letters"]["upper"] > f["letters"]["lower"],
    }
    out = F.when(direct[order[0].name], F.lit(False))
    for r in order[1:]:
        out = out.when(direct[r.name], F.lit(False))
    return docs.filter(out.otherwise(F.lit(True)))
