"""Graders: (action, label) to a reward in [0, 1], as column expressions; a slot for Python graders."""

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from trajkit.registry import register

_clean = lambda c: F.trim(F.regexp_replace(F.lower(F.coalesce(c, F.lit(""))), r"[^a-z0-9]+", " "))


@register("grader", "exact")
def exact(action: Column, label: Column) -> Column:
    return (action == label).cast("double")


@register("grader", "normalised")
def normalised(action: Column, label: Column) -> Column:
    return (_clean(action) == _clean(label)).cast("double")


@register("grader", "number")
def number(action: Column, label: Column) -> Column:
    """Equal last numbers; 0 where either text has none."""
    last = lambda c: F.try_element_at(F.regexp_extract_all(c, F.lit(r"(-?[0-9]+(?:\.[0-9]+)?)"), 1), F.lit(-1)).cast("double")
    return F.coalesce((last(action) == last(label)).cast("double"), F.lit(0.0))


@register("grader", "contains")
def contains(action: Column, label: Column) -> Column:
    return F.contains(action, label).cast("double")


@register("grader", "token_f1")
def token_f1(action: Column, label: Column) -> Column:
    """Harmonic mean of the shares of distinct words that both hold."""
    words = lambda c: F.array_distinct(F.filter(F.split(_clean(c), " "), lambda w: w != ""))
    both, a, b = F.size(F.array_intersect(words(action), words(label))), F.size(words(action)), F.size(words(label))
    return F.coalesce(F.try_divide(2.0 * both, a + b), F.lit(0.0))


@register("grader", "label")
def label_lookup(quality: Column, toxic: Column) -> Column:
    """Quality less toxicity, held in [0, 1]."""
    return F.greatest(F.lit(0), quality - toxic).cast("double")


def from_python(fn):
    """A pandas UDF from a plain function of two strings; Arrow batches, never a call per row across the boundary."""
    @F.pandas_udf("double")
    def grade(action: pd.Series, label: pd.Series) -> pd.Series:
        return pd.Series([float(fn(a, b)) for a, b in zip(action, label)])

    return grade
