"""Global ranks without a global sort in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Rows that a range holds, about; ranges at most.
RANGE_ROWS, RANGES = 250_000, 64


def with_range(df: DataFrame, key: Column, name: str = "_part", rows: int = RANGE_ROWS) -> DataFrame:
    """Adds the number of the range of values that ``key`` lies in; ranges ascend and follow the number of rows.

    One aggregate of at most RANGES numbers reaches the driver. The key is compared as a double, which keeps the order of
    its values or makes them equal, so no value of a lower range exceeds one of a higher range. Nulls are in the first.
    """
    value = key.cast("double")
    n, cuts = df.agg(F.count("*"), F.percentile_approx(value, [i / RANGES for i in range(1, RANGES)], 10 * RANGES)).first()
    wanted = max(8, min(RANGES, -(-n // rows)))
    cuts = sorted(set((cuts or [])[RANGES // wanted - 1 :: max(1, RANGES // wanted)]))
    part = F.lit(0)
    for c in cuts:
        part = part + F.when(value > c, 1).otherwise(0)
    return df.withColumn(name, part)


def global_rank(df: DataFrame, key: Column, ties: list[str], name: str = "rank", descending: bool = False) -> DataFrame:
    """Adds the 1-based rank of each row by (key, ties), nulls first.

    Ranges of ``key`` split the rows; each range is ranked on its own, by the key in its own type, and shifted by the counts
    of the ranges before it. The ranges shape the work, never the ranks. Rows of equal keys share a range.
    """
    df = with_range(df.withColumn("_key", key), -F.col("_key").cast("double") if descending else F.col("_key"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = df.groupBy("_part").count().withColumn("_before", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")  # one row a range
    local = Window.partitionBy("_part").orderBy(F.desc_nulls_first("_key") if descending else F.asc_nulls_first("_key"), *ties)
    return df.join(F.broadcast(counts), "_part").withColumn(name, F.row_number().over(local) + F.col("_before")).drop("_part", "_before", "_key")
