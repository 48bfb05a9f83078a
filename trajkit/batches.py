"""Microbatches of segments; they group partial sums and never change a loss."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def microbatch(items: DataFrame, how: str = "fixed", size: int = 1, budget: int = 0, rank: str = "rank_id", order: str = "rollout_id", length: str = "length") -> DataFrame:
    """Adds microbatch_id within each rank: a fixed number of items, or cumulated lengths cut at a token budget."""
    w = Window.partitionBy(rank).orderBy(order)
    if how == "fixed":
        return items.withColumn("microbatch_id", F.floor((F.row_number().over(w) - 1) / size))
    if how == "budget":
        before = F.coalesce(F.sum(length).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        return items.withColumn("microbatch_id", F.floor(before / budget))
    if how == "next_fit":

        def fit(pdf):
            pdf, used, number, ids = pdf.sort_values(order), 0, 0, []
            for n in pdf[length]:
                if used and used + n > budget:
                    number, used = number + 1, 0
                used += n
                ids.append(number)
            return pdf.assign(microbatch_id=ids)

        return items.groupBy(rank).applyInPandas(fit, f"{', '.join(f'`{c}` {t}' for c, t in items.dtypes)}, microbatch_id long")
    raise ValueError(how)


def pad_batch(segments: DataFrame, batch: str = "microbatch_id", tokens: str = "token_ids", pad: int = 0) -> DataFrame:
    """Right-pads each batch to its longest segment and adds the attention mask."""
    longest = F.max(F.size(tokens)).over(Window.partitionBy(batch))
    out = segments.withColumn("padded_length", longest)
    n = F.size(tokens)
    return out.withColumn("padded", F.concat(F.col(tokens), F.array_repeat(F.lit(pad).cast("long"), F.col("padded_length") - n))).withColumn(
        "attention", F.transform(F.sequence(F.lit(1), F.col("padded_length")), lambda i: i <= n)
    )
