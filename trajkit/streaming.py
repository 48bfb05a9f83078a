"""Completion streams: group assembly with state, lateness, window rates, and idempotent training sinks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructField, StructType

GROUP_OUT = "group_id long, n_rollouts long, finished long, state string"
HELD = np.dtype([("group_id", "<i8"), ("n", "<i8"), ("last", "<i8"), ("until", "<i8"), ("closed", "?")])  # until: milliseconds, the rest of time microseconds


def source(spark, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A file stream; files_per_trigger is the queue depth that bounds buffered work."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def lifecycle(events: DataFrame, samples: int = 4) -> DataFrame:
    """Event rows as rollouts with an event-time column; ntz times are cast first, a watermark needs it."""
    return events.select(F.col("event_id").alias("rollout_id"), F.floor(F.col("event_id") / samples).alias("group_id"), F.col("ts").cast("timestamp").alias("at"), F.col("value"), (F.col("event_type") == "error").alias("failed"))


def group_completion(stream: DataFrame, n: int, timeout: str = "2 days", span: int = 1024) -> DataFrame:
    """Emits each group once, when its n-th successful rollout arrives; a failed member closes it as failed.

    State is open groups only: a group that completes or fails leaves a tombstone until its timeout, so late members emit nothing.
    ``span`` neighbouring group ids share one state and one call, which counts them together in arrays; each has its own timeout.
    """
    millis = int(pd.Timedelta(timeout).total_seconds() * 1000)

    def update(key, frames, state: GroupState):
        mark, parts = state.getCurrentWatermarkMs(), []
        held = np.frombuffer(state.get[0], HELD) if state.exists else np.empty(0, HELD)
        for f in frames if not state.hasTimedOut else ():
            failed = f["failed"].fillna(False).astype(bool)
            ids = f["group_id"].astype("int64") if key[0] is not None else 0  # rows without an id are one group
            f = pd.DataFrame({"group_id": ids, "n": ~failed, "failed": failed, "last": f["us"].fillna(0).astype("int64")})
            parts.append(f.groupby("group_id").agg({"n": "sum", "failed": "max", "last": "max"}))
        now = pd.concat(parts).groupby(level=0).agg({"n": "sum", "failed": "max", "last": "max"}) if parts else pd.DataFrame({"n": [], "failed": [], "last": []}, dtype="int64")
        ids = now.index.to_numpy(dtype="int64")
        every = np.union1d(held["group_id"], ids)
        open_ = np.zeros(len(every), HELD)
        open_["group_id"] = every
        open_[np.searchsorted(every, held["group_id"])] = held
        k = np.searchsorted(every, ids)
        open_["n"][k] += now["n"].to_numpy(dtype="int64")
        open_["last"][k] = np.maximum(open_["last"][k], now["last"].to_numpy(dtype="int64"))
        open_["until"][k] = np.maximum(open_["last"][k] // 1000, mark) + millis
        failed = now["failed"].to_numpy(dtype=bool)
        emit = ~open_["closed"][k] & (failed | (open_["n"][k] >= n))
        open_["closed"][k] |= emit
        out, kept = open_[k][emit], open_[open_["until"] >= mark]
        if len(kept):
            state.update((kept.tobytes(),))
            state.setTimeoutTimestamp(int(kept["until"].min()))
        else:
            state.remove()
        if len(out):
            name = out["group_id"] if key[0] is not None else [None] * len(out)
            yield pd.DataFrame({"group_id": name, "n_rollouts": out["n"], "finished": out["last"], "state": np.where(failed[emit], "failed", "complete")})

    timed = stream.withWatermark("at", timeout).select(F.floor(F.col("group_id") / span).alias("_span"), "group_id", "at", F.unix_micros("at").alias("us"), "failed")
    return timed.groupBy("_span").applyInPandasWithState(update, GROUP_OUT, "held binary", "append", GroupStateTimeout.EventTimeTimeout)


def with_lateness(stream: DataFrame, bound: str = "1 day") -> DataFrame:
    """The lateness bound is the staleness bound: rows older than the watermark no longer change results."""
    return stream.withWatermark("at", bound)


def late_rows(batch: DataFrame, newest: Column, bound_us: int) -> DataFrame:
    """Side output of a batch: rows behind the bound, kept for an audit rather than dropped in silence."""
    return batch.filter(F.unix_micros("at") < newest - bound_us)


def rates(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str | None = None, gap: str = "30 minutes", by: tuple[str, ...] = ()) -> DataFrame:
    """start, n, total per window; works on batches and streams alike. kind: tumbling, sliding, session."""
    w = F.session_window("at", gap) if kind == "session" else F.window("at", size, slide) if kind == "sliding" else F.window("at", size)
    out = events.groupBy(w.alias("w"), *by).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return out.select(F.unix_micros("w.start").alias("start_us"), *by, "n", "total")


def latency_join(dispatched: DataFrame, completed: DataFrame, within: str = "1 day") -> DataFrame:
    """Dispatch to completion of the same rollout within a bound; on streams both sides carry watermarks, so state is bounded too."""
    on = (F.col("d.rollout_id") == F.col("c.rollout_id")) & (F.col("c.at") >= F.col("d.at")) & (F.col("c.at") <= F.col("d.at") + F.expr(f"interval {within}"))
    return dispatched.alias("d").join(completed.alias("c"), on).select(F.col("d.rollout_id").alias("rollout_id"), (F.unix_micros("c.at") - F.unix_micros("d.at")).alias("latency_us"))


def train_sink(step, path: str):
    """A foreachBatch function that runs ``step(batch)`` and publishes under the batch's id once: a replayed batch finds its marker and skips."""

    def sink(batch: DataFrame, batch_id: int) -> None:
        from trajkit.policy import publish, published

        if batch_id in published(batch.sparkSession, path):
            return
        publish(step(batch), batch_id, path)

    return sink


def drain(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now into files under ``folder``, which executors share, and returns them as a table: no row reaches the driver."""
    q = stream.writeStream.format("parquet").option("checkpointLocation", f"{folder}/checkpoint").outputMode(mode).trigger(availableNow=True).start(f"{folder}/rows")
    q.awaitTermination()
    plain = StructType([StructField(f.name, f.dataType) for f in stream.schema])  # without the watermark's mark
    return stream.sparkSession.read.schema(plain).parquet(f"{folder}/rows")
