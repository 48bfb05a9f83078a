"""Asynchronous scheduling: which groups make a batch, how long a step takes, which policy version a token saw."""

from __future__ import annotations

import heapq
from collections import Counter, deque

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trajkit.joins import as_of_few
from trajkit.ranking import global_rank

DAY = 86_400_000_000


def group_times(rollouts: DataFrame, n: int) -> DataFrame:
    """group_id, dispatched (first), finished (last) of groups whose n rollouts all succeeded; failed rollouts never complete their group."""
    g = rollouts.groupBy("group_id").agg(F.min("dispatched").alias("dispatched"), F.max("finished").alias("finished"), F.count("*").alias("_n"), F.bool_or("failed").alias("_bad"))
    return g.filter((F.col("_n") >= n) & ~F.col("_bad")).drop("_n", "_bad")


def _batches(groups: DataFrame, order: str, size: int) -> DataFrame:
    return global_rank(groups, F.col(order), ["group_id"]).withColumn("batch", F.floor((F.col("rank") - 1) / size))


def streaming(groups: DataFrame, size: int) -> DataFrame:
    """Batches of completed groups in the order of completion; the rest stay in flight."""
    return _batches(groups, "finished", size)


def barrier(groups: DataFrame, size: int) -> DataFrame:
    """Rounds in the order of dispatch; a round waits for its slowest group."""
    return _batches(groups, "dispatched", size)


def rounds(batched: DataFrame) -> DataFrame:
    """Per batch: start (first dispatch), ready (last completion)."""
    return batched.groupBy("batch").agg(F.min("dispatched").alias("start"), F.max("finished").alias("ready"), F.count("*").alias("n_groups"))


def one_step(batched: DataFrame, train_us: int) -> DataFrame:
    """Step times when round k trains on round k-1 while its own rollouts are generated: the longer of the two."""
    r = rounds(batched)
    gen = F.col("ready") - F.col("start")
    return r.withColumn("generation", gen).withColumn("step", F.greatest(gen, F.when(F.col("batch") > 0, F.lit(train_us)).otherwise(0)))


def pool_run(jobs: list[tuple[int, float]], workers: int, batch: int, queue: int, train_us: float, mode: str) -> dict:
    """One pool by events in time: ``jobs`` are (group, microseconds) in the order of dispatch, rollouts of a group together.

    streaming: the trainer takes the ``batch`` groups that were complete first; no group starts while ``queue`` of them wait.
    barrier: a round of ``batch`` groups starts when the round before is complete and trained on. one_step: when the
    round before is complete and the one before that trained on. A last batch that isn't full is not trained on.
    """
    left = Counter(g for g, _ in jobs)
    place = {g: k for k, g in enumerate(dict.fromkeys(g for g, _ in jobs))}
    in_round = Counter(k // batch for k in place.values())
    room = max(queue, batch)
    events, idle, at, busy, now = [], workers, 0, 0.0, 0.0
    waiting, rounds_ready, finished_rounds, trained, training, steps, widest = 0, deque(), 0, 0, False, [], 0

    def may_start(g: int) -> bool:
        if mode == "streaming":
            return waiting < room or place[g] in begun
        r = place[g] // batch
        return finished_rounds >= r and trained >= r - (mode == "one_step")

    begun: set[int] = set()
    while True:
        while at < len(jobs) and idle and may_start(jobs[at][0]):
            g, length = jobs[at]
            begun.add(place[g])
            heapq.heappush(events, (now + length, 1, g))
            idle, at, busy = idle - 1, at + 1, busy + length
        if not training and (waiting >= batch if mode == "streaming" else rounds_ready):
            if mode == "streaming":
                waiting -= batch
            else:
                rounds_ready.popleft()
            training = True
            heapq.heappush(events, (now + train_us, 0, -1))
            continue
        if not events:
            return {"steps": steps, "span": now, "busy": busy, "widest": widest}
        now, rollout, g = heapq.heappop(events)
        if not rollout:
            training, trained = False, trained + 1
            steps.append(now)
            continue
        idle += 1
        left[g] -= 1
        if left[g]:
            continue
        if mode == "streaming":
            waiting += 1
            widest = max(widest, waiting)
        else:
            r = place[g] // batch
            in_round[r] -= 1
            if not in_round[r]:
                finished_rounds += 1
                if place[g] // batch < len(place) // batch:
                    rounds_ready.append(r)


def simulate(rollouts: DataFrame, configs: list[dict], n: int = 4) -> DataFrame:
    """A pool of W workers with list scheduling, one row per config: makespan, mean step, utilisation, largest queue of finished groups.

    A config (name, workers, batch, queue, train_us, mode) is simulated by one task, configs run side by side; only light
    rows (group, duration) reach Python. See ``pool_run`` for the modes. Groups of at least ``n`` successful rollouts take part.
    """
    light = rollouts.filter("not failed").select("rollout_id", "group_id", "latency")
    spark = rollouts.sparkSession
    grid = spark.createDataFrame([(c["name"], c["workers"], c["batch"], c["queue"], c["train_us"], c["mode"]) for c in configs], "name string, workers int, batch int, queue int, train_us long, mode string")
    rows = light.crossJoin(F.broadcast(grid))  # rows times the few configs of a grid

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        c = pdf.iloc[0]
        jobs = pdf.sort_values(["group_id", "rollout_id"])
        jobs = jobs[jobs.groupby("group_id")["rollout_id"].transform("size") >= n]
        out = pool_run([(int(g), float(x) * 60e6) for g, x in zip(jobs["group_id"], jobs["latency"])], int(c["workers"]), int(c["batch"]), int(c["queue"]), float(c["train_us"]), c["mode"])
        gaps, span = [b - a for a, b in zip([0.0, *out["steps"]], out["steps"])] or [0.0], out["span"]
        return pd.DataFrame([{"name": c["name"], "mode": c["mode"], "n_steps": len(out["steps"]), "makespan_s": span / 1e6, "step_s": sum(gaps) / len(gaps) / 1e6, "utilisation": out["busy"] / (span * c["workers"]) if span else 0.0, "widest_queue": out["widest"]}])

    return rows.groupBy("name").applyInPandas(run, "name string, mode string, n_steps long, makespan_s double, step_s double, utilisation double, widest_queue long")


def refits(rollouts: DataFrame, every_us: int = DAY) -> DataFrame:
    """version, refit_at: one refit at each multiple of ``every_us`` from the first dispatch's on."""
    ends = rollouts.agg(F.floor(F.min("dispatched") / every_us).alias("a"), F.floor(F.max("finished") / every_us).alias("z"))
    return ends.select(F.explode(F.sequence("a", "z")).alias("k"), "a").select((F.col("k") - F.col("a")).alias("version"), (F.col("k") * every_us).alias("refit_at"))


def staleness(batched: DataFrame, refit_table: DataFrame) -> DataFrame:
    """Per batch: versions between a group's dispatch and its batch's consumption: min, mean, max."""
    ready = batched.withColumn("consumed", F.max("finished").over(Window.partitionBy("batch")))
    a = as_of_few(ready, refit_table.withColumnRenamed("version", "sampled_version"), "dispatched", "refit_at", ["sampled_version"])
    b = as_of_few(a, refit_table.withColumnRenamed("version", "used_version"), "consumed", "refit_at", ["used_version"])
    gap = F.col("used_version") - F.col("sampled_version")
    return b.groupBy("batch").agg(F.min(gap).alias("least"), F.avg(gap).alias("mean"), F.max(gap).alias("most"))


def token_times(rollouts: DataFrame, tokens: Column, seconds_per_token: float) -> DataFrame:
    """rollout_id, pos, at: when each token of a rollout was sampled."""
    r = rollouts.filter(tokens > 0).select("rollout_id", "dispatched", tokens.cast("long").alias("_n"))
    return r.select("rollout_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_n") - 1)).alias("pos"), "dispatched").withColumn("at", F.col("dispatched") + F.col("pos") * int(seconds_per_token * 1e6)).drop("dispatched")


def partial(times: DataFrame, refit_table: DataFrame) -> DataFrame:
    """version of each token: generation pauses at a refit and resumes with its prefix kept, so later tokens see a newer version."""
    return as_of_few(times, refit_table, "at", "refit_at", ["version"])


def restart_waste(versioned: DataFrame) -> DataFrame:
    """Tokens that aborting and restarting at a refit would throw away: those sampled under any but the rollout's last version."""
    last = F.max("version").over(Window.partitionBy("rollout_id"))
    w = versioned.withColumn("_last", last)
    return w.groupBy("rollout_id").agg(F.count("*").alias("n_tokens"), F.sum((F.col("version") < F.col("_last")).cast("long")).alias("wasted"), F.countDistinct("version").alias("n_versions"))


def inflight(rollouts: DataFrame, buckets_us: int = DAY) -> DataFrame:
    """Per time bucket: rollouts in flight at its end, dispatched and finished in it; +1/-1 events, summed per bucket before the running sum."""
    e = rollouts.select(F.col("dispatched").alias("at"), F.lit(1).alias("d")).unionByName(rollouts.select(F.col("finished").alias("at"), F.lit(-1).alias("d")))
    b = e.groupBy(F.floor(F.col("at") / buckets_us).alias("bucket")).agg(F.sum("d").alias("net"), F.sum((F.col("d") == 1).cast("long")).alias("dispatched"), F.sum((F.col("d") == -1).cast("long")).alias("finished"))
    w = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)  # one row a bucket
    return b.withColumn("in_flight", F.sum("net").over(w)).drop("net")
