"""Scheduling modes, staleness, partial rollouts and streams on events."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from trajkit import joins, measures, scheduling, streaming, workloads
from trajkit.registered import query
from trajkit.session import shared_folder

r6 = lambda c, name=None: F.round(F.col(c) if isinstance(c, str) else c, 6).alias(name or c)
LIFE = """life AS (SELECT event_id AS rollout_id, event_id // 4 AS group_id, epoch_us(ts) AS dispatched, epoch_us(ts) + round(value * 60e6)::BIGINT AS finished, event_type = 'error' AS failed, user_id AS worker, value AS latency, ts FROM events),
grp AS (SELECT group_id, min(dispatched) AS dispatched, max(finished) AS finished FROM life GROUP BY 1 HAVING count(*) >= 4 AND NOT bool_or(failed)),
byfin AS (SELECT *, row_number() OVER (ORDER BY finished, group_id) AS rank, (row_number() OVER (ORDER BY finished, group_id) - 1) // 32 AS batch FROM grp),
bydis AS (SELECT *, row_number() OVER (ORDER BY dispatched, group_id) AS rank, (row_number() OVER (ORDER BY dispatched, group_id) - 1) // 32 AS batch FROM grp),
refit AS (SELECT k - a AS version, k * 86400000000 AS refit_at FROM (SELECT unnest(range(min(dispatched) // 86400000000, max(finished) // 86400000000 + 1)) AS k, min(dispatched) // 86400000000 AS a FROM life))"""


def groups(s, d):
    return scheduling.group_times(workloads.lifecycle(s, d), workloads.SAMPLES)


query("sched_stream", f"WITH {LIFE} SELECT group_id, rank, batch FROM byfin")(lambda s, d: scheduling.streaming(groups(s, d), 32).select("group_id", "rank", "batch"))
query("sched_sync", f"WITH {LIFE} SELECT batch, min(dispatched) AS start, max(finished) AS ready, count(*) AS n_groups FROM bydis GROUP BY 1")(lambda s, d: scheduling.rounds(scheduling.barrier(groups(s, d), 32)))
query("sched_one_step", f"""WITH {LIFE}, r AS (SELECT batch, min(dispatched) AS start, max(finished) AS ready FROM bydis GROUP BY 1)
SELECT batch, ready - start AS generation, greatest(ready - start, CASE WHEN batch > 0 THEN 80000000000 ELSE 0 END)::BIGINT AS step FROM r""")(
    lambda s, d: scheduling.one_step(scheduling.barrier(groups(s, d), 32), 80_000_000_000).select("batch", "generation", F.col("step").cast("long").alias("step"))
)
_CONFIGS = [
    {"name": f"{m}_{w}", "workers": w, "batch": 32, "queue": 64, "train_us": 3_600_000_000, "mode": m} for m in ("streaming", "one_step", "barrier") for w in (64, 128)
]
query("sched_pool")(lambda s, d: scheduling.simulate(workloads.lifecycle(s, d), _CONFIGS, workloads.SAMPLES))
query("staleness", f"""WITH {LIFE}, c AS (SELECT *, max(finished) OVER (PARTITION BY batch) AS consumed FROM byfin),
v AS (SELECT batch, (SELECT max(version) FROM refit WHERE refit_at <= consumed) - (SELECT max(version) FROM refit WHERE refit_at <= dispatched) AS gap FROM c)
SELECT batch, min(gap) AS least, round(avg(gap), 6) AS mean, max(gap) AS most FROM v GROUP BY 1""")(
    lambda s, d: scheduling.staleness(scheduling.streaming(groups(s, d), 32), scheduling.refits(workloads.lifecycle(s, d))).select("batch", "least", r6("mean"), "most")
)
query("asof_version", f"WITH {LIFE} SELECT rollout_id, version FROM life ASOF JOIN refit ON dispatched >= refit_at")(
    lambda s, d: joins.as_of(workloads.lifecycle(s, d), scheduling.refits(workloads.lifecycle(s, d)), "dispatched", "refit_at", ["version"]).select("rollout_id", "version")
)
_TOK = f"WITH {LIFE}, t AS (SELECT rollout_id, pos, dispatched + pos * 600000000 AS tm FROM life, unnest(range(floor(latency / 10)::BIGINT + 1)) AS u(pos) WHERE NOT failed), v AS (SELECT t.*, version FROM t ASOF JOIN refit ON tm >= refit_at)"


def _versioned(s, d):
    life = workloads.lifecycle(s, d)
    times = scheduling.token_times(life.filter("not failed"), F.floor(F.col("latency") / 10) + 1, 600.0)
    return scheduling.partial(times, scheduling.refits(life))


query("partial_versions", _TOK + " SELECT rollout_id, min(version) AS first_version, max(version) AS last_version, count(*) AS n_tokens FROM v GROUP BY 1 HAVING min(version) < max(version)")(
    lambda s, d: _versioned(s, d).groupBy("rollout_id").agg(F.min("version").alias("first_version"), F.max("version").alias("last_version"), F.count("*").alias("n_tokens")).filter("first_version < last_version")
)
query("partial_waste", _TOK + ", m AS (SELECT *, max(version) OVER (PARTITION BY rollout_id) AS l FROM v) SELECT count(DISTINCT rollout_id) AS n_rollouts, count(*) AS n_tokens, sum(CASE WHEN version < l THEN 1 ELSE 0 END)::BIGINT AS wasted FROM m")(
    lambda s, d: scheduling.restart_waste(_versioned(s, d)).agg(F.count("*").alias("n_rollouts"), F.sum("n_tokens").alias("n_tokens"), F.sum("wasted").alias("wasted"))
)
query("inflight", f"""WITH {LIFE}, e AS (SELECT dispatched AS tm, 1 AS d FROM life UNION ALL SELECT finished, -1 FROM life), b AS (SELECT tm // 86400000000 AS bucket, sum(d) AS net, sum(CASE WHEN d = 1 THEN 1 ELSE 0 END)::BIGINT AS dispatched, sum(CASE WHEN d = -1 THEN 1 ELSE 0 END)::BIGINT AS finished FROM e GROUP BY 1)
SELECT bucket, dispatched, finished, (sum(net) OVER (ORDER BY bucket))::BIGINT AS in_flight FROM b""")(lambda s, d: scheduling.inflight(workloads.lifecycle(s, d)))


def events(s, d):
    return streaming.lifecycle(workloads.table(s, d, "events"))


query("win_tumbling", "SELECT epoch_us(date_trunc('day', ts)) AS start_us, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")(lambda s, d: streaming.rates(events(s, d)).select("start_us", "n", F.round("total", 4).alias("total")))
query("win_sliding", """SELECT k * 43200000000 AS start_us, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT epoch_us(ts) AS u, value, unnest([epoch_us(ts) // 43200000000 - 1, epoch_us(ts) // 43200000000]) AS k FROM events) GROUP BY 1""")(
    lambda s, d: streaming.rates(events(s, d), "sliding", "1 day", "12 hours").select("start_us", "n", F.round("total", 4).alias("total"))
)
query("win_session", """WITH e AS (SELECT user_id, epoch_us(ts) AS u, value, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events), g AS (SELECT *, sum(CASE WHEN p IS NULL OR u - p >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY u) AS k FROM e)
SELECT min(u) AS start_us, user_id, count(*) AS n, round(sum(value), 4) AS total FROM g GROUP BY user_id, k""")(
    lambda s, d: streaming.rates(workloads.table(s, d, "events").withColumn("at", F.col("ts").cast("timestamp")), "session", gap="6 hours", by=("user_id",)).select("start_us", "user_id", "n", F.round("total", 4).alias("total"))
)
query("lat_join", "SELECT event_id AS rollout_id, round(value * 60e6)::BIGINT AS latency_us FROM events WHERE event_type <> 'error'")(lambda s, d: _latency(s, d))


def _latency(s, d):
    e = events(s, d)
    done = e.filter("not failed").withColumn("at", F.timestamp_micros(F.unix_micros("at") + F.round(F.col("value") * 60e6).cast("long")))
    return streaming.latency_join(e, done)


def _events_folder(s, d):
    """The events as a folder of files in the shared folder, which is what a file stream reads."""
    path = f"{shared_folder(s)}/events_stream/{uuid.uuid4().hex}"
    workloads.table(s, d, "events").write.parquet(path)
    return path


def _stream(s, d, name):
    table = workloads.table(s, d, "events")
    return table.schema, f"{shared_folder(s)}/{name}/{uuid.uuid4().hex}"


@query("stream_groups")
def stream_groups(s, d):
    """Groups assembled by the stateful stream over the events file; equal to the batch answer."""
    schema, ck = _stream(s, d, "stream_groups")
    stream = s.readStream.schema(schema).parquet(_events_folder(s, d))
    return streaming.drain(streaming.group_completion(streaming.lifecycle(stream), 4), ck).filter("state = 'complete'").select("group_id", "n_rollouts")


@query("stream_late")
def stream_late(s, d):
    """Windowed counts of a stream with a watermark: rows behind the bound don't change closed windows."""
    schema, ck = _stream(s, d, "stream_late")
    stream = s.readStream.schema(schema).parquet(_events_folder(s, d))
    return streaming.drain(streaming.rates(streaming.with_lateness(streaming.lifecycle(stream)), "tumbling", "1 day"), ck)


@query("stream_dedup")
def stream_dedup(s, d):
    schema, ck = _stream(s, d, "stream_dedup")
    stream = streaming.with_lateness(streaming.lifecycle(s.readStream.schema(schema).parquet(_events_folder(s, d))))
    return streaming.drain(stream.dropDuplicatesWithinWatermark(["rollout_id"]).select("rollout_id", "group_id"), ck)


# ---- the throughput comparison, re-expressed ------------------------------------------------


@query("wl_async_modes", f"""WITH {LIFE}, runs AS (SELECT *, least(group_id // ((SELECT max(group_id) FROM life) // 3 + 1), 2) AS run FROM grp),
f AS (SELECT run, finished AS tm, (row_number() OVER (PARTITION BY run ORDER BY finished, group_id) - 1) // 32 AS batch FROM runs),
st AS (SELECT 'streaming' AS mode, run, batch + 1 AS step, max(tm) - coalesce(lag(max(tm)) OVER (PARTITION BY run ORDER BY batch), 0) AS us FROM f GROUP BY run, batch HAVING count(*) = 32),
g AS (SELECT run, dispatched, finished, (row_number() OVER (PARTITION BY run ORDER BY dispatched, group_id) - 1) // 32 AS batch FROM runs),
rd AS (SELECT run, batch, min(dispatched) AS a, max(finished) AS z FROM g GROUP BY run, batch HAVING count(*) = 32),
al AS (SELECT * FROM st UNION ALL SELECT 'one_step', run, batch + 1, greatest(z - a, 3600000000) FROM rd UNION ALL SELECT 'barrier', run, batch + 1, z - a + 3600000000 FROM rd),
pr AS (SELECT mode, run, avg(us) / 1e6 AS m FROM al WHERE step BETWEEN 2 AND 10 GROUP BY 1, 2)
SELECT mode, count(*) AS n_runs, round(avg(m), 4) AS step_s, round(stddev_samp(m), 4) AS step_std FROM pr GROUP BY 1""")
def wl_async_modes(s, d):
    """Streaming against one-step and barrier batches: mean step time over steps 2-10 of three runs."""
    life = workloads.lifecycle(s, d)
    third = life.agg(F.max("group_id").alias("_top"))
    g = groups(s, d).crossJoin(F.broadcast(third)).withColumn("run", F.least(F.floor(F.col("group_id") / (F.floor(F.col("_top") / 3) + 1)), F.lit(2))).drop("_top")
    from pyspark.sql import Window

    def cut(order):
        k = (F.row_number().over(Window.partitionBy("run").orderBy(order, "group_id")) - 1)
        return g.withColumn("batch", F.floor(k / 32)).groupBy("run", "batch").agg(F.min("dispatched").alias("a"), F.max("finished").alias("z"), F.count("*").alias("n")).filter("n = 32")

    done = cut("finished").withColumn("us", F.col("z") - F.coalesce(F.lag("z").over(Window.partitionBy("run").orderBy("batch")), F.lit(0))).withColumn("mode", F.lit("streaming"))
    rounds, train = cut("dispatched"), 3_600_000_000
    one = rounds.withColumn("us", F.greatest(F.col("z") - F.col("a"), F.lit(train))).withColumn("mode", F.lit("one_step"))
    bar = rounds.withColumn("us", F.col("z") - F.col("a") + train).withColumn("mode", F.lit("barrier"))
    steps = done.unionByName(one).unionByName(bar).select("mode", "run", (F.col("batch") + 1).alias("step"), (F.col("us") / 1e6).alias("seconds"))
    out = None
    for m in ("streaming", "one_step", "barrier"):
        part = measures.step_time(steps.filter(F.col("mode") == m)).select(F.lit(m).alias("mode"), "n_runs", F.round("step_s", 4).alias("step_s"), F.round("step_std", 4).alias("step_std"))
        out = part if out is None else out.unionByName(part)
    return out
