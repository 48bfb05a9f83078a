"""The whole loop over all entries of the policy."""

import hashlib
import os

from pyspark.sql import functions as F

from trajkit import pipeline, policy, worlds
from trajkit.session import materialise, shared_folder

number = lambda text, digits: int(hashlib.md5(text.encode()).hexdigest()[:digits], 16)


def documents(spark, n=300):
    return spark.createDataFrame([(i, " ".join(["the"] * 20 + [f"word{i}", f"word{i}", f"rare{i}"])) for i in range(n)], "doc_id long, text string")


def test_sampler_equals_inverse_distribution(spark):
    pol = policy.fit_once(documents(spark), 3)
    draws = spark.range(1000).select(F.col("id").alias("rollout_id"))
    for buckets in (1, 7, 1 << 20):
        got = {r["rollout_id"]: r["token_id"] for r in policy.sample_whole(draws, pol, 5, ["rollout_id"], 50, buckets).collect()}
        edges, total = [], 0
        for r in pol.withColumn("p", F.exp("logp")).orderBy("token_id").collect():
            total += max(1, int(r["p"] * 2**50 + 0.5))
            edges.append((total, r["token_id"]))
        want = {k: next(t for hi, t in edges if hi > number(f"5:{k}", 13) * total // 2**52) for k in range(1000)}
        assert got == want and len(set(got.values())) > 64


def test_loop_keeps_every_entry_and_reads_the_turns(spark, small):
    docs = documents(spark)
    turns = [(p, t, "user" if t % 2 == 0 else "assistant", f"ask {p}" if t % 2 == 0 else "the word1 the " * (3 + t)) for p in range(6) for t in range(4)]
    turns = spark.createDataFrame(turns, "prompt_id long, turn int, role string, content string")
    log, last = pipeline.train(spark, turns, docs, 2)
    assert last.count() == 601 == pipeline.start(docs).count()
    steps = log.orderBy("step").collect()
    assert steps[0]["n_tokens"] == 6 * 4 * 3 * (4 + 6) and 0 < steps[0]["reward_mean"] < 1
    assert (steps[0]["n_rejected"], steps[0]["largest_weight"], steps[0]["longest_dialogue"]) == (0, 1.0, 2) and steps[0]["reward_std"] > 0
    # A sampled token comes back from the captured reply as it was drawn.
    pol, cfg = policy.fit_once(docs, 3), pipeline.Config()
    said = pipeline.rollouts(turns, pol, policy.pieces(docs), cfg, 3)
    request = worlds.requests(said.select("rollout_id", "turn", "role", "content")).filter("rollout_id = 5 and request_seq = 1").first()
    assert [m["role"] for m in request["messages"]] == ["user", "assistant", "user"] and len(request["reply"].split()) == 18
    draws = spark.createDataFrame([(5, 3, i) for i in range(18)], "rollout_id long, turn int, pos int")
    drawn = [r["token_id"] for r in policy.sample_whole(draws, pol, 3, ["rollout_id", "turn", "pos"]).orderBy("pos").collect()]
    assert drawn == [number(w, 8) for w in request["reply"].split()]


def test_step_costs_few_jobs_and_leaves_only_the_policy(spark):
    docs = materialise(documents(spark))
    turns = [(p, t, "user" if t % 2 == 0 else "assistant", f"ask {p}" if t % 2 == 0 else "the word1 the " * (3 + t)) for p in range(6) for t in range(4)]
    turns = materialise(spark.createDataFrame(turns, "prompt_id long, turn int, role string, content string"))
    first = materialise(pipeline.start(docs))
    folder = f"{shared_folder(spark).removeprefix('file:')}/trajkit"
    jobs, moved = {}, {}
    for n in (1, 2):
        kept = set(os.listdir(folder))
        spark.sparkContext.setJobGroup(f"loop of {n}", "")
        _, last = pipeline.train(spark, turns, docs, n, first=first)
        spark.sparkContext.setJobGroup("rest", "")
        jobs[n] = len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"loop of {n}"))
        assert len(set(os.listdir(folder)) - kept) == 1  # tables that no later step reads are gone
        moved[n] = last.join(first.select("token_id", F.col("theta").alias("before")), "token_id").filter("theta <> before").count()
    # The driver holds buffers for each job and scan, whatever the input.
    assert 0 < jobs[2] - jobs[1] <= 40, jobs
    assert first.count() == last.count() == 601 and 0 < moved[1] <= moved[2]


def test_policy_with_its_words_says_the_same(spark):
    docs, pol = documents(spark), policy.fit_once(documents(spark), 3)
    turns = spark.createDataFrame([(p, 0, "assistant", "a b c d e f g h") for p in range(20)], "prompt_id long, turn int, role string, content string")
    words = policy.pieces(docs).filter("piece <> 'the'")  # an entry without a word is never said
    said = [sorted(map(tuple, pipeline.rollouts(turns, p, w, pipeline.Config(), 3).collect())) for p, w in ((pol, words), (materialise(pipeline.worded(pol, words)), None))]
    assert said[0] == said[1] and len(said[0]) == 80 and not any("the" in row[4].split() for row in said[0])
