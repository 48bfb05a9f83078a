"""The whole step on multi-turn groups against plain Python."""

import hashlib
import math


from trajkit import multiturn, policy

number = lambda w: int(hashlib.md5(w.encode()).hexdigest()[:8], 16)
said = {0: "red blue", 1: "red green sky", 2: "cloud", 3: "blue blue red tree", 4: "red"}


def test_step_equals_plain_python(spark):
    rows = [(r, t, role, text) for r, reply in said.items() for t, (role, text) in enumerate([("user", "red blue"), ("assistant", reply), ("user", "seen red"), ("assistant", "red")])]
    turns = spark.createDataFrame(rows, "rollout_id long, turn int, role string, content string")
    docs = spark.createDataFrame([(i, "red red blue green sky seen " * 3 + f"tree{i}") for i in range(8)], "doc_id long, text string")
    vectors = spark.createDataFrame([(7 * i, [1.0 if d == i % 10 else 0.1 * (i % 3) for d in range(64)], i % 10) for i in range(40)], "vec_id long, embedding array<float>, label int")
    actor = policy.fit_once(docs, 3)
    got = multiturn.step(turns, policy.serve_precision(actor, 1), actor, vectors).first()

    table, other = {r["token_id"]: r["logp"] for r in actor.collect()}, actor.first()["other_logp"]
    logp = lambda w: table.get(number(w), other)

    def f1(a, b):
        a, b = set(a.split()), set(b.split())
        return 2 * len(a & b) / (len(a) + len(b))

    reward = {r: (f1(said[r], "red blue") + f1("red", "seen red")) / 2 for r in range(4)}  # rollout 4 has no complete group
    mean = sum(reward.values()) / 4
    std = math.sqrt(sum((x - mean) ** 2 for x in reward.values()) / 3)
    tokens, actions, rejected, loss = 0, 0, 0, 0.0
    for r in range(4):
        words = [*said[r].split(), "red"]
        tokens += 4 * 2 + 4 + len(words)
        actions += len(words)
        gap = [logp(w) - round(logp(w), 1) for w in words]
        if 0.99 <= math.exp(sum(gap) / len(gap)) <= 1.01:
            loss -= sum(min(math.exp(g), 2) for g in gap) * (reward[r] - mean) / std
        else:
            rejected += len(words)
    assert 0 < rejected < actions
    assert (got["n_groups"], got["n_rollouts"], got["n_segments"], got["n_tokens"], got["n_actions"], got["n_rejected"], got["n_replayed"]) == (1, 4, 4, tokens, actions, rejected, tokens)
    assert abs(got["loss"] - loss / actions) < 1e-4 and abs(got["sharded"] - got["loss"]) < 1e-12
    assert got["ep2_most"] >= tokens / 2 and got["ep10_most"] <= got["ep5_most"] <= got["ep2_most"] <= tokens
