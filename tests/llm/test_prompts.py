"""Near duplicates of the prompt pool against brute force."""

from itertools import combinations

from trajkit.llm import shingle_join


def clusters(texts):
    """The smallest id of each component of the exact five-word Jaccard graph."""
    sets = {}
    for i, t in texts.items():
        w = t.lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    head = {i: i for i in texts}
    links = [(a, b) for a, b in combinations(texts, 2) if sets[a] and sets[b] and 4 * len(sets[a] & sets[b]) >= 3 * len(sets[a] | sets[b])]
    for _ in texts:
        for a, b in links:
            head[a] = head[b] = min(head[a], head[b])
    return head


def test_near_duplicates_equal_brute_force(spark):
    words = [f"w{k}" for k in range(104)]
    texts = {k: " ".join(words[4 * k : 4 * k + 64]) for k in range(8)}  # a chain: neighbours link (56 of 64 sets), its ends share too little
    texts |= {10: " ".join(f"a{k}" for k in range(40)), 11: " ".join(f"a{k}" if k % 7 else f"b{k}" for k in range(40))}  # many words in common, few shingles
    texts |= {20: "", 21: " ", 22: "one two", 23: "One  two"}
    got = {r["doc_id"]: r["cluster_id"] for r in shingle_join.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    want = clusters(texts)
    assert want[7] == 0 and want[11] == 11 and want[21] == 21 and want[23] == 22
    assert got == want
