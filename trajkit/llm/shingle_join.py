"""Exact n-gram Jaccard join by multiple-global-order filtering.

A document is the set of its hashed word shingles. Two sets of sizes m and n with Jaccard
similarity of at least t must share a token within the first ``size - ceil(t * size) + 1`` tokens
of both, under *any* global order of tokens. The first order puts rare tokens first (shared
passages, which many documents hold, come last and stay out of prefixes); its prefixes are
indexed and make candidates. Candidates must then share prefix tokens under further, hash-made
orders as well, and stay within the distance that parity sketches allow; only pairs that pass the intersection of
all filters are verified on whole sets. Prefixes and sketches are made with the sets' signatures, so no text is read to filter.

Equal sets are one node from the start. Two rounds keep groups of near copies from being
expanded: the first compares neighbours within each posting list only, and joins up what links;
the second takes the pairs of a posting list that lie in different components, all of them. Pairs
inside a component can't change the result, so no link between components is lost.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.llm.common import PIECE, Words, _mix, materialise, pieces, release, segments, tidy
from trajkit.llm.components import connected_components

WIDTH, PERCENT = 5, 75
#: Tokens in at least so many documents are ordered by their frequency class; the table of them is bounded.
FREQUENT, FREQUENT_ROWS = 24, 1 << 19
#: The further global orders, each a hash seed.
ORDERS = (0x51ED2701A4C93F57, 0x7C0FFEE5D00DFACE | 1)
#: Posting lists from this length on are also run through in hashed orders; tokens looked back at for an earlier meeting.
LONG_LIST, LOOK_BACK = 8, 6
#: Partners of a set that the first round verifies; rounds of its rough components.
NEAREST, ROUGH_ROUNDS = 2, 4
#: Ids that may be broadcast to filter texts; beyond it the texts are joined by shuffle.
BROADCAST_IDS = 200_000
#: Shingles of the corpus a counting bucket and an index bucket: buckets grow with the input, their size doesn't.
COUNT_BUCKET, INDEX_BUCKET = 1 << 20, 1 << 21
#: Tasks gather tokens until blocks hold about BLOCK of them, at most GATHER in all; so blocks shrink only on very large inputs.
BLOCK, GATHER = 16, 1 << 22


def shingle_sets(texts: pa.Array, width: int = WIDTH) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text: ``width`` consecutive words, or all words where there are fewer."""
    parts = [(w.hashes(), w.bounds) for w in (Words(part, lower=True) for part in segments(texts))]
    h, bounds = parts[0] if len(parts) == 1 else (np.concatenate([x for x, _ in parts]), [0, sum(len(x) for x, _ in parts)])
    factors = [np.uint64((0x9E3779B97F4A7C15 * (2 * j + 3)) & (2**64 - 1) | 1) for j in range(width)]
    wide = np.zeros(max(0, len(h) - width + 1), np.uint64)
    for at in range(0, len(wide), PIECE):
        end = min(len(wide), at + PIECE)
        for j in range(width):
            wide[at:end] += h[at + j : end + j] * factors[j]
        wide[at:end] = _mix(wide[at:end])
    out = []
    for a, b in zip(bounds[:-1], bounds[1:]):
        if b - a >= width:
            out.append(np.unique(wide[a : b - width + 1]))
        elif b > a:
            short = int(b - a) + sum(int(h[a + j]) * int(factors[j]) for j in range(b - a))
            out.append(_mix(np.array([short & (2**64 - 1)], np.uint64)))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def signature(tokens: np.ndarray) -> tuple[int, int]:
    """128 bits that stand for a whole set, as two signed longs."""
    a = _mix(tokens ^ np.uint64(0x1234567)).sum(dtype=np.uint64)
    b = _mix(tokens + np.uint64(0xABCDEF1)).sum(dtype=np.uint64)
    return int(_mix(np.array([a]))[0].astype(np.int64)), int(_mix(np.array([b]))[0].astype(np.int64))


def sketch_bits(n: int) -> int:
    """Bits of the sketch of a set of ``n`` tokens: the power of two from twice its size on, so that large sets are told apart too."""
    return 1 << max(8, (2 * n - 1).bit_length())


def parity_sketch(tokens: np.ndarray) -> bytes:
    """Each token toggles one bit: two sketches differ in at most as many bits as the sets differ in tokens."""
    bits = sketch_bits(len(tokens))
    odd = np.bincount((tokens >> np.uint64(20)).astype(np.int64) % bits, minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def bits_apart(x: bytes, y: bytes) -> int:
    """In how many bits two sketches differ; the longer one is folded to the size of the other, which can only lose differences."""
    x, y = sorted((np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)), key=len)
    return int(np.bitwise_count(x ^ np.bitwise_xor.reduce(y.reshape(-1, len(x)), axis=0)).sum())


def prefix_size(n: int, percent: int = PERCENT) -> int:
    return n - -(-percent * n // 100) + 1


def order_keys(tokens: np.ndarray, frequent: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """The first global order: frequency class, then hash. Tokens outside the frequent table are class 0."""
    key = _mix(tokens ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(6)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, tokens.astype(np.uint32)), len(frequent) - 1)
        hit = frequent[at] == tokens.astype(np.uint32)
        key = key | (np.where(hit, classes[at], 0).astype(np.uint64) << np.uint64(58))
    return key


def low_bits(prefix: int) -> np.dtype:
    """Prefix tokens under the further orders are kept by their lowest bits, so few that a chance meeting stays unlikely."""
    return np.dtype("<u2" if prefix <= 128 else "<u4")


def order_prefixes(tokens: np.ndarray, percent: int = PERCENT) -> bytes:
    """The prefix under each of ORDERS, one after another. An order sorts by a seeded hash, which is one-to-one on tokens."""
    p = prefix_size(len(tokens), percent)
    return b"".join(np.partition(_mix(tokens ^ np.uint64(seed)), p - 1)[:p].astype(low_bits(p)).tobytes() for seed in ORDERS)


def share_prefixes(x: bytes, y: bytes, m: int, n: int, percent: int = PERCENT) -> bool:
    """Whether the prefixes of two sets of sizes ``m`` and ``n`` meet under every one of ORDERS; never False for a pair that reaches the threshold."""
    sides = []
    for data, size in ((x, m), (y, n)):
        p = prefix_size(size, percent)
        sides.append(np.frombuffer(data, low_bits(p)).reshape(len(ORDERS), p))
    kind = min(sides[0].dtype, sides[1].dtype)
    return all(np.isin(k.astype(kind), l.astype(kind)).any() for k, l in zip(*sides))


def summaries(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, and for documents with words sig, sig2, sketch, orders (prefixes under the further orders)."""

    def run(batches):
        for b in pieces(batches):
            sets = shingle_sets(b.column(1), width)
            sigs = [signature(s) if len(s) else (None, None) for s in sets]
            cols = [pa.array([len(s) for s in sets], pa.int64()), *(pa.array([s[k] for s in sigs], pa.int64()) for k in (0, 1))]
            cols += [pa.array([parity_sketch(s) if len(s) else None for s in sets], pa.binary()), pa.array([order_prefixes(s, percent) if len(s) else None for s in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays([b.column(0), *cols], ["doc_id", "n_shingles", "sig", "sig2", "sketch", "orders"])

    return docs.mapInArrow(run, "doc_id long, n_shingles long, sig long, sig2 long, sketch binary, orders binary")


def frequent_tokens(docs: DataFrame, total: int, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """32-bit token prefixes that many documents hold, with log2 classes: counted over all documents, at most FREQUENT_ROWS kept.

    Tasks send sorted 32-bit tokens in blocks by hash bucket, so counting moves four bytes a shingle. The table only
    shapes the order of tokens: whatever is missing from it costs time, never a link.
    """
    buckets = max(64, total // COUNT_BUCKET)
    enough = min(GATHER, BLOCK * buckets)

    def blocks(sets):
        tokens, counts = np.unique(np.concatenate(sets), return_counts=True)
        bucket = (tokens.astype(np.int64) * buckets) >> 32
        first = np.flatnonzero(np.diff(bucket, prepend=-1))
        parts = list(zip(np.split(tokens, first[1:]), np.split(counts, first[1:])))
        many = [np.flatnonzero(c > 1) for _, c in parts]
        return pa.RecordBatch.from_arrays(
            [pa.array(bucket[first], pa.int32()), pa.array([t.tobytes() for t, _ in parts], pa.binary()), pa.array([np.stack([m, c[m]]).astype(np.uint32).tobytes() for (_, c), m in zip(parts, many)], pa.binary())],
            ["bucket", "tokens", "more"],
        )

    def send(batches):
        held, size = [], 0
        for b in pieces(batches):
            for s in shingle_sets(b.column(1), width):
                if len(s):
                    held.append(s.astype(np.uint32))
                    size += len(s)
            if size >= enough:
                yield blocks(held)
                held, size = [], 0
        if size:
            yield blocks(held)

    def count(group: pa.Table) -> pa.Table:
        tokens = [np.frombuffer(t.as_buffer(), np.uint32) for t in group.column("tokens")]
        counts = []
        for t, m in zip(tokens, group.column("more")):
            c = np.ones(len(t), np.int64)
            at, n = np.frombuffer(m.as_buffer(), np.uint32).reshape(2, -1)
            c[at] = n
            counts.append(c)
        tokens, counts = np.concatenate(tokens), np.concatenate(counts)
        order = np.argsort(tokens, kind="stable")
        tokens, counts = tokens[order], counts[order]
        first = np.flatnonzero(np.diff(tokens, prepend=np.uint32(tokens[0] ^ 1)))
        sums = np.add.reduceat(counts, first)
        keep = sums >= FREQUENT
        return pa.table({"token": tokens[first][keep].astype(np.int64), "n_docs": sums[keep]})

    found = docs.mapInArrow(send, "bucket int, tokens binary, more binary").groupBy("bucket").applyInArrow(count, "token long, n_docs long")
    top = found.orderBy(F.desc("n_docs"), "token").limit(FREQUENT_ROWS).toArrow().sort_by("token")
    return top["token"].to_numpy().astype(np.uint32), np.minimum(1 + np.log2(top["n_docs"].to_numpy().astype(np.float64)).astype(np.int64), 62)


def in_runs(ordered: np.ndarray) -> np.ndarray:
    """Where an entry equals one of its neighbours."""
    same, out = ordered[1:] == ordered[:-1], np.zeros(len(ordered), bool)
    out[1:] |= same
    out[:-1] |= same
    return out


def postings(docs: DataFrame, frequent: np.ndarray, classes: np.ndarray, total: int, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """token, sig, n, pos: index entries of prefix tokens that at least two different sets share.

    ``pos`` is a lower bound of the token's place in the set's order. Tokens of the frequent table skip the counting
    step (they are shared for certain), so no posting list of theirs meets in one task.
    """
    table = docs.sparkSession.sparkContext.broadcast((frequent, classes))  # at most FREQUENT_ROWS entries
    buckets = max(32, total // INDEX_BUCKET)
    enough = min(GATHER, BLOCK * buckets)

    def blocks(cols, sigs, sizes, number):
        bucket, token, row, pos = (np.concatenate(cols[k]) for k in ("bucket", "token", "row", "pos"))
        order = np.argsort(bucket, kind="stable")
        bucket, token, row, pos = bucket[order], token[order], row[order], pos[order]
        first = np.flatnonzero(np.diff(bucket, prepend=bucket[0] - 1))
        sigs, sizes = np.array(sigs, np.int64), np.array(sizes, np.uint32)
        rows = []
        for a, z in zip(first, [*first[1:], len(bucket)]):
            own, counts = np.unique(row[a:z], return_counts=True)
            k = int(bucket[a]) if bucket[a] >= 0 else -1 - (hash((int(sigs[0]), number)) & 0x3FFFFFFF)
            rows.append((k, sigs[own].tobytes(), sizes[own].tobytes(), counts.astype(np.uint32).tobytes(), token[a:z].tobytes(), pos[a:z].tobytes()))
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), [pa.int32(), *[pa.binary()] * 5])], ["bucket", "sigs", "sizes", "counts", "tokens", "pos"])

    def send(batches):
        freq, cls = table.value
        number, size, seen, sigs, sizes, cols = 0, 0, set(), [], [], defaultdict(list)
        for b in pieces(batches):
            for s in shingle_sets(b.column(1), width):
                if not len(s):
                    continue
                sig = signature(s)
                if sig in seen:
                    continue
                seen.add(sig)
                key = order_keys(s, freq, cls)
                p = prefix_size(len(s), percent)
                order = np.argsort(key, kind="stable")[:p]
                cols["token"].append(s[order])
                cols["bucket"].append(np.where(key[order] >> np.uint64(58), -1, (s[order] >> np.uint64(33)).astype(np.int64) % buckets))
                cols["row"].append(np.full(p, len(sigs), np.int32))
                cols["pos"].append((np.arange(p) * 255 // len(s)).astype(np.uint8))
                sigs.append(sig[0])
                sizes.append(len(s))
                size += p
            if size >= enough:
                yield blocks(cols, sigs, sizes, number)
                number, size, seen, sigs, sizes, cols = number + 1, 0, set(), [], [], defaultdict(list)
        if size:
            yield blocks(cols, sigs, sizes, number)

    def shared(group: pa.Table) -> pa.Table:
        joined = lambda name, kind: np.concatenate([np.frombuffer(x.as_buffer(), kind) for x in group.column(name)])
        counts, frequent_rows = joined("counts", np.uint32), group.column("bucket")[0].as_py() < 0
        sig, n = np.repeat(joined("sigs", np.int64), counts), np.repeat(joined("sizes", np.uint32), counts)
        token, pos = joined("tokens", np.uint64), joined("pos", np.uint8)
        if not frequent_rows:  # entries of tokens that a single set holds go; so do repeated entries
            keep = np.argsort(token, kind="stable")
            keep = keep[in_runs(token[keep])]
            keep = keep[np.lexsort((sig[keep], token[keep]))]
            t, g = token[keep], sig[keep]
            keep = keep[np.concatenate([np.ones(min(1, len(t)), bool), (t[1:] != t[:-1]) | (g[1:] != g[:-1])])]
            keep = keep[in_runs(token[keep])]
            sig, n, token, pos = sig[keep], n[keep], token[keep], pos[keep]
        return pa.table({"token": token.view(np.int64), "sig": sig, "n": n.astype(np.int64), "pos": (pos.astype(np.int64) * n + 254) // 255, "frequent": np.full(len(token), frequent_rows)})

    sent = docs.mapInArrow(send, "bucket int, sigs binary, sizes binary, counts binary, tokens binary, pos binary")
    found = materialise(sent.groupBy("bucket").applyInArrow(shared, "token long, sig long, n long, pos long, frequent boolean"))
    # Entries of frequent tokens come once a block of each task; copies of one set would repeat them.
    once = found.filter("frequent").groupBy("token", "sig").agg(F.min("n").alias("n"), F.min("pos").alias("pos"))
    index = materialise(found.filter("not frequent").drop("frequent").unionByName(once))
    release(found)
    return index


def neighbour_pairs(index: DataFrame, percent: int = PERCENT) -> DataFrame:
    """a, b: sets next to each other in a posting list, by size, and in long lists in hashed orders of their own; linear in the index.

    Orders that differ from token to token let each member of a large group meet many others, so that most of the
    group is joined up before pairs between components are looked at one by one.
    """

    def run(batches):
        for batch in batches:
            token, sig, n = (batch.column(k).to_numpy() for k in range(3))
            size = np.bincount(np.cumsum(np.diff(token, prepend=token[:1]) != 0))
            long = np.flatnonzero(np.repeat(size, size) >= LONG_LIST)
            salt = _mix(token[long].astype(np.uint64))
            found = []
            for order in (np.arange(len(token)), *(long[np.lexsort((_mix(sig[long].astype(np.uint64) ^ salt ^ np.uint64(s)), token[long]))] for s in ORDERS)):
                t, g, m = token[order], sig[order], n[order]
                ok = (t[1:] == t[:-1]) & (g[1:] != g[:-1]) & (100 * np.minimum(m[1:], m[:-1]) >= percent * np.maximum(m[1:], m[:-1]))
                found.append(np.stack([np.minimum(g[1:], g[:-1])[ok], np.maximum(g[1:], g[:-1])[ok]], 1))
            pairs = np.unique(np.concatenate(found), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"])

    ordered = index.repartitionByRange("token", "n", "sig").sortWithinPartitions("token", "n", "sig")
    return ordered.select("token", "sig", "n").mapInArrow(run, "a long, b long").distinct()


def cross_pairs(index: DataFrame, labels: DataFrame, percent: int = PERCENT) -> DataFrame:
    """a, b: all pairs of a posting list that lie in different components and pass the length and position filters.

    In each list the members outside its most frequent component meet all others, so a list whose members are joined up
    but for a few costs these few times its length. A pair is taken at its first common token: where the tokens just before it
    meet as well, the pair has been taken there.
    """
    few = labels.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    label = labels.select(F.col("node").alias("sig"), "component")
    known = index.join(F.broadcast(label) if few else label, "sig", "left").withColumn("component", F.coalesce("component", "sig"))
    before = Window.partitionBy("sig").orderBy("pos", "token")
    known = known.withColumn("last", F.array_compact(F.array(*[F.lag("token", k).over(before) for k in range(1, LOOK_BACK + 1)])))
    per = known.groupBy("token", "component").agg(F.count("*").alias("_k")).groupBy("token").agg(F.max_by("component", F.struct("_k", "component")).alias("main"), F.count("*").alias("_c"))
    known = materialise(known.join(per.filter("_c > 1").select("token", "main"), "token"))
    x = known.filter("component <> main").select("token", F.col("sig").alias("a"), F.col("n").alias("m"), F.col("pos").alias("p"), F.col("component").alias("c"), F.col("last").alias("k"))
    y = known.select("token", F.col("sig").alias("b"), F.col("n").alias("n"), F.col("pos").alias("q"), F.col("component").alias("d"), F.col("last").alias("l"), "main")
    need = F.expr(f"{percent} * (m + n)")  # times 1 / (100 + percent): the least overlap
    most = F.expr(f"{100 + percent} * least(m - p, n - q)")  # if this is their first common token
    once = (F.col("d") == F.col("main")) | (F.col("a") < F.col("b"))
    pair = (F.col("c") != F.col("d")) & once & (100 * F.least("m", "n") >= percent * F.greatest("m", "n")) & (most >= need) & ~F.arrays_overlap("k", "l")
    return x.join(y, "token").filter(pair).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def verified(pairs: DataFrame, docs: DataFrame, summary: DataFrame, nodes: DataFrame, width: int = WIDTH, percent: int = PERCENT, nearest: int | None = None) -> DataFrame:
    """The pairs whose whole sets reach the threshold. Sketches and the prefixes under the further orders discard others before a text is read.

    ``nodes``: sig, n, sketch, doc_id of one document of each set. ``nearest``: of each set's possible partners only so many,
    the closest by sketch, are verified; for a round that only has to join up most of a group.
    """

    def close(batches):
        for batch in batches:
            m, n = (batch.column(k).to_numpy() for k in (4, 5))
            apart = np.fromiter((bits_apart(x.as_buffer(), y.as_buffer()) for x, y in zip(batch.column(6), batch.column(7))), np.int64, len(m))
            keep = pa.array((100 + percent) * (m + n - apart) >= 2 * percent * (m + n))  # else so many exclude the threshold
            yield pa.RecordBatch.from_arrays([*(batch.column(k).filter(keep) for k in range(6)), pa.array(apart.astype(np.int32)).filter(keep)], ["a", "b", "a_doc", "b_doc", "m", "n", "apart"])
        tidy()

    def meeting(batches):
        for batch in batches:
            m, n = (batch.column(k).to_pylist() for k in (4, 5))
            keep = pa.array([share_prefixes(x.as_buffer(), y.as_buffer(), *size, percent) for x, y, *size in zip(batch.column(6), batch.column(7), m, n)], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(k).filter(keep) for k in range(4)], ["a", "b", "a_doc", "b_doc"])
        tidy()

    def both_sides(table: DataFrame, column: str) -> tuple[DataFrame, DataFrame]:
        return table.select(F.col("sig").alias("a"), F.col(column).alias("x")), table.select(F.col("sig").alias("b"), F.col(column).alias("y"))

    def of_ids(table: DataFrame, found: DataFrame) -> DataFrame:
        """Rows of ``table`` of the documents that stand for the sets of ``found``."""
        ids = found.select(F.col("a_doc").alias("doc_id")).unionByName(found.select(F.col("b_doc").alias("doc_id"))).distinct()
        few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
        return table.join(F.broadcast(ids) if few else ids, "doc_id", "left_semi")

    a = nodes.select(F.col("sig").alias("a"), F.col("n").alias("m"), F.col("sketch").alias("x"), F.col("doc_id").alias("a_doc"))
    b = nodes.select(F.col("sig").alias("b"), F.col("n"), F.col("sketch").alias("y"), F.col("doc_id").alias("b_doc"))
    row = ("a", "b", "a_doc", "b_doc", "m", "n")
    near = pairs.join(a, "a").join(b, "b").select(*row, "x", "y").mapInArrow(close, "a long, b long, a_doc long, b_doc long, m long, n long, apart int")
    if nearest:
        rank = [F.row_number().over(Window.partitionBy(x).orderBy("apart", y)) for x, y in (("a", "b"), ("b", "a"))]
        near = near.withColumn("_a", rank[0]).withColumn("_b", rank[1]).filter(F.least("_a", "_b") <= nearest)
    near = materialise(near.select(*row))
    x, y = both_sides(of_ids(summary, near).groupBy("sig").agg(F.min("orders").alias("orders")), "orders")
    met = materialise(near.join(x, "a").join(y, "b").select(*row, "x", "y").mapInArrow(meeting, "a long, b long, a_doc long, b_doc long"))
    release(near)
    texts = of_ids(docs, met)

    def sets(batches):
        for p in pieces(batches):
            found = [s for s in shingle_sets(p.column(1), width) if len(s)]
            yield pa.RecordBatch.from_arrays([pa.array([signature(s)[0] for s in found], pa.int64()), pa.array([s.tobytes() for s in found], pa.binary())], ["sig", "tokens"])

    whole = texts.select("doc_id", "text").mapInArrow(sets, "sig long, tokens binary")

    def compare(batches):
        for p in batches:
            a, b, keep = p.column(0).to_numpy(), p.column(1).to_numpy(), []
            for x, y in zip(p.column(2), p.column(3)):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                ok = 100 * min(len(x), len(y)) >= percent * max(len(x), len(y))
                if ok:
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    ok = 100 * common >= percent * (len(x) + len(y) - common)
                keep.append(ok)
            keep = np.array(keep, bool)
            yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(b[keep])], ["a", "b"])
        tidy()

    x, y = both_sides(whole, "tokens")
    both = met.select("a", "b").join(y, "b").join(x, "a").select("a", "b", "x", "y")
    out = materialise(both.mapInArrow(compare, "a long, b long").distinct())
    release(met)
    return out


def jaccard_components(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id (the smallest doc_id reachable by links, itself included) for every row.

    Null text, or text without words: an empty set, linked with nothing. Null doc_id: its row is returned with a null
    component and links nothing. Repeated rows give repeated results; rows that share a doc_id but not a text are
    judged by their own texts. Empty table: no rows. Other columns are ignored. Whole texts count, whatever their length.
    """
    texts = docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text")
    summary = materialise(summaries(texts, width, percent))
    total = summary.agg(F.sum("n_shingles")).first()[0] or 0
    named = summary.filter("doc_id is not null")
    nodes = materialise(named.filter("n_shingles > 0").groupBy("sig", "sig2").agg(F.min("doc_id").alias("doc_id"), F.first("n_shingles").alias("n"), F.first("sketch").alias("sketch")))
    usable = texts.filter("doc_id is not null")
    index = postings(usable, *frequent_tokens(usable, total, width), total, width, percent)
    links = verified(neighbour_pairs(index, percent), usable, summary, nodes, width, percent, NEAREST)
    labels = materialise(connected_components(links, ROUGH_ROUNDS, settle=False))
    more = verified(cross_pairs(index, labels, percent), usable, summary, nodes, width, percent)
    release(index)
    labels = connected_components(links.unionByName(more))
    # From sets to documents.
    own = nodes.join(labels.select(F.col("node").alias("sig"), "component"), "sig", "left").select("sig", "sig2", "doc_id", F.coalesce("component", "sig").alias("component"))
    least = own.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    own = own.join(least, "component").select("sig", "sig2", "component_id")
    out = summary.join(own, ["sig", "sig2"], "left")
    return out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))


def near_duplicates(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """doc_id, cluster_id: the components of the prompt pool. A document without words is a cluster of its own."""
    return jaccard_components(docs, width, percent).select("doc_id", F.col("component_id").alias("cluster_id"))


def keep_one(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """One document of each group stays: the one with the smallest doc_id; documents without words all stay.

    Of repeated rows with one doc_id a single one stays. A null doc_id stays.
    """
    labels = jaccard_components(docs, width, percent).filter("doc_id is not null and n_shingles > 0 and component_id <> doc_id").select("doc_id").distinct()
    kept = docs.join(labels, "doc_id", "left_anti").select(*docs.columns)
    return kept.filter("doc_id is null").unionByName(kept.filter("doc_id is not null").dropDuplicates(["doc_id"]))
