"""Exact top-k inner-product search by block-at-a-time pruning.

Vectors are ordered so that similar ones lie together and cut into blocks of consecutive rows.
A block keeps, for each term (a dimension), the largest and the smallest weight, and a forward
index (its rows as a matrix). For a query the largest possible score in a block is the sum over
terms of the better of the two products; blocks are visited in falling order of that bound, and
scored through their forward index until the bound falls below the query's k-th score so far.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trajkit.llm.common import materialise

SCALE = 256
BLOCK_ROWS, GROUP_BLOCKS, CHUNK_QUERIES = 128, 128, 2048
#: Seed and number of the random hyperplanes whose sign code orders the vectors.
PLANES, SEED = 14, 7


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id, w: integer weights floor(256 * x) of vectors without null or non-finite components."""
    x = F.col("embedding")
    bad = lambda v: v.isNull() | F.isnan(v.cast("double")) | (F.abs(v.cast("double")) == float("inf"))
    ok = x.isNotNull() & F.col("vec_id").isNotNull() & ~F.exists(x, bad) & (F.size(x) > 0)
    return vectors.filter(ok).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda v: F.floor(v.cast("double") * SCALE).cast("long")).alias("w"))


def with_codes(rows: DataFrame) -> DataFrame:
    def run(batches):
        planes: dict[int, np.ndarray] = {}
        for b in batches:
            codes = []
            for v in b.column(1):
                r = v.values.to_numpy()
                if len(r) not in planes:
                    planes[len(r)] = np.random.default_rng(SEED + len(r)).standard_normal((PLANES, len(r)))
                side = (planes[len(r)] @ r > 0).astype(np.int64)
                codes.append(int((np.bitwise_xor.accumulate(side) << np.arange(PLANES - 1, -1, -1)).sum()))
            yield pa.RecordBatch.from_arrays([pa.array(codes, pa.int32()), b.column(0), b.column(1)], ["code", "vec_id", "w"])

    return rows.select("vec_id", "w").mapInArrow(run, "code int, vec_id long, w array<long>")


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best, by score and then the smaller id."""
    if len(scores) > 4 * k:
        least = np.partition(scores, len(scores) - k)[len(scores) - k]
        at = np.flatnonzero(scores >= least)
    else:
        at = np.arange(len(scores))
    return at[np.lexsort((ids[at], -scores[at]))][:k]


class Block:
    """A block's ids, forward index and term extremes; all arithmetic on exact integers."""

    def __init__(self, ids: bytes, rows: bytes):
        self.ids = np.frombuffer(ids, np.int64)
        self.rows = np.frombuffer(rows, np.int64).reshape(len(self.ids), -1)
        self.high, self.low = self.rows.max(0), self.rows.min(0)
        # 53-bit floats hold every product and sum exactly while weights stay small; else integers are used.
        peak = max(int(self.high.max(initial=0)), -int(self.low.min(initial=0)))
        self.exact = peak * peak * self.rows.shape[1] < 2**52
        self.forward = self.rows.astype(np.float64) if self.exact else self.rows

    def bounds(self, queries: np.ndarray) -> np.ndarray:
        return np.maximum(queries, 0) @ self.high + np.minimum(queries, 0) @ self.low

    def scores(self, query: np.ndarray) -> np.ndarray:
        return (self.forward @ query.astype(self.forward.dtype)).astype(np.int64)


def search_blocks(blocks: list[Block], query_ids: np.ndarray, queries: np.ndarray, floor: np.ndarray, k: int) -> tuple[list[tuple], int]:
    """(query_id, vec_id, score) of each query's k best within ``blocks`` at or above its floor; and the number of blocks scored."""
    bounds = np.stack([b.bounds(queries) for b in blocks], 1)
    visited, out = 0, []
    for i in range(len(queries)):
        top_s, top_i, kth = np.empty(0, np.int64), np.empty(0, np.int64), floor[i]
        for j in np.argsort(-bounds[i], kind="stable"):
            if bounds[i, j] < kth:
                break
            visited += 1
            s = blocks[j].scores(queries[i])
            at = np.flatnonzero((s >= kth) & (blocks[j].ids != query_ids[i]))
            if not len(at):
                continue
            top_s, top_i = np.concatenate([top_s, s[at]]), np.concatenate([top_i, blocks[j].ids[at]])
            keep = best(top_s, top_i, k)
            top_s, top_i = top_s[keep], top_i[keep]
            if len(top_s) == k:
                kth = max(kth, top_s[-1])
        out += [(int(query_ids[i]), int(v), int(s)) for s, v in zip(top_s, top_i)]
    return out, visited


def top_k(vectors: DataFrame, k: int = 5, every: int = 50) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k highest integer inner products among all rows but its own id.

    Queries are the rows whose vec_id is divisible by ``every``. Vectors that are null, empty or hold
    null or non-finite components take no part, nor do rows with a null vec_id. Ties go to the smaller vec_id. Rows that
    repeat a vec_id are candidates each; a repeated query row asks once per distinct vector. Vectors of another length than the query's
    aren't compared with it. Fewer than k candidates give fewer rows; an empty table gives none. Other columns are ignored.
    """
    rows = with_codes(usable(vectors))
    spread = rows.repartitionByRange(F.size("w"), "code", "vec_id").sortWithinPartitions(F.size("w"), "code", "vec_id")

    def build(batches):
        """Blocks of consecutive rows of one length."""
        held_ids, held = [], []

        def made():
            return pa.RecordBatch.from_arrays(
                [pa.array([len(held[0])], pa.int32()), pa.array([np.array(held_ids, np.int64).tobytes()], pa.binary()), pa.array([np.stack(held).tobytes()], pa.binary())], ["dims", "ids", "rows"]
            )

        for b in batches:
            for i, v in zip(b.column(1).to_pylist(), b.column(2)):
                r = v.values.to_numpy().astype(np.int64)
                if held and (len(held) >= BLOCK_ROWS or len(r) != len(held[0])):
                    yield made()
                    held_ids, held = [], []
                held_ids.append(i)
                held.append(r)
        if held:
            yield made()

    blocks = materialise(spread.mapInArrow(build, "dims int, ids binary, rows binary").withColumn("grp", F.floor(F.monotonically_increasing_id() / GROUP_BLOCKS)))

    def seed(batches):
        """Each query row against its own block: a first k-th score that later bounds are held against."""
        for b in batches:
            out = []
            for ids, data in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                block = Block(ids, data)
                for at in np.flatnonzero(block.ids % every == 0):
                    s = np.sort(block.scores(block.rows[at])[block.ids != block.ids[at]])
                    out.append((int(block.ids[at]), block.rows.shape[1], block.rows[at].tobytes(), int(s[-k]) if len(s) >= k else -(2**62)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int32(), pa.binary(), pa.int64()))], ["query_id", "dims", "query", "floor"])

    asked = blocks.select("dims", "ids", "rows").mapInArrow(seed, "query_id long, dims int, query binary, floor long")
    asked = asked.groupBy("query_id", "dims", "query").agg(F.max("floor").alias("floor"))
    asked = materialise(asked.withColumn("chunk", F.floor(F.monotonically_increasing_id() / CHUNK_QUERIES)))
    chunks = asked.groupBy("dims", "chunk").agg(F.count("*").alias("_n")).drop("_n")
    groups = blocks.groupBy("dims", "grp").agg(F.count("*").alias("_n")).drop("_n")
    tasks = materialise(chunks.join(groups, "dims").withColumn("task", F.monotonically_increasing_id()))  # query chunks by block groups

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        blocks_here = [Block(i, r) for i, r in zip(right.column("ids").to_pylist(), right.column("rows").to_pylist())]
        q = np.stack([np.frombuffer(x, np.int64) for x in left.column("query").to_pylist()]) if left.num_rows else np.empty((0, 0), np.int64)
        found = search_blocks(blocks_here, left.column("query_id").to_numpy(), q, left.column("floor").to_numpy(), k)[0] if blocks_here and len(q) else []
        cols = list(zip(*found)) or [()] * 3
        return pa.table([pa.array(c, pa.int64()) for c in cols], ["query_id", "vec_id", "score"])

    left = asked.join(tasks, ["dims", "chunk"]).select("task", "query_id", "query", "floor")
    right = blocks.join(tasks, ["dims", "grp"]).select(F.col("task").alias("block_task"), "ids", "rows")
    found = left.groupBy("task").cogroup(right.groupBy("block_task")).applyInArrow(search, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order).cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
