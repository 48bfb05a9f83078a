"""Packing along a space-filling curve.

Each document's words are hashed into a few projected coordinates; the Hilbert index of that
point is its place on the curve. Documents are range-partitioned and sorted by that index,
so neighbours on the curve share sequences, and every partition is packed as a stream: pieces
are cut at the sequence length, and what is left at a partition's end is cut into sequences
whose lengths are powers of two, which need no padding.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.llm.common import Words, _mix, pieces, segments, tidy
from trajkit.llm.tokens_bpe import id_arrays

DIMS, BITS = 3, 10
#: One document in so many sets the ranges of the curve.
SAMPLE_ONE_IN = 16
NAMES = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def hilbert_index(points: np.ndarray, bits: int) -> np.ndarray:
    """Place on the Hilbert curve of integer points (rows), by the public transpose algorithm, for all rows at once."""
    x = [points[:, k].astype(np.int64) for k in range(points.shape[1])]
    n = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(n):
            high = (x[i] & q) != 0
            t = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ t)
            if i:
                x[i] = x[i] ^ t
        q >>= 1
    for i in range(1, n):
        x[i] = x[i] ^ x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where((x[n - 1] & q) != 0, t ^ (q - 1), t)
        q >>= 1
    x = [v ^ t for v in x]
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for v in x:
            out = (out << 1) | ((v >> b) & 1)
    return out


def curve_keys(texts: pa.Array) -> np.ndarray:
    """Hilbert index of each text's hashed word vector, projected to DIMS coordinates in [-1, 1]."""
    n, sums = np.zeros(len(texts), np.int64), np.zeros((len(texts), DIMS))
    for part in segments(texts):
        words = Words(part, lower=True)
        h = words.hashes()
        n += np.diff(words.bounds)
        for k in range(DIMS):
            value = ((h >> np.uint64(20 * k)) & np.uint64(0xFFFF)).astype(np.float64) / 32767.5 - 1
            sums[:, k] += np.bincount(words.doc, value, len(texts))
    # A mean of n terms has spread n**-0.5; frequent words dominate it, so texts of one kind stay close.
    spread = np.tanh(sums / np.maximum(n, 1)[:, None] * np.sqrt(np.minimum(n, 64))[:, None])
    points = np.where(n[:, None] > 0, np.clip((spread + 1) / 2 * ((1 << BITS) - 1), 0, (1 << BITS) - 1), 0).astype(np.int64)
    return hilbert_index(points, BITS)


def _places(ids: pa.Array, texts: pa.Array) -> np.ndarray:
    """30 bits of curve, then 32 bits of a hash of the id, so that many documents at one point still spread over partitions."""
    tie = _mix(ids.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).astype(np.uint64)) >> np.uint64(32)
    return (curve_keys(texts) << 32) | tie.astype(np.int64)


def with_curve_key(docs: DataFrame, partitions: int) -> DataFrame:
    """place, part, doc_id, text: the place along the curve and the range of places, by quantiles of a hash sample of all documents.

    The sample shapes only how many documents a partition gets; it spares the second scan that a range exchange would make.
    """

    def sample(batches):
        for b in pieces(batches):
            yield pa.RecordBatch.from_arrays([pa.array(_places(b.column(0), b.column(1)))], ["place"])

    def keys(batches):
        edges = np.array(cuts, np.int64)
        for b in pieces(batches):
            place = _places(b.column(0), b.column(1))
            part = np.searchsorted(edges, place, side="right").astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(place), pa.array(part), b.column(0), b.column(1)], ["place", "part", "doc_id", "text"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    some = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE_ONE_IN)) == 0).mapInArrow(sample, "place long")
    shares = [k / partitions for k in range(1, partitions)]
    cuts = (some.agg(F.percentile_approx("place", shares, 20 * partitions)).first()[0] if shares else None) or []
    return rows.mapInArrow(keys, "place long, part int, doc_id long, text string")


def pack(docs: DataFrame, length: int = 2048, end_id: int = 1, json_file: str = "byte_bpe_50k.json", with_ids: bool = False) -> DataFrame:
    """Pieces of documents in sequences of at most ``length`` ids; each id of each document (its end id included) lies in one piece.

    A null or empty text is its end id alone. Repeated rows are separate documents. A null doc_id is packed
    and keeps its null. Empty table: no rows. Sequences never span partitions; sequence_id is the partition's number
    times 2**32 plus a running number, and depends only on the sorted rows, so a re-run task gives the same pieces.
    ``with_ids`` adds the ids themselves as an array, for a writer of training files.
    """
    if length & (length - 1):
        raise ValueError("length must be a power of two")

    def packed(batches):
        from pyspark import TaskContext

        encode = id_arrays(json_file)
        base = TaskContext.get().partitionId() << 32
        ready: list[tuple] = []  # pieces of finished sequences
        held: list[tuple] = []  # pieces of the sequence that is being filled
        sequence, filled = 0, 0

        def piece(doc, start, ids, total, seq, offset):
            return doc, start, len(ids), zlib.crc32(ids), total, base + seq, offset, ids

        def finished(rows):
            return rows if with_ids else [r[:7] for r in rows]

        def batch_of(rows):
            cols = list(zip(*rows))
            made, names = [pa.array(c, pa.int64()) for c in cols[:7]], NAMES
            if with_ids:
                made, names = [*made, pa.array([a.tolist() for a in cols[7]], pa.list_(pa.int32()))], [*NAMES, "ids"]
            return pa.RecordBatch.from_arrays(made, names)

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = np.concatenate([*encode(text.as_py()), np.array([end_id], "<u4")])
                at = 0
                while at < len(ids):
                    n = min(length - filled, len(ids) - at)
                    held.append(piece(doc, at, ids[at : at + n], len(ids), sequence, filled))
                    at, filled = at + n, filled + n
                    if filled == length:
                        ready += finished(held)
                        held, filled, sequence = [], 0, sequence + 1
                if len(ready) >= 4096:
                    yield batch_of(ready)
                    ready = []
        # The rest is cut anew into sequences whose lengths are the powers of two that add up to it.
        room, offset = (1 << (filled.bit_length() - 1)) if filled else 0, 0
        for doc, start, _, _, total, _, _, ids in held:
            at = 0
            while at < len(ids):
                n = min(room - offset, len(ids) - at)
                ready += finished([piece(doc, start + at, ids[at : at + n], total, sequence, offset)])
                at, offset, filled = at + n, offset + n, filled - n
                if offset == room:
                    sequence, offset = sequence + 1, 0
                    room = (1 << (filled.bit_length() - 1)) if filled else 0
        if ready:
            yield batch_of(ready)
        tidy()

    partitions = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keyed = with_curve_key(docs, partitions).repartitionById(partitions, F.col("part")).sortWithinPartitions("place", "doc_id", "text")
    return keyed.select("doc_id", "text").mapInArrow(packed, SCHEMA + (", ids array<int>" if with_ids else ""))
