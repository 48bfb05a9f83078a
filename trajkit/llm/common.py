"""Helpers that several operators share: shared-folder materialisation and vectorised word kernels.

Memory: a batch is cut into pieces of about ``PIECE`` bytes, and a longer text into segments of about that size, so every
temporary is bounded by that constant and not by the longest text. What an operator keeps of one text (its set of
shingles, its ids) is as long as the text by nature.
"""

from __future__ import annotations

import ctypes
import hashlib
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: The white space of the word pattern [^\x20\x09-\x0D]+.
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: Bytes of text that are worked on at once.
PIECE = 1 << 19


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; one of our own only where it is unset on a local master (tests)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="trajkit-"))
    return spark.sparkContext.getCheckpointDir()


def materialise(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/trajkit/{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(*tables: DataFrame) -> None:
    """Delete materialised tables that nothing reads any more (what was made of them has been materialised itself)."""
    for df in tables:
        spark = df.sparkSession
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if "/trajkit/" in folder:
                path = spark._jvm.org.apache.hadoop.fs.Path(folder)
                path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def _mix(x: np.ndarray) -> np.ndarray:
    """The public splitmix64 finaliser on an array of uint64."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_GOLDEN = np.uint64(0x9E3779B97F4A7C15)
#: Words of more bytes are hashed one by one.
_LONG_WORD = 128
_MASKS = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
SPACES = np.zeros(256, bool)
SPACES[list(SPACE_BYTES)] = True
LETTERS = np.zeros(256, bool)
LETTERS[[*range(65, 91), *range(97, 123), *range(128, 256), 39]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


class Words:
    """Words of a batch of UTF-8 texts, as byte ranges, with 64-bit hashes computed for all words at once.

    ``data`` holds the joined bytes, one space between texts and eight zero bytes at the end; ``start``/``end`` are the
    byte ranges of words, ``doc`` the text that each belongs to, ``bounds`` the first word of each text (length texts + 1).
    ``lower`` maps A-Z to a-z. ``letters`` splits at all that isn't a letter.
    """

    def __init__(self, texts: pa.Array, lower: bool = False, letters: bool = False):
        raw = [memoryview(v.as_buffer()) if v.is_valid else b"" for v in texts]
        sizes = np.fromiter((len(x) + 1 for x in raw), np.int64, len(raw))
        self.text_end = np.cumsum(sizes)
        self.data = np.frombuffer(b" ".join([*raw, b"\0" * 8]), np.uint8)
        size = int(self.text_end[-1]) if len(raw) else 0
        edges, last = [], False
        for at in range(0, size, PIECE):
            part = self.data[at : min(size, at + PIECE)]
            is_word = LETTERS[part] if letters else ~SPACES[part]
            change = np.flatnonzero(is_word[1:] != is_word[:-1]) + (at + 1)
            edges.append(np.concatenate([[at], change]) if bool(is_word[0]) != last else change)
            last = bool(is_word[-1])
        if last:
            edges.append(np.array([size]))
        edge = np.concatenate(edges) if edges else np.empty(0, np.int64)
        self.start, self.end = edge[0::2], edge[1::2]
        if lower:
            self.data = _LOWER[self.data]
        self.bounds = np.concatenate([[0], np.searchsorted(self.start, self.text_end)])
        self.doc = np.repeat(np.arange(len(raw)), np.diff(self.bounds))

    def hashes(self, start: np.ndarray | None = None, end: np.ndarray | None = None) -> np.ndarray:
        """64-bit hashes of byte ranges (words by default): eight bytes a step, mixed in turn; long words one by one."""
        start = self.start if start is None else start
        end = self.end if end is None else end
        size = end - start
        eight = np.ndarray((len(self.data) - 7,), "<u8", self.data, 0, (1,))  # the eight bytes from each place on
        out = size.astype(np.uint64) * _GOLDEN
        out = _mix(out ^ (eight[start] & _MASKS[np.minimum(size, 8)]))
        some, done = np.flatnonzero((size > 8) & (size <= _LONG_WORD)), 8
        while len(some):
            left = np.minimum(size[some] - done, 8)
            out[some] = _mix(out[some] * _GOLDEN ^ (eight[start[some] + done] & _MASKS[left]))
            done += 8
            some = some[size[some] > done]
        for k in np.flatnonzero(size > _LONG_WORD).tolist():
            out[k] = int.from_bytes(hashlib.blake2b(self.data[start[k] : end[k]], digest_size=8).digest(), "little")
        return out


def hash_word(word: str) -> np.uint64:
    """The hash that Words gives to one word."""
    w = Words(pa.array([word]))
    return w.hashes(np.array([0]), np.array([len(w.data) - 9]))[0]


def tidy() -> None:
    """Hand freed memory back to the system, so that idle workers that wait for the next task don't hold it."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to hand back by this way
        pass


def pieces(batches, rows: int = 256) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches into slices of at most ``rows`` rows and about ``PIECE`` bytes (a longer row is a slice of its own)."""
    for batch in batches:
        at = 0
        while at < batch.num_rows:
            n = min(rows, batch.num_rows - at)
            while n > 1 and batch.slice(at, n).nbytes > PIECE:
                n //= 2
            yield batch.slice(at, n)
            at += n
    tidy()


def cuts(data: np.ndarray, ends: np.ndarray, size: int) -> Iterator[tuple[int, int]]:
    """Ranges of about ``size`` bytes that cover ``data``; each but the last ends behind a byte that ``ends`` (a table of 256) marks."""
    at, total = 0, len(data)
    while at < total:
        z = at + size
        while z < total:
            marks = np.flatnonzero(ends[data[z - size : z]])
            if len(marks):
                z = z - size + int(marks[-1]) + 1
                break
            z += size
        z = min(z, total)
        yield at, z
        at = z


def segments(texts: pa.Array, ends: np.ndarray = SPACES) -> Iterator[pa.Array]:
    """The texts as they are; a single text of more than twice ``PIECE`` bytes as one-row arrays of its segments, in order.

    Every array has as many rows as ``texts``, so per-text sums can be added up over them.
    """
    if len(texts) != 1 or not texts[0].is_valid or len(texts[0].as_buffer()) <= 2 * PIECE:
        yield texts
        return
    data = np.frombuffer(texts[0].as_buffer(), np.uint8)
    for a, z in cuts(data, ends, PIECE):
        yield pa.array([data[a:z].tobytes()], pa.binary())
