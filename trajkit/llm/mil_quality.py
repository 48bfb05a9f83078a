"""Quality classification by attention-based multiple-instance learning.

A document is a bag of passages of a fixed number of words. Every passage is encoded from
vectorised counts (letters, symbols, repeats, lengths, hashed words); a gated attention, learned
from document labels alone, weighs the passages, and the weighted representation is scored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.llm import common
from trajkit.llm.common import SPACES, Words, cuts, pieces
from trajkit.llm.labelled import fold, training_rows

PASSAGE_WORDS = 96
HASHED = 8
ENCODED, GATE = 24, 12
EPOCHS, BATCH, RATE, SEED = 40, 256, 0.01, 11


def _byte_class(chars: bytes) -> np.ndarray:
    out = np.zeros(256, np.uint8)
    out[list(chars)] = 1
    return out


_CLASSES = [
    _byte_class(bytes(range(65, 91))), _byte_class(bytes(range(97, 123))), _byte_class(bytes(range(48, 58))), _byte_class(b"#*$%&"),
    _byte_class(b"|<>"), _byte_class(b"!?"), _byte_class(b".,;:"), _byte_class(bytes(range(128, 256))),
]
_NEW_LINE = _byte_class(b"\n")
N_FEATURES, _TEXT_SIZE = len(_CLASSES) + 9 + HASHED, len(_CLASSES) + 8
#: Passages of one training text that are learned from at most, evenly spaced; scoring uses all of them.
TRAIN_PASSAGES = 256


def passages(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages of all texts, and the first passage of each text (texts + 1 places). A text without words is one zero passage."""
    if len(texts) == 1 and texts[0].is_valid and len(texts[0].as_buffer()) > 2 * common.PIECE:
        return _of_long_text(np.frombuffer(texts[0].as_buffer(), np.uint8))
    return _encoded(Words(texts))


def _encoded(words: Words) -> tuple[np.ndarray, np.ndarray]:
    n = np.diff(words.bounds)
    count = np.maximum(1, -(-n // PASSAGE_WORDS))
    first = np.concatenate([[0], np.cumsum(count)])
    out = np.zeros((first[-1], N_FEATURES))
    if not len(words.start):
        return out, first
    within = np.arange(len(words.start)) - words.bounds[words.doc]
    own = first[words.doc] + within // PASSAGE_WORDS
    starts = np.flatnonzero(np.diff(own, prepend=-1))
    ends = np.append(starts[1:], len(own))
    rows = own[starts]
    size = ends - starts
    a, z = words.start[starts], words.end[ends - 1]
    span = np.maximum(z - a, 1)
    limits = np.stack([a, z], 1).ravel()  # the data end with spare bytes, so every limit is a place in them

    def inside(table: np.ndarray) -> np.ndarray:
        return np.add.reduceat(table[words.data], limits, dtype=np.int64)[::2]

    for k, c in enumerate(_CLASSES):
        out[rows, k] = inside(c) / span
    k = len(_CLASSES)
    length = np.minimum(words.end - words.start, 64).astype(np.float64)
    mean = np.add.reduceat(length, starts) / size
    out[rows, k] = mean / 10
    out[rows, k + 1] = np.sqrt(np.maximum(0, np.add.reduceat(length**2, starts) / size - mean**2)) / 10
    h = words.hashes()
    for j, lag in enumerate((1, 2, 3, 7)):
        same = np.zeros(len(h))
        same[lag:] = (h[lag:] == h[:-lag]) & (own[lag:] == own[:-lag])
        out[rows, k + 2 + j] = np.add.reduceat(same, starts) / size
    out[rows, k + 6] = inside(_NEW_LINE) / size
    out[rows, k + 7] = np.log1p(size) / 5
    out[rows, _TEXT_SIZE] = np.log1p(n[words.doc[starts]]) / 8
    for j in range(HASHED):
        out[rows, k + 9 + j] = np.add.reduceat(((h >> np.uint64(8 * j)) & np.uint64(0xFF)).astype(np.float64) / 127.5 - 1, starts) / size
    return out, first


def _of_long_text(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same for one long text, in segments of whole passages."""
    words_of = lambda a, z: Words(pa.array([data[a:z].tobytes()], pa.binary()))
    found, n, at, size = [], 0, 0, common.PIECE
    while at < len(data):
        z = at + next(cuts(data[at:], SPACES, size))[1]
        words = words_of(at, z)
        whole = len(words.start)
        if z < len(data):
            whole -= whole % PASSAGE_WORDS
            if not whole:  # very long words: look further
                size *= 2
                continue
            if whole < len(words.start):
                z = at + int(words.start[whole])
                words = words_of(at, z)
        if whole:
            found.append(_encoded(words)[0])
        n, at, size = n + whole, z, common.PIECE
    if not found:
        return np.zeros((1, N_FEATURES)), np.array([0, 1])
    out = np.concatenate(found)
    out[:, _TEXT_SIZE] = np.log1p(n) / 8
    return out, np.array([0, len(out)])


def _softmax_by(x: np.ndarray, first: np.ndarray, doc: np.ndarray) -> np.ndarray:
    e = np.exp(x - np.maximum.reduceat(x, first[:-1])[doc])
    return e / np.add.reduceat(e, first[:-1])[doc]


class GatedAttention:
    """tanh encoder, gated attention over a bag, logistic head; plain numpy with Adam."""

    def __init__(self, d: int, seed: int = SEED):
        r = np.random.default_rng(seed)
        g = lambda *s: r.standard_normal(s) / np.sqrt(s[0])
        self.p = {"W": g(d, ENCODED), "b": np.zeros(ENCODED), "V": g(ENCODED, GATE), "U": g(ENCODED, GATE), "w": g(GATE), "c": g(ENCODED), "k": np.zeros(1)}
        self.mean, self.std = np.zeros(d), np.ones(d)

    def forward(self, x: np.ndarray, first: np.ndarray):
        p, doc = self.p, np.repeat(np.arange(len(first) - 1), np.diff(first))
        e = np.tanh(x @ p["W"] + p["b"])
        t, s = np.tanh(e @ p["V"]), 1 / (1 + np.exp(-(e @ p["U"])))
        a = _softmax_by((t * s) @ p["w"], first, doc)
        z = np.add.reduceat(a[:, None] * e, first[:-1], axis=0)
        return e, t, s, a, z, doc, 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["k"], -30, 30)))

    def gradients(self, x, first, y, ridge: float = 1e-4):
        p = self.p
        e, t, s, a, z, doc, out = self.forward(x, first)
        d = (out - y) / len(y)
        dz = np.outer(d, p["c"])[doc]
        da = (dz * e).sum(1)
        de = a[:, None] * dz
        du = a * (da - np.add.reduceat(a * da, first[:-1])[doc])  # through the softmax
        dt, ds = np.outer(du, p["w"]) * s, np.outer(du, p["w"]) * t
        dt, ds = dt * (1 - t * t), ds * s * (1 - s)
        de = de + dt @ p["V"].T + ds @ p["U"].T
        de = de * (1 - e * e)
        g = {"W": x.T @ de, "b": de.sum(0), "V": e.T @ dt, "U": e.T @ ds, "w": (t * s).T @ du, "c": z.T @ d, "k": np.array([d.sum()])}
        return {k: v + ridge * p[k] for k, v in g.items()}

    def fit(self, x: np.ndarray, first: np.ndarray, y: np.ndarray, seed: int = SEED):
        self.mean, self.std = x.mean(0), x.std(0) + 1e-6
        x, r = (x - self.mean) / self.std, np.random.default_rng(seed)
        m, v, step = {k: 0.0 for k in self.p}, {k: 0.0 for k in self.p}, 0
        size = np.diff(first)
        for _ in range(EPOCHS):
            order = r.permutation(len(y))
            for at in range(0, len(y), BATCH):
                docs = order[at : at + BATCH]
                rows = np.concatenate([np.arange(first[i], first[i + 1]) for i in docs])
                g = self.gradients(x[rows], np.concatenate([[0], np.cumsum(size[docs])]), y[docs])
                step += 1
                for k in self.p:
                    m[k] = 0.9 * m[k] + 0.1 * g[k]
                    v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                    self.p[k] = self.p[k] - RATE * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def score(self, x: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Scores of bags, and the attention weight of each passage."""
        _, _, _, a, _, _, out = self.forward((x - self.mean) / self.std, first)
        return out, a


def learn(docs: DataFrame, labels: DataFrame, parts: int = 5, held_out: int = 0) -> GatedAttention | float:
    """A model from at most labelled.SAMPLE_ROWS labelled documents, and TRAIN_PASSAGES passages of each; with labels of one kind only, their value; without any, 0.5."""
    rows = training_rows(docs, labels, "quality", parts, held_out)

    def encode(batches):
        for b in pieces(batches):
            x, first = passages(b.column(1))
            bags = [x[i:j] if j - i <= TRAIN_PASSAGES else x[np.linspace(i, j - 1, TRAIN_PASSAGES).astype(int)] for i, j in zip(first[:-1], first[1:])]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([bag.astype(np.float32).tobytes() for bag in bags], pa.binary())], ["doc_id", "label", "bag"])

    got = rows.select("doc_id", "text", "label").mapInArrow(encode, "doc_id long, label int, bag binary").toPandas().sort_values("doc_id", kind="stable")
    if got["label"].nunique() < 2:
        return float(got["label"].iloc[0]) if len(got) else 0.5
    bags = [np.frombuffer(b, np.float32).reshape(-1, N_FEATURES).astype(np.float64) for b in got["bag"]]
    first = np.concatenate([[0], np.cumsum([len(b) for b in bags])])
    return GatedAttention(N_FEATURES).fit(np.concatenate(bags), first, got["label"].to_numpy().astype(float))


def quality(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, parts: int = 5, held_out: int = 0) -> DataFrame:
    """doc_id, held_out, score, predicted, n_passages, top_passage (the one with the most attention) for every row.

    Null or empty text: one empty passage, scored like any other. Null doc_id: scored, held_out null. Repeated rows score
    alike. Whole texts are encoded. Labels, language, source and id are no inputs of a score. Empty table: no rows.
    """
    model = learn(docs, labels, parts, held_out)

    def run(batches):
        for b in pieces(batches):
            x, first = passages(b.column(1))
            if isinstance(model, float):
                score, weight = np.full(b.num_rows, model), np.ones(len(x))
            else:
                score, weight = model.score(x, first)
            top = [int(np.argmax(weight[i:j])) for i, j in zip(first[:-1], first[1:])]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score), pa.array(np.diff(first).astype(np.int64)), pa.array(top, pa.int64())], ["doc_id", "score", "n_passages", "top_passage"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double, n_passages long, top_passage long")
    return out.select("doc_id", (fold(F.col("doc_id"), parts) == held_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_passages", "top_passage")
