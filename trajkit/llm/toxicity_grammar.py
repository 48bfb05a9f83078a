"""Toxicity by a weighted finite-state pattern grammar.

Five small transducers read the word classes of a clause: insults and threats write weights,
targets strengthen, negation and reported speech weaken what follows them. Their product is one
deterministic table, composed once; a document's evidence is the sum of its matched clauses, and
a logistic curve turns evidence and its density into a score.

Insult stems are learned from labelled documents (whole words and word beginnings that mark
toxic documents), beside a short fixed list. Only clauses that hold an insult or a threat are
parsed; finding them is vectorised over word hashes.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.llm.common import Words, hash_word, pieces, segments
from trajkit.llm.labelled import fold, one_row_per_text, training_rows

#: Seed words of each class, in English, German, French and Spanish.
INSULTS = (
    "idiot moron clown scum trash pathetic disgusting loser worthless stupid imbecile bastard asshole bitch retard dumbass cretin filth vermin "
    "dummkopf arschloch abschaum schwachkopf versager connard imbécile salaud ordure abruti estúpido imbécil basura escoria inútil"
).split()
THREATS = "kill hurt destroy beat stab shoot burn töten schlagen tuer frapper matar golpear".split()
TARGETS = "you your you're youre u they them he she him her his their du dich dein ihr euch tu toi ton vous tú te vosotros usted".split()
NEGATIONS = "not no never isn't aren't don't doesn't nobody nothing nicht kein keine nie pas jamais nunca jamás".split()
REPORTS = "said says wrote writes called claimed quoted reported alleged sagte schrieb dit écrit dijo escribió".split()
CLASSES = ("other", "insult", "threat", "target", "negation", "report")
OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT = range(6)
PREFIXES = (4, 5, 6, 7)
#: A stem is learned if so many and such a share of toxic documents hold it, at such a log ratio of its rates per word.
MIN_DOCS, MIN_SHARE, MIN_WEIGHT, MAX_WEIGHT = 3, 0.012, 2.5, 8.0
#: So few documents are enough if they hold it so often.
FEW_DOCS, FEW_TIMES = 2, 6
SEED_WEIGHT = 5.0
REACH = 3  # words that a negation governs, and within which a threat needs its target
_CLAUSE_MARKS = np.zeros(256, bool)
_CLAUSE_MARKS[list(b".,;:!?\n")] = True


# ---- transducers: state, class -> next state, factor, amount ---------------------------------


@dataclass(frozen=True)
class Transducer:
    """``step(state, cls)`` gives the next state, a factor on weights written at this word, and an amount it writes itself."""

    states: tuple
    step: callable


def _negation(state: int, cls: int):
    return (REACH if cls == NEGATION else max(0, state - 1)), (0.4 if state and cls in (INSULT, THREAT) else 1.0), 0.0


def _reported(state: int, cls: int):
    return (1 if cls == REPORT else state), (0.5 if state and cls in (INSULT, THREAT) else 1.0), 0.0


def _target(state: int, cls: int):
    """1: a target was named, which strengthens what follows; 2: an insult came first, and a target after it adds to it."""
    if cls == TARGET:
        return 1, 1.0, (1.0 if state == 2 else 0.0)
    if cls == INSULT:
        return (state or 2), (1.5 if state == 1 else 1.0), 0.0
    return state, 1.0, 0.0


def _threat(state: int, cls: int):
    """A threat word writes only when its target follows closely."""
    if cls == THREAT:
        return REACH, 1.0, 0.0
    if cls == TARGET and state:
        return 0, 1.0, 5.0
    return max(0, state - 1), 1.0, 0.0


def _insult(state: int, cls: int):
    return 0, (1.0 if cls == INSULT else 0.0), 0.0


GRAMMAR = (
    Transducer(tuple(range(REACH + 1)), _negation), Transducer((0, 1), _reported), Transducer((0, 1, 2), _target),
    Transducer(tuple(range(REACH + 1)), _threat), Transducer((0,), _insult),
)


def compose(parts: tuple[Transducer, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The product automaton: next[state, class], factor[state, class] on the word's own weight, amount[state, class].

    An amount that one part writes is scaled by the factors that negation and report give at that place.
    """
    states = list(itertools.product(*(p.states for p in parts)))
    place = {s: k for k, s in enumerate(states)}
    nxt, factor, amount = (np.zeros((len(states), len(CLASSES)), t) for t in (np.int32, np.float64, np.float64))
    for s in states:
        weaken = (0.4 if s[0] else 1.0) * (0.5 if s[1] else 1.0)
        for c in range(len(CLASSES)):
            steps = [p.step(q, c) for p, q in zip(parts, s)]
            nxt[place[s], c] = place[tuple(x[0] for x in steps)]
            factor[place[s], c] = np.prod([x[1] for x in steps])
            amount[place[s], c] = weaken * sum(x[2] for x in steps)
    return nxt, factor, amount


NEXT, FACTOR, AMOUNT = compose(GRAMMAR)


def clause_score(classes, weights) -> float:
    """What the composed transducer writes over one clause."""
    state, total = 0, 0.0
    for c, w in zip(classes, weights):
        total += FACTOR[state, c] * w + AMOUNT[state, c]
        state = NEXT[state, c]
    return total


# ---- lexicon ----------------------------------------------------------------------------------


def _ranges(words: Words) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(length, word numbers, hashes): whole words (length 0) and word beginnings."""
    out = [(0, np.arange(len(words.start)), words.hashes())]
    size = words.end - words.start
    for k in PREFIXES:
        at = np.flatnonzero(size >= k)
        out.append((k, at, words.hashes(words.start[at], words.start[at] + k) ^ np.uint64(k)))
    return out


def _marks(texts: pa.Array, labels: np.ndarray) -> tuple[np.ndarray, dict[int, str], np.ndarray, np.ndarray, np.ndarray]:
    """Features of a few texts, the spelling of those in toxic ones, toxic texts that hold each, and its places in toxic and other texts."""
    words = Words(texts, lower=True, letters=True)
    docs, found, spelt = [], [], {}
    for k, at, h in _ranges(words):
        docs.append(words.doc[at])
        found.append(h)
        toxic = np.flatnonzero(labels[words.doc[at]] == 1)
        own, first = np.unique(h[toxic], return_index=True)
        for x, i in zip(own.tolist(), at[toxic[first]].tolist()):
            spelt.setdefault(x, bytes(words.data[words.start[i] : words.start[i] + k if k else words.end[i]]).decode(errors="replace") + "*" * bool(k))
    feature, doc = np.concatenate(found), np.concatenate(docs)
    order = np.lexsort((doc, feature))
    feature, doc = feature[order], doc[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (feature[1:] != feature[:-1])
    first = np.flatnonzero(np.diff(feature, prepend=~feature[:1]))
    toxic = labels[doc] == 1
    return feature[first], spelt, *(np.add.reduceat(x.astype(np.int64), first) if len(first) else np.empty(0, np.int64) for x in (toxic & new, toxic, ~toxic))


def _of_one_text(parts: list) -> tuple:
    """What _marks gives for a whole text, from its segments."""
    feature, place = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    spelt = {x: t for p in parts for x, t in p[1].items()}
    docs, yes, no = (np.bincount(place, np.concatenate([p[k] for p in parts]), len(feature)).astype(np.int64) for k in (2, 3, 4))
    return feature, spelt, np.minimum(docs, 1), yes, no


def learn_stems(rows: DataFrame) -> list[tuple[int, float, str]]:
    """(hash, weight, text): words and word beginnings that mark toxic documents; as many reach the driver as the bounded sample of rows holds."""
    texts = one_row_per_text(rows)
    counts = {r["label"]: (r["docs"], r["chars"]) for r in texts.groupBy("label").agg(F.count("*").alias("docs"), F.sum(F.length("text")).alias("chars")).collect()}
    (pos, pos_chars), (neg, neg_chars) = counts.get(1, (0, 0)), counts.get(0, (0, 0))
    if not pos or not neg:
        return []

    def features(batches):
        for b in pieces(batches):
            labels = b.column(1).to_numpy()
            parts = [_marks(part, labels) for part in segments(b.column(0))]
            own, stem, docs, yes, no = parts[0] if len(parts) == 1 else _of_one_text(parts)
            yield pa.RecordBatch.from_arrays([pa.array(own.astype(np.int64)), pa.array([stem.get(int(x)) for x in own], pa.string()), pa.array(docs), pa.array(yes), pa.array(no)], ["feature", "stem", "docs", "yes", "no"])

    table = texts.select("text", "label").mapInArrow(features, "feature long, stem string, docs long, yes long, no long")
    table = table.groupBy("feature").agg(F.max("stem").alias("stem"), *[F.sum(c).alias(c) for c in ("docs", "yes", "no")])
    weight = F.log(F.col("yes") / float(pos_chars)) - F.log((F.col("no") + 0.5) / float(neg_chars or 1))
    enough = (F.col("docs") >= MIN_DOCS) | ((F.col("docs") >= FEW_DOCS) & (F.col("yes") >= FEW_TIMES))
    table = table.filter((F.col("docs") >= MIN_SHARE * pos) & enough).withColumn("weight", weight).filter(F.col("weight") >= MIN_WEIGHT)
    return sorted((r["feature"], min(MAX_WEIGHT, r["weight"]), r["stem"]) for r in table.collect())


@dataclass
class Model:
    keys: np.ndarray  # sorted hashes of insult and threat stems
    classes: np.ndarray
    weights: np.ndarray
    curve: tuple[float, ...] = (-5.0, 1.5, 1.0, 0.3)
    stems: tuple = ()

    def __post_init__(self):
        self.door = np.zeros(1 << 16, bool)
        self.door[(self.keys & np.uint64(0xFFFF)).astype(np.int64)] = True
        self.cues = {w: c for c, ws in ((TARGET, TARGETS), (NEGATION, NEGATIONS), (REPORT, REPORTS)) for w in ws}


def build(stems: list[tuple[int, float, str]]) -> Model:
    table = {int(hash_word(w)): (INSULT, SEED_WEIGHT) for w in INSULTS} | {int(hash_word(w)): (THREAT, 0.0) for w in THREATS}
    for h, w, _ in stems:
        table[int(np.int64(h).astype(np.uint64))] = (INSULT, w)
    keys = np.array(sorted(table), np.uint64)
    return Model(keys, np.array([table[int(k)][0] for k in keys]), np.array([table[int(k)][1] for k in keys]), stems=tuple(s for _, _, s in stems))


def evidence(texts: pa.Array, model: Model) -> tuple[np.ndarray, list[tuple[int, int, int, float]]]:
    """Per text: the sum and the largest of its clauses' scores, its number of words; and (text, first byte, last byte, score) of each matched clause.

    A long text is read in segments that end at the end of a clause.
    """
    found, clauses, at = np.zeros((len(texts), 3)), [], 0
    for part in segments(texts, _CLAUSE_MARKS):
        own, matched = _evidence(part, model)
        found[:, [0, 2]] += own[:, [0, 2]]
        found[:, 1] = np.maximum(found[:, 1], own[:, 1])
        clauses += [(d, a + at, z + at, s) for d, a, z, s in matched]
        at += len(part[0].as_buffer()) if part is not texts else 0
    return found, clauses


def _evidence(texts: pa.Array, model: Model) -> tuple[np.ndarray, list[tuple[int, int, int, float]]]:
    words = Words(texts, lower=True, letters=True)
    found, clauses = np.zeros((len(texts), 3)), []
    found[:, 2] = np.diff(words.bounds)
    if not len(words.start):
        return found, clauses
    cls, weight = np.zeros(len(words.start), np.int64), np.zeros(len(words.start))
    for _, at, h in _ranges(words):
        some = np.flatnonzero(model.door[(h & np.uint64(0xFFFF)).astype(np.int64)])
        place = np.minimum(np.searchsorted(model.keys, h[some]), len(model.keys) - 1)
        hit = model.keys[place] == h[some]
        own, place = at[some[hit]], place[hit]
        cls[own] = np.where(cls[own] == INSULT, INSULT, model.classes[place])
        weight[own] = np.maximum(weight[own], model.weights[place])
    marked = np.flatnonzero(cls)
    if not len(marked):
        return found, clauses
    marks = np.cumsum(_CLAUSE_MARKS[words.data], dtype=np.int32)
    opens = np.ones(len(words.start), bool)
    opens[1:] = (marks[words.start[1:]] != marks[words.end[:-1] - 1]) | (words.doc[1:] != words.doc[:-1])
    first = np.flatnonzero(opens)
    ends = np.append(first[1:], len(words.start))
    for c in np.unique(np.searchsorted(first, marked, side="right") - 1).tolist():
        a, z = int(first[c]), int(ends[c])
        kinds = cls[a:z].copy()
        for i in range(a, z):
            if not kinds[i - a] and words.end[i] - words.start[i] <= 12:
                kinds[i - a] = model.cues.get(bytes(words.data[words.start[i] : words.end[i]]).decode(errors="replace"), OTHER)
        s = clause_score(kinds.tolist(), weight[a:z].tolist())
        d = int(words.doc[a])
        found[d, 0] += s
        found[d, 1] = max(found[d, 1], s)
        if s > 0:
            base = int(words.text_end[d - 1]) if d else 0
            clauses.append((d, int(words.start[a]) - base, int(words.end[z - 1]) - base, s))
    return found, clauses


def inputs_of(found: np.ndarray) -> np.ndarray:
    total, most, n = found.T
    return np.stack([np.ones(len(total)), np.log1p(total), np.log1p(20 * total / np.maximum(n, 20)), most / MAX_WEIGHT], 1)


def score_of(found: np.ndarray, curve) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(inputs_of(found) @ np.asarray(curve), -30, 30)))


def fit_curve(found: np.ndarray, label: np.ndarray, rounds: int = 100, ridge: float = 0.02) -> tuple[float, ...]:
    """Ridge logistic regression by damped Newton steps, slopes held at or above zero."""
    x = inputs_of(found)
    w = np.array([-3.0, *[1.0] * (x.shape[1] - 1)])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - label) + ridge * np.array([0, *w[1:]])
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.clip(np.linalg.solve(h, g), -2, 2)
        w = w - step
        w[1:] = np.maximum(w[1:], 0)
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in w)


def learn(docs: DataFrame, labels: DataFrame, parts: int = 4, held_out: int = 2) -> Model:
    """Stems and curve from at most labelled.SAMPLE_ROWS labelled documents outside the held-out fold; seeds alone without labels."""
    rows = training_rows(docs, labels, "toxic", parts, held_out)
    model = build(learn_stems(rows))

    def measure(batches):
        for b in pieces(batches):
            found, _ = evidence(b.column(1), model)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(found[:, k]) for k in range(3)), b.column(2)], ["doc_id", "total", "most", "n", "label"])

    got = rows.select("doc_id", "text", "label").mapInArrow(measure, "doc_id long, total double, most double, n double, label int").toPandas().sort_values("doc_id")
    if got["label"].nunique() == 2:
        model.curve = fit_curve(got[["total", "most", "n"]].to_numpy(), got["label"].to_numpy().astype(float))
    return model


def toxicity(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, parts: int = 4, held_out: int = 2) -> DataFrame:
    """doc_id, held_out, score, predicted, n_clauses for every row; whole texts are parsed.

    Null or empty text: no evidence, so the lowest score. Null doc_id: scored, held_out null. Repeated rows score alike.
    Labels, language, source and id are no inputs of a score. Empty table: no rows.
    """
    model = learn(docs, labels, parts, held_out)

    def run(batches):
        for b in pieces(batches):
            found, clauses = evidence(b.column(1), model)
            hits = np.bincount([c[0] for c in clauses], minlength=b.num_rows) if clauses else np.zeros(b.num_rows, np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score_of(found, model.curve)), pa.array(hits.astype(np.int64))], ["doc_id", "score", "n_clauses"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double, n_clauses long")
    return out.select("doc_id", (fold(F.col("doc_id"), parts) == held_out).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_clauses")


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with their own columns, in one pass."""
    model, names, place = learn(docs, labels), docs.columns, docs.columns.index("text")

    def run(batches):
        for b in pieces(batches):
            found, _ = evidence(b.column(place), model)
            yield b.filter(pa.array(score_of(found, model.curve) < threshold))

    return docs.mapInArrow(run, docs.schema).select(*names)
