"""Toxicity from a logistic regression whose scores may not depend on which group a sentence names.

Features are the words of a text and the beginnings of its words, each present or not. Every training text has counterfactuals: a group term
is put into it, and another of the same ring in its place; where it names groups itself, they are swapped, and left out. The loss adds the
squared differences of the scores of a text and its counterfactuals, so that a neutral mention of a group weighs as much as that of another,
and next to nothing. Weights are kept for features whose share differs between the labels, and for those of all group terms.

Defined cases: a null or empty text has no features and gets the score of the intercept; with no training labels, or labels of one
kind, every score is that kind's share (0 without any). Repeated rows get a row each; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import held_out, table, training_rows
from diversify.llm.textblocks import U, Words, mixed, slices

#: Most labelled documents that training takes, most features that get a weight, and weight of the counterfactual penalty.
SAMPLE, FEATURES, FAIRNESS = 6000, 4096, 1.0
#: Group terms put into each training text.
INSERTED = 2
THRESHOLD = 0.7
BITS, BEGINNINGS = 20, (4, 5, 6, 7)

# Terms that name groups of people, in rings; a swap takes the next of the ring.
IDENTITY = (
    ("women", "men"), ("woman", "man"), ("girls", "boys"), ("girl", "boy"), ("female", "male"), ("mother", "father"), ("wife", "husband"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"), ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino"), ("african", "european", "american", "mexican", "chinese", "indian", "arab"),
    ("gay", "straight", "lesbian", "bisexual"), ("transgender", "cisgender"), ("immigrant", "native"), ("immigrants", "natives"),
    ("old", "young"), ("disabled", "blind", "deaf"), ("femmes", "hommes"), ("femme", "homme"), ("frauen", "männer"), ("frau", "mann"),
    ("mujeres", "hombres"), ("mujer", "hombre"), ("musulman", "chrétien", "juif"), ("muslimisch", "christlich", "jüdisch"), ("musulmán", "cristiano", "judío"),
)
#: Neutral sentences for ``neutral_mentions``.
NEUTRAL = (
    "the GROUP neighbour reads a book in the garden", "a GROUP teacher answered all questions of the class", "my GROUP friend cooked dinner for us",
    "the report counts GROUP workers in the town", "GROUP families came to the concert", "she wrote about the history of GROUP people",
)
NEXT = {a.encode(): b.encode() for ring in IDENTITY for a, b in pairwise((*ring, ring[0]))}
_POINTS = np.isin(np.arange(256), list(b".,;:!?\"')"))


def features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(text, feature) of the distinct features, in order."""
    words = Words(texts, lower=True)
    if not words.n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    letters, ends = words.letters(), words.ends.copy()
    for _ in range(2):
        ends -= _POINTS[words.bytes[np.maximum(ends - 1, 0)]] & (ends - words.starts > 1)
    size = ends - words.starts
    found = [(words.doc, letters.of(words.starts, ends))]
    for n in BEGINNINGS:
        long = size >= n
        found.append((words.doc[long], mixed(letters.of(words.starts[long], words.starts[long] + n) + U(n))))
    doc, value = (np.concatenate(x) for x in zip(*found, strict=True))
    both = np.unique((doc.astype(U) << U(BITS)) | (value >> U(64 - BITS)))
    return (both >> U(BITS)).astype(np.int64), (both & U((1 << BITS) - 1)).astype(np.int64)


def counterfactuals(text: bytes) -> tuple[bytes, bytes] | None:
    """The text with its groups swapped, and with them left out; None where it names no group.

    The second keeps the model from finding all groups equally toxic.
    """
    words = text.lower().split()
    bare = [w.strip(b".,;:!?\"'()") for w in words]
    if not any(w in NEXT for w in bare):
        return None
    return b" ".join(NEXT.get(w, w) for w in bare), b" ".join(w for w in bare if w not in NEXT)


@dataclass
class GroupBlindModel:
    weights: np.ndarray  # by feature
    bias: float

    def scores(self, texts: list[bytes]) -> np.ndarray:
        doc, feature = features(texts)
        level = self.bias + np.bincount(doc, weights=self.weights[feature], minlength=len(texts))
        return 1 / (1 + np.exp(-np.clip(level, -30, 30)))


def pairs_of(rows: list[tuple[int, np.ndarray, list[np.ndarray]]]) -> list[tuple[np.ndarray, np.ndarray]]:
    """(features that only the one has, that only the other has) of each text and its counterfactuals."""
    terms = list(NEXT)
    alone = dict(zip(terms, np.split(*_by_text(terms)), strict=True))
    out = []
    for _, own, twins in rows:
        out += [(np.setdiff1d(own, twin), np.setdiff1d(twin, own)) for twin in twins]
        for k in range(INSERTED):
            term = terms[int(mixed(np.array([own.sum() * INSERTED + k], U))[0] % U(len(terms)))]
            one, other = np.setdiff1d(alone[term], own), np.setdiff1d(alone[NEXT[term]], own)
            out += [(one, one[:0]), (np.setdiff1d(one, other), np.setdiff1d(other, one))]
    return out


def _by_text(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The features of some texts one after the other, and where the next text's begin."""
    doc, feature = features(texts)
    return feature, np.searchsorted(doc, np.arange(1, len(texts)))


def fit(rows: list[tuple[int, np.ndarray, list[np.ndarray]]], rounds: int = 300, penalty: float = 2e-4, fairness: float = FAIRNESS) -> GroupBlindModel:
    """rows: label, features, features of the counterfactuals of a text that names groups itself."""
    y = np.array([r[0] for r in rows], float)
    if len(set(y.tolist())) < 2:
        share = float(y.mean()) if len(y) else 0.0
        return GroupBlindModel(np.zeros(1 << BITS), 30.0 if share else -30.0)
    count = lambda keep: np.bincount(np.concatenate([f for (_, f, _), k in zip(rows, keep, strict=True) if k]), minlength=1 << BITS)
    one, none = count(y == 1), count(y == 0)
    n1, n0 = y.sum(), (1 - y).sum()
    share = (one + none + 1) / (n1 + n0 + 2)
    z = np.abs(one / n1 - none / n0) / np.sqrt(share * (1 - share) * (1 / n1 + 1 / n0))
    z[(one + none < 3) | (z < 3)] = 0
    groups = np.unique(features([b" ".join(NEXT)])[1])
    chosen = np.union1d(np.argsort(-z, kind="stable")[: min(FEATURES, int((z > 0).sum()))], groups)
    place = np.full(1 << BITS, -1)
    place[chosen] = np.arange(len(chosen))

    def matrix(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        row, col = np.repeat(np.arange(len(sets)), [len(s) for s in sets]), place[np.concatenate([*sets, np.zeros(0, np.int64)])]
        return row[col >= 0], col[col >= 0]

    row, col = matrix([r[1] for r in rows])
    pairs = pairs_of(rows)
    (r1, c1), (r2, c2) = matrix([a for a, _ in pairs]), matrix([b for _, b in pairs])
    w, bias, m, v = np.zeros(len(chosen) + 1), float(np.log(n1 / n0)), 0.0, 0.0
    w[-1] = bias
    for step in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(w[-1] + np.bincount(row, weights=w[col], minlength=len(y)), -30, 30)))
        slope = np.append(np.bincount(col, weights=(p - y)[row], minlength=len(chosen)), (p - y).sum()) / len(y)
        gap = np.bincount(r1, weights=w[c1], minlength=len(pairs)) - np.bincount(r2, weights=w[c2], minlength=len(pairs))
        change = np.bincount(c1, weights=gap[r1], minlength=len(chosen)) - np.bincount(c2, weights=gap[r2], minlength=len(chosen))
        slope[:-1] += 2 * fairness / len(pairs) * change
        slope[:-1] += penalty * w[:-1]
        m, v = 0.9 * m + 0.1 * slope, 0.99 * v + 0.01 * slope**2
        w = w - 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
    weights = np.zeros(1 << BITS)
    weights[chosen] = w[:-1]
    return GroupBlindModel(weights, float(w[-1]))


def neutral_mentions(model: GroupBlindModel) -> dict[str, float]:
    """How the model takes neutral sentences that name a group: the share scored as toxic, and the mean and largest change beside the sentence without it."""
    texts = [s.encode() for s in NEUTRAL]
    named = [s.replace(b"GROUP", t) for s in texts for t in NEXT]
    plain = np.repeat(model.scores([s.replace(b"GROUP ", b"") for s in texts]), len(NEXT))
    found = model.scores(named)
    return {"false_positives": float((found >= THRESHOLD).mean()), "mean_change": float(np.abs(found - plain).mean()), "largest_change": float(np.abs(found - plain).max())}


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE, fairness: float = FAIRNESS) -> GroupBlindModel:
    """The model for ``labels.toxic``; features are made where the texts are, and those of at most ``most`` documents come to the driver."""

    def made(batches):
        for batch in batches:
            for first, texts in slices(batch.column("text")):
                other = [counterfactuals(t) for t in texts]
                split = lambda d, f: [f[a:b].astype(np.int32).tobytes() for a, b in pairwise(np.searchsorted(d, np.arange(len(texts) + 1)))]  # noqa: E731, B023
                own, swap, none = split(*features(texts)), split(*features([t[0] if t else b"" for t in other])), split(*features([t[1] if t else b"" for t in other]))
                named = pa.array([t is not None for t in other])
                yield pa.RecordBatch.from_arrays([batch.column("y").slice(first, len(texts)), pa.array(own, pa.binary()), named, pa.array(swap, pa.binary()), pa.array(none, pa.binary())], ["y", "own", "named", "swap", "none"])

    rows = training_rows(docs, labels, "toxic", most).mapInArrow(made, "y int, own binary, named boolean, swap binary, none binary").collect()
    read = lambda b: np.frombuffer(b, np.int32).astype(np.int64)
    return fit([(r.y, read(r.own), [read(r.swap), read(r.none)] if r.named else []) for r in sorted(rows, key=lambda r: (r.y, r.own))], fairness=fairness)


def score(docs: DataFrame, model: GroupBlindModel) -> DataFrame:
    """``docs`` with score and predicted; every column kept, the whole text read."""
    names = [c for c in docs.columns if c not in ("score", "predicted")]
    docs = docs.select(*names)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", score double, predicted int"
    used = np.flatnonzero(model.weights)
    value, bias = model.weights[used], model.bias

    def scored(batches):
        weights = np.zeros(1 << BITS)
        weights[used] = value
        own = GroupBlindModel(weights, bias)
        for batch in batches:
            for first, texts in slices(batch.column("text")):
                p = own.scores(texts)
                part = batch.slice(first, len(texts))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(p, pa.float64()), pa.array((p >= THRESHOLD).astype(np.int32))], [*names, "score", "predicted"])

    return docs.mapInArrow(scored, schema)


def toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


QUERIES = {"op2_group_blind_toxicity": toxicity}
SQL: dict[str, str] = {}
