"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad. Emissions look at the line and at its two neighbours, transitions at the state of the line before. Training
knows documents only: their label is first given to each of their lines, then lines of bad documents that look good by themselves are
made good and the field is fitted again. A document's score is the length-weighted mean of the lines' forward-backward marginals, put
on a scale of probabilities by a logistic fit on the same training documents.

Defined cases: a null or empty text has one empty line; a document without labels is scored like any other; with no training labels,
or labels of one kind, every score is that kind's share (0.5 without any). Repeated rows get a row each; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import held_out, renamed, table, training_rows
from diversify.llm.textblocks import BYTE_BASE, Prefixes, U, mixed, slices

#: Most labelled documents that training takes, most lines of a training sequence (longer documents are cut into several), and most sequences of a document.
SAMPLE, SEQUENCE, SEQUENCES = 3000, 64, 4
THRESHOLD = 0.5

_UPPER, _LOWER, _DIGIT, _SPACE, _POINT, _SYMBOL, _OTHER, _TRAIL = range(8)
_CLASS = np.full(256, _SYMBOL, np.uint8)
_CLASS[list(range(65, 91))] = _UPPER
_CLASS[list(range(97, 123))] = _LOWER
_CLASS[list(range(48, 58))] = _DIGIT
_CLASS[[9, 10, 11, 12, 13, 32]] = _SPACE
_CLASS[list(b".,;:'\"()?-")] = _POINT
_CLASS[128:192] = _TRAIL
_CLASS[192:] = _OTHER


def line_features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features by line, characters by line, lines by text); features of a line, of the one before and of the one after."""
    counts = np.array([x.count(b"\n") + 1 for x in texts], np.int64)
    raw = np.frombuffer(b"\n".join(texts), np.uint8)
    ends = np.concatenate((np.flatnonzero(raw == 10), [len(raw)]))
    starts = np.concatenate(([0], ends[:-1] + 1))
    doc = np.repeat(np.arange(len(texts)), counts)
    kind = _CLASS[raw]

    def per_line(flags: np.ndarray) -> np.ndarray:
        sums = np.zeros(len(flags) + 1, np.int64)
        np.cumsum(flags, out=sums[1:])
        return (sums[ends] - sums[starts]).astype(float)

    n = {k: per_line(kind == k) for k in range(8)}
    chars = sum(n[k] for k in range(7))
    letters = n[_UPPER] + n[_LOWER] + n[_OTHER]
    space = np.concatenate(([True], kind == _SPACE, [True]))
    begins, closes = np.flatnonzero(space[:-1] & ~space[1:]), np.flatnonzero(~space[:-1] & space[1:])
    line = np.searchsorted(starts, begins, "right") - 1
    prefixes = Prefixes(raw.astype(U) + U(1), BYTE_BASE)
    word = prefixes.of(begins, closes)
    words = np.bincount(line, minlength=len(starts)).astype(float)
    same = np.zeros(len(word), bool)
    for gap in (1, 2):
        same[gap:] |= (word[gap:] == word[:-gap]) & (line[gap:] == line[:-gap])
    last = kind[np.maximum(closes - 1, 0)] if len(closes) else kind[:0]
    marked = np.bincount(line, weights=last == _SYMBOL, minlength=len(starts))
    again = np.bincount(line, weights=same, minlength=len(starts))
    own = mixed(prefixes.of(starts, ends) ^ mixed(doc.astype(U)))
    _, at, copies = np.unique(own, return_inverse=True, return_counts=True)
    closed = np.isin(raw[np.maximum(ends - 1, 0)], list(b".!?:;\"")) & (ends > starts) if len(raw) else ends > starts
    share = lambda a, b: a / np.maximum(b, 1)
    upper, symbol, marks, repeats = share(n[_UPPER], letters), share(n[_SYMBOL], chars), share(marked, words), share(again, words)
    x = np.column_stack([
        np.log1p(chars) / 5, np.log1p(words) / 4, upper, symbol, marks, repeats, share(n[_DIGIT], chars), share(n[_POINT], chars), share(n[_SPACE], chars),
        np.minimum(share(letters, words), 20) / 10, closed, (copies[at] > 1) & (words > 0), words == 0, upper > 0.5, symbol > 0.05, marks > 0.25, repeats > 0.25,
    ]).astype(float)
    shifted = np.zeros((2, *x.shape))
    linked = doc[1:] == doc[:-1]
    shifted[0, 1:][linked] = x[:-1][linked]
    shifted[1, :-1][linked] = x[1:][linked]
    edge = np.column_stack([np.concatenate(([True], ~linked)), np.concatenate((~linked, [True]))])
    return np.hstack([np.ones((len(x), 1)), x, shifted[0], shifted[1], edge]), chars, counts


@dataclass
class LineField:
    """Weights of the field: emission of the good state, scores of the four steps, and the two of the final scale."""

    weights: np.ndarray
    steps: np.ndarray
    scale: tuple[float, float]
    constant: float | None = None

    def marginals(self, emission: np.ndarray, counts: np.ndarray, with_steps: bool = False):
        """P(good) by line; with_steps: also the expected number of each of the four steps and the log of the partition sum by text."""
        order = np.argsort(-counts, kind="stable")
        first = np.concatenate(([0], np.cumsum(counts)))[:-1]
        sorted_counts, lines = counts[order], np.zeros(len(emission))
        longest = int(counts.max(initial=0))
        active = np.searchsorted(-sorted_counts, -np.arange(1, longest + 1), "right")
        a = np.zeros((len(emission), 2))
        for t in range(longest):
            rows = first[order[: active[t]]] + t
            score = np.column_stack([np.zeros(len(rows)), emission[rows]])
            if t:
                before = a[rows - 1]
                score = score + np.logaddexp(before[:, :1] + self.steps[0], before[:, 1:] + self.steps[1])
            a[rows] = score
        b = np.zeros((len(emission), 2))
        expected = np.zeros((2, 2))
        whole = np.zeros(len(counts))
        ends = first[order] + sorted_counts - 1
        whole[order] = np.logaddexp(a[ends, 0], a[ends, 1])
        for t in range(longest - 2, -1, -1):
            now = order[: active[t + 1]]
            rows = first[now] + t
            after = b[rows + 1] + np.column_stack([np.zeros(len(rows)), emission[rows + 1]])
            b[rows] = np.logaddexp(self.steps[:, 0] + after[:, :1], self.steps[:, 1] + after[:, 1:])
            if with_steps:
                both = a[rows][:, :, None] + self.steps + after[:, None, :] - whole[now][:, None, None]
                expected += np.exp(both).sum(0)
        lines = np.exp(a[:, 1] + b[:, 1] - np.repeat(whole, counts))
        return (lines, expected, whole) if with_steps else lines

    def level(self, x: np.ndarray, chars: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Length-weighted mean of the marginals by text, as log odds."""
        good = self.marginals(x @ self.weights, counts)
        first = np.concatenate(([0], np.cumsum(counts)))[:-1]
        mean = np.add.reduceat(good * (chars + 1), first) / np.add.reduceat(chars + 1, first)
        mean = np.clip(mean, 1e-4, 1 - 1e-4)
        return np.log(mean / (1 - mean))

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        x, chars, counts = line_features(texts)
        return 1 / (1 + np.exp(-np.clip(self.scale[0] * self.level(x, chars, counts) + self.scale[1], -30, 30)))


def _fit_field(x: np.ndarray, y: np.ndarray, counts: np.ndarray, rounds: int) -> LineField:
    """Adam on the mean negative log likelihood of the lines' states, with a small quadratic penalty; starts at zero, so runs agree."""
    field = LineField(np.zeros(x.shape[1]), np.zeros((2, 2)), (1.0, 0.0))
    first = np.concatenate(([0], np.cumsum(counts)))[:-1]
    inner = np.ones(len(y), bool)
    inner[first] = False
    inner = np.flatnonzero(inner)
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[inner - 1], y[inner]), 1)
    size, moments = len(y), [np.zeros(x.shape[1] + 4) for _ in range(2)]
    for step in range(1, rounds + 1):
        good, expected, _ = field.marginals(x @ field.weights, counts, True)
        slope = np.concatenate((x.T @ (good - y), (expected - seen).ravel())) / size + 1e-4 * np.concatenate((field.weights, field.steps.ravel()))
        for k, value in ((0, slope), (1, slope**2)):
            moments[k] += (0.1, 0.01)[k] * (value - moments[k])
        move = 0.15 * moments[0] / (1 - 0.9**step) / (np.sqrt(moments[1] / (1 - 0.99**step)) + 1e-8)
        field.weights -= move[:-4]
        field.steps = field.steps - move[-4:].reshape(2, 2)
    return field


def _pieces(counts: np.ndarray) -> np.ndarray:
    return np.array([min(SEQUENCE, c - k) for c in counts for k in range(0, c, SEQUENCE)], np.int64)


def _training_lines(first: int, n: int) -> np.ndarray:
    """Lines of a document that training takes: all, or SEQUENCES sequences from its beginning to its end."""
    if n <= SEQUENCE * SEQUENCES:
        return np.arange(first, first + n)
    begins = first + np.linspace(0, n - SEQUENCE, SEQUENCES).astype(np.int64)
    return (begins[:, None] + np.arange(SEQUENCE)).ravel()


def fit(features: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, rounds: int = 100) -> LineField:
    """features: (features by line, characters by line) of each training text."""
    if len(set(labels.tolist())) < 2:
        return LineField(np.zeros(0), np.zeros((2, 2)), (1.0, 0.0), float(labels.mean()) if len(labels) else 0.5)
    counts = np.array([len(c) for _, c in features], np.int64)
    x, chars = np.vstack([f for f, _ in features]).astype(float), np.concatenate([c for _, c in features])
    y = np.repeat(labels, counts).astype(np.int64)
    pieces = _pieces(counts)
    field = _fit_field(x, y, pieces, rounds)
    alone = x[:, : (x.shape[1] - 3) // 3 + 1]
    alone_weights = _logistic(alone, y.astype(float), 200)
    y = np.where((y == 0) & (alone @ alone_weights > 2), 1, y)
    field = _fit_field(x, y, pieces, rounds) if len(set(y.tolist())) == 2 else field
    level = field.level(x, chars, counts)
    bias, slope = _logistic(np.column_stack([np.ones(len(level)), level]), labels.astype(float), 30)
    field.scale = (float(slope), float(bias))
    return field


def _logistic(x: np.ndarray, y: np.ndarray, rounds: int, penalty: float = 1e-3) -> np.ndarray:
    """Newton steps for a logistic regression."""
    w = np.zeros(x.shape[1])
    for _ in range(min(rounds, 25)):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        curve = (x * (p * (1 - p) + 1e-6)[:, None]).T @ x / len(y) + penalty * np.eye(x.shape[1])
        w = w - np.linalg.solve(curve, x.T @ (p - y) / len(y) + penalty * w)
    return w


def train(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> LineField:
    """The field for ``labels.quality``; features are made where the texts are, and those of at most ``most`` documents come to the driver."""

    def features(batches):
        for batch in batches:
            for first, texts in slices(batch.column("text")):
                x, chars, counts = line_features(texts)
                lines = [_training_lines(int(e - c), int(c)) for c, e in zip(counts, np.cumsum(counts), strict=True)]
                part = lambda a: pa.array([a[at].tobytes() for at in lines], pa.binary())  # noqa: E731, B023
                yield pa.RecordBatch.from_arrays([batch.column("y").slice(first, len(texts)), part(x.astype(np.float32)), part(chars.astype(np.float32))], ["y", "x", "chars"])

    rows = training_rows(docs, labels, "quality", most).mapInArrow(features, "y int, x binary, chars binary").collect()
    parts = []
    for r in rows:
        chars = np.frombuffer(r.chars, np.float32)
        parts.append((np.frombuffer(r.x, np.float32).reshape(len(chars), -1), chars.astype(float)))
    order = sorted(range(len(rows)), key=lambda i: (rows[i].y, rows[i].x))
    return fit([parts[i] for i in order], np.array([rows[i].y for i in order], np.int64))


def score(docs: DataFrame, field: LineField) -> DataFrame:
    """``docs`` with score and predicted; every column kept, the whole text read."""
    names = [c for c in docs.columns if c not in ("score", "predicted")]
    docs = docs.select(*names)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", score double, predicted int"

    def scored(batches):
        for batch in batches:
            for first, texts in slices(batch.column("text")):
                p = field.scores(texts)
                part = batch.slice(first, len(texts))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(p, pa.float64()), pa.array((p >= THRESHOLD).astype(np.int32))], [*names, "score", "predicted"])

    return docs.mapInArrow(scored, schema)


def quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents that the classifier accepts."""
    field = train(docs, table(spark, sf_dir, "labels"))
    return renamed(docs, lambda d: score(d, field).where("predicted = 1"))


QUERIES = {"op10_line_field_quality": quality}
SQL: dict[str, str] = {}
