"""Document quality from a linear-chain conditional random field over lines.

Every line of a document is labelled good or bad. A line's emission looks at
its own features and at those of the lines before and after it; transitions
couple neighbouring labels. Forward-backward gives each line's probability of
being good, and the document's score is their mean weighted by line length.

Features are shares of character classes, word repetition, lengths and whether
the line occurred before in the document: nothing of the document's number,
language or source. In training every line bears its document's label; the
likelihood is maximised by full-batch gradient steps on the driver, over the
line features of at most ``sample_docs`` labelled documents (drawn by a hash of
``doc_id``, so a rerun draws the same).

Defined results: null text is an empty text, which is one empty line; null
``doc_id`` is scored and never held out; repeated rows are scored each; with
labels of a single class or none the score is the smoothed share of label 1;
conflicting labels of a document count as the larger one; other columns are
ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labelled documents to fit on, at most; documents featurised together; gradient steps; weight of the penalty.
SAMPLE_DOCS, CHUNK_DOCS, STEPS, PENALTY = 4000, 200, 150, 1e-3
THRESHOLD = 0.3

_CLASSES = 9
#: Class of every byte: lower, upper, digit, space, bar, exclamation, symbol, punctuation, beyond ASCII.
_CLASS = np.full(256, 6, np.uint8)
_CLASS[128:] = 8
for _k, _chars in enumerate((range(97, 123), range(65, 91), range(48, 58), b" \t\r\x0b\x0c", b"|", b"!", b"", b".,;:?'\"()-")):
    _CLASS[list(_chars)] = _k
N_FEATURES = _CLASSES + 7


def line_features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(features, weights, lines per document)`` of all lines of some documents."""
    words: list[tuple] = []
    n_lines, pieces = [], []
    for text in texts:
        lines = (text or "").encode("utf-8", "surrogatepass").split(b"\n")
        seen: set[bytes] = set()
        n_lines.append(len(lines))
        for line in lines:
            w = line.split()
            n = len(w)
            words.append((len(line), n, len(set(w)), sum(map(eq, w, w[1:])), max(map(len, w), default=0), line in seen))
            seen.add(line)
        pieces += lines
    w = np.array(words, np.float64).reshape(-1, 6)
    size, n = w[:, 0], np.maximum(w[:, 1], 1)
    raw = np.frombuffer(b"".join(pieces), np.uint8)
    line_no = np.repeat(np.arange(len(pieces)), size.astype(np.int64))
    counts = np.bincount(line_no * _CLASSES + _CLASS[raw], minlength=len(pieces) * _CLASSES).reshape(-1, _CLASSES)
    share = counts / np.maximum(size, 1)[:, None]
    rest = [w[:, 2] / n, w[:, 3] / n, np.log1p(size) / 8, size / n / 10, np.minimum(w[:, 4], 50) / 50, w[:, 5], size == 0]
    return np.column_stack([share, *rest]).astype(np.float32), np.maximum(size, 1), np.array(n_lines, np.int64)


def with_neighbours(x: np.ndarray, n_lines: np.ndarray) -> np.ndarray:
    """A line's own features, those of the lines around it, and whether there are such lines."""
    ends = np.cumsum(n_lines)
    first, last = np.zeros(len(x), bool), np.zeros(len(x), bool)
    first[ends - n_lines], last[ends - 1] = True, True
    before = np.where(first[:, None], 0, np.roll(x, 1, 0))
    after = np.where(last[:, None], 0, np.roll(x, -1, 0))
    return np.column_stack([np.ones(len(x)), x, before, after, first, last]).astype(np.float64)


def _logaddexp(a: np.ndarray) -> np.ndarray:
    return np.logaddexp(a[..., 0], a[..., 1])


def forward_backward(emit: np.ndarray, n_lines: np.ndarray, trans: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Log-partition per document, P(good) per line, and expected transitions per document.

    ``emit`` is the score of good per line (of bad: 0); ``trans[from, to]``. Documents
    advance together, the longest first, so step t touches only those that have a line t.
    """
    order = np.argsort(-n_lines, kind="stable")
    n, begin = n_lines[order], (np.cumsum(n_lines) - n_lines)[order]
    steps = int(n[0]) if len(n) else 0
    live = np.searchsorted(-n, -np.arange(steps), side="left")  # documents with more than t lines
    score = np.zeros((len(emit), 2))
    score[:, 1] = emit
    forward, backward = score.copy(), np.zeros_like(score)
    for t in range(1, steps):
        k = live[t]
        at = begin[:k] + t
        forward[at] = score[at] + _logaddexp((forward[at - 1][:, :, None] + trans).transpose(0, 2, 1))
    for t in range(steps - 2, -1, -1):
        k = live[t + 1]
        at = begin[:k] + t
        backward[at] = _logaddexp(trans + (score[at + 1] + backward[at + 1])[:, None, :])
    z = np.empty(len(n))
    z[order] = _logaddexp(forward[begin + n - 1])
    doc = np.repeat(np.arange(len(n_lines)), n_lines)
    good = np.exp(forward[:, 1] + backward[:, 1] - z[doc])
    expected = np.zeros((2, 2))
    inner = np.ones(len(emit), bool)
    inner[(np.cumsum(n_lines) - n_lines)[n_lines > 0]] = False
    to = np.flatnonzero(inner)
    if len(to):
        joint = forward[to - 1][:, :, None] + trans + (score[to] + backward[to])[:, None, :] - z[doc[to]][:, None, None]
        expected = np.exp(joint).sum(0)
    return z, good, expected


@dataclass
class LineField:
    """The field's weights; ``constant`` stands for a score where nothing could be learned."""

    weights: np.ndarray
    trans: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    constant: float | None = None

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(texts), self.constant)
        x, size, n_lines = line_features(texts)
        _, good, _ = forward_backward(with_neighbours((x - self.mean) / self.scale, n_lines) @ self.weights, n_lines, self.trans)
        doc = np.repeat(np.arange(len(texts)), n_lines)
        return np.clip(np.bincount(doc, good * size) / np.bincount(doc, size), 0, 1)


def fit(x: np.ndarray, n_lines: np.ndarray, labels: np.ndarray, steps: int = STEPS) -> LineField:
    """Maximise the penalised likelihood; every line bears its document's label."""
    if len(labels) == 0 or labels.min() == labels.max():
        return LineField(*[np.zeros(0)] * 4, constant=float((labels.sum() + 1) / (len(labels) + 2)))
    mean, scale = x.mean(0), x.std(0) + 1e-3
    wide = with_neighbours((x - mean) / scale, n_lines)
    y = np.repeat(labels, n_lines)
    per_class = np.where(labels == 1, 0.5 / (labels == 1).mean(), 0.5 / (labels == 0).mean())
    each = np.repeat(per_class / n_lines, n_lines)  # classes and documents weigh alike
    weights, trans = np.zeros(wide.shape[1]), np.zeros((2, 2))
    m, v = np.zeros(len(weights) + 4), np.zeros(len(weights) + 4)
    doc = np.repeat(np.arange(len(labels)), n_lines)
    pairs = np.bincount(labels, np.maximum(n_lines - 1, 0), 2)
    for step in range(1, steps + 1):
        _, good, expected = forward_backward(wide @ weights, n_lines, trans)
        grad_w = wide.T @ ((y - good) * each) / len(labels) - PENALTY * weights
        grad_t = (np.diag(pairs) - expected) / max(1, len(doc)) - 10 * PENALTY * trans
        g = np.concatenate([grad_w, grad_t.ravel()])
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        move = 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-9)
        weights, trans = weights + move[:-4], trans + move[-4:].reshape(2, 2)
    return LineField(weights, trans, mean, scale)


def held_out(doc_id: Column) -> Column:
    """Whether crc32 of the number's text leaves no remainder modulo 5."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def _featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(0, batch.num_rows, CHUNK_DOCS):
            part = batch.slice(k, CHUNK_DOCS)
            x, _, n = line_features(part.column("text").to_pylist())
            cuts = np.concatenate([[0], np.cumsum(n)])
            raw = [np.ascontiguousarray(x[a:b]).tobytes() for a, b in zip(cuts, cuts[1:])]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("label"), pa.array(raw, pa.binary())], ["doc_id", "label", "x"])


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", sample_docs: int = SAMPLE_DOCS) -> LineField:
    """Fit on labelled documents that are not held out; ``sample_docs`` at most."""
    known = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(label).cast("int").alias("label"))
    drawn = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    rows = docs.select("doc_id", "text").join(F.broadcast(drawn), "doc_id").select("doc_id", "label", "text")
    found = rows.mapInArrow(_featurise, "doc_id long, label int, x binary").collect()
    found.sort(key=lambda r: (r["doc_id"], bytes(r["x"])))
    x = [np.frombuffer(bytes(r["x"]), np.float32).reshape(-1, N_FEATURES) for r in found]
    return fit(np.concatenate(x) if x else np.zeros((0, N_FEATURES), np.float32), np.array([len(a) for a in x], np.int64), np.array([r["label"] for r in found], np.int64))


def _score(batches: Iterator[pa.RecordBatch], model: LineField) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for k in range(0, batch.num_rows, CHUNK_DOCS):
            part = batch.slice(k, CHUNK_DOCS)
            scores = model.scores(part.column(part.num_columns - 1).to_pylist())
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(scores)], [*part.schema.names, "score"])


def score_documents(docs: DataFrame, model: LineField) -> DataFrame:
    """All columns of ``docs`` and ``score``; ``text`` goes last but one."""
    rows = docs.select(*[c for c in docs.columns if c not in ("text", "score")], "text")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
    return rows.mapInArrow(lambda it: _score(it, model), f"{schema}, score double")
