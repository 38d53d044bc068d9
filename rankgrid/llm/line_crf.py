"""Document quality by a linear-chain conditional random field over lines.

Each line is good or bad; its potentials come from its own features and its neighbours', and from the label of the line
before. Lines of a labelled document all have its label when the field is fitted. A document's quality is the
length-weighted mean of the marginals that forward-backward gives, put on a probability scale by a logistic function.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.learn import fold, labelled_sample, logistic, probability
from rankgrid.llm.textblocks import LOWER, flat_text, map_arrow, small_batches, span_hash, word_spans
from rankgrid.llm.token_counts import id_and_text

#: Bound of the labelled rows learnt from, and rounds of gradient ascent.
SAMPLE, ROUNDS = 6_000, 200
#: Bytes of text whose features a worker holds at once.
BATCH = 1 << 20
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_SYMBOL = np.zeros(256, bool)
_SYMBOL[[c for c in range(33, 127) if not chr(c).isalnum() and chr(c) not in ".,'"]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".!?"]] = True


def _per(flags: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags)])
    return (total[ends] - total[starts]).astype(np.float64)


class Lines:
    """The lines that have a word, of all texts of a column: row, bytes, and features."""

    def __init__(self, column: pa.Array):
        data, offsets = flat_text(column)
        first = np.zeros(len(data) + 1, bool)
        first[offsets] = True
        cut = np.flatnonzero(data == 10)
        starts = np.unique(np.concatenate([offsets[:-1][np.diff(offsets) > 0], cut + 1]))
        starts = starts[starts < len(data)]
        ends = np.append(starts[1:], len(data)) if len(starts) else starts
        ws, we, _ = word_spans(data, np.append(starts, len(data)))
        lo, hi = np.searchsorted(ws, starts), np.searchsorted(ws, ends)
        keep = hi > lo
        starts, ends, lo, hi = starts[keep], ends[keep], lo[keep], hi[keep]
        self.row = np.searchsorted(offsets, starts, "right") - 1
        self.size = (ends - starts).astype(np.float64)
        self.n_rows = len(column)
        lower = LOWER[data]
        words = span_hash(lower, ws, we)
        n = (hi - lo).astype(np.float64)
        again = np.zeros(len(words), bool)
        again[1:] = words[1:] == words[:-1]
        again[lo[lo < len(words)]] = False
        doc = np.searchsorted(offsets, ws, "right") - 1
        order = np.lexsort((np.arange(len(words)), words, doc))
        seen = np.zeros(len(words), bool)
        if len(order):
            same = (words[order][1:] == words[order][:-1]) & (doc[order][1:] == doc[order][:-1])
            seen[order[1:][same]] = True
        whole = span_hash(lower, starts, ends)
        twice = np.zeros(len(starts))
        if len(starts):
            pair = np.stack([whole, self.row.astype(np.uint64)], axis=1)
            _, which, count = np.unique(pair, axis=0, return_inverse=True, return_counts=True)
            twice = (count[which.ravel()] > 1).astype(np.float64)
        letters = np.maximum(self.size - n, 1)
        symbol_words = np.zeros(len(data), np.int8)
        if len(we):
            symbol_words[ws] = _SYMBOL[data[we - 1]] | _SYMBOL[data[ws]]
        high = data >= 0x80
        self.features = np.stack(
            [
                np.log(self.size), np.log(n), letters / n / 10, _per(_UPPER[data], starts, ends) / letters, _per(_DIGIT[data], starts, ends) / letters, _per(_SYMBOL[data], starts, ends) / letters,
                _per(high, starts, ends) / letters, _per(symbol_words, starts, ends) / n, _per(again, lo, hi) / n, _per(seen, lo, hi) / n, twice, _per(_STOP[data], starts, ends) / n, _per(data == 124, starts, ends) / n,
                (n <= 3).astype(np.float64),
            ],
            axis=1,
        )

    def with_neighbours(self) -> np.ndarray:
        """Own features, those of the line before and after in the same document (zeros without one), and flags of the ends."""
        x = self.features
        before, after = np.zeros_like(x), np.zeros_like(x)
        same = self.row[1:] == self.row[:-1]
        before[1:][same] = x[:-1][same]
        after[:-1][same] = x[1:][same]
        ends = np.ones((len(x), 2))
        ends[1:, 0], ends[:-1, 1] = ~same, ~same
        return np.hstack([x, before, after, ends])


@dataclass
class Field:
    """mean and scale of the features; weights of the good label; 2 x 2 transitions; the logistic weights of the document."""

    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    step: np.ndarray
    model: np.ndarray

    def line_scores(self, x: np.ndarray) -> np.ndarray:
        return ((x - self.mean) / self.scale) @ self.weights + self.bias


def forward_backward(scores: np.ndarray, row: np.ndarray, n_rows: int, step: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Marginal of the good label for each line, and the pairwise marginals summed for each row (n_rows x 2 x 2).

    Rows of about equal length go through the recursions together; a row of any length takes memory in proportion.
    """
    first = np.searchsorted(row, np.arange(n_rows + 1))
    length = np.diff(first)
    good, pairs = np.zeros(len(scores)), np.zeros((n_rows, 2, 2))
    hop = np.exp(step)
    bucket = np.ceil(np.log2(np.maximum(length, 1))).astype(int)
    for k in np.unique(bucket[length > 0]):
        rows = np.flatnonzero((bucket == k) & (length > 0))
        n, t = length[rows], int(length[rows].max())
        at = np.minimum(first[rows][:, None] + np.arange(t)[None, :], len(scores) - 1)
        inside = np.arange(t)[None, :] < n[:, None]
        s = np.where(inside, np.clip(scores[at], -30, 30), 0.0)
        psi = np.stack([np.exp(-s / 2), np.exp(s / 2)], axis=2)
        a, b = np.empty_like(psi), np.ones_like(psi)
        a[:, 0] = psi[:, 0] / psi[:, 0].sum(1, keepdims=True)
        for i in range(1, t):
            v = (a[:, i - 1] @ hop) * psi[:, i]
            v /= v.sum(1, keepdims=True)
            a[:, i] = np.where(inside[:, i : i + 1], v, a[:, i - 1])
        for i in range(t - 2, -1, -1):
            v = (b[:, i + 1] * psi[:, i + 1]) @ hop.T
            v /= v.sum(1, keepdims=True)
            b[:, i] = np.where(inside[:, i + 1 : i + 2], v, 1.0)
        m = a * b
        m /= m.sum(2, keepdims=True)
        good[at[inside]] = m[:, :, 1][inside]
        if t > 1:
            q = a[:, :-1, :, None] * hop[None, None] * (psi * b)[:, 1:, None, :]
            q /= q.sum((2, 3), keepdims=True)
            pairs[rows] = (q * inside[:, 1:, None, None]).sum(1)
    return good, pairs


def document_features(lines: Lines, good: np.ndarray) -> np.ndarray:
    """Log odds of the length-weighted marginal, the share of good bytes, and the log of the size; zeros without lines."""
    total = np.bincount(lines.row, weights=lines.size, minlength=lines.n_rows)
    mean = np.bincount(lines.row, weights=lines.size * good, minlength=lines.n_rows) / np.maximum(total, 1)
    mean = np.where(total > 0, np.clip(mean, 1e-3, 1 - 1e-3), 0.5)
    sure = np.bincount(lines.row, weights=lines.size * (good > 0.5), minlength=lines.n_rows) / np.maximum(total, 1)
    return np.stack([np.log(mean / (1 - mean)), sure, np.log1p(total) / 10], axis=1)


def _training_lines(texts: DataFrame, sample: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Features of the lines, their documents (ascending numbers), bytes, and the documents' labels."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            lines = Lines(b.column("text"))
            at = pa.array(lines.row)
            x = lines.with_neighbours().astype(np.float32)
            yield pa.RecordBatch.from_arrays([b.column("doc_id").take(at), b.column("label").take(at), pa.array(lines.size), pa.array(np.arange(len(at))), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "label", "size", "at", "x"])

    rows = map_arrow(texts.join(F.broadcast(sample), F.col("doc_id") == F.col("sample_id")).select("doc_id", "text", "label"), each, "doc_id long, label int, size double, at long, x binary").toPandas()
    rows = rows.sort_values(["doc_id", "at"], kind="stable")
    _, doc = np.unique(rows["doc_id"].to_numpy(), return_inverse=True)
    x = np.frombuffer(b"".join(rows["x"]), np.float32).reshape(len(rows), -1).astype(np.float64) if len(rows) else np.zeros((0, 44))
    label = rows["label"].to_numpy(np.float64)
    return x, doc, rows["size"].to_numpy(np.float64), label


def fit(docs: DataFrame, labels: DataFrame, modulus: int = 4, held_out: int = 2, sample_rows: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> Field:
    """The field fitted to at most sample_rows labelled rows outside the held-out fold, by gradient ascent on the conditional likelihood."""
    sample = labelled_sample(labels, "quality", modulus, held_out, sample_rows)
    x, doc, size, label = _training_lines(id_and_text(docs, id_col, text_col), sample)
    width = x.shape[1]
    if not len(x) or label.min() == label.max():
        rate = (label.sum() + 1) / (len(label) + 1.1)
        return Field(np.zeros(width), np.ones(width), np.zeros(width), 0.0, np.zeros((2, 2)), np.array([0.0, 0.0, 0.0, np.log(rate / (1 - rate))]))
    field = Field(x.mean(0), x.std(0) + 1e-6, np.zeros(width), 0.0, np.zeros((2, 2)), np.zeros(4))
    z = (x - field.mean) / field.scale
    n_docs = int(doc[-1]) + 1
    starts = np.searchsorted(doc, np.arange(n_docs))
    truth = label[starts]
    sizes = np.diff(np.append(starts, len(doc)))
    # every document counts the same, and both labels together the same
    weight = np.where(truth == 1, 0.5 / truth.mean(), 0.5 / (1 - truth.mean())) / np.sqrt(sizes)
    theta, moment, spread = np.zeros(width + 5), np.zeros(width + 5), np.zeros(width + 5)
    for k in range(1, ROUNDS + 1):
        step = theta[width + 1 :].reshape(2, 2)
        good, pairs = forward_backward(z @ theta[:width] + theta[width], doc, n_docs, step)
        error = (label - good) * weight[doc]
        seen = np.zeros((n_docs, 2, 2))
        seen[np.arange(n_docs), truth.astype(int), truth.astype(int)] = sizes - 1
        grad = np.concatenate([error @ z - 0.5 * theta[:width], [error.sum()], ((seen - pairs) * weight[:, None, None]).sum(0).ravel() - 5 * theta[width + 1 :]]) / n_docs
        moment, spread = 0.9 * moment + 0.1 * grad, 0.99 * spread + 0.01 * grad**2
        theta = theta + 0.1 * 0.99**k * (moment / (1 - 0.9**k)) / (np.sqrt(spread / (1 - 0.99**k)) + 1e-8)
        # lines of a document share its label in training, which would bind them wholly: keep the bond moderate
        theta[width + 1 :] = np.clip(theta[width + 1 :], -1.0, 1.0)
    field.weights, field.bias, field.step = theta[:width], float(theta[width]), theta[width + 1 :].reshape(2, 2)
    good, _ = forward_backward(z @ field.weights + field.bias, doc, n_docs, field.step)
    lines = Lines(pa.array([], pa.string()))
    lines.row, lines.size, lines.n_rows = doc, size, n_docs
    field.model = logistic(document_features(lines, good), truth, ridge=0.5)
    return field


def score(docs: DataFrame, field: Field, modulus: int = 4, held_out: int = 2, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, held_out, score (0 to 1), predicted (score >= threshold).

    Null and empty texts, and texts without a word, have no lines and get the score of even odds; repeated rows are
    scored each; a null id stays null and is not held out; an empty table gives no rows; long texts are read whole;
    other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = shared.value
        for b in small_batches(batches, "text", BATCH):
            lines = Lines(b.column("text"))
            good, _ = forward_backward(f.line_scores(lines.with_neighbours()), lines.row, lines.n_rows, f.step)
            p = probability(document_features(lines, good), f.model)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(p), pa.array((p >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    texts = id_and_text(docs, id_col, text_col).withColumn("held_out", F.coalesce(fold(F.col("doc_id"), modulus) == held_out, F.lit(False)))
    return map_arrow(texts, each, "doc_id long, held_out boolean, score double, predicted int")


def drop_bad(docs: DataFrame, field: Field, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """docs without the documents scored below threshold; columns stay as they are. Rows are judged one by one, without a join."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = shared.value
        for b in small_batches(batches, text_col, BATCH):
            lines = Lines(b.column(text_col))
            good, _ = forward_backward(f.line_scores(lines.with_neighbours()), lines.row, lines.n_rows, f.step)
            keep = np.flatnonzero(probability(document_features(lines, good), f.model) >= threshold)
            yield b.take(pa.array(keep))

    return map_arrow(docs, each, docs.schema)
