"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad.  Its features are shares of character classes, word
repetition and length, the same of the lines before and after it, and whether the line repeats in the document.  The field is fitted
on a bounded sample of labelled documents: lines first take their document's label; lines of bad
documents that the fitted field finds good change theirs, and it is fitted again.  Forward-backward
marginals, weighted by line length, are gathered per document and calibrated.

Defined results: null and empty texts have one empty line; without labels of both kinds the score is 0.5;
texts of any length and lines of any number are read whole; an empty table gives no rows;
repeated rows are scored each; labels that repeat an id count once; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, lean, text_chunks, texts
from .toxicity import labelled_sample, logistic

#: Labelled rows that the model is fitted on, at most (about; chosen by a hash of doc_id).
SAMPLE_ROWS = 6_000

_CLASS = np.full(256, 6, np.uint8)  # letters beyond ASCII count as lower-case letters
_CLASS[:128] = [0 if chr(b).isupper() else 6 if chr(b).islower() else 1 if chr(b).isdigit() else 2 if chr(b) in " \t" else 3 if chr(b) in "!?" else 4 if chr(b) in "|<>{}[]\\/=_~^" else 5 if chr(b) in "%*&$#@+" else 7 for b in range(128)]
CLASSES = 8
BASE = CLASSES + 5
FEATURES = 3 * BASE + 1


def line_features(batch: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features of all lines, their lengths in bytes, where each text's lines begin)."""
    per = [t.split("\n") for t in batch]
    lines = [x for p in per for x in p]
    raw = "\n".join(lines).encode() + b"\n"
    code = np.frombuffer(raw, np.uint8)
    ends = np.flatnonzero(code == 10)
    starts = np.concatenate([[0], ends[:-1] + 1])
    size = ends - starts
    kind = _CLASS[code]
    x = np.zeros((len(lines), BASE))
    for c in range(CLASSES):
        x[:, c] = np.add.reduceat(kind == c, starts, dtype=np.int64)
    x[:, CLASSES - 1] -= 1  # the line's end itself
    x[:, :CLASSES] /= np.maximum(size, 1)[:, None]
    n_words, n_own = np.zeros(len(lines)), np.zeros(len(lines))
    for k, line in enumerate(lines):
        w = line.split()
        n_words[k], n_own[k] = len(w), len(set(w))
    x[:, CLASSES] = 1 - n_own / np.maximum(n_words, 1)
    x[:, CLASSES + 1] = np.minimum(size / np.maximum(n_words, 1), 30) / 10
    x[:, CLASSES + 2] = np.log1p(size) / 5
    x[:, CLASSES + 3] = n_own / np.sqrt(np.maximum(n_words, 1)) / 10
    start = np.concatenate([[0], np.cumsum([len(p) for p in per])])
    again = [0.0] * len(lines)
    for d, p in enumerate(per):
        if len(set(p)) < len(p):
            count: dict[str, int] = {}
            for line in p:
                count[line] = count.get(line, 0) + 1
            for k, line in enumerate(p):
                again[start[d] + k] = float(count[line] > 1 and len(line) > 0)
    x[:, CLASSES + 4] = again
    before, after = np.roll(x, 1, 0), np.roll(x, -1, 0)
    before[start[:-1]] = 0
    after[start[1:] - 1] = 0
    return np.concatenate([x, before, after, np.ones((len(x), 1))], axis=1), size, start


class LineField:
    """States: 0 bad, 1 good.  ``w`` scores a line as good; ``t`` scores transitions."""

    def __init__(self, w: np.ndarray, t: np.ndarray):
        self.w, self.t = w, t

    def marginals(self, x: np.ndarray, start: np.ndarray, pairs: bool = False):
        """P(good) of every line; with ``pairs``, also the summed marginals of transitions and the log normalisers."""
        e = np.zeros((len(x), 2))
        e[:, 1] = x @ self.w
        lens = np.diff(start)
        order = np.argsort(-lens, kind="stable")
        first, lens = start[:-1][order], lens[order]
        alpha, beta = np.zeros_like(e), np.zeros_like(e)
        longest = int(lens[0]) if len(lens) else 0
        active = np.searchsorted(-lens, -np.arange(1, longest + 1), side="right")
        total = np.zeros((2, 2))
        for s in range(longest):
            own = first[: active[s]] + s
            alpha[own] = e[own] if s == 0 else e[own] + np.logaddexp(alpha[own - 1, :1] + self.t[0], alpha[own - 1, 1:] + self.t[1])
        for s in range(longest - 2, -1, -1):
            own = first[: active[s + 1]] + s
            nxt = e[own + 1] + beta[own + 1]
            beta[own] = np.logaddexp(nxt[:, :1] + self.t[:, 0], nxt[:, 1:] + self.t[:, 1])
        both = alpha + beta
        log_z = np.logaddexp(both[:, 0], both[:, 1])
        p = np.exp(both[:, 1] - log_z)
        if not pairs:
            return p
        has_next = np.ones(len(x), bool)
        has_next[start[1:] - 1] = False
        at = np.flatnonzero(has_next)
        for a in range(2):
            for b in range(2):
                total[a, b] = np.exp(alpha[at, a] + self.t[a, b] + e[at + 1, b] + beta[at + 1, b] - log_z[at]).sum()
        return p, total

    @classmethod
    def train(cls, x, start, y, weight, *, steps: int = 150, rate: float = 0.15, l2: float = 1e-3) -> LineField:
        """Adam on the conditional likelihood; ``weight`` weighs the lines of the emission gradient."""
        field = cls(np.zeros(x.shape[1]), np.zeros((2, 2)))
        m, v = np.zeros(x.shape[1] + 4), np.zeros(x.shape[1] + 4)
        has_next = np.ones(len(x), bool)
        has_next[start[1:] - 1] = False
        at = np.flatnonzero(has_next)
        seen = np.array([[((y[at] == a) & (y[at + 1] == b)).sum() for b in range(2)] for a in range(2)], float)
        n = weight.sum()
        for step in range(1, steps + 1):
            p, pair = field.marginals(x, start, pairs=True)
            g = np.concatenate([x.T @ ((p - y) * weight) / n + l2 * field.w, ((pair - seen) / max(1, len(at))).ravel() + l2 * field.t.ravel()])
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
            field.w = field.w - move[:-4]
            field.t = field.t - move[-4:].reshape(2, 2)
        return field


def document_features(p: np.ndarray, size: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Length-weighted mean of the lines' P(good), its log odds, the lowest of a long line's, and a constant."""
    w = size + 1.0
    mean = np.add.reduceat(p * w, start[:-1]) / np.add.reduceat(w, start[:-1])
    low = np.minimum.reduceat(np.where(size >= 20, p, 1.0), start[:-1])
    c = np.clip(mean, 1e-4, 1 - 1e-4)
    return np.stack([np.log(c / (1 - c)), mean, low, np.ones(len(mean))], axis=1)


class QualityModel:
    def __init__(self, field: LineField | None, weights: np.ndarray | None):
        self.field, self.weights = field, weights

    @classmethod
    def train(cls, x, size, start, y_doc) -> QualityModel:
        if not len(y_doc) or y_doc.min() == y_doc.max():
            return cls(None, None)
        y = np.repeat(y_doc, np.diff(start)).astype(float)
        doc = np.repeat(np.arange(len(y_doc)), np.diff(start))
        share = np.where(y_doc == 1, 0.5 / max(1, (y_doc == 1).sum()), 0.5 / max(1, (y_doc == 0).sum()))
        weight = share[doc] * (size + 1.0) / np.add.reduceat(size + 1.0, start[:-1])[doc]
        field = LineField.train(x, start, y, weight)
        p = field.marginals(x, start)
        worst = np.minimum.reduceat(p, start[:-1])[doc]
        y = np.where((y == 0) & (p > 0.5) & (p > worst), 1.0, y)
        field = LineField.train(x, start, y, weight)
        docs = document_features(field.marginals(x, start), size, start)
        return cls(field, logistic(docs, y_doc.astype(float), l2=1e-1))

    def score(self, batch: list[str]) -> np.ndarray:
        if self.field is None:
            return np.full(len(batch), 0.5)
        x, size, start = line_features(batch)
        return 1 / (1 + np.exp(-np.clip(document_features(self.field.marginals(x, start), size, start) @ self.weights, -30, 30)))


def learn(docs: DataFrame, labels: DataFrame, *, sample_rows: int = SAMPLE_ROWS) -> QualityModel:
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            if not batch.num_rows:
                continue
            x, size, start = line_features(batch.column(1).to_pylist())
            x = x[:, :BASE].astype("<f4")
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([x[a:b].tobytes() for a, b in zip(start[:-1], start[1:])], pa.binary()), pa.array([size[a:b].astype("<i4").tobytes() for a, b in zip(start[:-1], start[1:])], pa.binary())], ["doc_id", "y", "x", "size"])

    rows = labelled_sample(docs, labels, "quality", 3, 1, sample_rows).mapInArrow(lean(run), "doc_id long, y int, x binary, size binary").collect()
    rows.sort(key=lambda r: r["doc_id"])
    if not rows:
        return QualityModel(None, None)
    x = np.concatenate([np.frombuffer(r["x"], "<f4").reshape(-1, BASE) for r in rows]).astype(float)
    start = np.concatenate([[0], np.cumsum([len(r["size"]) // 4 for r in rows])])
    before, after = np.roll(x, 1, 0), np.roll(x, -1, 0)
    before[start[:-1]] = 0
    after[start[1:] - 1] = 0
    x = np.concatenate([x, before, after, np.ones((len(x), 1))], axis=1)
    return QualityModel.train(x, np.concatenate([np.frombuffer(r["size"], "<i4") for r in rows]).astype(float), start, np.array([r["y"] for r in rows]))


def score_documents(docs: DataFrame, labels: DataFrame, *, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    model = learn(docs, labels, sample_rows=sample_rows)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 4_000_000):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(model.score(part.column(1).to_pylist()))], ["doc_id", "score"])

    out = texts(docs).mapInArrow(lean(run), "doc_id long, score double")
    return out.select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
