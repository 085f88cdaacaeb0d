"""Language identification by averaged hashed subword embeddings and a linear softmax.

Subwords are 3- and 4-byte grams of lower-cased words with their edges.  Each is hashed to a row of an
embedding table; a text is the mean of its rows.  Table and softmax are trained by stochastic gradient descent in
numpy on a bounded sample.  For prediction table and softmax are multiplied out once, so that a text costs one gather per gram.
A temperature, fitted on a part of the sample that was not trained on, calibrates the score; texts below the
score that all but ``reject`` of the rightly predicted of that part reach are not ``accepted``.

Defined results: null texts and texts without a letter are ``und`` with score 0; without training rows every text is;
texts of any length are read whole; an empty table gives no rows and an untrained model;
repeated rows are predicted each; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, lean, text_chunks, texts

#: Documents that the model is fitted on, at most (about; chosen by a hash of doc_id).
SAMPLE_ROWS = 4_000
BUCKETS, DIM, GRAMS = 1 << 15, 16, (3, 4)

_PLAIN = np.arange(256, dtype=np.uint8)
_PLAIN[[b for b in range(128) if not chr(b).isalpha()]] = 32


def grams(batch: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all grams of the texts, and where each text's begin (length + 1)."""
    raw = [b" " + t.lower().encode() + b" " for t in batch]
    code = _PLAIN[np.frombuffer(b"".join(raw), np.uint8)]
    start = np.concatenate([[0], np.cumsum([len(r) for r in raw])])
    n = len(code)
    code = np.concatenate([code, np.full(4, 32, np.uint8)])
    wide = code.astype(np.uint32)
    three = wide[:n] | (wide[1 : n + 1] << np.uint32(8)) | (wide[2 : n + 2] << np.uint32(16))
    four = three | (wide[3 : n + 3] << np.uint32(24))
    blank = code == 32
    out, pos = [], []
    for size, value in zip(GRAMS, (three, four)):
        ok = ~blank[1 : n + 1]
        for k in range(2, size - 1):
            ok &= ~blank[k : n + k]
        at = np.flatnonzero(ok)
        out.append(((value[at] * np.uint32(2654435761 + 2 * size)) >> np.uint32(17)).astype(np.int32))
        pos.append(at)
    where = np.concatenate(pos)
    order = np.argsort(where, kind="stable") if len(batch) > 1 else slice(None)
    where = where[order]
    # a gram with an edge of the next text has a blank inside, so it never counts
    return np.concatenate(out)[order], np.searchsorted(where, start)


def _histogram(text: str) -> tuple[np.ndarray, np.ndarray]:
    own, _ = grams([text])
    return np.unique(own, return_counts=True)


class LanguageModel:
    def __init__(self, languages: list[str], table: np.ndarray, temperature: float = 1.0, floor: float = 0.0):
        self.languages, self.table, self.temperature, self.floor = languages, table, temperature, floor

    @classmethod
    def train(cls, rows: list[tuple[np.ndarray, np.ndarray, str]], *, epochs: int = 6, rate: float = 0.6, reject: float = 0.01, seed: int = 7) -> LanguageModel:
        languages = sorted({r[2] for r in rows})
        rng = np.random.default_rng(seed)
        table, soft = rng.normal(0, 0.1, (BUCKETS, DIM)), np.zeros((DIM, max(1, len(languages))))
        soft[:] = rng.normal(0, 0.1, soft.shape)
        rows = [(i, c / max(1, c.sum()), languages.index(y)) for i, c, y in rows if len(i)]
        rng.shuffle(rows)
        held = rows[::5] if len(rows) >= 50 else []
        fit = [r for k, r in enumerate(rows) if k % 5 or not held]
        steps, step = max(1, epochs * len(fit)), 0
        for _ in range(epochs):
            for k in rng.permutation(len(fit)).tolist():
                i, c, y = fit[k]
                lr = rate * (1 - step / steps)
                step += 1
                mean = c @ table[i]
                z = mean @ soft
                p = np.exp(z - z.max())
                p /= p.sum()
                p[y] -= 1
                back = soft @ p
                soft -= lr * np.outer(mean, p)
                table[i] -= (lr * len(i) * 0.05) * c[:, None] * back
        flat = (table @ soft).astype(np.float32)
        out = cls(languages, flat)
        if held:
            z = np.array([c @ flat[i] for i, c, _ in held])
            y = np.array([r[2] for r in held])
            loss = [(-(_log_softmax(z / t)[np.arange(len(y)), y]).mean(), t) for t in np.geomspace(0.05, 5, 60)]
            out.temperature = float(min(loss)[1])
            p = np.exp(_log_softmax(z / out.temperature))
            right = p.max(1)[p.argmax(1) == y]
            out.floor = float(np.quantile(right, reject)) if len(right) else 0.0
        return out

    def predict(self, batch: list[str]) -> tuple[list[str], np.ndarray]:
        own, start = grams(batch)
        total = np.zeros((len(batch), self.table.shape[1]))
        count = np.diff(start)
        some = np.flatnonzero(count)
        if len(some):
            total[some] = np.add.reduceat(self.table[own], start[:-1][some], axis=0)
        p = np.exp(_log_softmax(total / np.maximum(count, 1)[:, None] / self.temperature))
        letters = [len(self.languages) > 0 and any(map(str.isalpha, t)) for t in batch]
        best = p.argmax(1) if len(self.languages) else np.zeros(len(batch), int)
        return [self.languages[b] if ok else "und" for b, ok in zip(best.tolist(), letters)], np.where(letters, p.max(1), 0.0)


def _log_softmax(z: np.ndarray) -> np.ndarray:
    z = z - z.max(1, keepdims=True)
    return z - np.log(np.exp(z).sum(1, keepdims=True))


def learn(docs: DataFrame, *, sample_rows: int = SAMPLE_ROWS, **options) -> LanguageModel:
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang").filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & (fold(F.col("doc_id"), 5) != 0))
    n = own.select("doc_id", "lang").count()
    if n > sample_rows:
        own = own.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) < int(1_000_003 * sample_rows / n))

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            got = [_histogram(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([i.astype("<i4").tobytes() for i, _ in got], pa.binary()), pa.array([c.astype("<f4").tobytes() for _, c in got], pa.binary())], ["doc_id", "lang", "i", "c"])

    rows = own.mapInArrow(lean(run), "doc_id long, lang string, i binary, c binary").collect()
    rows.sort(key=lambda r: (r["doc_id"] is not None, r["doc_id"]))
    return LanguageModel.train([(np.frombuffer(r["i"], "<i4"), np.frombuffer(r["c"], "<f4"), r["lang"]) for r in rows], **options)


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score, accepted."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 4_000_000):
                lang, p = model.predict(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(lang, pa.string()), pa.array(p, pa.float64()), pa.array((p >= model.floor) & (p > 0))], ["doc_id", "lang_pred", "score", "accepted"])

    return texts(docs).mapInArrow(lean(run), "doc_id long, lang_pred string, score double, accepted boolean")


def predict_languages(docs: DataFrame, *, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred, score, accepted."""
    return identify(docs, learn(docs, sample_rows=sample_rows)).select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), "lang_pred", "score", "accepted")
