"""Toxicity by fuzzy lexicon search.

The lexicon (words, and stems of inflected words) is learned from a bounded sample of labelled
rows.  Terms form a trie; a document's words run through the product of that trie
with Levenshtein automata, made deterministic lazily and kept per worker, so misspelled
terms are found without trying term by term.  Each hit is scored in its window: quotation marks and reporting words around it
speak for quotation, words of address for abuse.  A logistic model over the hits gives the score.

Lexicon, clean neighbours and weights come from the sample alone, so their size is bounded by its rows; nothing else is capped.
Automaton states and remembered words are dropped and made anew when a worker holds ``keep`` of them, which changes no result.

Defined results: null and empty texts have no hits and get the model's base score; without labels of both kinds the lexicon is empty and the score 0;
texts of any length are read whole; a word that repeats counts each time; repeated rows are scored each; an empty table gives no rows; labels
that repeat an id count once, in no defined order; null labels and ids without a document are left out; any other columns of the input are ignored.
"""

from __future__ import annotations

import math
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, fold, lean, text_chunks, texts

#: Labelled rows that the model is fitted on, at most (about; chosen by a hash of doc_id).
SAMPLE_ROWS = 20_000
FEATURES = 8

TOKEN = re.compile(r"[^\W_]+(?:[@$*'][^\W_]+)*")
LEET = str.maketrans("013457@$", "oieastas")
QUOTES = re.compile("[\"“”«»„‘’]")
# fixed values: words of report and of address in the languages at hand
REPORT = frozenset("said says called quote quoted quotes word term wrote writes dit disait citation wort sagte zitat dijo llamado cita palabra mot".split())
ADDRESS = frozenset("you your youre u ur du dich dein sie tu te toi vous ton eres tú usted".split())


class FuzzyLexicon:
    """Terms as a trie, intersected with Levenshtein automata.  A term that ends in ``*`` is a stem: what follows it is free."""

    def __init__(self, terms: list[str], clean: set[str] = frozenset(), keep: int = 100_000):
        self.terms, self.clean, self.keep = terms, clean, keep
        self.child: list[dict[str, int]] = [{}]
        self.budget, self.word, self.stem = [0], [-1], [-1]
        for t, term in enumerate(terms):
            allowed, node, path = self.allowed(term), 0, [0]
            for c in term.removesuffix("*"):
                if c not in self.child[node]:
                    self.child[node][c] = len(self.child)
                    self.child.append({})
                    self.budget.append(0)
                    self.word.append(-1)
                    self.stem.append(-1)
                node = self.child[node][c]
                path.append(node)
            (self.stem if term.endswith("*") else self.word)[node] = t
            for n in path:
                self.budget[n] = max(self.budget[n], allowed)
        self._restart()

    def _restart(self) -> None:
        self._ids: dict[tuple, int] = {}
        self._sets: list[tuple] = []
        self._step: list[dict[str, int]] = []
        self._word_hit: list[tuple[int, int] | None] = []
        self._stem_hit: list[tuple[int, int] | None] = []
        self._start = self._state({0: 0})

    @staticmethod
    def allowed(term: str) -> int:
        if term.endswith("*"):
            return int(len(term) > 8)
        return 0 if len(term) < 5 else 1 if len(term) < 9 else 2

    def _state(self, errors: dict[int, int]) -> int:
        todo = list(errors)
        while todo:  # a character of the term may be missing
            n = todo.pop()
            for m in self.child[n].values():
                if errors[n] + 1 <= self.budget[m] and errors[n] + 1 < errors.get(m, 99):
                    errors[m] = errors[n] + 1
                    todo.append(m)
        key = tuple(sorted(errors.items()))
        if key not in self._ids:
            self._ids[key] = len(self._sets)
            self._sets.append(key)
            self._step.append({})
            for hits, ends in ((self._word_hit, self.word), (self._stem_hit, self.stem)):
                hits.append(min(((e, ends[n]) for n, e in key if ends[n] >= 0 and e <= self.allowed(self.terms[ends[n]])), default=None))
        return self._ids[key]

    def _move(self, state: int, c: str) -> int:
        errors: dict[int, int] = {}
        for n, e in self._sets[state]:
            for k, m in self.child[n].items():
                own = e + (k != c)
                if own <= self.budget[m] and own < errors.get(m, 99):
                    errors[m] = own
            if e + 1 <= self.budget[n] and e + 1 < errors.get(n, 99):  # an extra character
                errors[n] = e + 1
        if len(self._sets) >= self.keep:  # the old states go; the new one starts the next tables
            self._restart()
            return self._state(errors)
        to = self._state(errors)
        self._step[state][c] = to
        return to

    def search(self, token: str) -> tuple[int, int] | None:
        """(errors, term) of the best match, or None."""
        state, best = self._start, None
        for c in token:
            to = self._step[state].get(c)
            state = self._move(state, c) if to is None else to
            if not self._sets[state]:
                return best
            hit = self._stem_hit[state]
            if hit is not None and (best is None or hit < best):
                best = hit
        hit = self._word_hit[state]
        if hit is not None and (best is None or hit < best):
            best = hit
        return best

    def match(self, token: str) -> tuple[int, int] | None:
        """Like search, for a word as it is written: digits read as letters, known clean neighbours left out."""
        hit = self.search(token)
        if (hit is None or hit[0]) and not token.isalpha():
            plain = self.search(token.translate(LEET))
            if plain is not None and (hit is None or plain[0] + 1 < hit[0] + 1):
                hit = (max(1, plain[0]), plain[1])
        return None if hit is not None and hit[0] and token in self.clean else hit


class Scanner:
    """Features of texts; words known to be clean are kept per worker."""

    def __init__(self, lexicon: FuzzyLexicon, window: int = 6, keep: int = 200_000):
        self.lexicon, self.window, self.keep = lexicon, window, keep
        self.none: set[str] = set()
        self.hits: dict[str, tuple[int, int]] = {}

    def found(self, words: set[str]) -> dict[str, tuple[int, int]]:
        out = {}
        for w in words - self.none:
            hit = self.hits.get(w)
            if hit is None:
                hit = self.lexicon.match(w)
                if hit is None:
                    self.none.add(w)
                    continue
                self.hits[w] = hit
            out[w] = hit
        if len(self.none) + len(self.hits) > self.keep:
            self.none.clear()
            self.hits.clear()
        return out

    def context(self, low: str, places: list[re.Match], k: int) -> float:
        """Share of abuse in hit ``k``: 1 for plain use or address, less for quotation and report."""
        a, b = max(0, k - self.window), min(len(places), k + self.window + 1)
        start, end = places[k].span()
        left = max(low.rfind("\n", 0, start) + 1, start - 200)
        quoted = len(QUOTES.findall(low, left, start)) % 2 == 1 and QUOTES.search(low, end, end + 200) is not None
        near = {places[i].group() for i in range(a, b)}
        score = 1.0 - 0.6 * quoted - 0.25 * bool(near & REPORT) + 0.25 * bool(near & ADDRESS)
        return min(1.0, max(0.05, score))

    def features(self, text: str) -> list[float]:
        low = text.lower()
        found = self.found(set(TOKEN.findall(low)))
        exact = fuzzy = stem = quoted = 0.0
        n = 0
        if found:
            places = list(TOKEN.finditer(low))
            n = len(places)
            for k, m in enumerate(places):
                hit = found.get(m.group())
                if hit is not None:
                    abuse = self.context(low, places, k)
                    quoted += 1 - abuse
                    if hit[0]:
                        fuzzy += abuse
                    elif self.lexicon.terms[hit[1]].endswith("*"):
                        stem += abuse
                    else:
                        exact += abuse
        total = exact + fuzzy + stem
        return [math.log1p(exact), math.log1p(fuzzy), math.log1p(stem), math.log1p(quoted), float(exact + stem >= 0.5), 100 * total / (n + 1), float(total >= 1.5), 1.0]


def logistic(x: np.ndarray, y: np.ndarray, l2: float = 1e-2, steps: int = 60) -> np.ndarray:
    """Weights by damped Newton steps; the last feature is the constant."""
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + l2 * w
        h = (x * (p * (1 - p))[:, None]).T @ x + (l2 + 1e-6) * np.eye(x.shape[1])
        step = np.linalg.solve(h, g)
        w -= step * min(1.0, 5.0 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-6:
            break
    return w


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, folds: int, out: int, rows: int) -> DataFrame:
    """(doc_id, text, y) of about ``rows`` labelled documents outside fold ``out``."""
    own = labels.select(F.col("doc_id").cast("long").alias("__l"), F.col(column).cast("int").alias("y")).filter(F.col("y").isin(0, 1) & (fold(F.col("__l"), folds) != out)).dropDuplicates(["__l"])
    n = own.count()
    if n > rows:
        own = own.filter(F.pmod(F.xxhash64("__l"), F.lit(1_000_003)) < int(1_000_003 * rows / n))
    return texts(docs).join(F.broadcast(own) if n <= 200_000 or n > rows else own, F.col("doc_id") == F.col("__l")).select("doc_id", "text", "y")


def learn(docs: DataFrame, labels: DataFrame, *, sample_rows: int = SAMPLE_ROWS, precision: float = 0.95) -> tuple[list[str], set[str], list[float]]:
    """Lexicon terms, known clean neighbours of terms, and the weights of the features."""
    sample = cut(labelled_sample(docs, labels, "toxic", 5, 0, sample_rows))
    n_toxic = sample.filter("y = 1").count()

    def count(batches):
        import pyarrow as pa

        tally: dict[str, list[int]] = {}
        for batch in batches:
            for text, y in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                words = set(TOKEN.findall(text.lower()))
                for w in words | {w[:k] + "*" for w in words for k in range(4, 8) if len(w) > k}:
                    tally.setdefault(w, [0, 0])[y] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(tally), pa.string()), pa.array([v[1] for v in tally.values()], pa.int64()), pa.array([v[0] for v in tally.values()], pa.int64())], ["term", "toxic", "other"])

    terms = cut(sample.mapInArrow(lean(count), "term string, toxic long, other long").groupBy("term").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other")))
    support = max(4, n_toxic // 100)
    strong = terms.filter((F.col("toxic") >= support) & (F.col("toxic") >= precision * (F.col("toxic") + F.col("other")))).orderBy(F.desc("toxic"), "term").collect()
    stems = {r["term"] for r in strong if r["term"].endswith("*")}
    stems = {s for s in stems if not any(s[:k] + "*" in stems for k in range(4, len(s) - 1))}
    covered = tuple(s[:-1] for s in stems)
    words = [r for r in strong if not r["term"].endswith("*")]
    whole = {r["term"]: r["toxic"] for r in words}
    rows = {r["term"]: r["toxic"] for r in strong}
    # a stem is worth keeping only where it covers more documents than its best whole word
    stems = {s for s in stems if rows[s] > 1.2 * max([0, *(n for w, n in whole.items() if w.startswith(s[:-1]))])}
    covered = tuple(s[:-1] for s in stems)
    lexicon_terms = sorted(stems) + [w for w in whole if not w.startswith(covered)] if stems else list(whole)

    def neighbours(batches):
        import pyarrow as pa

        lexicon = FuzzyLexicon(lexicon_terms)
        for batch in batches:
            own = [t for t in batch.column(0).to_pylist() if (hit := lexicon.match(t)) is not None and hit[0]]
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.string())], ["term"])

    # neighbours seen in one clean document alone stay hits here, as new ones will when texts are scored
    seen = terms.filter("other > 1 and other * 3 > toxic and not endswith(term, '*')")
    clean = {r["term"] for r in seen.select("term").mapInArrow(lean(neighbours), "term string").collect()} if lexicon_terms else set()

    def featured(batches):
        import pyarrow as pa

        scan = Scanner(FuzzyLexicon(lexicon_terms, clean))
        for batch in batches:
            x = [scan.features(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), batch.column(2)], ["x", "y"])

    rows = sample.select("doc_id", "text", "y").mapInArrow(lean(featured), "x array<double>, y int").collect()
    y = np.array([r["y"] for r in rows], float)
    if not len(y) or y.min() == y.max():
        return [], set(), [0.0] * (FEATURES - 1) + [-30.0]
    return lexicon_terms, clean, logistic(np.array([r["x"] for r in rows]), y).tolist()


def score(docs: DataFrame, model: tuple[list[str], set[str], list[float]], columns: list[str] | None = None) -> DataFrame:
    """doc_id, score, n_hits; with ``columns``, those columns of the input and the score."""
    terms, clean, weights = model
    w = np.array(weights)

    def run(batches):
        import pyarrow as pa

        scan = Scanner(FuzzyLexicon(terms, clean))
        for batch in batches:
            for part in text_chunks(batch, 8_000_000):
                x = np.array([scan.features(t or "") for t in part.column(part.schema.get_field_index("text")).to_pylist()])
                p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(p)], [*part.schema.names, "__score"])

    rows = texts(docs) if columns is None else docs.select(*columns)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields) + ", __score double"
    return rows.mapInArrow(lean(run), schema)


def judge(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.5, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    out = score(docs, learn(docs, labels, sample_rows=sample_rows))
    return out.select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.5, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """All columns of the documents that are not rejected."""
    return score(docs, learn(docs, labels, sample_rows=sample_rows), docs.columns).filter(F.col("__score") < threshold).drop("__score")
