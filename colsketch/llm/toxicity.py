"""Toxicity by a lexicon that is learned from labels, with misspelled terms and the context of each hit.

Terms are words and word beginnings that labelled toxic texts have and others lack. They form a trie; its intersection
with the Levenshtein automaton of distance one is walked as one deterministic automaton, whose states are made when
they are first met, so most words leave it after a few letters. A hit counts by its context window of WINDOW words to
each side: quoted if an opening and a closing quotation mark inside the window enclose it, else reported if the window has
words that labelled clean texts have around terms and toxic ones lack, else bare; and by how many hits the window holds.
A logistic model over these figures, fitted on the same bounded sample, gives the score.

Null and empty texts, and texts without letters, have no hits and get the score of a text without hits. Without
labelled rows of both kinds no term is learned and every score is 0. Repeated rows are scored each. An empty table gives
no rows. Of equally near terms a word matches the first in code point order. Texts of any length are read whole.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import lean

#: Most labelled rows that the lexicon and the model are fitted on.
MAX_LABELLED = 20_000
PREFIXES = (4, 5, 6)
WINDOW = 12
WORD = re.compile(r"[^\W_]+")
_QUOTES = re.compile('["“”„«»]')
_MEMO = 300_000


class Automaton:
    """Trie of terms with at most one edit for whole words of `shortest` letters or more; word beginnings match exactly.

    match() gives (term, edits) of the best match or None. A state is a set of (trie node, edits).
    """

    def __init__(self, words: dict[str, float], beginnings: dict[str, float], shortest: int = 5):
        self.weights = {**{b + "*": w for b, w in beginnings.items()}, **words}
        self.children: list[dict[str, int]] = [{}]
        self.word: list[str | None] = [None]
        self.begin: list[str | None] = [None]
        self.fuzzy: list[bool] = [False]  # a term that may be misspelled lies below
        for term, begins in [*((w, False) for w in sorted(words)), *((b, True) for b in sorted(beginnings))]:
            node, path = 0, [0]
            for c in term:
                if c not in self.children[node]:
                    self.children[node][c] = len(self.children)
                    self.children.append({})
                    self.word.append(None)
                    self.begin.append(None)
                    self.fuzzy.append(False)
                node = self.children[node][c]
                path.append(node)
            if begins:
                self.begin[node] = term + "*"
            else:
                self.word[node] = term
                if len(term) >= shortest:
                    for p in path:
                        self.fuzzy[p] = True
        self.shortest = shortest
        self.states: dict[frozenset, int] = {}
        self.sets: list[frozenset] = []
        self.moves: list[dict[str, int]] = []
        self.first = self._state(self._closed({(0, 0)}))

    def _closed(self, pairs: set) -> frozenset:
        out = set(pairs)
        for node, edits in pairs:  # a letter of the term is missing
            if edits == 0 and self.fuzzy[node]:
                out |= {(c, 1) for c in self.children[node].values() if self.fuzzy[c]}
        return frozenset(x for x in out if not (x[1] and (x[0], 0) in out))

    def _state(self, pairs: frozenset) -> int:
        if pairs not in self.states:
            self.states[pairs] = len(self.sets)
            self.sets.append(pairs)
            self.moves.append({})
        return self.states[pairs]

    def _move(self, state: int, c: str) -> int:
        out = set()
        for node, edits in self.sets[state]:
            child = self.children[node].get(c)
            if child is not None and (edits == 0 or self.fuzzy[child]):
                out.add((child, edits))
            if edits == 0 and self.fuzzy[node]:
                out.add((node, 1))  # a letter too many
                out |= {(k, 1) for k in self.children[node].values() if self.fuzzy[k]}  # another letter
        return self._state(self._closed(out)) if out else -1

    def match(self, word: str) -> tuple[str, int] | None:
        state, moves, found = self.first, self.moves, None
        for c in word:
            to = moves[state].get(c)
            if to is None:
                to = moves[state][c] = self._move(state, c)
            if to < 0:
                return found
            state = to
            for node, edits in self.sets[state]:
                if not edits and self.begin[node]:
                    found = (self.begin[node], 0)
        ends = [(edits, self.word[node]) for node, edits in self.sets[state] if self.word[node] and (not edits or len(self.word[node]) >= self.shortest)]
        if ends:
            edits, term = min(ends)
            if not edits or not found:
                return term, edits
        return found


FIGURES = ("bare", "quoted", "reported", "misspelled", "dense", "share")


@dataclass
class Model:
    words: dict[str, float] = field(default_factory=dict)
    beginnings: dict[str, float] = field(default_factory=dict)
    innocent: frozenset = frozenset()
    report: frozenset = frozenset()
    weights: np.ndarray | None = None


def quotations(text: str) -> list[tuple[int, int]]:
    """(start, end) between an opening mark and the next closing one, in order.

    A straight mark opens if text follows and none stands before it, and closes the other way round; one with text or
    space on both sides is neither, as in 6" of rain. The German closing mark is an opening one elsewhere: it closes where
    a low mark is open.
    """
    out, opened, low = [], -1, False
    for m in _QUOTES.finditer(text):
        at, mark = m.start(), m.group()
        before, after = at > 0 and not text[at - 1].isspace() and text[at - 1] not in "([{-—–", at + 1 < len(text) and (text[at + 1].isalnum() or text[at + 1] in "¿¡'’.…")
        if mark == '"':
            opens, closes = after and not before, before and not after
        elif mark == "“":
            opens, closes = not low, low and opened >= 0
        else:
            opens, closes = mark in "„«", mark in "”»"
            if mark in "«»" and ((mark == "«") == (before and not after)) and before != after:
                opens, closes = closes, opens
        if closes and opened >= 0:
            out.append((opened + 1, at))
            opened = -1
        elif opens:
            opened, low = at, mark == "„"
    return out


class Scorer:
    def __init__(self, model: Model):
        self.model, self.automaton = model, Automaton(model.words, model.beginnings)
        self.seen: set[str] = set()
        self.hits: dict[str, tuple[float, int]] = {}

    def figures(self, text: str | None) -> tuple[list[float], int]:
        """FIGURES, and the number of hits."""
        low = (text or "").lower()
        words, at = self.found(low)
        if not at:
            return [0.0] * len(FIGURES), 0
        known, report = self.hits, self.model.report
        spans = [m.span() for m in WORD.finditer(low)]
        quotes = quotations(low)
        bare = quoted = reported = wrong = 0.0
        dense, first, j = 0, 0, 0
        for place, i in enumerate(at):
            weight, edits = known[words[i]]
            a, z = max(0, i - WINDOW), min(len(words), i + WINDOW + 1)
            while j < len(quotes) and quotes[j][1] <= spans[i][0]:
                j += 1
            # Both marks lie inside the window, or just beside its words.
            inside = j < len(quotes) and quotes[j][0] <= spans[i][0] and quotes[j][0] >= (spans[a - 1][1] if a else 0) and quotes[j][1] <= (spans[z][0] if z < len(words) else len(low))
            if edits:
                wrong += weight
            elif inside:
                quoted += weight
            elif report and any(w in report for w in words[a:z]):
                reported += weight
            else:
                bare += weight
            while at[first] < i - WINDOW:
                first += 1
            dense = max(dense, place - first + 1)
        return [np.log1p(bare), np.log1p(quoted), np.log1p(reported), np.log1p(wrong), np.log1p(dense), min(1.0, 10 * len(at) / len(words))], len(at)

    def found(self, low: str) -> tuple[list[str], list[int]]:
        """The words of a lower-case text and the places of hits among them."""
        words = WORD.findall(low)
        new = set(words) - self.seen
        if new:
            if len(self.seen) > _MEMO:
                self.seen.clear()
                self.hits.clear()
                new = set(words)
            self.seen |= new
            for w in new:
                m = self.automaton.match(w)
                if m and not (m[1] and w in self.model.innocent):
                    self.hits[w] = (self.automaton.weights[m[0]], m[1])
        return words, [i for i, w in enumerate(words) if w in self.hits]

    def around(self, text: str | None) -> set[str] | None:
        """The words in the windows of hits, without hits; None without hits."""
        words, at = self.found((text or "").lower())
        if not at:
            return None
        return {w for i in at for w in words[max(0, i - WINDOW) : i + WINDOW + 1]} - self.hits.keys()

    def score(self, x: np.ndarray) -> np.ndarray:
        w = self.model.weights
        if w is None:
            return np.zeros(len(x))
        return 1 / (1 + np.exp(-np.clip(x @ w[1:] + w[0], -30, 30)))


def _terms(words: set[str]) -> set[str]:
    return words | {w[:k] + "*" for w in words for k in PREFIXES if len(w) > k}


@lean
def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    n, toxic = Counter(), Counter()
    for batch in batches:
        for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist(), strict=True):
            terms = _terms(set(WORD.findall((text or "").lower())))
            n.update(terms)
            if label:
                toxic.update(terms)
        if len(n) > 500_000:
            yield _counts(n, toxic)
            n, toxic = Counter(), Counter()
    yield _counts(n, toxic)


def _counts(n: Counter, toxic: Counter) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64()), pa.array([toxic[t] for t in n], pa.int64())], names=["term", "n", "toxic"])


@lean
def _sampled(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    scorer = Scorer(model)
    for batch in batches:
        x = [scorer.figures(t)[0] for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), batch.column("label").cast(pa.int32())], names=["x", "label"])


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05, steps: int = 40) -> np.ndarray:
    """Weights, the constant first, by Newton's method with a ridge."""
    z = np.hstack([np.ones((len(x), 1)), x])
    w = np.zeros(z.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        g = z.T @ (p - y) + ridge * np.append(0, w[1:])
        h = (z * (p * (1 - p))[:, None]).T @ z + ridge * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-9:
            break
    return w


def fit(labelled: DataFrame, least: int = 4, odds: float = 3.0) -> Model:
    """labelled: (text, label 0/1), a bounded sample. A term needs `least` toxic texts and log odds of `odds`.

    All terms, near misses and context words of the sample are kept; the sample's bound is theirs.
    """
    counts = {r.label: r.n for r in labelled.groupBy("label").agg(F.count("*").alias("n")).collect()}
    toxic, other = sum(n for k, n in counts.items() if k), counts.get(0, 0)
    if not toxic or not other:
        return Model()
    rows = labelled.select("text", "label").mapInArrow(_counted, "term string, n long, toxic long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("toxic").alias("toxic"))
    score = F.log((F.col("toxic") + 0.5) / (toxic + 1)) - F.log((F.col("n") - F.col("toxic") + 0.5) / (other + 1))
    some = rows.where(F.col("toxic") >= least).withColumn("odds", score).where(F.col("odds") >= odds).collect()  # terms of the sample, which is bounded
    words = {r.term: float(r.odds) for r in some if not r.term.endswith("*")}
    begins = {r.term[:-1]: float(r.odds) for r in some if r.term.endswith("*")}
    # A beginning that one word alone accounts for says no more than the word.
    most = {}
    for r in some:
        if not r.term.endswith("*"):
            for k in PREFIXES:
                most[r.term[:k]] = max(most.get(r.term[:k], 0), r.toxic)
    begins = {b: w for b, w in begins.items() if next(r.toxic for r in some if r.term == b + "*") > 1.5 * most.get(b, 0)}
    model = Model(words, begins)
    # Words of other texts that lie one edit from a term are no misspellings of it.
    model.innocent = frozenset(r.word for r in labelled.where("label = 0").select("text").mapInArrow(lambda it: _close(it, Model(words, {})), "word string").distinct().collect())
    # Words that clean texts have around hits, and toxic ones lack: the hit is then reported, not meant.
    seen = labelled.select("text", "label").mapInArrow(lambda it: _surrounded(it, model), "term string, n long, toxic long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("toxic").alias("toxic")).collect()
    whole = next((r for r in seen if r.term == ""), None)
    if whole is not None:
        clean = whole.n - whole.toxic
        model.report = frozenset(r.term for r in seen if r.term and r.n - r.toxic >= least and np.log((r.n - r.toxic + 0.5) / (clean + 1)) - np.log((r.toxic + 0.5) / (whole.toxic + 1)) >= odds)
    sample = labelled.select("text", "label").mapInArrow(lambda it: _sampled(it, model), "x array<double>, label int").collect()
    model.weights = logistic(np.array([r.x for r in sample]), np.array([float(r.label) for r in sample]))
    return model


@lean
def _close(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    automaton, seen, out = Automaton(model.words, {}), set(), set()
    for batch in batches:
        for text in batch.column("text").to_pylist():
            new = set(WORD.findall((text or "").lower())) - seen
            seen |= new
            out |= {w for w in new if (m := automaton.match(w)) and m[1]}
    yield pa.RecordBatch.from_arrays([pa.array(sorted(out), pa.string())], names=["word"])


@lean
def _surrounded(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    """Texts with each word around their hits, by label; the empty word counts all texts with hits."""
    scorer, n, toxic = Scorer(model), Counter(), Counter()
    for batch in batches:
        for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist(), strict=True):
            terms = scorer.around(text)
            if terms is not None:
                terms.add("")
                n.update(terms)
                if label:
                    toxic.update(terms)
    yield _counts(n, toxic)


@lean
def _scored(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    scorer = Scorer(model)
    for batch in batches:
        found = [scorer.figures(t.as_py()) for t in batch.column("text")]
        x = np.array([f for f, _ in found]).reshape(-1, len(FIGURES))
        score = scorer.score(x)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array((score >= 0.5).astype(np.int32)), pa.array([n for _, n in found], pa.int64())], names=["doc_id", "score", "predicted", "n_hits"])


def toxicity(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score, predicted, n_hits) for each row of docs (doc_id, text)."""
    return docs.select("doc_id", "text").mapInArrow(lambda it: _scored(it, model), "doc_id long, score double, predicted int, n_hits long")


def toxic_flags(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs that are not toxic, with their columns as they are."""
    order, names = docs.schema, docs.columns

    @lean
    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in batches:
            x = np.array([scorer.figures(t.as_py())[0] for t in batch.column(names.index("text"))]).reshape(-1, len(FIGURES))
            yield batch.filter(pa.array(scorer.score(x) < 0.5))

    return docs.mapInArrow(kept, order)
