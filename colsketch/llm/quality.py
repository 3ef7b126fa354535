"""Rule figures of each text, and selection by a hashed n-gram log-likelihood ratio.

The ratio compares two multinomials over hashed words and word pairs: that of trusted target texts and that of the
whole raw corpus. A text's score is the mean logarithm over its n-grams, so that length does not count. A null or an
empty text has no words, score 0, and fails the rules. Repeated rows are judged each, texts of any length whole; an empty
table gives no rows. A score that equals the threshold is kept.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .kernels import SPACE_WORDS, Block, blocks, covered, mix, repeated, sums_by

SYMBOLS = np.isin(np.arange(256), list(b"#*$%&|<>"))
BUCKETS = 10_000
#: Not a bound: all labelled rows count. The name is kept for callers that set it.
MAX_LABELLED = None
_DOC = np.uint64(0x9E3779B97F4A7C15)


def _by_doc(keys: np.ndarray, doc: np.ndarray) -> np.ndarray:
    return mix(keys + doc.astype(np.uint64) * _DOC)


def repeated_lines(block: Block) -> np.ndarray:
    """Lines with a word that equal an earlier line of the same document, counted by document."""
    n = len(block.raw)
    cuts = np.flatnonzero(block.raw == 10)
    start = np.unique(np.concatenate([block.offsets[:-1], cuts + 1]))
    start = start[start < n]
    if not len(start):
        return np.zeros(block.n_docs, np.int64)
    nonempty_doc = np.searchsorted(block.offsets, start, side="right") - 1
    end = np.minimum(np.append(start[1:], n), block.offsets[nonempty_doc + 1])
    end = end - ((end > start) & (block.raw[np.maximum(end - 1, 0)] == 10))
    has_word = np.searchsorted(block.start, end) > np.searchsorted(block.start, start)
    start, end, doc = start[has_word], end[has_word], nonempty_doc[has_word]
    keys = _by_doc(block.range_hash(start, end), doc)
    _, first = np.unique(keys, return_index=True)
    later = np.ones(len(keys), bool)
    later[first] = False
    return np.bincount(doc[later], minlength=block.n_docs).astype(np.int64)


def repeated_words(block: Block, window: int = 8) -> np.ndarray:
    """Words inside windows of `window` words that occur twice or more in the document, counted by document."""
    grams, good = block.grams(window)
    at = np.flatnonzero(good)
    twice = at[repeated(_by_doc(grams[at], block.doc[at]))]
    return sums_by(covered(twice, window, len(block.start)).astype(np.int64), block.ptr)


def gram_buckets(block: Block, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of words, then of word pairs, and the document of each."""
    pairs, good = block.grams(2)
    doc = block.doc
    both = np.concatenate([block.hash, pairs[good]])
    return (both % np.uint64(buckets)).astype(np.int64), np.concatenate([doc, doc[good]])


def _counted(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[pa.RecordBatch]:
    total = np.zeros(buckets, np.int64)
    for batch in batches:
        for _, _, block in blocks(batch.column("text")):
            total += np.bincount(gram_buckets(block, buckets)[0], minlength=buckets)
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["bucket", "n"])


def multinomial(texts: DataFrame, buckets: int = BUCKETS) -> np.ndarray:
    """Counts of hashed n-grams over all texts; `buckets` rows at most reach the driver."""
    rows = texts.select("text").mapInArrow(lambda it: _counted(it, buckets), "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    out = np.zeros(buckets, np.float64)
    for bucket, n in rows.collect():
        out[bucket] = n
    return out


@dataclass
class Selector:
    """log_ratio by bucket, and the least score that is kept."""

    log_ratio: np.ndarray
    threshold: float

    def scores(self, block: Block) -> np.ndarray:
        at, doc = gram_buckets(block, len(self.log_ratio))
        n = np.bincount(doc, minlength=block.n_docs)
        return np.bincount(doc, self.log_ratio[at], minlength=block.n_docs) / np.maximum(n, 1)


def _scored(batches: Iterator[pa.RecordBatch], selector: Selector, key: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, block in blocks(batch.column("text")):
            yield pa.RecordBatch.from_arrays([batch.column(key)[i:j], pa.array(selector.scores(block)), pa.array(block.n_words.astype(np.int64))], names=[key, "score", "n"])


def _below(batches: Iterator[pa.RecordBatch], cuts: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(at, n): scores by the number of cuts that they reach."""
    total = np.zeros(len(cuts) + 1, np.int64)
    for batch in batches:
        total += np.bincount(np.searchsorted(cuts, np.asarray(batch.column("score")), side="right"), minlength=len(total))
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["at", "n"])


def threshold(scores: DataFrame, most_lost: float) -> float:
    """scores: (label, score). Of the trusted scores that lose at most the share `most_lost`, the one with the fewest errors.

    These scores reach the driver, 8 bytes each; all others are counted between them in their tasks.
    """
    scores = cut(scores)
    n = {r.label: r.n for r in scores.groupBy("label").agg(F.count("*").alias("n")).collect() if r.label in (0, 1)}
    if len(n) < 2:
        return -np.inf
    lowest = scores.where("label = 1").select("score").orderBy("score").limit(int(most_lost * n[1]) + 1)
    cuts = np.sort(np.asarray(lowest.toArrow().column("score")))
    found = scores.where("label = 0").select("score").mapInArrow(lambda it: _below(it, cuts), "at long, n long").groupBy("at").agg(F.sum("n").alias("n"))
    other = np.zeros(len(cuts) + 1, np.int64)
    for at, m in found.collect():  # a row for each cut at most
        other[at] = m
    errors = np.searchsorted(cuts, cuts) / n[1] + 1 - other.cumsum()[np.searchsorted(cuts, cuts)] / n[0]
    return float(cuts[np.argmin(errors)])


def fit(docs: DataFrame, labelled: DataFrame, trusted: DataFrame | None = None, *, buckets: int = BUCKETS, smoothing: float = 1.0, most_lost: float = 0.002, shortest: int = 20, labels: DataFrame | None = None) -> Selector:
    """docs: the raw corpus, all of it. labelled: (text, label), all labelled texts, label 1 for trusted ones; or (doc_id, text)
    if labels (doc_id, label) are given, so that scores are joined rather than texts.
    trusted: (text), all trusted texts, those of labelled if not given.

    The threshold parts the labelled texts with the fewest errors (trusted and other texts weighed alike), but loses
    at most the share `most_lost` of the trusted texts of `shortest` words or more. Without both kinds nothing is rejected.
    """
    raw, target = multinomial(docs, buckets), multinomial(labelled.where("label = 1") if trusted is None else trusted, buckets)
    ratio = np.log((target + smoothing) / (target.sum() + smoothing * buckets)) - np.log((raw + smoothing) / (raw.sum() + smoothing * buckets))
    if not target.sum():
        return Selector(np.zeros(buckets), -np.inf)
    first = Selector(ratio, -np.inf)
    key = "label" if labels is None else "doc_id"
    rows = labelled.select(F.col(key).cast("long"), "text").mapInArrow(lambda it: _scored(it, first, key), f"{key} long, score double, n long").where(F.col("n") >= shortest)
    scores = rows if labels is None else rows.join(labels, "doc_id")
    return Selector(ratio, threshold(scores.select("label", "score"), most_lost))


def figures(block: Block, selector: Selector | None) -> dict[str, np.ndarray]:
    n = block.n_words.astype(np.int64)
    symbols = sums_by(SYMBOLS[block.raw].astype(np.int64), block.offsets)
    repeat = repeated_words(block)
    failed = (n < 20) | (100 * repeat > 30 * n)
    score = selector.scores(block) if selector else np.zeros(block.n_docs)
    kept = ~failed & (score >= (selector.threshold if selector else -np.inf))
    return {"n_words": n, "word_chars": block.characters(), "n_symbols": symbols, "n_dup_lines": repeated_lines(block), "n_repeat_words": repeat, "base_failed": failed, "kept": kept, "score": score}


def _figures(batches: Iterator[pa.RecordBatch], selector: Selector | None) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, block in blocks(batch.column("text"), SPACE_WORDS):
            out = figures(block, selector)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")[i:j], *map(pa.array, out.values())], names=["doc_id", *out])


def quality(docs: DataFrame, selector: Selector | None = None) -> DataFrame:
    """Rule figures and verdict for each row of docs (doc_id, text)."""
    sent = selector
    return docs.select("doc_id", "text").mapInArrow(lambda it: _figures(it, sent), "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, score double")

