"""Language identification with unigram piece models, summing over all segmentations of each word.

The pieces are those of a fixed public vocabulary, with single bytes for all else. Each language has a probability for
each piece, estimated by expectation maximisation over the segmentations of its training words. A word's probability in
a language is the sum over all ways to cut it into pieces, by the forward recursion; a text's is the product over its
words. Words are runs of ASCII letters and characters outside ASCII, A-Z lower-cased; runs of over LONGEST_WORD bytes count
as consecutive words, so that the products of a word's probabilities stay in range. Every piece of the vocabulary that
words can contain takes part, however long.

The language of a null text or one without a letter is `und`, with score 0. Repeated rows are predicted each. Ties go to
the first language in code point order. An empty table gives no rows; without labelled rows every language is `und`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import Block, blocks

#: Most labelled rows that the piece probabilities are fitted on.
MAX_LABELLED = 12_000
LONGEST_WORD = 64
_b = np.arange(256)
LETTERS = ((_b >= 65) & (_b <= 90)) | ((_b >= 97) & (_b <= 122)) | (_b >= 128)
_CODE = np.random.Generator(np.random.PCG64(5)).integers(1, 1 << 63, 256, dtype=np.uint64) | np.uint64(1)
_STEP = np.uint64(0x9E3779B97F4A7C15)
#: Each byte's probability is scaled by this in the recursion, so that long words stay in range.
_SCALE = 24.0


def default_vocabulary() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("piece_bpe_32k.model"))


def _hash(piece: bytes) -> int:
    h = 0
    for x in piece:
        h = (h * int(_STEP) + int(_CODE[x])) & ((1 << 64) - 1)
    return h


class Lattice(NamedTuple):
    """Pieces met in words: where each starts, its length in bytes, and its number."""

    at: np.ndarray
    size: np.ndarray
    piece: np.ndarray


class Pieces:
    """Looks pieces up at every place and length at once: a filter of 2^20 bits, then a sorted table of hashes."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        found = {bytes([x]) for x in range(256)}
        for k in range(model.get_piece_size()):
            if not (model.is_byte(k) or model.is_control(k) or model.is_unknown(k)):
                p = model.id_to_piece(k).replace("▁", " ").encode()
                body = p.removeprefix(b" ")
                if p and LETTERS[list(body)].all() and body == body.lower():
                    found.add(p)
        self.pieces = sorted(found)
        h = np.array([_hash(p) for p in self.pieces], np.uint64)
        order = np.argsort(h)
        self.hash, self.ids = h[order], order.astype(np.int32)
        self.filter = np.zeros(1 << 20, bool)
        self.filter[h >> np.uint64(44)] = True
        self.n, self.longest = len(self.pieces), max(map(len, self.pieces))

    def lattice(self, data: np.ndarray, left: np.ndarray) -> Lattice:
        """Every piece at every place. left: bytes from a place to the end of its word."""
        places, sizes, ids = [], [], []
        at, h = np.arange(len(data)), np.zeros(len(data), np.uint64)
        for length in range(1, self.longest + 1):
            inside = left[at] >= length
            at, h = at[inside], h[inside]
            if not len(at):
                break
            h = h * _STEP + _CODE[data[at + length - 1]]
            maybe = np.flatnonzero(self.filter[h >> np.uint64(44)])
            place = np.searchsorted(self.hash, h[maybe])
            place[place == self.n] = 0
            good = self.hash[place] == h[maybe]
            places.append(at[maybe[good]])
            sizes.append(np.full(int(good.sum()), length))
            ids.append(self.ids[place[good]])
        if not places:
            return Lattice(*(np.zeros(0, np.int64) for _ in range(3)))
        return Lattice(np.concatenate(places), np.concatenate(sizes), np.concatenate(ids))


@lru_cache(maxsize=2)
def pieces(path: str) -> Pieces:
    return Pieces(path)


class Words:
    """Distinct words of a block, each with a space before it, longest first and end to end."""

    def __init__(self, block: Block):
        start, end, doc = block.start, block.end, block.doc
        sizes = end - start
        if len(sizes) and sizes.max() > LONGEST_WORD:
            parts = -(-sizes // LONGEST_WORD)
            k = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
            start = np.repeat(start, parts) + k * LONGEST_WORD
            end = np.minimum(start + LONGEST_WORD, np.repeat(end, parts))
            doc = np.repeat(doc, parts)
        self.doc = doc
        h = block.range_hash(start, end)
        _, first, self.of = np.unique(h, return_index=True, return_inverse=True)
        sizes = end[first] - start[first] + 1
        order = np.argsort(-sizes, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.of = place[self.of]
        first, self.size = first[order], sizes[order]
        self.at = np.cumsum(self.size) - self.size
        total = int(self.size.sum())
        inner = np.arange(total) - np.repeat(self.at, self.size)
        source = np.repeat(start[first], self.size) + inner - 1
        self.data = np.where(inner == 0, 32, block.data[np.maximum(source, 0)]).astype(np.uint8) if total else np.zeros(0, np.uint8)
        self.left = np.repeat(self.size, self.size) - inner
        self.n = len(self.size)

    def _swept(self, lattice: Lattice, p: np.ndarray, backwards: bool) -> np.ndarray:
        """Sums over all ways to cut each word up to each place (backwards: from each place on); words have one place more
        than bytes. The pieces that end (start) at the same distance are taken together, word by word."""
        word = np.repeat(np.arange(self.n), self.size)
        own = word[lattice.at]
        start = lattice.at - self.at[own]
        far = self.size[own] - start if backwards else start + lattice.size
        order = np.lexsort((own, far))
        own, far, piece = own[order], far[order], lattice.piece[order]
        begin = self.at + np.arange(self.n)
        near = begin[own] + (start + lattice.size if backwards else start)[order]
        into = begin[own] + (start if backwards else start + lattice.size)[order]
        out = np.zeros((len(self.data) + self.n, p.shape[1]))
        out[begin + (self.size if backwards else 0)] = 1.0
        edge = np.searchsorted(far, np.arange(1, int(self.size[0]) + 2 if self.n else 1))
        for x, y in zip(edge[:-1], edge[1:], strict=True):
            if y > x:
                new = np.flatnonzero(np.append(True, own[x + 1 : y] != own[x : y - 1]))
                out[into[x:y][new]] = np.add.reduceat(out[near[x:y]] * p[piece[x:y]], new, axis=0)
        return out

    def forward(self, lattice: Lattice, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Sums up to each place (a row of languages), and where words begin among the places."""
        return self._swept(lattice, p, False), self.at + np.arange(self.n)

    def backward(self, lattice: Lattice, p: np.ndarray) -> np.ndarray:
        return self._swept(lattice, p, True)


@dataclass
class Model:
    vocabulary: str
    languages: list[str]
    p: np.ndarray  # pieces x languages

    def scaled(self) -> np.ndarray:
        table = pieces(self.vocabulary)
        size = np.array([len(x) for x in table.pieces])
        return self.p * (_SCALE ** size)[:, None]

    def log_likelihoods(self, block: Block, scaled: np.ndarray) -> np.ndarray:
        """Documents x languages."""
        words = Words(block)
        out = np.zeros((block.n_docs, len(self.languages)))
        if words.n:
            lattice = pieces(self.vocabulary).lattice(words.data, words.left)
            alpha, begin = words.forward(lattice, scaled)
            logs = np.log(np.maximum(alpha[begin + words.size], 1e-280)) - (words.size * np.log(_SCALE))[:, None]
            for k in range(out.shape[1]):
                out[:, k] = np.bincount(words.doc, logs[words.of, k], minlength=block.n_docs)
        return out


def _expected(batches: Iterator[pa.RecordBatch], vocabulary: str, languages: list[str], p: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """Expected piece counts by language; without p, every piece found anywhere counts once."""
    table = pieces(vocabulary)
    total = np.zeros((table.n, len(languages)))
    place = {x: k for k, x in enumerate(languages)}
    model = Model(vocabulary, languages, p) if p is not None else None
    scaled = model.scaled() if model else None
    for batch in batches:
        label = np.array([place[x] for x in batch.column("label").to_pylist()])
        for i, j, block in blocks(batch.column("text"), LETTERS, lower=True):
            words = Words(block)
            if not words.n:
                continue
            lattice = table.lattice(words.data, words.left)
            n = np.zeros((words.n, len(languages)))
            np.add.at(n, (words.of, label[i:j][words.doc]), 1.0)
            word = np.repeat(np.arange(words.n), words.size)
            own = word[lattice.at]
            if model is None:
                share = n[own]
            else:
                alpha, begin = words.forward(lattice, scaled)
                beta = words.backward(lattice, scaled)
                z = np.maximum(alpha[begin + words.size], 1e-280)
                inner = lattice.at - words.at[own] + begin[own]
                share = alpha[inner] * scaled[lattice.piece] * beta[inner + lattice.size] / z[own] * n[own]
            for k in range(len(languages)):
                total[:, k] += np.bincount(lattice.piece, share[:, k], minlength=table.n)
    at, lang = np.nonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int64)), pa.array(lang.astype(np.int64)), pa.array(total[at, lang])], names=["piece", "lang", "n"])


def fit(labelled: DataFrame, vocabulary: str | None = None, rounds: int = 2, smoothing: float = 0.3) -> Model | None:
    """labelled: (text, label), a bounded sample; None where it is empty. Pieces x languages figures reach the driver."""
    vocabulary = vocabulary or default_vocabulary()
    labelled = labelled.where(F.col("label").isNotNull()).select("text", "label")
    languages = sorted(r.label for r in labelled.select("label").distinct().collect())
    if not languages:
        return None
    p = None
    for _ in range(rounds + 1):
        rows = labelled.mapInArrow(lambda it, now=p: _expected(it, vocabulary, languages, now), "piece long, lang long, n double").groupBy("piece", "lang").agg(F.sum("n").alias("n")).collect()
        n = np.full((pieces(vocabulary).n, len(languages)), smoothing)
        for piece, lang, x in rows:
            n[piece, lang] += x
        p = n / n.sum(axis=0)
    return Model(vocabulary, languages, p)


def _predicted(batches: Iterator[pa.RecordBatch], model: Model | None) -> Iterator[pa.RecordBatch]:
    scaled = model.scaled() if model else None
    for batch in batches:
        for i, j, block in blocks(batch.column("text"), LETTERS, lower=True):
            ascii_letter = LETTERS[block.data] & (block.data < 128)
            counts = np.diff(np.concatenate([[0], np.cumsum(ascii_letter)])[block.offsets])
            letters = np.array([c > 0 or (block.n_words[d] > 0 and any(x.isalpha() for x in block.text(d).decode("utf-8", "replace"))) for d, c in enumerate(counts)], bool)
            if model is None:
                lang, score = ["und"] * block.n_docs, np.zeros(block.n_docs)
            else:
                ll = model.log_likelihoods(block, scaled)
                best = ll.argmax(axis=1)
                score = 1 / np.exp(ll - ll.max(axis=1, keepdims=True)).sum(axis=1)
                lang = [model.languages[b] if ok else "und" for b, ok in zip(best.tolist(), letters.tolist(), strict=True)]
                score = np.where(letters, score, 0.0)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")[i:j], pa.array(lang, pa.string()), pa.array(score)], names=["doc_id", "lang_pred", "score"])


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """(doc_id, lang_pred, score) for each row; score is the language's posterior probability under equal priors."""
    return docs.select("doc_id", "text").mapInArrow(lambda it: _predicted(it, model), "doc_id long, lang_pred string, score double")
