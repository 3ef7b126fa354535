"""Stupid-backoff scores of each text against the n-gram counts of the whole corpus.

Texts are taken in groups of some megabytes, as the scan gives them. Each group sends every n-gram it has, once and with
its count, to the n-gram's hash partition; there the counts of all groups are summed, the count table of that partition
(`count_table`), and each group gets back the totals of the n-grams it asked for, which are then summed for each text.
So n-grams are exploded, counted and joined in blocks of sorted hashes instead of a row each, and neither the table nor a
group's share of it is ever in one place. A group has a row only for buckets it has n-grams of, so rows never outnumber
n-grams; an n-gram that all texts have is one entry a group. Hashes of 54 bits are sent as gaps between sorted values.

A text's own n-grams are not counted for it: the score uses the corpus count less the text's own, so that a text does
not vouch for itself. Of the n-grams that end in a word w, the longest that the rest of the corpus has counts: for v w of
m words, S(w | v) = alpha^(order - m) c(v w) / c(v); without any, S is alpha^(order - 1) c(w) / N. The first words of a
text, whose context is shorter, pay alpha for each word that lacks. Words that the rest lacks count as one occurrence.
Scores are mean log10 S by word.

Null and empty texts have 0 words and score 0; an empty table gives no rows. Repeated rows and copies vouch for each
other: each is a text. A text longer than a group is a group of its own, so memory is bounded by the longest text. Equal
n-grams have equal counts, so there are no ties to break.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import BLOCK_BYTES, Block, lean, text_arrays

ALPHA = 0.4
GROUP_BYTES = 8_000_000
_BITS = 54
_LOW = np.uint64((1 << _BITS) - 1)


def squeezed(a: np.ndarray) -> bytes:
    return pa.compress(a.tobytes(), codec="zstd", asbytes=True)


def unsqueezed(data: bytes, dtype, n: int) -> np.ndarray:
    dtype = np.dtype(dtype)
    return np.frombuffer(pa.decompress(data, n * dtype.itemsize, codec="zstd", asbytes=True), dtype) if n else np.zeros(0, dtype)


def pack_keys(keys: np.ndarray) -> bytes:
    """Sorted distinct values: the low 32 bits of the gaps as they are, the rest squeezed."""
    gaps = np.diff(keys, prepend=np.uint64(0))
    return (gaps & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes() + squeezed((gaps >> np.uint64(32)).astype(np.uint32))


def unpack_keys(data: bytes, n: int) -> np.ndarray:
    low, high = np.frombuffer(data, np.uint32, n).astype(np.uint64), unsqueezed(data[4 * n :], np.uint32, n).astype(np.uint64)
    return np.cumsum(low + (high << np.uint64(32)), dtype=np.uint64)


def pack_counts(n: np.ndarray) -> bytes:
    """Counts of any size: a byte each, and those from 255 on in full."""
    return n[n >= 255].astype(np.int64).tobytes() + squeezed(np.minimum(n, 255).astype(np.uint8)) + int((n >= 255).sum()).to_bytes(8, "little")


def unpack_counts(data: bytes, n: int) -> np.ndarray:
    large = int.from_bytes(data[-8:], "little")
    out = unsqueezed(data[8 * large : -8], np.uint8, n).astype(np.int64)
    out[out == 255] = np.frombuffer(data, np.int64, large)
    return out


@lean
def _dealt(batches: Iterator[pa.RecordBatch], group_bytes: int) -> Iterator[pa.RecordBatch]:
    """Rows of the partition in groups of about group_bytes of text: a row each, with the texts end to end, squeezed."""
    from pyspark import TaskContext

    part, number = TaskContext.get().partitionId(), 0
    ids, texts, sizes, held = [], [], [], 0

    def group():
        data = np.concatenate(texts)
        size = np.concatenate(sizes).astype(np.int64)
        one = [pa.array([(part << 32) + number], pa.int64()), pa.array([[x for i in ids for x in i.to_pylist()]], pa.list_(pa.int64())), pa.array([squeezed(size)], pa.binary()), pa.array([squeezed(data)], pa.binary())]
        return pa.RecordBatch.from_arrays(one, names=["grp", "ids", "sizes", "texts"])

    for batch in batches:
        data, offsets = text_arrays(batch.column("text"))
        i, n = 0, batch.num_rows
        while i < n:
            j = min(n, max(i + 1, int(np.searchsorted(offsets, offsets[i] + max(1, group_bytes - held), side="right")) - 1))
            ids.append(batch.column("doc_id")[i:j])
            texts.append(data[offsets[i] : offsets[j]])
            sizes.append(np.diff(offsets[i : j + 1]))
            held += int(offsets[j] - offsets[i])
            i = j
            if held >= group_bytes or i < n:
                yield group()
                number, held = number + 1, 0
                ids, texts, sizes = [], [], []
    if ids:
        yield group()


def group_blocks(row: dict) -> list[Block]:
    """The texts of a group, in blocks."""
    size = unsqueezed(row["sizes"], np.int64, len(row["ids"]))
    offsets = np.concatenate([[0], np.cumsum(size)])
    data = unsqueezed(row["texts"], np.uint8, int(offsets[-1]))
    out, i = [], 0
    while i < len(size):
        j = min(len(size), max(i + 1, int(np.searchsorted(offsets, offsets[i] + BLOCK_BYTES, side="right")) - 1))
        out.append(Block(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]))
        i = j
    return out


def grams_of(block: Block, order: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """For 1 to `order` words: 54-bit hashes of n-grams, and the place of the first word of each."""
    out = [(block.hash & _LOW, np.arange(len(block.start)))]
    for n in range(2, order + 1):
        grams, good = block.grams(n)
        out.append((grams[good] & _LOW, np.flatnonzero(good)))
    return out


def _counted(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and how often each occurs; sorts its argument."""
    keys.sort()
    at = np.flatnonzero(np.append(True, keys[1:] != keys[:-1])) if len(keys) else np.zeros(0, np.int64)
    return keys[at], np.diff(np.append(at, len(keys)))


@lean
def _asked(batches: Iterator[pa.RecordBatch], bits: int, order: int) -> Iterator[pa.RecordBatch]:
    """One row for each group and bucket that it has n-grams of: these, sorted, and their counts."""
    for batch in batches:
        for row in batch.to_pylist():
            found = [g for block in group_blocks(row) for g, _ in grams_of(block, order)]
            keys, counts = _counted(np.concatenate(found) if found else np.zeros(0, np.uint64))
            del found
            bucket = (keys >> np.uint64(_BITS - bits)).astype(np.int64)
            edge = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])) if len(keys) else np.zeros(0, np.int64)
            spans = list(zip(edge.tolist(), [*edge[1:].tolist(), len(keys)], strict=False))
            columns = [pa.array(bucket[edge].astype(np.int32)), pa.array(np.full(len(edge), row["grp"])), pa.array(np.array([b - a for a, b in spans], np.int32)), pa.array([pack_keys(keys[a:b]) for a, b in spans], pa.binary()), pa.array([pack_counts(counts[a:b]) for a, b in spans], pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=["bucket", "grp", "n", "grams", "counts"])


def _summed(table: pa.Table) -> tuple[list[dict], list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
    """A hash partition's rows, their keys, and its count table: sorted keys, totals, and the place of each key sent."""
    rows = table.to_pylist()
    keys = [unpack_keys(r["grams"], r["n"]) for r in rows]
    every, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.zeros(len(every), np.int64)
    end = 0
    for r in rows:
        total[inverse[end : end + r["n"]]] += unpack_counts(r["counts"], r["n"])
        end += r["n"]
    return rows, keys, every, total, inverse


def _answered(table: pa.Table) -> pa.Table:
    """A hash partition: sums the counts of all groups and answers each group in the order it asked."""
    rows, keys, _, total, inverse = _summed(table)
    ends = np.cumsum([len(k) for k in keys])
    out = [pack_counts(total[inverse[e - len(k) : e]]) for k, e in zip(keys, ends, strict=True)]
    return pa.table({"grp": pa.array([r["grp"] for r in rows], pa.int64()), "bucket": pa.array([r["bucket"] for r in rows], pa.int32()), "n": pa.array([r["n"] for r in rows], pa.int32()), "totals": pa.array(out, pa.binary())})


def _tabled(table: pa.Table) -> pa.Table:
    _, _, every, total, _ = _summed(table)
    return pa.table({"gram": pa.array(every.astype(np.int64)), "n": pa.array(total)})


def _scores(groups: pa.Table, answers: pa.Table, words: int, order: int) -> pa.Table:
    rows = sorted(answers.select(["bucket", "n", "totals"]).to_pylist(), key=lambda r: r["bucket"])
    total = np.concatenate([unpack_counts(r["totals"], r["n"]) for r in rows]) if rows else np.zeros(0, np.int64)
    ids, score, n_words = [], [], []
    for row in groups.to_pylist():  # one
        found = group_blocks(row)
        grams = [grams_of(block, order) for block in found]
        keys = np.concatenate([g for one in grams for g, _ in one])
        # Numbers of texts rise along each n-gram length of a block only, so the stable order is by key, block, length and text.
        docs = np.concatenate([(block.doc[first] + at).astype(np.int32) for at, block, one in zip(np.cumsum([0, *(b.n_docs for b in found)]), found, grams, strict=False) for _, first in one])
        order_ = np.argsort(keys, kind="stable")
        sorted_, owner = keys[order_], docs[order_]
        del keys, docs
        new = np.append(True, sorted_[1:] != sorted_[:-1]) if len(sorted_) else np.zeros(0, bool)
        fresh = new.copy()
        fresh[1:] |= owner[1:] != owner[:-1]
        del sorted_, owner
        run = np.cumsum(fresh, dtype=np.int32) - 1
        rest = np.empty(len(run), np.int64)
        # The corpus count of each n-gram's occurrence less the count in its own text.
        if len(run):
            rest[order_] = total[np.cumsum(new, dtype=np.int32) - 1] - np.bincount(run)[run]
        del new, fresh, run, order_
        at = 0
        for block, one in zip(found, grams, strict=True):
            n, doc = block.n_words, block.doc
            count = rest[at : at + len(doc)]
            at += len(doc)
            logs = np.log10(ALPHA ** (order - 1) * np.maximum(count, 1) / words)
            for m, (_, first) in enumerate(one[1:], 2):
                c = rest[at : at + len(first)]
                at += len(first)
                seen = c > 0
                logs[first[seen] + m - 1] = np.log10(ALPHA ** (order - m) * c[seen] / np.maximum(count[first[seen]], c[seen]))
                count = np.zeros(len(doc), np.int64)
                count[first] = c
            score.append(np.bincount(doc, logs, minlength=block.n_docs) / np.maximum(n, 1))
            n_words.append(n)
        ids += row["ids"]
    return pa.table({"doc_id": pa.array(ids, pa.int64()), "n_words": pa.array(np.concatenate(n_words).astype(np.int64)), "score": pa.array(np.concatenate(score))})


def _grouped(docs: DataFrame, group_bytes: int, order: int) -> tuple[DataFrame, DataFrame, int]:
    """(groups, asked, words): the texts by group, what each group asks of each bucket, and the number of words."""
    if order < 1:
        raise ValueError(f"order {order} is less than 1")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    n_bytes, words = texts.agg(F.sum(F.octet_length("text")), F.sum(F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+")))).first()
    groups = max(1, -(-(n_bytes or 0) // group_bytes))
    bits = max(3, (groups - 1).bit_length() - 1)  # buckets grow with the groups, so a partition's table keeps its size
    dealt = texts.mapInArrow(lambda it: _dealt(it, group_bytes), "grp long, ids array<long>, sizes binary, texts binary").repartition(groups, "grp")
    return dealt, dealt.mapInArrow(lambda it: _asked(it, bits, order), "bucket int, grp long, n int, grams binary, counts binary"), max(1, words or 0)


def count_table(docs: DataFrame, group_bytes: int = GROUP_BYTES, order: int = 2) -> DataFrame:
    """(gram, n): how often each n-gram of 1 to `order` words, by its hash, occurs in docs (doc_id, text); partitioned by hash."""
    return _grouped(docs, group_bytes, order)[1].groupBy("bucket").applyInArrow(_tabled, "gram long, n long")


def backoff_scores(docs: DataFrame, group_bytes: int = GROUP_BYTES, order: int = 2) -> DataFrame:
    """(doc_id, n_words, score) for each row of docs (doc_id, text), by n-grams of up to `order` words."""
    dealt, asked, words = _grouped(docs, group_bytes, order)
    answers = asked.groupBy("bucket").applyInArrow(_answered, "grp long, bucket int, n int, totals binary")
    return dealt.groupBy("grp").cogroup(answers.groupBy("grp")).applyInArrow(lambda a, b: _scores(a, b, words, order), "doc_id long, n_words long, score double")
