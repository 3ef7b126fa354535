"""Removal of repeated word windows by level-wise doubling.

Windows that repeat at one length alone are looked at again at twice that length, up to the wanted length. A level
does not count every window: of the windows of `length` words inside a wanted window it takes the one with the least
hash, which two equal wanted windows have at the same place, so equal windows are never parted.

Nulls and empty texts have no words. Equal rows (same doc_id and text) are distinct documents for counting, but share
their key (doc_id, position): of such rows none precedes the other. Rows with a null doc_id keep all words and count
for no other row, as they have no place in the order.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernels import MAX64, Block, blocks, covered, mix, sliding

#: Rows that a task gathers before it combines and hands them on.
CHUNK_ROWS = 1_500_000
_PACKED = "bucket int, known boolean, keys binary, docs binary, pos binary"


def alive_windows(block: Block, window: int) -> np.ndarray:
    """True for each word at which a whole window of one document starts."""
    at = np.arange(len(block.start))
    return at + window <= np.repeat(block.ptr[1:], block.n_words)


def least_grams(block: Block, length: int, window: int, alive: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of n-grams, the least hash in each window that is alive, and the places chosen by some such window."""
    grams, _ = block.grams(length)
    width = window - length + 1
    least = np.where(alive, sliding(grams, width), np.uint64(0))
    back = sliding(least[::-1], width, np.maximum, np.uint64(0))[::-1]
    return grams, least, np.flatnonzero((back == grams) & (back > 0))


def windows_of(block: Block, length: int, window: int, alive: np.ndarray, repeats: np.ndarray) -> np.ndarray:
    """The windows that stay alive, as their least n-gram is among the repeated ones (places in `repeats`)."""
    grams, least, _ = least_grams(block, length, window, alive)
    only = np.full(len(grams), MAX64, np.uint64)
    only[repeats] = grams[repeats]
    return alive & (sliding(only, window - length + 1) == least) & (least != MAX64)


def _packets(keys: np.ndarray, docs: np.ndarray, pos: np.ndarray, buckets: int) -> pa.RecordBatch:
    """A chunk's places as one packet for each bucket of keys, and one, marked known, of places that are settled here.

    Of equal keys only the first place goes on, sent twice so that it counts as repeated; all others are known to come
    later. So a key has two places from a chunk at most, however many texts share its words.
    """
    order = np.lexsort((pos, docs, keys))
    keys, docs, pos = keys[order], docs[order], pos[order]
    new = np.ones(len(keys), bool)
    new[1:] = (keys[1:] != keys[:-1]) | (docs[1:] != docs[:-1]) | (pos[1:] != pos[:-1])
    keys, docs, pos = keys[new], docs[new], pos[new]
    known = np.zeros(len(keys), bool)
    known[1:] = keys[1:] == keys[:-1]
    several = np.zeros(len(keys), bool)
    several[:-1] = known[1:]
    sent = np.concatenate([np.flatnonzero(~known), np.flatnonzero(~known & several)])
    # The leading bits of a sorted key are its bucket; inside, places stand as in the texts, which packs best.
    bucket = (keys[sent] >> np.uint64(40)).astype(np.int64) % buckets
    sent = sent[np.lexsort((pos[sent], docs[sent], bucket))]
    bucket = (keys[sent] >> np.uint64(40)).astype(np.int64) % buckets
    edge = np.searchsorted(bucket, np.arange(buckets + 1))
    at = [sent[edge[b] : edge[b + 1]] for b in range(buckets)]
    later = np.flatnonzero(known)
    at.append(later[np.lexsort((pos[later], docs[later]))])
    used = [b for b, x in enumerate(at) if len(x)]
    spread = int(keys[0] % np.uint64(buckets)) if len(keys) else 0
    columns = ([at[b] for b in used], keys, docs, pos.astype(np.int32))
    return pa.RecordBatch.from_arrays([pa.array([spread if b == buckets else b for b in used], pa.int32()), pa.array([b == buckets for b in used], pa.bool_()), *(pa.array([c[x].tobytes() for x in columns[0]], pa.binary()) for c in columns[1:])], names=["bucket", "known", "keys", "docs", "pos"])


def _settled(table: pa.Table, last: bool) -> pa.Table:
    """A bucket's places that repeat (last: that come later than another), as one list for each document."""
    whole = [(k.as_py(), *(np.frombuffer(table.column(c)[i].as_py(), t) for c, t in (("keys", np.uint64), ("docs", np.int64), ("pos", np.int32)))) for i, k in enumerate(table.column("known"))]
    out = [(d, p) for known, _, d, p in whole if known]
    rest = [x[1:] for x in whole if not x[0]]
    if rest:
        keys, docs, pos = (np.concatenate(x) for x in zip(*rest, strict=True))
        order = np.lexsort((pos, docs, keys))
        keys, docs, pos = keys[order], docs[order], pos[order]
        same = np.zeros(len(keys) + 1, bool)
        same[1:-1] = keys[1:] == keys[:-1]
        take = same[:-1] if last else same[1:] | same[:-1]
        if last:  # not the first place itself, which may be there twice
            start = np.maximum.accumulate(np.where(same[:-1], 0, np.arange(len(keys))))
            take &= (docs != docs[start]) | (pos != pos[start])
        out.append((docs[take], pos[take]))
    docs, pos = (np.concatenate(x) for x in zip(*out, strict=True))
    order = np.lexsort((pos, docs))
    docs, pos = docs[order], pos[order]
    edge = np.append(np.flatnonzero(np.append(True, docs[1:] != docs[:-1])), len(docs)) if len(docs) else np.zeros(1, np.int64)
    lists = pa.ListArray.from_arrays(pa.array(edge.astype(np.int32)), pa.array(pos))
    return pa.table({"doc_id": pa.array(docs[edge[:-1]]), "repeats": lists})


def _settled_any(table: pa.Table) -> pa.Table:
    return _settled(table, False)


def _settled_last(table: pa.Table) -> pa.Table:
    return _settled(table, True)


def _rows_in(batches: Iterator[pa.RecordBatch], length: int, before: int | None, window: int, buckets: int) -> Iterator[pa.RecordBatch]:
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    n = 0
    for batch in batches:
        batch = batch.filter(batch.column("doc_id" if before is None else "repeats").is_valid())
        ids = np.asarray(batch.column("doc_id"))
        for i, j, block in blocks(batch.column("text")):
            alive = alive_windows(block, window)
            if before is not None:
                alive = windows_of(block, before, window, alive, _places(block, batch.column("repeats")[i:j]))
            if length == window:
                keys, at = block.grams(length)[0], np.flatnonzero(alive)
            else:
                keys, _, at = least_grams(block, length, window, alive)
            doc = block.doc[at]
            held.append((keys[at], ids[i:j][doc], at - block.ptr[doc]))
            n += len(at)
            if n >= CHUNK_ROWS:
                yield _packets(*(np.concatenate(x) for x in zip(*held, strict=True)), buckets)
                held, n = [], 0
    if n:
        yield _packets(*(np.concatenate(x) for x in zip(*held, strict=True)), buckets)


def _places(block: Block, lists: pa.Array) -> np.ndarray:
    """Word places in the block from lists of places in each document."""
    sizes = np.asarray(lists.value_lengths().fill_null(0))
    flat = np.asarray(lists.flatten()).astype(np.int64)
    return flat + np.repeat(block.ptr[:-1], sizes)


def repeated_windows(docs: DataFrame, window: int = 20, base: int | None = None) -> DataFrame:
    """(doc_id, repeats): the starts, in words, of windows whose words also start earlier; documents without any are left out.

    base: the length of the first level, half of `window` unless given; each next level is twice as long.
    """
    texts = docs.select("doc_id", "text").repartition("doc_id")
    lengths = [base or max(1, window // 2)]
    while lengths[-1] < window:
        lengths.append(min(window, 2 * lengths[-1]))
    # Buckets follow the input's size: some for each of its partitions.
    buckets = max(64, 2 * texts.sparkSession.sparkContext.defaultParallelism, 2 * docs.rdd.getNumPartitions())
    source, before = docs.select("doc_id", "text"), None
    for length in lengths:
        packets = source.mapInArrow(lambda it, a=length, b=before: _rows_in(it, a, b, window, buckets), _PACKED)
        lists = packets.groupBy("bucket").applyInArrow(_settled_last if length == window else _settled_any, "doc_id long, repeats array<int>")
        found = lists.groupBy("doc_id").agg(F.flatten(F.collect_list("repeats")).alias("repeats"))
        # A left join, as in remove_repeats(), so that both read one exchange of the texts.
        source, before = texts.join(found, "doc_id", "left"), length
    return found


_CLEAN = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_text", T.StringType())])


def _removed(batches: Iterator[pa.RecordBatch], window: int, digest: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i, j, block in blocks(batch.column("text")):
            starts = _places(block, batch.column("repeats")[i:j])
            gone = covered(starts, window, len(block.start))
            keep = ~gone
            words = block.n_words
            counts = np.add.reduceat(np.append(gone, False).astype(np.int64), np.minimum(block.ptr[:-1], len(gone))) if len(gone) else np.zeros(len(words), np.int64)
            counts = np.where(words > 0, counts, 0)
            out, raw = [], block.raw.tobytes()
            for d in range(block.n_docs):
                a, b = block.ptr[d], block.ptr[d + 1]
                mask = keep[a:b]
                kept = b" ".join([raw[s:e] for s, e in zip(block.start[a:b][mask].tolist(), block.end[a:b][mask].tolist(), strict=True)])
                out.append(hashlib.sha256(kept).hexdigest() if digest else kept.decode("utf-8", "replace"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")[i:j], pa.array(words.astype(np.int64)), pa.array(counts), pa.array(out, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_text"])


def remove_repeats(docs: DataFrame, window: int = 20, base: int | None = None, digest: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_text) for each row: words outside all repeated windows, joined by one space.

    digest: kept_text is the SHA-256 of that text, in hexadecimal, made where the text is.
    """
    spans = repeated_windows(docs, window, base)
    texts = docs.select("doc_id", "text").repartition("doc_id")
    return texts.join(spans, "doc_id", "left").mapInArrow(lambda it: _removed(it, window, digest), _CLEAN)
