"""Exact Jaccard self-join of shingle sets by parity sketches.

A set's sketch at 2^p blocks holds, for each block, the XOR of the 64-bit hashes that fall into it. A hash that only
one of two sets has can change one block alone, so the number of blocks that differ is a lower bound of the symmetric
difference. Two sets of a and b shingles with intersection / union >= s differ in at most
d = floor((a + b) (1 - s) / (1 + s)) shingles; so of any d + 1 blocks that are not empty, one at least is equal. The
sizes a + b fall into bands, each with its own number of blocks, and a set sends the first d + 1 + k of its blocks that
are not empty, under each band it can meet a partner in (two at most). First, in the one order that all sets share, come
blocks with a shingle that isn't frequent; a bit map of fixed size has the shingles that some task met often, and the
result doesn't depend on which these are. The slack k serves against blocks that very many
sets share (common passages): a set drops its most common blocks, as many as the slack of its smallest partner. Of the
blocks that two linked sets share, the least common has that many others after it in both, so neither drops it.

Candidates are compared by parity sketches of single bits first: bit k is the parity of the hashes that fall on it, and
the Hamming distance of two sketches is a lower bound of the symmetric difference, too.

Sets that are equal are one class, joined as one row. In each bucket of equal blocks all sets meet the first and the
last of them; what verification leaves in different components is then compared in full by sketches, chunk by chunk, and
only pairs that these do not rule out become rows. Candidates are verified on the sets themselves (hashes of 48 bits).

A block that very many sets may send, as it has frequent shingles alone, is dealt to SALTS parts, whose figures are summed.

Null and empty texts and texts without words have no shingles and link with nothing; an empty table gives no rows. Rows with a null doc_id are left
out of links. Repeated rows with one doc_id count by the union-free rule that each row stands for itself; they share
the component of their doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bit_map, components, cut, found_in, in_bit_map, stored
from .kernels import SPACE_WORDS, Block, blocks, lean, mix, mix_int

#: A bucket with more sets than this is a common block, see above. No pair is lost by it.
COMMON = 24
#: A shingle that OFTEN sets have, of sets with CHUNK shingles in all, goes to the map of frequent shingles.
OFTEN, CHUNK, MAP_BITS = 6, 3_000_000, 1 << 25
#: Sets of a bucket that are compared with as many others at a time.
CELL = 1024
#: Parts into which a bucket that very many sets may share is dealt; its figures are summed by part first.
SALTS = 32


def shingle_sets(block: Block, words: int) -> Iterator[np.ndarray]:
    """Sorted distinct hashes of each document's shingles; of a shorter text the whole sequence is one."""
    grams, _ = block.grams(words)
    h = block.hash
    for d in range(block.n_docs):
        a, b = int(block.ptr[d]), int(block.ptr[d + 1])
        if b - a >= words:
            s = np.sort(grams[a : b - words + 1])
            yield s[np.append(True, s[1:] != s[:-1])]
        elif b > a:
            x = b - a
            for v in h[a:b].tolist():
                x = mix_int(x * 0x9E3779B97F4A7C15 + v)
            yield np.array([x], np.uint64)
        else:
            yield np.zeros(0, np.uint64)


class Bands:
    """Which blocks a set of n shingles sends; num / den is the similarity that links."""

    def __init__(self, num: int, den: int):
        self.num, self.den = num, den

    def most_apart(self, total: int) -> int:
        return total * (self.den - self.num) // (self.den + self.num)

    def level(self, total: int) -> int:
        """log2 of the number of blocks for pairs with a + b = total; it never falls as total grows."""
        d = self.most_apart(total)
        return int(np.ceil(np.log2(1.3 * (d + 1 + self.slack(total // 2)) + min(2 * total, 126))))

    @staticmethod
    def slack(n: int) -> int:
        return 4 + n // 16

    def free(self, n: int) -> int:
        """Common blocks that a set may drop: the slack of its smallest partner, none where that is too small to be sure of it."""
        least = n * self.num // self.den
        return self.slack(least) if least >= 32 else 0

    def totals(self, n: int) -> tuple[int, int]:
        """Least and largest a + b of a set of n shingles and a partner."""
        return n + -(-n * self.num // self.den), n + n * self.den // self.num

    def sketches(self, s: np.ndarray, frequent: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """Keys of the blocks that a set sends, which of them very many sets may send, and how many common blocks it may drop.

        frequent marks shingles; blocks of nothing else come last, which is an order all sets agree on.
        """
        n = len(s)
        low, high = self.totals(n)
        out, hot = [], []
        levels = range(self.level(low), self.level(high) + 1)
        for p in levels:
            top = high
            if p < levels[-1]:  # the largest total of this band
                lo, hi = low, high
                while lo < hi:
                    mid = (lo + hi + 1) // 2
                    lo, hi = (mid, hi) if self.level(mid) <= p else (lo, mid - 1)
                top = lo
            d = self.most_apart(top)
            block = s >> np.uint64(64 - p)
            first = np.flatnonzero(np.append(True, block[1:] != block[:-1]))
            k = min(self.slack(n), len(first) - d - 1)
            m = d + 1 + k if k >= 0 else len(first)
            last = np.logical_and.reduceat(frequent, first)
            taken = np.concatenate([np.flatnonzero(~last), np.flatnonzero(last)])[:m] if last.any() else np.arange(m)
            parity = np.bitwise_xor.reduceat(s, first)[taken]
            out.append(mix(mix(parity) + block[first[taken]] * np.uint64(64) + np.uint64(p)))
            hot.append(last[taken])
            if k < 0:  # nothing is sure of its blocks: such sets all meet
                out.append(np.array([mix_int(p + 7_777_777)], np.uint64))
                hot.append(np.ones(1, bool))
        return np.concatenate(out), np.concatenate(hot), self.free(n)


def map_place(s: np.ndarray) -> np.ndarray:
    """A shingle's place in the bit map of frequent ones."""
    return ((s >> np.uint64(20)) & np.uint64(MAP_BITS - 1)).astype(np.int64)


def in_map(s: np.ndarray, bits: np.ndarray) -> np.ndarray:
    x = map_place(s)
    return ((bits[x >> 6] >> (x & 63)) & 1).astype(bool)


def frequent_map(rows: DataFrame) -> np.ndarray:
    """Bit map of the hashes h1; MAP_BITS / 64 rows at most reach the driver."""
    place = F.shiftrightunsigned("h1", 20).bitwiseAND(F.lit(MAP_BITS - 1))
    words = rows.select(F.shiftright(place, 6).alias("w"), F.expr(f"shiftleft(1L, cast((shiftrightunsigned(h1, 20) & {MAP_BITS - 1}) & 63 as int))").alias("v")).groupBy("w").agg(F.bit_or("v").alias("v"))
    out = np.zeros(MAP_BITS // 64, np.int64)
    for w, v in words.collect():
        out[w] = v
    return out


def parity_bits(s: np.ndarray, bits: int) -> bytes:
    """Bit k is the parity of the hashes whose remainder by `bits` is k."""
    at = (s & np.uint64(bits - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=bits) & 1).astype(np.uint8)).tobytes()


def bits_apart(a: np.ndarray, b: np.ndarray) -> int:
    """Hamming distance of two parity sketches; the longer is folded to the other's length, which keeps its parities."""
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] ^ b[len(b) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def _frequent(held: list[np.ndarray]) -> pa.RecordBatch:
    """Rows of the shingles that OFTEN of the sets in `held` have, which it empties."""
    s = np.concatenate(held) if held else np.zeros(0, np.uint64)
    held.clear()
    s.sort()
    at = np.flatnonzero(s[OFTEN - 1 :] == s[: len(s) - OFTEN + 1]) if len(s) >= OFTEN else np.zeros(0, np.int64)
    found = np.unique(s[at])
    n = len(found)
    return pa.RecordBatch.from_arrays([pa.nulls(n, pa.int64()), pa.array(np.full(n, -1)), pa.array(found.view(np.int64)), pa.array(np.zeros(n, np.int64)), pa.array([b""] * n, pa.binary())], names=["doc_id", "n_shingles", "h1", "h2", "sketch"])


@lean
def _meta(batches: Iterator[pa.RecordBatch], words: int, bands: Bands) -> Iterator[pa.RecordBatch]:
    """A row for each document; n_shingles -1 marks rows of shingles (h1) that occur often among CHUNK shingles of the task."""
    held: list[np.ndarray] = []
    n = 0
    for batch in batches:
        for i, j, block in blocks(batch.column("text"), SPACE_WORDS, lower=True):
            sets = list(shingle_sets(block, words))
            sums = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64)
            turned = np.array([mix(s).sum(dtype=np.uint64) for s in sets], np.uint64)
            bits = [parity_bits(s, 4 << bands.level(bands.totals(len(s))[1])) if len(s) else b"" for s in sets]
            held += sets
            n += sum(len(s) for s in sets)
            if n > CHUNK:
                yield _frequent(held)
                n = 0
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")[i:j], pa.array(np.array([len(s) for s in sets], np.int64)), pa.array(sums.view(np.int64)), pa.array(turned.view(np.int64)), pa.array(bits, pa.binary())], names=["doc_id", "n_shingles", "h1", "h2", "sketch"])
    yield _frequent(held)


@lean
def _sent(batches: Iterator[pa.RecordBatch], words: int, bands: Bands, often) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch.column("doc_id")
        for i, j, block in blocks(batch.column("text"), SPACE_WORDS, lower=True):
            keys, at, slack, hot = [], [], [], []
            for d, s in enumerate(shingle_sets(block, words)):
                if len(s) and ids[i + d].is_valid:
                    k, many, free = bands.sketches(s, in_map(s, often.value))
                    keys.append(k)
                    hot.append(many)
                    at.append(np.full(len(k), d))
                    slack.append(np.full(len(k), free, np.int32))
            if keys:
                doc = np.asarray(ids[i:j].fill_null(0))[np.concatenate(at)]
                salt = np.where(np.concatenate(hot), 1 + mix(doc.view(np.uint64)) % np.uint64(SALTS), 0).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys).view(np.int64)), pa.array(doc), pa.array(np.concatenate(slack)), pa.array(salt)], names=["key", "doc_id", "slack", "salt"])


@lean
def _packed(batches: Iterator[pa.RecordBatch], words: int, sent) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        batch = batch.filter(pa.array(found_in(sent.value, batch.column("h"))))
        for i, j, block in blocks(batch.column("text"), SPACE_WORDS, lower=True):
            low = [np.unique(s >> np.uint64(16)) for s in shingle_sets(block, words)]
            out = [s.view(np.uint8).reshape(-1, 8)[:, :6].tobytes() for s in low]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")[i:j], pa.array(out, pa.binary())], names=["doc_id", "shingles"])


def _unpack(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // 6, 8), np.uint8)
    out[:, :6] = np.frombuffer(data, np.uint8).reshape(-1, 6)
    return out.view(np.uint64).ravel()


@lean
def _verified(batches: Iterator[pa.RecordBatch], num: int, den: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        a, b = batch.column("set_a"), batch.column("set_b")
        good = np.zeros(len(a), bool)
        last, left = None, None
        for k in range(len(a)):
            x, y = a[k].as_buffer(), b[k].as_buffer()
            n, m = x.size // 6, y.size // 6
            if den * min(n, m) < num * max(n, m):
                continue
            key = batch.column("a")[k].as_py()
            if key != last:
                last, left = key, _unpack(x)
            right = _unpack(y)
            at = np.searchsorted(left, right)
            at[at == n] = n - 1
            both = int((left[at] == right).sum())
            good[k] = den * both >= num * (n + m - both)
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(good)], names=["a", "b", "linked"])


@lean
def _not_apart(batches: Iterator[pa.RecordBatch], bands: Bands) -> Iterator[pa.RecordBatch]:
    """Pairs that the sizes and the parity sketches don't rule out."""
    for batch in batches:
        n, m = np.asarray(batch.column("n_a")), np.asarray(batch.column("n_b"))
        good = bands.den * np.minimum(n, m) >= bands.num * np.maximum(n, m)
        a, b = batch.column("sketch_a"), batch.column("sketch_b")
        for k in np.flatnonzero(good).tolist():
            x, y = np.frombuffer(a[k].as_buffer(), np.uint8), np.frombuffer(b[k].as_buffer(), np.uint8)
            good[k] = bits_apart(x, y) <= bands.most_apart(int(n[k] + m[k]))
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(good))


@lean
def _halved(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sketches folded to about two to four bits a shingle."""
    for batch in batches:
        out = []
        for n, bits in zip(batch.column("n_shingles").to_pylist(), batch.column("sketch").to_pylist(), strict=True):
            x = np.frombuffer(bits, np.uint8)
            while len(x) > 64 and len(x) * 2 > n:
                x = x[: len(x) // 2] ^ x[len(x) // 2 :]
            out.append(x.tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_shingles"), pa.array(out, pa.binary())], names=["doc_id", "n_shingles", "sketch"])


def _close_in(cell: list[tuple], bands: Bands, out: tuple[list, list]) -> None:
    """cell: (doc_id, c, chunk, n, sketch); appends pairs of different components that sketches don't rule out."""
    size = min(len(r[4]) for r in cell)
    folded = []
    for r in cell:
        x = np.frombuffer(r[4], np.uint8)
        while len(x) > size:
            x = x[: len(x) // 2] ^ x[len(x) // 2 :]
        folded.append(x)
    bits = np.array(folded).view(np.uint64)
    ids, c, chunk, n = (np.array([r[k] for r in cell], np.int64) for k in range(4))
    alone = chunk.min() == chunk.max()
    for i in range(len(cell) - 1):
        j = np.arange(i + 1, len(cell))
        j = j[(c[j] != c[i]) & (bands.den * np.minimum(n[j], n[i]) >= bands.num * np.maximum(n[j], n[i])) & (alone | (chunk[j] != chunk[i]))]
        if len(j):
            apart = np.bitwise_count(bits[j] ^ bits[i]).sum(axis=1)
            j = j[apart <= (n[j] + n[i]) * (bands.den - bands.num) // (bands.den + bands.num)]
            out[0].append(np.minimum(ids[i], ids[j]))
            out[1].append(np.maximum(ids[i], ids[j]))


@lean
def _cells(batches: Iterator[pa.RecordBatch], bands: Bands) -> Iterator[pa.RecordBatch]:
    """Rows of a partition, sorted by cell; a cell has two chunks of a bucket at most, so its size is bounded."""
    cell, now, out = [], None, ([], [])

    def rows():
        a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in out)
        pairs = np.unique(np.stack([a, b]), axis=1)
        return pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], names=["a", "b"])

    for batch in batches:
        for key, one, two, *row in zip(*(batch.column(k).to_pylist() for k in ("key", "one", "two", "doc_id", "c", "chunk", "n_shingles", "sketch")), strict=True):
            if (key, one, two) != now:
                if len(cell) > 1:
                    _close_in(cell, bands, out)
                cell, now = [], (key, one, two)
            cell.append(row)
        if sum(map(len, out[0])) > 500_000:
            yield rows()
            out = ([], [])
    if len(cell) > 1:
        _close_in(cell, bands, out)
    yield rows()


def _spans(rows: DataFrame, *figures) -> DataFrame:
    """rows (key, salt, ...) with figures by key: partial sums, joined back by key and salt, so that no key is in one task."""
    stats = rows.groupBy("key").agg(F.max("salt").alias("top"), *figures)
    salts = F.when(F.col("top") > 0, F.sequence(F.lit(1), F.lit(SALTS))).otherwise(F.array(F.lit(0)))
    return rows.join(stats.withColumn("salt", F.explode(salts)).drop("top"), ["key", "salt"])


def _first_last() -> tuple:
    return F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.count("*").alias("n")


def _meetings(keys: DataFrame) -> DataFrame:
    """The rows of keys (key, doc_id, slack, salt) whose key two documents have, with the number n of its rows.

    Salt 0 needs one exchange and no sum; the rows of the other salts, of keys that many sets may have, are summed by key
    and salt, and then by key.
    """
    part = "over (partition by key, salt)"
    own = stored(keys.selectExpr("*", f"min(doc_id) {part} as first", f"max(doc_id) {part} as last", f"count(*) {part} as n").where("first < last or salt > 0"))
    hot = own.where("salt > 0")
    heads = hot.where("doc_id = first").select("key", "salt", "first", "last", "n").distinct()
    whole = heads.groupBy("key").agg(F.min("first").alias("first"), F.max("last").alias("last"), F.sum("n").alias("n")).where("first < last")
    whole = whole.select("key", "n", F.explode(F.sequence(F.lit(1), F.lit(SALTS))).alias("salt"))
    columns = ("key", "doc_id", "slack", "salt", "n")
    return own.where("salt = 0").select(*columns).unionByName(hot.drop("n").join(whole, ["key", "salt"]).select(*columns))


def _across(meta: DataFrame, mixed: DataFrame, bands: Bands) -> DataFrame:
    """Close pairs (a, b) of different components c in mixed (key, doc_id, c): within each bucket, chunk by chunk.

    Chunks hold sets of one size class; linked sets are in the same class or in neighbours, so no others meet.
    """
    some = meta.where("n_shingles > 0").select("doc_id", "n_shingles", "sketch").mapInArrow(_halved, "doc_id long, n_shingles long, sketch binary")
    level = F.floor(F.log("n_shingles") / (1.0001 * float(np.log(bands.den / bands.num)))).cast("int")
    sized = stored(mixed.join(meta.where("n_shingles > 0").select("doc_id", level.alias("level")).distinct(), "doc_id"))
    tops = sized.groupBy("key", "level").agg(F.ceil(F.count("*") / F.lit(CELL)).cast("long").alias("top"))
    chunk = F.col("level").cast("long") * (1 << 32) + F.pmod(F.xxhash64("doc_id"), F.col("top"))
    placed = sized.join(tops, ["key", "level"]).select("key", "doc_id", "c", chunk.alias("chunk"), F.explode(F.array(*[F.col("level") + k for k in (-1, 0, 1)])).alias("level"))
    dealt = placed.join(tops, ["key", "level"]).select("key", "doc_id", "c", "chunk", F.explode(F.transform(F.sequence(F.lit(0).cast("long"), F.col("top") - 1), lambda k: F.col("level").cast("long") * (1 << 32) + k)).alias("other")).join(some, "doc_id")
    dealt = dealt.withColumn("one", F.least("chunk", "other")).withColumn("two", F.greatest("chunk", "other")).drop("other")
    count = int(meta.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return dealt.repartition(count, "key", "one", "two").sortWithinPartitions("key", "one", "two").mapInArrow(lambda it: _cells(it, bands), "a long, b long").distinct()


def _close(meta: DataFrame, pairs: DataFrame, bands: Bands) -> DataFrame:
    """The pairs (a, b) that their parity sketches don't rule out."""
    sent = meta.sparkSession.sparkContext.broadcast(bit_map(pairs.select(F.explode(F.array("a", "b")).alias("doc_id")), "doc_id"))
    some = meta.where("n_shingles > 0").select("doc_id", "n_shingles", "sketch").where(in_bit_map("doc_id", sent))
    one, two = some.toDF("a", "n_a", "sketch_a"), some.toDF("b", "n_b", "sketch_b")
    return pairs.join(one, "a").join(two, "b").mapInArrow(lambda it: _not_apart(it, bands), "a long, b long").distinct()


def _links(docs: DataFrame, close: DataFrame, words: int, bands: Bands) -> DataFrame:
    """The pairs (a, b) that link, by the sets of the documents in them."""
    sent = docs.sparkSession.sparkContext.broadcast(bit_map(close.select(F.explode(F.array("a", "b")).alias("doc_id")), "doc_id"))
    sets = stored(docs.select("doc_id", "text", F.xxhash64("doc_id").alias("h")).mapInArrow(lambda it: _packed(it, words, sent), "doc_id long, shingles binary"))
    one, two = sets.toDF("a", "set_a"), sets.toDF("b", "set_b")
    return close.join(one, "a").join(two, "b").mapInArrow(lambda it: _verified(it, bands.num, bands.den), "a long, b long, linked boolean").where("linked").select("a", "b").distinct()


def similarity_join(docs: DataFrame, words: int = 5, num: int = 3, den: int = 4) -> tuple[DataFrame, DataFrame]:
    """Over docs (doc_id, text): the members (doc_id, n_shingles, class_id) and the verified links (a, b) between classes.

    class_id is the smallest doc_id with that very set, null without shingles. Where doc_id repeats with other texts,
    the rows' classes are joined as if the text of each row were one of the document's.
    """
    docs = docs.select("doc_id", "text")
    bands = Bands(num, den)
    every = stored(docs.mapInArrow(lambda it: _meta(it, words, bands), "doc_id long, n_shingles long, h1 long, h2 long, sketch binary"))
    often = docs.sparkSession.sparkContext.broadcast(frequent_map(every.where("n_shingles < 0").select("h1")))
    meta = every.where("n_shingles >= 0")
    classes = meta.where("n_shingles > 0 and doc_id is not null").groupBy("n_shingles", "h1", "h2").agg(F.min("doc_id").alias("class_id"))
    members = meta.join(classes, ["n_shingles", "h1", "h2"], "left").select("doc_id", "n_shingles", "class_id")
    keys = docs.mapInArrow(lambda it: _sent(it, words, bands, often), "key long, doc_id long, slack int, salt int")
    # Of a class only its first member goes on; which ones are is a matter of one more join on the few rows that met.
    one_each = members.where("doc_id = class_id").select("doc_id").distinct()
    met = stored(_meetings(keys).join(one_each, "doc_id", "left_semi").distinct())
    # Each set drops the most common of its blocks, as many as its slack allows. The order (n, key) is the same for all.
    common = met.where(F.col("n") > COMMON).selectExpr("*", "row_number() over (partition by doc_id order by n desc, key desc) as place").where("place > slack")
    kept = met.where(F.col("n") <= COMMON).select("key", "doc_id", "salt").unionByName(common.select("key", "doc_id", "salt"))
    kept = stored(_spans(kept, *_first_last()).where("first < last"))
    star = kept.select(F.col("first").alias("a"), F.col("doc_id").alias("b")).unionByName(kept.select(F.col("doc_id").alias("a"), F.col("last").alias("b"))).where("a != b").distinct()
    links = cut(_links(docs, stored(_close(meta, stored(star), bands)), words, bands))
    labels = components(links)
    # Buckets of three sets and fewer are fully compared by now.
    rest = kept.where("n > 3").select("key", "salt", "doc_id").join(labels.withColumnRenamed("id", "doc_id"), "doc_id", "left").select("key", "salt", "doc_id", F.coalesce("component", "doc_id").alias("c"))
    mixed = _spans(rest, F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 < c1").select("key", "doc_id", "c")
    mixed = stored(mixed)
    close = stored(_across(meta, mixed, bands))
    if not close.isEmpty():
        links = cut(links.unionByName(_links(docs, close, words, bands)))
    return members, links


def near_duplicates(docs: DataFrame, words: int = 5, num: int = 3, den: int = 4) -> DataFrame:
    """(doc_id, n_shingles, component_id) for each row; component_id is the smallest doc_id reachable by links."""
    members, links = similarity_join(docs, words, num, den)
    labels = components(links)
    out = members.join(labels.withColumnRenamed("id", "class_id"), "class_id", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "class_id", "doc_id").alias("component_id"))
