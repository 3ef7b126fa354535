"""Row-local kernels of the learned sketch: numpy over Arrow batches of rows, joined with their part of the centres.

A row of a batch is (row_id, idx, val, cb, cv): its non-zeros, and the centres' values at it, null where there are none.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

from ..functions.hashing import PRIME, coefficient, drawn_array, signs_array

PRODUCTS = "part int, f array<long>, b array<int>, p array<double>"
NEAREST = "feature_id long, bucket int, flip int, dist double"
CENTRES = "row_id long, cb array<int>, cv array<double>"
#: Pairs of a non-zero and a centre, or cells of a dense block, that a kernel holds at a time.
CELLS = 2_000_000


def _lists(column: pa.Array, dtype) -> tuple[np.ndarray, np.ndarray]:
    """Sizes and values of a list column; a null is an empty list."""
    return np.asarray(column.value_lengths().fill_null(0)).astype(np.int64), np.asarray(column.flatten()).astype(dtype)


def _centres(batch: pa.RecordBatch, theta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sizes by row, buckets and values of the centres after their pending thresholds."""
    sizes, cb = _lists(batch.column("cb"), np.int64)
    _, cv = _lists(batch.column("cv"), np.float64)
    cv = np.sign(cv) * np.maximum(np.abs(cv) - theta[cb], 0)
    keep = cv != 0
    row = np.repeat(np.arange(len(sizes)), sizes)[keep]
    return np.bincount(row, minlength=len(sizes)), cb[keep], cv[keep]


def _sums(keys: np.ndarray, values: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys below `size` and the sums of their values."""
    if size <= 4 * len(keys) + CELLS:
        met = np.flatnonzero(np.bincount(keys, minlength=size))
        return met, np.bincount(keys, values, minlength=size)[met]
    met, at = np.unique(keys, return_inverse=True)
    return met, np.bincount(at, values, minlength=len(met))


#: Cells of a block of rows by centres that stays near a core, and of one of packed rows.
NEAR, WIDE = 250_000, 4_000_000


class Replay(NamedTuple):
    """How a row's part of the centres follows from its own entries, whose features are numbered from 0.

    signs: an array by feature, sent to the tasks, or None. Steps: ('set', sent, theta) makes columns the centres of their
    buckets, shrunk; ('move', sent, table) takes a step as steps() does; ('shrink', theta). sent holds (bucket by feature,
    below 0 for none; flip by feature).
    """

    r: int
    signs: object
    steps: tuple
    packed: object = None  # opens batches as blocks of rows, in the order of features, as blocks.unpacked() does
    without: int | None = None  # a fold whose rows are left out of blocks

    def signed(self, f: np.ndarray, v: np.ndarray) -> np.ndarray:
        return v if self.signs is None else v * self.signs.value[f]

    def centres(self, row: np.ndarray, f: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
        """n rows x r, of signed entries."""
        r, c = self.r, np.zeros((n, self.r))
        for kind, *x in self.steps:
            if kind == "shrink":
                c = np.sign(c) * np.maximum(np.abs(c) - x[0], 0)
                continue
            bucket, flip = x[0].value
            b = bucket[f]
            some = slice(None) if len(b) and b.min() >= 0 else b >= 0
            if kind == "set":
                new = np.bincount(row[some] * r + b[some], v[some], minlength=n * r).reshape(n, r)
                if x[1] is not None:
                    new = np.sign(new) * np.maximum(np.abs(new) - x[1], 0)
                at = np.unique(bucket[bucket >= 0])
                c[:, at] = new[:, at]
            else:
                keep, gain, size = x[1]
                w = v if flip is None else v * flip[f]
                t = np.bincount(row[some] * r + b[some], w[some], minlength=n * r).reshape(n, r)
                c = np.where(keep == 0, t / size, c * keep + t * gain)
        return c

    def blocks(self, batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(row ids, row of each entry, feature, signed value, centres) of some rows at a time."""
        if self.packed is not None:
            for block in self.packed(batches, self.without):
                n, many = len(block.ids), max(1, WIDE // self.r)
                for a in range(0, n, many):
                    ids, row, f, v = block if n <= many else block.only((np.arange(n) >= a) & (np.arange(n) < a + many))
                    v = self.signed(f, v)
                    yield ids, row, f, v, self.centres(row, f, v, len(ids))
            return
        many = max(1, NEAR // self.r)
        for batch in batches:
            for a in range(0, batch.num_rows, many):
                part = batch.slice(a, many)
                sizes, f = _lists(part.column("idx"), np.int64)
                _, v = _lists(part.column("val"), np.float64)
                row, v = np.repeat(np.arange(len(sizes)), sizes), self.signed(f, v)
                yield np.asarray(part.column("row_id")), row, f, v, self.centres(row, f, v, len(sizes))


def profile(batches: Iterator[pa.RecordBatch], d: int) -> Iterator[pa.RecordBatch]:
    """The sum of magnitudes, and a bit for each of the d features that is met."""
    l1, met = 0.0, np.zeros(d, bool)
    for batch in batches:
        met[np.asarray(batch.column("idx").flatten())] = True
        l1 += float(np.abs(np.asarray(batch.column("val").flatten())).sum())
    yield pa.RecordBatch.from_arrays([pa.array([l1]), pa.array([np.packbits(met).tobytes()], pa.binary())], names=["l1", "met"])


def profile_of_blocks(batches: Iterator[pa.RecordBatch], d: int, opened, without: int | None) -> Iterator[pa.RecordBatch]:
    """As profile(), of packed rows."""
    l1, met = 0.0, np.zeros(d, bool)
    for block in opened(batches, without):
        met[block.f] = True
        l1 += float(np.abs(block.v).sum())
    yield pa.RecordBatch.from_arrays([pa.array([l1]), pa.array([np.packbits(met).tobytes()], pa.binary())], names=["l1", "met"])


def mapped(batches: Iterator[pa.RecordBatch], sent, signs) -> Iterator[pa.RecordBatch]:
    """(feature_id, bucket, sign) of the features that the map in sent has, as in Replay."""
    bucket, flip = sent.value
    for batch in batches:
        f = np.asarray(batch.column("id"))
        f = f[bucket[f] >= 0]
        sign = np.ones(len(f), np.int32)
        for x in (signs and signs.value, flip):
            sign = sign if x is None else sign * x[f]
        yield pa.RecordBatch.from_arrays([pa.array(f), pa.array(bucket[f]), pa.array(sign.astype(np.int32))], names=["feature_id", "bucket", "sign"])


def coordinates(batches: Iterator[pa.RecordBatch], replay: Replay) -> Iterator[pa.RecordBatch]:
    """(row_id, bucket, value) of the centres, without zeros."""
    for ids, _, _, _, c in replay.blocks(batches):
        i, b = np.nonzero(c)
        yield pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(b.astype(np.int32)), pa.array(c[i, b])], names=["row_id", "bucket", "value"])


def centre_sums(batches: Iterator[pa.RecordBatch], replay: Replay) -> Iterator[pa.RecordBatch]:
    """(bucket, l1, linf, sq) of the rows of a task, for centres that are not zero there."""
    l1, linf, sq = np.zeros((3, replay.r))
    for *_, c in replay.blocks(batches):
        a = np.abs(c)
        l1 += a.sum(axis=0)
        linf = np.maximum(linf, a.max(axis=0, initial=0))
        sq += (a * a).sum(axis=0)
    at = np.flatnonzero(linf)
    yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), *(pa.array(x[at]) for x in (l1, linf, sq))], names=["bucket", "l1", "linf", "sq"])


def centre_cells(batches: Iterator[pa.RecordBatch], replay: Replay, bounds: tuple[np.ndarray, ...], cells: int) -> Iterator[pa.RecordBatch]:
    """(bucket, cell, n, total, sq) of the magnitudes between the bounds (bucket, low, high, upper bound too)."""
    r, place = replay.r, np.full(replay.r, -1)
    bucket, low, high, top = bounds
    place[bucket] = np.arange(len(bucket))
    held: list[tuple[np.ndarray, ...]] = []

    def merged() -> tuple[np.ndarray, ...]:
        keys, *figures = (np.concatenate(x) for x in zip(*held, strict=True))
        met, at = np.unique(keys, return_inverse=True)
        return met, *(np.bincount(at, x, minlength=len(met)) for x in figures)

    n = 0
    for *_, c in replay.blocks(batches):
        a = np.abs(c[:, bucket])
        i, k = np.nonzero((a > 0) & (a >= low) & ((a < high) | top))
        x = a[i, k]
        cell = np.minimum((x - low[k]) / (high[k] - low[k]) * cells, cells - 1).astype(np.int64)
        met, at = np.unique(k * cells + cell, return_inverse=True)
        held.append((met, np.bincount(at, minlength=len(met)).astype(float), np.bincount(at, x, minlength=len(met)), np.bincount(at, x * x, minlength=len(met))))
        n += len(met)
        if n > CELLS:
            held = [merged()]
            n = len(held[0][0]) // 2
    if held:
        keys, count, total, sq = merged()
        yield pa.RecordBatch.from_arrays([pa.array(bucket[keys // cells].astype(np.int32)), pa.array((keys % cells).astype(np.int32)), pa.array(count.astype(np.int64)), pa.array(total), pa.array(sq)], names=["bucket", "cell", "n", "total", "sq"])


#: Rows and entries that products() takes at a time, so that each of their features is summed once.
ROWS, ENTRIES = 8_192, 3_000_000


def _grouped(blocks: Iterator[tuple[np.ndarray, ...]]) -> Iterator[tuple[np.ndarray, ...]]:
    """(row of each entry, feature, value, centres) of about ROWS rows or ENTRIES entries of Replay.blocks()."""
    held, rows, entries = [], 0, 0
    for ids, row, f, v, c in blocks:
        held.append((row + rows, f, v, c))
        rows, entries = rows + len(ids), entries + len(f)
        if rows >= ROWS or entries >= ENTRIES:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held, rows, entries = [], 0, 0
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def _by_feature(row: np.ndarray, f: np.ndarray, v: np.ndarray, c: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(feature, bucket, product), not zero, of some features at a time, in the order of features."""
    order = np.argsort(f, kind="stable")
    k = f[order]
    edge = np.append(np.flatnonzero(np.append(True, k[1:] != k[:-1])), len(k))
    many = max(1, CELLS // c.shape[1])
    for a in range(0, len(edge) - 1, many):
        ends = edge[a : a + many + 1]
        dots, at = np.empty((len(ends) - 1, c.shape[1])), order[ends[:-1]]
        one = np.flatnonzero(np.diff(ends) == 1)
        dots[one] = c[row[at[one]]] * v[at[one], None]
        for j in np.flatnonzero(np.diff(ends) > 1).tolist():
            at = order[ends[j] : ends[j + 1]]
            np.dot(v[at], c[row[at]], out=dots[j])
        i, b = np.nonzero(dots)
        yield k[ends[:-1]][i], b, dots[i, b]


def products(batches: Iterator[pa.RecordBatch], theta: np.ndarray | None, parts: int, r: int, seed: int, batch_of: tuple[float, str] | None, replay: Replay | None = None) -> Iterator[pa.RecordBatch]:
    """Products of columns with centres over the rows of a task, packed by the features' partition; a column that meets no
    centre has one product of 0. The centres are those of the batches' rows, or those that replay makes."""
    held, n = [], 0

    def combined() -> tuple[np.ndarray, ...]:
        f, b, p = (np.concatenate(x) for x in zip(*held, strict=True))
        features, at = np.unique(f, return_inverse=True)
        met, sums = _sums(at * r + b, p, len(features) * r)
        return features[met // r], met % r, sums

    def packed(f, b, p) -> pa.RecordBatch:
        part = (f % parts + parts) % parts
        order = np.argsort(part, kind="stable")
        f, b, p, part = f[order], b[order].astype(np.int32), p[order], part[order]
        edge = np.flatnonzero(np.append(True, part[1:] != part[:-1])).astype(np.int32)
        ends = pa.array(np.append(edge, len(part)).astype(np.int32))
        return pa.RecordBatch.from_arrays([pa.array(part[edge].astype(np.int32)), *(pa.ListArray.from_arrays(ends, pa.array(x)) for x in (f, b, p))], names=["part", "f", "b", "p"])

    def given() -> Iterator[tuple]:
        """(rows, row of each entry, feature, value, centres by row, their buckets, their values, and of a replay all cells)"""
        if replay is None:
            for batch in batches:
                sizes, f = _lists(batch.column("idx"), np.int64)
                _, v = _lists(batch.column("val"), np.float64)
                yield len(sizes), np.repeat(np.arange(len(sizes)), sizes), f, v, *_centres(batch, theta)
        else:
            for row, f, v, c in _grouped(replay.blocks(batches)):
                i, b = np.nonzero(c)
                yield len(c), row, f, v, np.bincount(i, minlength=len(c)), b, c[i, b], c

    for rows, row, f, v, met, cb, cv, *full in given():
        if batch_of is not None:
            some = drawn_array(f, batch_of[0], seed, batch_of[1])
            f, v, row = f[some], v[some], row[some]
        if not len(f):
            continue
        start = np.cumsum(met) - met
        per = met[row]
        features = np.unique(f)
        total = int(per.sum())
        if full and total * 32 > len(f) * r:  # centres have many buckets a row: each feature is summed once, nothing is to be combined
            if held:
                yield packed(*combined())
                held, n = [], 0
            own, n = [(features, np.zeros(len(features), np.int64), np.zeros(len(features)))], len(features)
            for x in _by_feature(row, f, v, *full):
                own.append(x)
                n += len(x[0])
                if n > CELLS:
                    yield packed(*(np.concatenate(y) for y in zip(*own, strict=True)))
                    own, n = [], 0
            if own:
                yield packed(*(np.concatenate(y) for y in zip(*own, strict=True)))
            n = 0
            continue
        held.append((features, np.zeros(len(features), np.int64), np.zeros(len(features))))
        n += len(features)
        if total * 32 > rows * len(features) * r:  # mostly full: blocks of rows by features
            at = np.searchsorted(features, f)
            dots, many = np.zeros((len(features), r)), max(1, CELLS // max(len(features), r))
            crow = np.repeat(np.arange(rows), met)
            for low in range(0, rows, many):
                high = min(rows, low + many)
                x, y = np.searchsorted(row, [low, high])
                cx, cy = np.searchsorted(crow, [low, high])
                left = np.bincount((row[x:y] - low) * len(features) + at[x:y], v[x:y], minlength=(high - low) * len(features)).reshape(high - low, -1)
                right = np.bincount((crow[cx:cy] - low) * r + cb[cx:cy], cv[cx:cy], minlength=(high - low) * r).reshape(high - low, -1)
                dots += left.T @ right
            i, b = np.nonzero(dots)
            held.append((features[i], b, dots[i, b]))
            n += len(i)
            total = 0
        cuts = [] if not total else np.searchsorted(np.cumsum(per), np.arange(0, total + CELLS, CELLS), side="right")
        for a, z in zip(cuts, [*cuts[1:], len(per)], strict=False):
            k = per[a:z]
            if not k.sum():
                continue
            inner = np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)
            at = np.repeat(start[row[a:z]], k) + inner
            local, where = np.unique(f[a:z], return_inverse=True)
            keys, sums = _sums(np.repeat(where, k) * r + cb[at], np.repeat(v[a:z], k) * cv[at], len(local) * r)
            held.append((local[keys // r], keys % r, sums))
            n += len(keys)
        if n > CELLS:
            held = [combined()]
            n = len(held[0][0])
            if 2 * n > CELLS:
                yield packed(*held[0])
                held, n = [], 0
    if held:
        yield packed(*combined())


def nearest(table: pa.Table, norms: np.ndarray, both_signs: bool) -> pa.Table:
    """The nearest centre of each feature of a partition: least norm - 2 product, ties to the lowest bucket.

    dist leaves out the column's own squared norm. both_signs: centres' mirror images count, too, as flip -1.
    """
    f, b, p = (np.asarray(table.column(c).combine_chunks().flatten()) for c in ("f", "b", "p"))
    r = len(norms)
    features, at = np.unique(f, return_inverse=True)
    order = np.argsort(at, kind="stable")
    at, b, p = at[order], b[order].astype(np.int64), p[order]
    bucket, flip, dist = np.zeros(len(features), np.int32), np.ones(len(features), np.int32), np.zeros(len(features))
    step = max(1, CELLS // r)
    for low in range(0, len(features), step):
        high = min(len(features), low + step)
        x, y = np.searchsorted(at, [low, high])
        dots = np.bincount((at[x:y] - low) * r + b[x:y], p[x:y], minlength=(high - low) * r).reshape(-1, r)
        far = norms - 2 * (np.abs(dots) if both_signs else dots)
        best = far.argmin(axis=1)
        rows = np.arange(high - low)
        bucket[low:high], dist[low:high] = best, far[rows, best]
        if both_signs:
            flip[low:high] = np.where(dots[rows, best] < 0, -1, 1)
    return pa.table({"feature_id": pa.array(features), "bucket": pa.array(bucket), "flip": pa.array(flip), "dist": pa.array(dist)})


class Short(NamedTuple):
    """Centres as sums of rows that are hashed to `seen`, buckets of rows x r, with signs."""

    seed: int
    seen: object  # sent

    def at(self, ids: np.ndarray) -> np.ndarray:
        """At each row, its sign times the centres of its bucket: products of columns with these are those of columns so shortened."""
        bucket, sign = hashed_rows(ids, len(self.seen.value), self.seed)
        return self.seen.value[bucket] * sign[:, None]


def hashed_rows(ids: np.ndarray, rows: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """The bucket and the sign of rows, as bucket_of() and sign_of() with the next seed."""
    x = ids.astype(np.int64) % PRIME
    return (x * coefficient(seed + 1, "bucket", 0) + coefficient(seed + 1, "bucket", 1)) % PRIME % rows, signs_array(ids, seed + 1)


def shortened(batches: Iterator[pa.RecordBatch], replay: Replay, rows: int, seed: int) -> Iterator[pa.RecordBatch]:
    """(h, bucket, value): the sums of a task's centres by bucket of rows."""
    total = np.zeros((rows, replay.r))
    for ids, _, _, _, c in replay.blocks(batches):
        at, sign = hashed_rows(ids, rows, seed)
        i, b = np.nonzero(c)
        total += np.bincount(at[i] * replay.r + b, c[i, b] * sign[i], minlength=total.size).reshape(total.shape)
    i, b = np.nonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(b.astype(np.int32)), pa.array(total[i, b])], names=["h", "bucket", "value"])


SENT = "part int, data binary"
#: Entries up to which a feature is summed together with others that have as many.
FEW = 16


def _dots(row: np.ndarray, f: np.ndarray, v: np.ndarray, c: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(features, products with all centres) of some features at a time; entries are in the order of features."""
    edge = np.flatnonzero(np.append(True, f[1:] != f[:-1]))
    met, count, step = f[edge], np.diff(np.append(edge, len(f))), max(1, CELLS // c.shape[1])
    for a in range(0, len(met), step):
        e, k = edge[a : a + step], count[a : a + step]
        dots = np.empty((len(e), c.shape[1]))
        for x in np.unique(k[k <= FEW]).tolist():
            at = np.flatnonzero(k == x)
            first = e[at]
            total = c[row[first]] * v[first, None]
            for j in range(1, x):
                total += c[row[first + j]] * v[first + j, None]
            dots[at] = total
        for j in np.flatnonzero(k > FEW).tolist():
            mine = slice(e[j], e[j] + k[j])
            np.dot(v[mine], c[row[mine]], out=dots[j])
        yield met[a : a + step], dots


def sent_products(batches: Iterator[pa.RecordBatch], per: int, seed: int, batch_of: tuple[float, str] | None, replay: Replay, short: Short | None = None) -> Iterator[pa.RecordBatch]:
    """As products(), of a replay, for parts of `per` features each, in bytes: the products that are not zero, the features,
    the number of products of each, and their buckets; or all products, if most are not zero, and the features."""

    def given() -> Iterator[tuple[np.ndarray, ...]]:
        found = replay.blocks(batches)
        if short is not None:
            found = ((ids, row, f, v, short.at(ids)) for ids, row, f, v, _ in found)
        if replay.packed is not None:
            yield from (x[1:] for x in found)
            return
        for row, f, v, c in _grouped(found):
            order = np.argsort(f, kind="stable")
            yield row[order], f[order], v[order], c

    for row, f, v, c in given():
        if batch_of is not None and len(f):
            edge = np.flatnonzero(np.append(True, f[1:] != f[:-1]))
            some = np.repeat(drawn_array(f[edge], batch_of[0], seed, batch_of[1]), np.diff(np.append(edge, len(f))))
            row, f, v = row[some], f[some], v[some]
        if not len(f):
            continue
        for met, dots in _dots(row, f, v, c):
            part, data = met // per, []
            cuts = np.flatnonzero(np.append(True, part[1:] != part[:-1]))
            ranges = list(zip(cuts.tolist(), [*cuts[1:].tolist(), len(met)], strict=True))
            if 2 * np.count_nonzero(dots) > dots.size:
                data = [b"".join(o.tobytes() for o in (np.array([y - x, -1]), dots[x:y], met[x:y].astype(np.int64))) for x, y in ranges]
            else:
                i, b = np.nonzero(dots)
                p, many = dots[i, b], np.bincount(i, minlength=len(met))
                ends, b = np.append(0, np.cumsum(many)), b.astype(np.int32 if c.shape[1] > 1 << 16 else np.uint16)
                for x, y in ranges:
                    mine = slice(ends[x], ends[y])
                    data.append(b"".join(o.tobytes() for o in (np.array([y - x, ends[y] - ends[x]]), p[mine], met[x:y].astype(np.int64), many[x:y].astype(np.int32), b[mine])))
            yield pa.RecordBatch.from_arrays([pa.array(part[cuts].astype(np.int32)), pa.array(data, pa.binary())], names=["part", "data"])


def nearest_sent(table: pa.Table, norms: np.ndarray, both_signs: bool, per: int) -> pa.Table:
    """As nearest(), of a part of `per` features of sent_products()."""
    r = len(norms)
    low, dots, seen = table.column("part")[0].as_py() * per, np.zeros((per, r)), np.zeros(per, bool)
    for x in table.column("data"):
        data = x.as_buffer()
        n, m = np.frombuffer(data, np.int64, 2).tolist()
        if m < 0:
            met = np.frombuffer(data, np.int64, n, 16 + 8 * n * r) - low
            dots[met] += np.frombuffer(data, np.float64, n * r, 16).reshape(n, r)  # each feature once
            seen[met] = True
            continue
        p, met = np.frombuffer(data, np.float64, m, 16), np.frombuffer(data, np.int64, n, 16 + 8 * m) - low
        many = np.frombuffer(data, np.int32, n, 16 + 8 * m + 8 * n)
        b = np.frombuffer(data, np.int32 if r > 1 << 16 else np.uint16, m, 16 + 8 * m + 12 * n)
        dots.ravel()[np.repeat(met, many) * r + b] += p  # each pair once
        seen[met] = True
    at = np.flatnonzero(seen)
    bucket, flip, dist = np.zeros(len(at), np.int32), np.ones(len(at), np.int32), np.zeros(len(at))
    step = max(1, CELLS // r)
    for a in range(0, len(at), step):
        x = dots[at[a : a + step]]
        far = norms - 2 * (np.abs(x) if both_signs else x)
        best = far.argmin(axis=1)
        one = np.arange(len(x))
        bucket[a : a + step], dist[a : a + step] = best, far[one, best]
        if both_signs:
            flip[a : a + step] = np.where(x[one, best] < 0, -1, 1)
    return pa.table({"feature_id": pa.array(at + low), "bucket": pa.array(bucket), "flip": pa.array(flip), "dist": pa.array(dist)})


def move_table(plan: list[tuple[int, float, float, int]], r: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """keep, gain and size by bucket; a bucket without a plan keeps its centre."""
    keep, gain, size = np.ones(r), np.zeros(r), np.ones(r)
    for b, k, g, n in plan:
        keep[b], gain[b], size[b] = k, g, n
    return keep, gain, size


def steps(batches: Iterator[pa.RecordBatch], theta: np.ndarray, sent, table: tuple[np.ndarray, np.ndarray, np.ndarray], r: int) -> Iterator[pa.RecordBatch]:
    """Each row's part of the centres after the step; sent holds the map (sorted feature ids, buckets, flips)."""
    ids, buckets, flips = sent.value
    keep, gain, size = table
    for batch in batches:
        sizes, f = _lists(batch.column("idx"), np.int64)
        _, v = _lists(batch.column("val"), np.float64)
        met, cb, cv = _centres(batch, theta)
        row, crow = np.repeat(np.arange(len(sizes)), sizes), np.repeat(np.arange(len(sizes)), met)
        at = np.searchsorted(ids, f)
        at[at == len(ids)] = 0
        known = ids[at] == f if len(ids) else np.zeros(len(f), bool)
        row, v, at = row[known], v[known], at[known]
        v = v * flips[at]
        many = max(1, CELLS // r)
        out_row, out_b, out_v = [], [], []
        for low in range(0, len(sizes), many):
            high = min(len(sizes), low + many)
            x, y = np.searchsorted(row, [low, high])
            cx, cy = np.searchsorted(crow, [low, high])
            cells = (high - low) * r
            t = np.bincount((row[x:y] - low) * r + buckets[at[x:y]], v[x:y], minlength=cells).reshape(-1, r)
            c = np.bincount((crow[cx:cy] - low) * r + cb[cx:cy], cv[cx:cy], minlength=cells).reshape(-1, r)
            new = np.where(keep == 0, t / size, c * keep + t * gain)
            i, b = np.nonzero(new)
            out_row.append(i + low)
            out_b.append(b.astype(np.int32))
            out_v.append(new[i, b])
        if not out_row:
            continue
        i, b, x = (np.concatenate(o) for o in (out_row, out_b, out_v))
        some = np.unique(i)
        ends = pa.array(np.append(np.searchsorted(i, some), len(i)).astype(np.int32))
        row_ids = np.asarray(batch.column("row_id"))[some]
        yield pa.RecordBatch.from_arrays([pa.array(row_ids), pa.ListArray.from_arrays(ends, pa.array(b)), pa.ListArray.from_arrays(ends, pa.array(x))], names=["row_id", "cb", "cv"])
