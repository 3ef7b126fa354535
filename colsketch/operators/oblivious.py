"""Data-oblivious sketches and the data-dependent Hadamard baseline. Sketches have columns (row_id, bucket, value) without zeros."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket_of, normal_of, sample_features, sign_of, signs_array, uniform_of
from ..session import cut
from ..sources.matrix import FeatureMatrix

SKETCH = "row_id long, bucket int, value double"


def feature_map(features: DataFrame, r: int, seed: int, signs: str = "random", family: str = "poly") -> DataFrame:
    """D and Phi of a count-sketch as a table (feature_id, bucket, sign)."""
    f = F.col("feature_id")
    return features.select("feature_id", bucket_of(f, r, seed, family).alias("bucket"), sign_of(f, seed, signs).alias("sign"))


def group_sizes(fmap: DataFrame) -> DataFrame:
    return fmap.groupBy("bucket").agg(F.count("*").alias("size"))


def countsketch(fm: FeatureMatrix, r: int, seed: int, scale: str = "sum", signs: str = "random", family: str = "poly") -> DataFrame:
    """Signed sums by bucket; scale 'mean' divides by the group's size, 'ortho' by its root. One shuffle, on (row, bucket)."""
    f = F.col("feature_id")
    e = fm.entries.select("row_id", bucket_of(f, r, seed, family).alias("bucket"), (F.col("value") * sign_of(f, seed, signs)).alias("v"))
    out = e.groupBy("row_id", "bucket").agg(F.sum("v").alias("value")).where("value != 0")
    if scale == "sum":
        return out
    sizes = F.broadcast(group_sizes(feature_map(fm.features(), r, seed, signs, family)))  # r rows
    by = F.col("size") if scale == "mean" else F.sqrt("size")
    return out.join(sizes, "bucket").select("row_id", "bucket", (F.col("value") / by).alias("value"))


def gaussian(fm: FeatureMatrix, r: int, seed: int, variance: str = "per_d", d: int | None = None, family: str = "md5") -> DataFrame:
    """Every (feature, bucket) has a normal coefficient of variance 1/d, or 1/r; coefficients come from hashes, R is never stored.

    family 'md5' has a SQL twin and makes a row for each non-zero and bucket; 'hash64' is the one for large matrices, a
    row-local product with coefficients made for the features of a block of rows.
    """
    scale = float((d or fm.d or fm.features().count()) if variance == "per_d" else r) ** 0.5
    if family == "hash64":
        return _projected(fm, r, lambda f: normals(f, r, seed) / scale)
    e = fm.entries.select("row_id", "feature_id", "value", F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("bucket"))
    g = normal_of(seed, F.col("feature_id"), F.col("bucket")) / scale
    return e.groupBy("row_id", "bucket").agg(F.sum(F.col("value") * g).alias("value"))


def ternary(fm: FeatureMatrix, r: int, seed: int, density: float = 1 / 3, scaled: bool = True, family: str = "md5") -> DataFrame:
    """Coefficients -1, 0, 1; only the buckets that are live for a feature become rows. The scale sqrt(1/density) is our choice.

    For family see gaussian().
    """
    if family == "hash64":
        size = (1 / density) ** 0.5 if scaled else 1.0
        return _projected(fm, r, lambda f: trits(f, r, seed, density) * size)
    buckets = F.sequence(F.lit(0), F.lit(r - 1))
    live = F.filter(buckets, lambda b: uniform_of(seed, F.col("feature_id"), b) < density)
    e = fm.entries.select("row_id", "feature_id", "value", F.explode(live).alias("bucket"))
    sign = F.when(uniform_of(seed, F.col("feature_id"), F.col("bucket")) < density / 2, -1.0).otherwise(1.0)
    out = e.groupBy("row_id", "bucket").agg(F.sum(F.col("value") * sign).alias("v"))
    return out.select("row_id", "bucket", (F.col("v") * ((1 / density) ** 0.5 if scaled else 1.0)).alias("value")).where("value != 0")


def _hashed(f: np.ndarray, r: int, seed: int, salt: int) -> np.ndarray:
    """64-bit hashes of (feature, bucket), a row for each feature."""
    x = f.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(r, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95) + np.uint64((seed * 2 + salt) & (2**63 - 1))
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def _unit(h: np.ndarray) -> np.ndarray:
    return ((h >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53


def normals(f: np.ndarray, r: int, seed: int) -> np.ndarray:
    return np.sqrt(-2 * np.log(_unit(_hashed(f, r, seed, 0)))) * np.cos(2 * np.pi * _unit(_hashed(f, r, seed, 1)))


def trits(f: np.ndarray, r: int, seed: int, density: float) -> np.ndarray:
    u = _unit(_hashed(f, r, seed, 0))
    return np.where(u < density / 2, -1.0, np.where(u < density, 1.0, 0.0))


#: Cells of a dense block in a row-local kernel.
CELLS = 4_000_000
#: Rows with less than a SPARSE-th of the features, or of the rotation's width, are handled by their entries.
SPARSE = 8
#: Pairs of a row's entries that a kernel holds at a time.
PAIRS = 1_000_000


def _coordinates_of(ids: np.ndarray, y: np.ndarray) -> pa.RecordBatch:
    i, j = np.nonzero(y)
    return pa.RecordBatch.from_arrays([pa.array(ids[i]), pa.array(j.astype(np.int32)), pa.array(y[i, j])], names=["row_id", "bucket", "value"])


#: Rows and entries whose figures a kernel gathers, so that their features' coefficients are made once.
ROWS, ENTRIES = 8_192, 3_000_000


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(row ids, sizes, features, values) of about ROWS rows or ENTRIES entries at a time."""
    held, rows, entries = [], 0, 0
    for batch in batches:
        one = [np.asarray(x) for x in (batch.column("row_id"), batch.column("idx").value_lengths(), batch.column("idx").flatten(), batch.column("val").flatten())]
        held.append(one)
        rows, entries = rows + len(one[0]), entries + len(one[2])
        if rows >= ROWS or entries >= ENTRIES:
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held, rows, entries = [], 0, 0
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def _times(n: int, row: np.ndarray, f: np.ndarray, v: np.ndarray, r: int, coefficients) -> np.ndarray:
    """n rows times coefficients(features), a block of the features that occur in them at a time: as a dense block of rows
    where the rows have most of them, else by the entries alone. row is sorted."""
    width, y = max(1, CELLS // max(r, 1) // 2), np.zeros((n, r))
    order = np.argsort(f, kind="stable")
    met, first = np.unique(f[order], return_index=True)
    ends = np.append(first, len(f))
    many = max(1, min(4096, CELLS // width))
    for low in range(0, len(met), width):
        some = met[low : low + width]
        mine = np.sort(order[ends[low] : ends[low + len(some)]])
        i, at, x, c = row[mine], np.searchsorted(some, f[mine]), v[mine], coefficients(some)
        if SPARSE * len(mine) >= n * len(some):
            for a in range(0, n, many):
                z = min(n, a + many)
                p, q = np.searchsorted(i, [a, z])
                y[a:z] += np.bincount((i[p:q] - a) * len(some) + at[p:q], x[p:q], minlength=(z - a) * len(some)).reshape(z - a, -1) @ c
            continue
        edge = np.flatnonzero(np.append(True, i[1:] != i[:-1])).tolist()
        for a, z in zip(edge, [*edge[1:], len(i)], strict=True):
            y[i[a]] += x[a:z] @ c[at[a:z]]
    return y


def _projected(fm: FeatureMatrix, r: int, coefficients) -> DataFrame:
    """Row-local product with coefficients(features)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, sizes, f, v in _gathered(batches):
            yield _coordinates_of(ids, _times(len(ids), np.repeat(np.arange(len(ids)), sizes), f, v, r, coefficients))

    return fm.as_rows().mapInArrow(run, SKETCH)


def butterfly(x: np.ndarray) -> np.ndarray:
    """Walsh-Hadamard transform of each row, length a power of two, unscaled."""
    x, h = x.copy(), 1
    while h < x.shape[1]:
        y = x.reshape(len(x), -1, 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(len(x), -1)
        h *= 2
    return x


def hadamard_entries(features: DataFrame) -> DataFrame:
    """(i, j, h) of all pairs of the features, as a table; h is the parity of i & j as a sign."""
    i, j = features.select(F.col("feature_id").alias("i")), features.select(F.col("feature_id").alias("j"))
    h = 1 - 2 * F.pmod(F.bit_count(F.col("i").bitwiseAND(F.col("j"))), F.lit(2))
    return i.crossJoin(j).select(F.col("i").cast("int"), F.col("j").cast("int"), h.cast("int").alias("h"))


def _signs(d: int, seed: int) -> np.ndarray:
    """sign_of() for the features below d."""
    return signs_array(np.arange(d), seed)


def _dense_blocks(batches: Iterator[pa.RecordBatch], d: int, cells: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row ids, dense block) of as_rows(); the number of rows follows from the width, so a block has about CELLS cells."""
    many = max(1, CELLS // max(cells, 1))
    for batch in batches:
        for a in range(0, batch.num_rows, many):
            part = batch.slice(a, many)
            sizes = np.asarray(part.column("idx").value_lengths())
            x = np.zeros((part.num_rows, d))
            x[np.repeat(np.arange(part.num_rows), sizes), np.asarray(part.column("idx").flatten())] = np.asarray(part.column("val").flatten())
            yield np.asarray(part.column("row_id")), x


def _kernel(fm: FeatureMatrix, d: int, cells: int, apply) -> DataFrame:
    """Row-local block product over Arrow batches: apply(dense block) gives the sketch's columns; no shuffle after as_rows()."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, x in _dense_blocks(batches, d, cells):
            yield _coordinates_of(ids, apply(x))

    return fm.as_rows().mapInArrow(run, SKETCH)


def _rotation(d: int, seed: int):
    """(width, rotate): signs, zeros up to a power of two, butterfly, over sqrt(width), so that lengths stay."""
    signs, width = _signs(d, seed), 1 << max(0, (d - 1).bit_length())

    def rotate(x: np.ndarray) -> np.ndarray:
        padded = np.zeros((len(x), width))
        padded[:, :d] = x * signs
        return butterfly(padded) / np.sqrt(width)

    return width, rotate


def hadamard_rotate(fm: FeatureMatrix, d: int, seed: int) -> DataFrame:
    """All rotated coordinates."""
    width, rotate = _rotation(d, seed)
    return _kernel(fm, d, 2 * width, rotate)


def coordinates(fm: FeatureMatrix, width: int, r: int, seed: int, replace: bool = False) -> DataFrame:
    """(feature_id, bucket): r coordinates of the rotation, without replacement or, with `replace`, each drawn anew."""
    spark = fm.entries.sparkSession
    if replace:
        draws = spark.range(r).select(F.floor(uniform_of(seed, F.lit("draw"), F.col("id")) * width).cast("long").alias("feature_id"), F.col("id").cast("int").alias("bucket"))
        return draws
    return sample_features(spark.range(width).withColumnRenamed("id", "feature_id"), r, seed, "coordinates")


def _picked(found: DataFrame) -> np.ndarray:
    """The coordinate of each bucket, r figures."""
    return np.array([x.feature_id for x in found.orderBy("bucket").collect()], np.int64)


def hadamard(fm: FeatureMatrix, d: int, r: int, seed: int, replace: bool = False) -> DataFrame:
    """r of the rotated coordinates, without replacement unless `replace`, times sqrt(d'/r); only these leave the kernel."""
    width = 1 << max(0, (d - 1).bit_length())
    return _rotated(fm, d, seed, _picked(coordinates(fm, width, r, seed, replace)), (width / r) ** 0.5)


def _rotated(fm: FeatureMatrix, d: int, seed: int, at: np.ndarray, scale: float = 1.0) -> DataFrame:
    """The rotated coordinates `at`, times scale: the rotation of dense rows, of sparse ones their products with the
    transform's entries, which are the parities of feature & coordinate, so that a row costs by its entries and not by d."""
    width, rotate = _rotation(d, seed)
    sent = fm.entries.sparkSession.sparkContext.broadcast(_signs(d, seed).astype(np.int8))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dense = []

        def sparse() -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if SPARSE * len(batch.column("idx").flatten()) < batch.num_rows * width:
                    yield batch
                else:
                    dense.append(batch)
                    return

        while True:
            for ids, sizes, f, v in _gathered(sparse()):
                row = np.repeat(np.arange(len(ids)), sizes)
                yield _coordinates_of(ids, _times(len(ids), row, f, v * sent.value[f], len(at), lambda some: _parities(some, at)) / np.sqrt(width) * scale)
            if not dense:
                return
            for ids, x in _dense_blocks(dense, d, 2 * width):
                yield _coordinates_of(ids, rotate(x)[:, at] * scale)
            dense.clear()

    return fm.as_rows().mapInArrow(run, SKETCH)


def _parities(f: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Entries (f, at) of the transform."""
    return 1.0 - 2.0 * (np.bitwise_count(f[:, None] & at[None, :]) & 1)


def hadamard_pruned(fm: FeatureMatrix, d: int, r: int, seed: int) -> DataFrame:
    """The same numbers as hadamard() from direct sums over non-zeros: entry (i, j) of the transform is the parity of i & j."""
    width = 1 << max(0, (d - 1).bit_length())
    picked = F.broadcast(coordinates(fm, width, r, seed).select(F.col("feature_id").alias("at"), "bucket"))
    e = fm.entries.crossJoin(picked)  # r rows a non-zero
    sign = (1 - 2 * F.pmod(F.bit_count(F.col("feature_id").bitwiseAND(F.col("at"))), F.lit(2))) * sign_of(F.col("feature_id"), seed)
    return e.groupBy("row_id", "bucket").agg((F.sum(F.col("value") * sign) / float(r) ** 0.5).alias("value")).where("value != 0")


def hadamard_scores(fm: FeatureMatrix, d: int, seed: int, score: str = "sqnorm", labels: DataFrame | None = None) -> DataFrame:
    """(bucket, score) of each rotated coordinate: its energy, or the spread of class means (extension)."""
    width, rotate = _rotation(d, seed)
    if score == "between_class":
        means = hadamard_rotate(fm, d, seed).join(labels, "row_id").groupBy("bucket", "label").agg(F.sum("value").alias("m"))
        means = means.join(F.broadcast(fm.rows.join(labels, "row_id").groupBy("label").agg(F.count("*").alias("n"))), "label").withColumn("m", F.col("m") / F.col("n"))
        return means.groupBy("bucket").agg(F.coalesce(F.var_pop("m"), F.lit(0.0)).alias("score"))

    return energies(fm.as_rows(), d, seed).withColumnRenamed("part0", "score")


def energies(rows: DataFrame, d: int, seed: int, groups: list[int] | None = None) -> DataFrame:
    """(bucket, part0, ...): the energy of each rotated coordinate over rows (row_id, idx, val), or over those of each fold in groups."""
    width, rotate = _rotation(d, seed)
    bits, names = width.bit_length() - 1, [f"part{k}" for k in range(len(groups or [0]))]
    sent = rows.sparkSession.sparkContext.broadcast(_signs(d, seed).astype(np.int8))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, shifts = np.zeros((2, len(names), width))
        for batch in batches:
            sizes = np.asarray(batch.column("idx").value_lengths()).astype(np.int64)
            few = sizes * sizes < 2 * width * bits  # pairs of entries cost less than the rotation
            for k in range(len(names)):
                mine = np.ones(len(sizes), bool) if groups is None else np.asarray(batch.column("fold")) == groups[k]
                part = batch.filter(pa.array(mine & few))
                f = np.asarray(part.column("idx").flatten()).astype(np.int64)
                _add_shifts(shifts[k], sizes[mine & few], f, np.asarray(part.column("val").flatten()) * sent.value[f])
                if (mine & ~few).any():
                    for _, x in _dense_blocks([batch.filter(pa.array(mine & ~few))], d, 2 * width):
                        total[k] += (rotate(x) ** 2).sum(axis=0)
        for k in range(len(names)):
            if shifts[k].any():
                total[k] += np.maximum(butterfly(shifts[k : k + 1])[0], 0) / width
        met = np.flatnonzero(total.any(axis=0))
        yield pa.RecordBatch.from_arrays([pa.array(met.astype(np.int32)), *(pa.array(x[met]) for x in total)], names=["bucket", *names])

    # A task sends one figure a coordinate and group, whatever the number of its rows.
    found = rows.mapInArrow(run, "bucket int, " + ", ".join(f"{x} double" for x in names))
    return found.groupBy("bucket").agg(*(F.sum(x).alias(x) for x in names))


def _add_shifts(total: np.ndarray, sizes: np.ndarray, f: np.ndarray, v: np.ndarray) -> None:
    """Adds to total[x] the products of each row's entries at features f and f ^ x, whose transform is the energy by coordinate."""
    keys, values = np.empty(PAIRS, np.int64), np.empty(PAIRS)
    n = start = 0
    for size in sizes.tolist():
        end = start + size
        step = max(1, PAIRS // max(1, size))
        for a in range(start, end, step):
            z = min(end, a + step)
            m = (z - a) * size
            if n + m > PAIRS:
                total += np.bincount(keys[:n], values[:n], minlength=len(total))
                n = 0
            np.bitwise_xor(f[a:z, None], f[None, start:end], out=keys[n : n + m].reshape(z - a, size))
            np.multiply(v[a:z, None], v[None, start:end], out=values[n : n + m].reshape(z - a, size))
            n += m
        start = end
    if n:
        total += np.bincount(keys[:n], values[:n], minlength=len(total))


def top_without(parts: DataFrame, k: int | None, r: int) -> np.ndarray:
    """As top_coordinates(), of the rows outside group k (of all if None), from the stored energies() of all groups."""
    score = sum((F.col(x) for x in parts.columns if x not in ("bucket", f"part{k}")), F.lit(0.0))
    return np.array([x.bucket for x in parts.select("bucket", score.alias("score")).where("score > 0").orderBy(F.desc("score"), "bucket").limit(r).collect()], np.int64)


def hadamard_topr(fm: FeatureMatrix, d: int, r: int, seed: int, score: str = "sqnorm", labels: DataFrame | None = None) -> DataFrame:
    """The r rotated coordinates with the largest scores; 'sample' draws them in proportion to energy (extension)."""
    return hadamard_at(fm, d, seed, top_coordinates(fm, d, r, seed, score, labels))


def top_coordinates(fm: FeatureMatrix, d: int, r: int, seed: int, score: str = "sqnorm", labels: DataFrame | None = None) -> np.ndarray:
    """The coordinates that hadamard_topr() keeps, best first; fitted on fm, to be used on any rows."""
    scores = hadamard_scores(fm, d, seed, "sqnorm" if score == "sample" else score, labels)
    by = -F.log(uniform_of(seed, F.col("bucket"))) / F.col("score") if score == "sample" else -F.col("score")
    return np.array([x.bucket for x in scores.withColumn("by", by).orderBy("by", "bucket").limit(r).collect()], np.int64)


def hadamard_at(fm: FeatureMatrix, d: int, seed: int, at: np.ndarray) -> DataFrame:
    """The rotated coordinates `at`, in that order."""
    return _rotated(fm, d, seed, at)


#: Features up to which a d x d or d x r matrix is made on the driver.
MOST_DENSE = 20_000


def _small(d: int) -> None:
    if d > MOST_DENSE:
        raise ValueError(f"{d} features are more than the {MOST_DENSE} for which a matrix of that side is made")


def orthonormal(fm: FeatureMatrix, d: int, r: int, seed: int) -> DataFrame:
    """Random orthonormal columns, by a QR on the driver; for d up to some thousands."""
    _small(d)
    q, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, r)))
    sent = fm.entries.sparkSession.sparkContext.broadcast(q)
    return _kernel(fm, d, d, lambda x: x @ sent.value)


def pca(fm: FeatureMatrix, d: int, r: int) -> DataFrame:
    """Principal components by the d x d Gram matrix (contrast only)."""
    return _subspace(fm, d, r, _gram(fm, d))


def _gram(fm: FeatureMatrix, d: int) -> np.ndarray:
    _small(d)
    a, b = fm.entries.alias("a"), fm.entries.alias("b")
    rows = a.join(b, "row_id").groupBy(F.col("a.feature_id").alias("i"), F.col("b.feature_id").alias("j")).agg(F.sum(F.col("a.value") * F.col("b.value")).alias("v"))
    out = np.zeros((d, d))
    t = rows.toArrow()  # d x d, for small d
    out[np.asarray(t.column("i")), np.asarray(t.column("j"))] = np.asarray(t.column("v"))
    return out


def _subspace(fm: FeatureMatrix, d: int, r: int, gram: np.ndarray) -> DataFrame:
    _, vectors = np.linalg.eigh(gram)
    top = fm.entries.sparkSession.sparkContext.broadcast(vectors[:, ::-1][:, :r])
    return _kernel(fm, d, d, lambda x: x @ top.value)


def _gram_of(y: DataFrame, m: int) -> np.ndarray:
    """Y'Y of a sketch with m columns."""
    a, b, g = y.alias("a"), y.alias("b"), np.zeros((m, m))
    for i, j, v in a.join(b, "row_id").groupBy(F.col("a.bucket"), F.col("b.bucket")).agg(F.sum(F.col("a.value") * F.col("b.value"))).collect():
        g[i, j] = v
    return g


def _turned(y: DataFrame, w: np.ndarray) -> DataFrame:
    """Y times a small matrix w."""
    spark = y.sparkSession
    turn = F.broadcast(spark.createDataFrame([(i, j, float(w[i, j])) for i in range(w.shape[0]) for j in range(w.shape[1])], "bucket int, b int, w double"))
    return y.join(turn, "bucket").groupBy("row_id", F.col("b").alias("bucket")).agg(F.sum(F.col("value") * F.col("w")).alias("value"))


def approx_svd(fm: FeatureMatrix, r: int, seed: int, oversample: int = 8, power_iters: int = 0) -> DataFrame:
    """Range finder: a Gaussian sketch Y, the Gram of Y on the driver, and Y turned to its leading directions.

    Each power iteration replaces Y by X X' Y, turned to orthonormal columns first, two sparse products.
    """
    m = r + oversample
    y = cut(gaussian(fm, m, seed, "per_r", family="hash64"))
    for _ in range(power_iters):
        values, vectors = np.linalg.eigh(_gram_of(y, m))
        live = values > 1e-12 * max(values.max(), 1e-300)
        q = _turned(y, vectors[:, live] / np.sqrt(values[live]))
        z = fm.entries.join(q.withColumnRenamed("value", "q"), "row_id").groupBy("feature_id", "bucket").agg(F.sum(F.col("value") * F.col("q")).alias("q"))
        y = cut(fm.entries.join(z, "feature_id").groupBy("row_id", "bucket").agg(F.sum(F.col("value") * F.col("q")).alias("value")))
    _, vectors = np.linalg.eigh(_gram_of(y, m))
    return _turned(y, vectors[:, ::-1][:, :r])


METHODS = ("gaussian", "ternary", "orthonormal", "countsketch", "hadamard", "hadamard_pruned", "hadamard_topr", "pca", "approx_svd", "identity")


def sketch(fm: FeatureMatrix, method: str, r: int, seed: int, **options) -> DataFrame:
    """X times the method's projection. Methods that need it take the number of features from fm.d, or count them."""
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}")
    if method == "identity":
        return identity(fm)
    if method in ("countsketch", "gaussian", "ternary", "approx_svd"):
        return {"countsketch": countsketch, "gaussian": gaussian, "ternary": ternary, "approx_svd": approx_svd}[method](fm, r, seed, **options)
    d = fm.d or (fm.features().agg(F.max("feature_id")).first()[0] or 0) + 1
    if method == "pca":
        return pca(fm, d, r)
    return {"orthonormal": orthonormal, "hadamard": hadamard, "hadamard_pruned": hadamard_pruned, "hadamard_topr": hadamard_topr}[method](fm, d, r, seed, **options)


def identity(fm: FeatureMatrix) -> DataFrame:
    return fm.entries.select("row_id", F.col("feature_id").alias("bucket"), "value")
