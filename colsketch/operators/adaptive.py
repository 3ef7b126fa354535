"""The learned sketch: k-means on signed columns whose centres are kept inside an L1 ball, in full batch and in mini-batches.

Centres are stored by row: no centre is ever in one place. The steps are given as relations over (row_id, bucket, value)
and, for learning, as row-local kernels (row_kernels) over lists, which the matrix is written to once. A pass joins the
rows with their part of the centres, without moving the matrix, sends (feature, bucket) products once, takes an argmin for
each feature, and sums each row by bucket through the map, which is sent to all tasks up to MAX_BROADCAST features and
joined beyond. A pass's thresholds stay pending: they are applied where centres are read, which are never rewritten for it.

Choices: rate 1 / (2 size) by default, 5 passes, ties to the lowest bucket, empty groups keep their centres unless
reseed_empty. A matrix with fewer columns than r raises ValueError; one without entries has no model.
"""

from __future__ import annotations

import json
import threading
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import bucket_of, sample_features, sign_of, uniform_of
from ..session import cut, drop, free
from ..sources.matrix import FeatureMatrix
from . import l1ball, row_kernels
from .oblivious import SKETCH, _signs, feature_map, group_sizes

#: Features whose (id, bucket, flip) go to every task, about 50 MB; larger maps are joined.
MAX_BROADCAST = 4_000_000
#: Non-zeros that a partition of the matrix has at least while there are fewer partitions than the session's.
PART_ENTRIES = 50_000


#: Figures by centre that tasks send to the driver without summing them by a shuffle, about 100 MB at most.
MAX_CELLS = 3_000_000


def signed(fm: FeatureMatrix, seed: int, signs: str = "random") -> DataFrame:
    return fm.entries.select("row_id", "feature_id", (F.col("value") * sign_of(F.col("feature_id"), seed, signs)).alias("value"))


INITS = ("columns", "nonempty", "oblivious_groups", "plusplus")


def init_centres(m: DataFrame, r: int, seed: int, init: str = "columns", signs: str = "random") -> DataFrame:
    """r signed columns picked by hash; the means of count-sketch's own groups (extension), from which error cannot rise; or
    'plusplus' (extension): each next column drawn in proportion to its squared distance from those picked so far.

    A column without entries has no id, so 'columns' never picks one and 'nonempty' is the same.
    """
    if init not in INITS:
        raise ValueError(f"unknown init {init!r}")
    features = m.select("feature_id").distinct()
    if init == "oblivious_groups":
        return means(m, feature_map(features, r, seed, signs))
    picked = spread_columns(m, r, seed) if init == "plusplus" else sample_features(features, r, seed)
    return m.join(F.broadcast(picked), "feature_id").select("row_id", "bucket", "value")  # r rows


def spread_columns(m: DataFrame, r: int, seed: int) -> DataFrame:
    """(feature_id, bucket): r passes, each with the products of one column; the draw is the least -ln(u) / distance."""
    sizes = column_norms(m)
    first = sample_features(m.select("feature_id").distinct(), 1, seed, "/spread").first()
    picked = [first.feature_id] if first is not None else []
    least = cut(sizes.withColumn("least", F.lit(float("inf"))))
    while picked and len(picked) < r:
        one = m.where(F.col("feature_id") == picked[-1]).select("row_id", F.col("value").alias("c"))
        sq = sizes.where(F.col("feature_id") == picked[-1]).first().sq
        cross = m.join(one, "row_id").groupBy("feature_id").agg(F.sum(F.col("value") * F.col("c")).alias("product"))
        near = F.greatest(F.lit(0.0), F.col("sq") - 2 * F.coalesce("product", F.lit(0.0)) + sq)
        least = cut(least.join(cross, "feature_id", "left").select("feature_id", "sq", F.least("least", near).alias("least")))
        left = least.where(~F.col("feature_id").isin(picked))
        found = left.orderBy(F.try_divide(-F.log(uniform_of(seed + len(picked), F.col("feature_id"))), "least").asc_nulls_last(), "feature_id").first()
        if found is None:
            break
        picked.append(found.feature_id)
    return m.sparkSession.createDataFrame([(f, b) for b, f in enumerate(picked)], "feature_id long, bucket int")


def cross_products(m: DataFrame, centres: DataFrame) -> DataFrame:
    """(feature_id, bucket, product) of the pairs that share a row."""
    c = centres.select("row_id", "bucket", F.col("value").alias("c"))
    return m.join(c, "row_id").groupBy("feature_id", "bucket").agg(F.sum(F.col("value") * F.col("c")).alias("product"))


def column_norms(m: DataFrame) -> DataFrame:
    return m.groupBy("feature_id").agg(F.sum(F.col("value") * F.col("value")).alias("sq"))


def assign(m: DataFrame, centres: DataFrame, r: int) -> DataFrame:
    """(feature_id, bucket): the nearest centre. Of centres that share no row with a column only the one of least norm matters,
    the first in the order of (norm, bucket) that the column does not overlap; so d x r pairs are never made."""
    norms = {b: 0.0 for b in range(r)} | {x.bucket: x.sq for x in l1ball.stats(centres).select("bucket", "sq").collect()}  # r rows
    order = sorted((v, b) for b, v in norms.items())
    spark = m.sparkSession
    sq = F.broadcast(spark.createDataFrame([(b, float(v)) for b, v in norms.items()], "bucket int, centre_sq double"))
    near = cross_products(m, centres).join(sq, "bucket").select("feature_id", "bucket", (F.col("centre_sq") - 2 * F.col("product")).alias("dist"))
    best = near.groupBy("feature_id").agg(F.min(F.struct("dist", "bucket")).alias("best"), F.collect_set("bucket").alias("met"))
    listed = F.from_json(F.lit(json.dumps([{"dist": v, "bucket": b} for v, b in order])), "array<struct<dist:double,bucket:int>>")
    first = F.get(F.filter(listed, lambda x: ~F.array_contains(F.col("met"), x["bucket"])), F.lit(0))
    picked = F.when(first.isNull() | (F.col("best") < first), F.col("best")).otherwise(first)
    everything = m.select("feature_id").distinct().join(best, "feature_id", "left")
    return everything.select("feature_id", F.coalesce(picked["bucket"], F.lit(order[0][1])).alias("bucket"))


def free_signs(m: DataFrame, centres: DataFrame, r: int) -> DataFrame:
    """(feature_id, bucket, flip): the nearest of centres and their mirror images (extension).

    With a mirror image the cross term is -2 |product|, so only pairs that share a row and the centre of least norm can win.
    """
    norms = {b: 0.0 for b in range(r)} | {x.bucket: x.sq for x in l1ball.stats(centres).select("bucket", "sq").collect()}  # r rows
    low, first = min((v, b) for b, v in norms.items())
    sq = F.broadcast(m.sparkSession.createDataFrame([(b, float(v)) for b, v in norms.items()], "bucket int, centre_sq double"))
    near = cross_products(m, centres).join(sq, "bucket")
    near = near.select("feature_id", F.struct((F.col("centre_sq") - 2 * F.abs("product")).alias("dist"), "bucket", F.when(F.col("product") < 0, -1).otherwise(1).alias("flip")).alias("c"))
    best = near.groupBy("feature_id").agg(F.min("c").alias("best"))
    else_ = F.struct(F.lit(float(low)).alias("dist"), F.lit(first).cast("int").alias("bucket"), F.lit(1).alias("flip"))
    picked = F.least(F.coalesce("best", else_), else_)
    return m.select("feature_id").distinct().join(best, "feature_id", "left").select("feature_id", picked["bucket"].alias("bucket"), picked["flip"].alias("flip"))


def row_sketched(df: DataFrame, key: str, rows: int, seed: int) -> DataFrame:
    """Rows hashed to `rows` signed sums, so that columns of any length are short ones with nearly the same distances (extension)."""
    at, sign = bucket_of(F.col("row_id"), rows, seed + 1), sign_of(F.col("row_id"), seed + 1)
    short = df.select(at.cast("long").alias("row_id"), key, (F.col("value") * sign).alias("value"))
    return short.groupBy("row_id", key).agg(F.sum("value").alias("value")).where("value != 0")


def ball_size(m: DataFrame, lam) -> float | None:
    """lam itself, or for ('relative', f) the f-th part of the mean L1 norm of the columns (extension)."""
    if not isinstance(lam, tuple):
        return lam
    total = m.agg(F.sum(F.abs("value")).alias("l1"), F.countDistinct("feature_id").alias("d")).first()
    return lam[1] * total.l1 / total.d if total.d else None


def moved_share(before: DataFrame, after: DataFrame) -> float:
    """Share of the features whose bucket differs between two maps."""
    old = before.select("feature_id", F.col("bucket").alias("old"))
    return after.join(old, "feature_id", "left").agg(F.avg((~F.col("bucket").eqNullSafe(F.col("old"))).cast("double"))).first()[0] or 0.0


def kmeans_reference(fm: FeatureMatrix, r: int, seed: int, signs: str = "random") -> DataFrame:
    """(feature_id, bucket) by plain k-means on the signed columns as dense vectors; for small numbers of rows only."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    ids = [x.row_id for x in fm.rows.orderBy("row_id").limit(20_001).collect()]
    if len(ids) > 20_000:
        raise ValueError("the reference takes 20,000 rows at most")
    m = signed(fm, seed, signs).groupBy("feature_id").agg(F.map_from_entries(F.collect_list(F.struct("row_id", "value"))).alias("v"))
    every = F.from_json(F.lit(json.dumps(ids)), "array<bigint>")
    data = m.select("feature_id", array_to_vector(F.transform(every, lambda i: F.coalesce(F.try_element_at("v", i), F.lit(0.0)))).alias("features"))
    return KMeans(k=r, seed=seed).fit(data).transform(data).select("feature_id", F.col("prediction").alias("bucket"))


def group_sums(m: DataFrame, fmap: DataFrame) -> DataFrame:
    return m.join(fmap.select("feature_id", "bucket"), "feature_id").groupBy("row_id", "bucket").agg(F.sum("value").alias("total"))


def means(m: DataFrame, fmap: DataFrame) -> DataFrame:
    sizes = F.broadcast(group_sizes(fmap))  # r rows
    return group_sums(m, fmap).join(sizes, "bucket").select("row_id", "bucket", (F.col("total") / F.col("size")).alias("value")).where("value != 0")


def gradient(m: DataFrame, fmap: DataFrame, centres: DataFrame) -> DataFrame:
    """-2 (sum of the group's columns - size x centre), by row and bucket."""
    sizes = F.broadcast(group_sizes(fmap))
    sums = group_sums(m, fmap).select("row_id", "bucket", F.col("total").alias("t"), F.lit(0.0).alias("c"))
    held = centres.select("row_id", "bucket", F.lit(0.0).alias("t"), F.col("value").alias("c"))
    both = sums.unionByName(held).groupBy("row_id", "bucket").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    return both.join(sizes, "bucket").select("row_id", "bucket", (-2 * (F.col("t") - F.col("size") * F.col("c"))).alias("value"))


def rates(sizes: dict[int, int], rate, counts: dict | None = None, turn: int = 1) -> dict[int, float]:
    """The rate of each group by its size. rate: 'per_centre' (or 'per_batch', the same on a batch's sizes), ('constant', eta),
    ('decay', eta0), or 'running_mean' with cumulative counts, which it adds to."""
    if rate == "running_mean":
        for b, n in sizes.items():
            counts[b] = counts.get(b, 0) + n
        return {b: 1 / (2 * counts[b]) for b in sizes}
    if rate in ("per_centre", "per_batch"):
        return {b: 1 / (2 * n) for b, n in sizes.items()}
    kind, e = rate
    if kind not in ("constant", "decay"):
        raise ValueError(f"unknown rate {rate!r}")
    return {b: e / (turn if kind == "decay" else 1) for b in sizes}


def repeatable(sizes: dict[int, int], rate) -> None:
    """Raises if repeated steps at a constant rate diverge; one step alone, as in step(), is defined for any rate."""
    if isinstance(rate, tuple) and rate[0] == "constant" and sizes and rate[1] >= 1 / max(sizes.values()):
        raise ValueError("a constant rate must be below 1 / the largest group's size")


def moves(sizes: dict[int, int], eta: dict[int, float]) -> list[tuple[int, float, float, int]]:
    """(bucket, keep, gain, size): a step is keep x centre + gain x the group's sum, or the group's mean where keep is 0."""
    return [(b, 0.0 if abs(1 - 2 * eta[b] * n) < 1e-12 else 1 - 2 * eta[b] * n, 2 * eta[b], n) for b, n in sizes.items()]


def sizes_of(fmap: DataFrame) -> dict[int, int]:
    return {b: n for b, n in group_sizes(fmap).select("bucket", "size").collect()}  # r rows


def step(m: DataFrame, fmap: DataFrame, centres: DataFrame, rate="per_centre", counts: dict | None = None, turn: int = 1) -> DataFrame:
    """One gradient step of the groups in fmap; others keep their centres. For rate see rates()."""
    sizes = sizes_of(fmap)
    return stepped(m, fmap, centres, moves(sizes, rates(sizes, rate, counts, turn)))


def stepped(m: DataFrame, fmap: DataFrame, centres: DataFrame, plan: list[tuple[int, float, float, int]]) -> DataFrame:
    plan = F.broadcast(m.sparkSession.createDataFrame([(b, float(k), float(g), int(n)) for b, k, g, n in plan], "bucket int, keep double, gain double, n long"))
    sums = group_sums(m, fmap).select("row_id", "bucket", F.col("total").alias("t"), F.lit(0.0).alias("c"))
    held = centres.select("row_id", "bucket", F.lit(0.0).alias("t"), F.col("value").alias("c"))
    both = sums.unionByName(held).groupBy("row_id", "bucket").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    moved = F.when(F.col("keep").isNull(), F.col("c")).when(F.col("keep") == 0, F.col("t") / F.col("n")).otherwise(F.col("c") * F.col("keep") + F.col("t") * F.col("gain"))
    return both.join(plan, "bucket", "left").select("row_id", "bucket", moved.alias("value")).where("value != 0")


@dataclass
class SketchModel:
    feature_map: DataFrame  # feature_id, bucket, sign
    groups: DataFrame  # bucket, size, theta
    centres: DataFrame | None
    meta: dict = field(default_factory=dict)
    held: list[DataFrame] = field(default_factory=list)  # stored tables that the centres and the map are read from
    means: row_kernels.Replay | None = None  # for matrices in lists: the groups' means of a row

    def training_sketch(self) -> DataFrame:
        """The sparse centres of the last pass, one column of the sketch each."""
        return self.centres

    def transform(self, fm: FeatureMatrix, shrink: str = "theta", unseen: str = "drop", max_broadcast: int = MAX_BROADCAST) -> DataFrame:
        """New rows: group means of signed values; shrink 'none', 'theta' (stored thresholds, extension) or 'project'.

        unseen 'hash' gives features that were not met the group of a count-sketch.
        """
        if self.means is not None and fm.lists is not None and fm.d == self.meta["width"] and unseen == "drop":
            return self._of_lists(fm, shrink)
        fmap = self.feature_map
        fmap = F.broadcast(fmap) if self.meta.get("d", max_broadcast + 1) <= max_broadcast else fmap
        e = fm.entries.join(fmap, "feature_id", "left" if unseen == "hash" else "inner")
        if unseen == "hash":
            f = F.col("feature_id")
            e = e.withColumn("bucket", F.coalesce("bucket", bucket_of(f, self.meta["r"], self.meta["seed"]))).withColumn("sign", F.coalesce("sign", sign_of(f, self.meta["seed"])))
        sums = e.groupBy("row_id", "bucket").agg(F.sum(F.col("value") * F.col("sign")).alias("t"))
        out = sums.join(F.broadcast(self.groups), "bucket").select("row_id", "bucket", (F.col("t") / F.col("size")).alias("value"), "theta")
        if shrink == "theta":
            out = out.withColumn("value", l1ball.soft(F.col("value"), F.col("theta")))
        out = out.select("row_id", "bucket", "value").where("value != 0")
        return l1ball.project(out, self.meta["lam"], self.meta["eps"]) if shrink == "project" and self.meta.get("lam") else out

    def _of_lists(self, fm: FeatureMatrix, shrink: str) -> DataFrame:
        """transform() where each row is, without a shuffle."""
        replay = self.means._replace(packed=fm.opened, without=fm.without)
        if shrink == "theta":
            theta = {x.bucket: x.theta for x in self.groups.collect()}  # r rows
            replay = replay._replace(steps=(*replay.steps, ("shrink", np.array([theta.get(b, 0.0) for b in range(replay.r)]))))
        out = _read_from(fm).mapInArrow(lambda it: row_kernels.coordinates(it, replay), SKETCH)
        return l1ball.project(out, self.meta["lam"], self.meta["eps"]) if shrink == "project" and self.meta.get("lam") else out

    def save(self, path: str) -> None:
        self.feature_map.write.mode("overwrite").parquet(f"{path}/map")
        self.groups.write.mode("overwrite").parquet(f"{path}/groups")
        spark = self.groups.sparkSession
        spark.createDataFrame([(json.dumps(self.meta),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> SketchModel:
        meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
        return SketchModel(spark.read.parquet(f"{path}/map"), spark.read.parquet(f"{path}/groups"), None, meta)


def _read_from(fm: FeatureMatrix) -> DataFrame:
    """What a replay reads of a matrix in lists: its blocks if it has some."""
    return fm.lists.select("row_id", "idx", "val") if fm.packed is None else fm.packed


@dataclass
class PendingCentres:
    """Centres before their projection, in lists by row, and the thresholds that a reader applies; none where already applied."""

    rows: DataFrame  # row_id, cb, cv
    theta: dict[int, float] | None
    parts: int

    @staticmethod
    def of(coordinates: DataFrame, parts: int) -> PendingCentres:
        lists = coordinates.repartition(parts, "row_id").groupBy("row_id").agg(F.collect_list("bucket").alias("cb"), F.collect_list("value").alias("cv"))
        return PendingCentres(cut(lists), None, parts)

    def raw(self) -> DataFrame:
        return self.rows.select("row_id", F.explode(F.arrays_zip("cb", "cv")).alias("x")).select("row_id", F.col("x.cb").alias("bucket"), F.col("x.cv").alias("value"))

    def sketch(self) -> DataFrame:
        if not self.theta:
            return self.raw()
        t = self.rows.sparkSession.createDataFrame(list(self.theta.items()), "bucket int, theta double")
        return l1ball.shrunk(self.raw(), t)

    def thresholds(self, r: int) -> np.ndarray:
        out = np.zeros(r)
        for b, t in (self.theta or {}).items():
            out[b] = t
        return out


@dataclass
class ReplayedCentres:
    """As PendingCentres, of a matrix in lists: each reader makes a row's centres from the row, and nothing is stored."""

    lists: DataFrame  # (row_id, idx, val), or blocks
    replay: row_kernels.Replay  # before the thresholds
    tasks: int  # that read the lists
    theta: dict[int, float] | None = None
    rows = None

    @property
    def sparkSession(self) -> SparkSession:
        return self.lists.sparkSession

    def whole(self) -> row_kernels.Replay:
        if not self.theta:
            return self.replay
        return self.replay._replace(steps=(*self.replay.steps, ("shrink", PendingCentres.thresholds(self, self.replay.r))))

    def _read(self, kernel, schema: str, *more) -> DataFrame:
        return self.lists.mapInArrow(lambda it: kernel(it, *more), schema)

    def raw(self) -> DataFrame:
        return self._read(row_kernels.coordinates, SKETCH, self.replay)

    def sketch(self) -> DataFrame:
        return self._read(row_kernels.coordinates, SKETCH, self.whole())

    def stats(self) -> DataFrame:
        found = self._read(row_kernels.centre_sums, "bucket int, l1 double, linf double, sq double", self.replay)
        return found.groupBy("bucket").agg(F.sum("l1").alias("l1"), F.max("linf").alias("linf"), F.sum("sq").alias("sq"))

    def figures(self) -> list[Row]:
        """The rows of stats(), in any order; tasks send theirs to the driver where these are MAX_CELLS at most."""
        if self.tasks * self.replay.r > MAX_CELLS:
            return self.stats().collect()
        t = self._read(row_kernels.centre_sums, "bucket int, l1 double, linf double, sq double", self.replay).toArrow()
        bucket, l1, linf, sq = (np.asarray(c) for c in t.columns)
        most = np.zeros(self.replay.r)
        np.maximum.at(most, bucket, linf)
        l1, sq = (np.bincount(bucket, x, minlength=self.replay.r) for x in (l1, sq))
        return [Row(bucket=b, l1=float(l1[b]), linf=float(most[b]), sq=float(sq[b])) for b in np.flatnonzero(most).tolist()]

    def cells(self, search: list) -> DataFrame | pa.Table:
        """As a table on the driver where all tasks have MAX_CELLS at most."""
        bounds = tuple(np.array([getattr(s, c) for s in search], kind) for c, kind in (("bucket", np.int64), ("low", float), ("high", float))) + (np.array([s.n == 0 for s in search]),)
        found = self._read(row_kernels.centre_cells, "bucket int, cell int, n long, total double, sq double", self.replay, bounds, l1ball.CELLS)
        if self.tasks * len(search) * l1ball.CELLS > MAX_CELLS:
            return found.groupBy("bucket", "cell").agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.sum("sq").alias("sq"))
        t = found.toArrow()
        bucket, cell, *figures = (np.asarray(c) for c in t.columns)
        met, at = np.unique(bucket.astype(np.int64) * l1ball.CELLS + cell, return_inverse=True)
        n, total, sq = (np.bincount(at, x, minlength=len(met)) for x in figures)
        return pa.table({"bucket": met // l1ball.CELLS, "cell": met % l1ball.CELLS, "n": n, "total": total, "sq": sq})


@dataclass
class _Map:
    """The groups of features: on the driver up to MAX_BROADCAST features, else a table (feature_id, bucket, flip, dist)."""

    ids: np.ndarray | None
    bucket: np.ndarray | None
    flip: np.ndarray | None
    dist: np.ndarray | None = None
    stored: DataFrame | None = None

    @staticmethod
    def of(found: DataFrame, d: int) -> _Map:
        if d > MAX_BROADCAST:
            return _Map(None, None, None, stored=cut(found))
        t = found.toArrow()
        order = np.argsort(np.asarray(t.column("feature_id")))
        return _Map(*(np.asarray(t.column(c))[order] for c in ("feature_id", "bucket", "flip", "dist")))

    @property
    def table(self) -> DataFrame:
        """Made of the arrays where it is asked for."""
        if self.stored is None:
            kinds = (("feature_id", pa.int64()), ("bucket", pa.int32()), ("flip", pa.int32()), ("dist", pa.float64()))
            columns = (self.ids, self.bucket, self.flip, self.dist)
            self.stored = SparkSession.active().createDataFrame(pa.table([pa.array(x, t) for x, (_, t) in zip(columns, kinds, strict=True)], schema=pa.schema(kinds)))
        return self.stored

    def sizes(self) -> dict[int, int]:
        if self.ids is None:
            return sizes_of(self.table)
        return {b: int(n) for b, n in enumerate(np.bincount(self.bucket)) if n}

    def moved(self, before: _Map) -> float:
        if self.ids is None:
            return moved_share(before.table, self.table)
        return float((self.bucket != before.bucket).mean()) if len(self.ids) else 0.0


#: One learner at a time makes a form that others wait for.
_SHARING = threading.Lock()


class _Learner:
    """A matrix written once as signed rows, and the passes over it."""

    def __init__(self, fm: FeatureMatrix, r: int, seed: int, signs: str, lam, eps: float):
        self.r, self.seed, self.signs, self.eps = r, seed, signs, eps
        self.drawn = "random" if signs == "learned" else signs
        self.lists = fm.lists if fm.lists is not None and fm.d <= MAX_BROADCAST else None
        if self.lists is not None:
            self._profiled(fm, lam)
            return
        with _SHARING:
            made = None if fm.shared is None else fm.shared.get((seed, self.drawn))
            self.rows, self.d, l1, self.parts = made or self._written(fm)
            if fm.shared is not None:
                fm.shared[seed, self.drawn] = (self.rows, self.d, l1, self.parts)
        self._sized(lam, l1)

    def _sized(self, lam, l1: float) -> None:
        if self.d < self.r:
            raise ValueError(f"{self.d} columns with entries are fewer than the {self.r} centres")
        self.lam = lam[1] * l1 / self.d if isinstance(lam, tuple) else lam
        # Products of a feature partition's columns with all centres fit a task.
        self.feature_parts = max(self.parts, -(-self.d * self.r // 4_000_000))
        self.counts: dict[int, int] = {}

    def _profiled(self, fm: FeatureMatrix, lam) -> None:
        """The matrix is read from its lists in each pass; signs are a figure a feature."""
        self.rows, self.width, spark = self.lists, fm.d, self.lists.sparkSession
        self.read, self.packed, self.without = _read_from(fm), fm.opened, fm.without
        with _SHARING:
            if fm.profile is None:
                d, met, l1 = fm.d, np.zeros(fm.d, bool), 0.0
                without, opened = self.without, self.packed
                found = self.read.mapInArrow(lambda it: row_kernels.profile_of_blocks(it, d, opened, without) if opened is not None else row_kernels.profile(it, d), "l1 double, met binary").collect()
                for x in found:  # a bit a feature from each task
                    met |= np.unpackbits(np.frombuffer(x.met, np.uint8), count=fm.d).astype(bool)
                    l1 += x.l1
                fm.profile = met, l1, len(found)
        self.met, l1, self.tasks = fm.profile
        self.d, self.parts = int(self.met.sum()), int(spark.conf.get("spark.sql.shuffle.partitions"))
        self._sized(lam, l1)
        if self.drawn == "identity":
            self.sent_signs = None
        else:
            self.sent_signs = spark.sparkContext.broadcast(_signs(fm.d, self.seed).astype(np.int8))

    def features(self) -> DataFrame:
        """Those with entries."""
        if self.lists is None:
            return self.entries().select("feature_id").distinct()
        if self.met.all():
            return self.rows.sparkSession.range(self.width).withColumnRenamed("id", "feature_id")
        return self.rows.sparkSession.createDataFrame(pa.table({"feature_id": pa.array(np.flatnonzero(self.met).astype(np.int64))}))

    def _sent(self, ids: np.ndarray, bucket: np.ndarray, flip: np.ndarray | None = None):
        """A map of features as arrays by feature."""
        out, turn = np.full(self.width, -1, np.int32), None
        out[ids] = bucket
        if flip is not None and (flip != 1).any():
            turn = np.ones(self.width, np.int8)
            turn[ids] = flip
        return self.rows.sparkSession.sparkContext.broadcast((out, turn))

    def _picked(self, picked: DataFrame, theta: dict[int, float] | None = None) -> tuple:
        """The step that makes columns (feature_id, bucket) centres, r rows."""
        rows = picked.select("feature_id", "bucket").collect()
        shrunk = None if theta is None else np.array([theta.get(b, 0.0) for b in range(self.r)])
        return "set", self._sent(np.array([x.feature_id for x in rows], np.int64), np.array([x.bucket for x in rows], np.int32)), shrunk

    def _started(self, init: str) -> ReplayedCentres:
        if init not in INITS:
            raise ValueError(f"unknown init {init!r}")
        if init == "oblivious_groups":
            t = feature_map(self.features(), self.r, self.seed, self.drawn).select("feature_id", "bucket").toArrow()
            groups = _Map(np.asarray(t.column("feature_id")), np.asarray(t.column("bucket")), None)
            first = "move", self._sent(groups.ids, groups.bucket), row_kernels.move_table([(b, 0.0, 0.0, n) for b, n in groups.sizes().items()], self.r)
        else:
            first = self._picked(spread_columns(self.entries(), self.r, self.seed) if init == "plusplus" else sample_features(self.features(), self.r, self.seed))
        return self._replayed((first,))

    def _replayed(self, steps: tuple) -> ReplayedCentres:
        return ReplayedCentres(self.read, row_kernels.Replay(self.r, self.sent_signs, steps, self.packed, self.without), self.tasks)

    def _written(self, fm: FeatureMatrix) -> tuple[DataFrame, int, float, int]:
        """(rows in lists, number of columns, sum of magnitudes, partitions). Lists have 4 bytes a figure where that loses nothing."""
        m = signed(fm, self.seed, self.drawn)
        inside, same = F.col("feature_id").between(-(1 << 31), (1 << 31) - 1), F.col("value") == F.col("value").cast("float").cast("double")
        nnz, d, l1, short, single = m.agg(F.count("*"), F.countDistinct("feature_id"), F.sum(F.abs("value")), F.bool_and(inside), F.bool_and(same)).first()
        most = int(m.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        parts = max(1, min(most, -(-nnz // PART_ENTRIES)))
        m = m.select("row_id", F.col("feature_id").cast("int" if short else "long"), F.col("value").cast("float" if single else "double"))
        lists = m.repartition(parts, "row_id").groupBy("row_id").agg(F.collect_list("feature_id").alias("idx"), F.collect_list("value").alias("val"))
        rows = cut(lists.sortWithinPartitions("row_id"))
        if fm.shared is not None:
            del m, lists
            free(rows.sparkSession)
        return rows, d, l1, parts

    def entries(self) -> DataFrame:
        e = self.rows.select("row_id", F.explode(F.arrays_zip("idx", "val")).alias("x")).select("row_id", F.col("x.idx").cast("long").alias("feature_id"), F.col("x.val").cast("double").alias("value"))
        return e if self.lists is None else e.select("row_id", "feature_id", (F.col("value") * sign_of(F.col("feature_id"), self.seed, self.drawn)).alias("value"))

    def start(self, init: str) -> PendingCentres | ReplayedCentres:
        if self.lists is not None:
            return self._started(init)
        return PendingCentres.of(init_centres(self.entries(), self.r, self.seed, init, self.drawn), self.parts)

    def norms(self, centres: PendingCentres) -> np.ndarray:
        out = np.zeros(self.r)
        whole = centres.sketch() if self.lists is None else self._replayed(centres.whole().steps)
        for x in l1ball.figures(whole):  # r rows
            out[x.bucket] = x.sq
        return out

    def assign(self, centres: PendingCentres, norms: np.ndarray, batch: tuple[float, str] | None = None, short: row_kernels.Short | None = None) -> _Map:
        """batch: the share of the features that take part, and the role of the draw; short: centres to use in place of these."""
        parts, r, seed, both = self.feature_parts, self.r, self.seed, self.signs == "learned"
        if self.lists is not None:
            replay, per = centres.whole() if short is None else self._replayed(()).replay, -(-self.width // parts)
            products = self.read.mapInArrow(lambda it: row_kernels.sent_products(it, per, seed, batch, replay, short), row_kernels.SENT)
            return _Map.of(products.groupBy("part").applyInArrow(lambda t: row_kernels.nearest_sent(t, norms, both, per), row_kernels.NEAREST), self.d)
        theta = centres.thresholds(self.r)
        joined = self.rows.join(centres.rows, "row_id", "left")
        products = joined.mapInArrow(lambda it: row_kernels.products(it, theta, parts, r, seed, batch), row_kernels.PRODUCTS)
        found = products.groupBy("part").applyInArrow(lambda t: row_kernels.nearest(t, norms, both), row_kernels.NEAREST)
        return _Map.of(found, self.d)

    def assign_short(self, centres: ReplayedCentres, rows: int) -> _Map:
        """assign() on rows hashed to that many sums, of which only the centres' are made: a column's product with a centre so
        shortened is the sum of its entries, each times its row's sign and the centre at its row's bucket."""
        replay, seed, seen = centres.whole(), self.seed, np.zeros((rows, self.r))
        found = self.read.mapInArrow(lambda it: row_kernels.shortened(it, replay, rows, seed), "h int, bucket int, value double").groupBy("h", "bucket").agg(F.sum("value").alias("value")).toArrow()
        h, b, value = (np.asarray(c) for c in found.columns)  # rows x r figures
        seen[h, b] = value
        return self.assign(centres, (seen * seen).sum(axis=0), short=row_kernels.Short(seed, self.read.sparkSession.sparkContext.broadcast(seen)))

    def step(self, centres: PendingCentres, fmap: _Map, rate, turn: int) -> tuple[PendingCentres, np.ndarray]:
        """The centres after a gradient step, with pending thresholds, and their squared norms."""
        sizes = fmap.sizes()
        repeatable(sizes, rate)
        plan = moves(sizes, rates(sizes, rate, self.counts, turn))
        if self.lists is not None:
            table = row_kernels.move_table(plan, self.r)
            # Where each centre is its group's mean, what was before does not count.
            before = () if (table[0] == 0).all() else centres.whole().steps
            moved = self._replayed((*before, ("move", self._sent(fmap.ids, fmap.bucket, fmap.flip), table)))
        elif fmap.ids is None:
            m = self.entries().join(fmap.table.select("feature_id", "flip"), "feature_id").select("row_id", "feature_id", (F.col("value") * F.col("flip")).alias("value"))
            moved = PendingCentres.of(stepped(m, fmap.table, centres.sketch(), plan), self.parts)
        else:
            theta, r = centres.thresholds(self.r), self.r
            table = row_kernels.move_table(plan, r)
            sent = self.rows.sparkSession.sparkContext.broadcast((fmap.ids, fmap.bucket.astype(np.int32), fmap.flip.astype(np.int8)))
            joined = self.rows.join(centres.rows, "row_id", "left")
            moved = PendingCentres(cut(joined.mapInArrow(lambda it: row_kernels.steps(it, theta, sent, table, r), row_kernels.CENTRES).repartition(self.parts, "row_id")), None, self.parts)
        norms = np.zeros(self.r)
        if self.lam:
            found = l1ball.solved(moved.raw() if self.lists is None else moved, self.lam, self.eps)  # r rows
            moved.theta = {b: t for b, t, *_ in found}
            for b, *_, sq in found:
                norms[b] = sq
            return moved, norms
        return moved, self.norms(moved)

    def model(self, centres: PendingCentres, fmap: _Map, meta: dict) -> SketchModel:
        sign = sign_of(F.col("feature_id"), self.seed, self.drawn) * F.col("flip")
        spark = self.rows.sparkSession
        theta = centres.theta or {}
        groups = spark.createDataFrame([(b, n, float(theta.get(b, 0.0))) for b, n in fmap.sizes().items()], "bucket int, size long, theta double")
        meta = {"r": self.r, "lam": self.lam, "eps": self.eps, "seed": self.seed, "signs": self.signs, "d": self.d} | meta
        if self.lists is not None:
            sent, own = self._sent(fmap.ids, fmap.bucket, fmap.flip), self.sent_signs
            table = spark.range(self.width).mapInArrow(lambda it: row_kernels.mapped(it, sent, own), "feature_id long, bucket int, sign int")
            means = self._replayed((("move", sent, row_kernels.move_table([(b, 0.0, 0.0, n) for b, n in fmap.sizes().items()], self.r)),)).replay
            return SketchModel(table, groups, centres.sketch(), meta | {"width": self.width}, means=means)
        table = cut(fmap.table.select("feature_id", "bucket", sign.cast("int").alias("sign")))
        return SketchModel(table, groups, centres.sketch(), meta, [centres.rows, table])


def learn_full(fm: FeatureMatrix, r: int, iters: int = 5, lam=None, eps: float = 0.1, seed: int = 0, rate="per_centre", init: str = "columns", signs: str = "random", tol: float | None = None, row_sketch: int | None = None, reseed_empty: bool = False) -> SketchModel:
    """Full batch: assign every column, step every centre, project every centre; iters times. lam None is plain k-means.

    Extensions: lam ('relative', f); signs 'learned'; tol ends when at most that share of columns moved; row_sketch
    assigns on rows hashed to that many sums, while centres stay exact; reseed_empty moves the centres of empty groups to
    the columns that are farthest from theirs.
    """
    work = _Learner(fm, r, seed, signs, lam, eps)
    centres = work.start(init)
    norms, fmap, turn = work.norms(centres), None, 0
    here = work.lists is not None and row_sketch and row_sketch * r <= MAX_CELLS
    short = cut(row_sketched(work.entries(), "feature_id", row_sketch, seed)) if row_sketch and not here else None
    for turn in range(1, iters + 1):
        before = fmap
        if here:
            fmap = work.assign_short(centres, row_sketch)
        elif short is None:
            fmap = work.assign(centres, norms)
        else:
            seen = row_sketched(centres.sketch(), "bucket", row_sketch, seed)
            found = free_signs(short, seen, r) if signs == "learned" else assign(short, seen, r).withColumn("flip", F.lit(1))
            fmap = _Map.of(found.withColumn("dist", F.lit(0.0)), work.d)
        last = tol is not None and before is not None and fmap.moved(before) <= tol
        used = [centres.rows]
        centres, norms = work.step(centres, fmap, rate, turn)
        if reseed_empty and not row_sketch:
            used.append(centres.rows)
            centres, norms = _reseeded(work, centres, norms, fmap)
        drop(*[x for x in used if x is not centres.rows])
        del used, before
        if fm.shared is not None:
            free(work.rows.sparkSession)
        if last:
            break
    return work.model(centres, fmap, {"method": "learned_full", "iters": turn, "init": init})


def _reseeded(work: _Learner, centres: PendingCentres, norms: np.ndarray, fmap: _Map) -> tuple[PendingCentres, np.ndarray]:
    empty = sorted(set(range(work.r)) - set(fmap.sizes()))
    if not empty:
        return centres, norms
    far = fmap.table.join(column_norms(work.entries()), "feature_id").orderBy(F.desc(F.col("dist") + F.col("sq")), "feature_id").limit(len(empty)).select("feature_id").collect()
    picked = work.rows.sparkSession.createDataFrame([(x.feature_id, b) for x, b in zip(far, empty, strict=False)], "feature_id long, bucket int")
    if work.lists is not None:
        theta = None
        if work.lam:
            one = work._replayed((work._picked(picked),))
            theta = {b: t for b, t, *_ in l1ball.solved(one, work.lam, work.eps)}
        centres = work._replayed((*centres.whole().steps, work._picked(picked, theta)))
        return centres, work.norms(centres)
    fresh = work.entries().join(F.broadcast(picked), "feature_id").select("row_id", "bucket", "value")
    if work.lam:
        fresh = l1ball.project(fresh, work.lam, work.eps)
    kept = centres.sketch().join(F.broadcast(picked.select("bucket")), "bucket", "left_anti").select("row_id", "bucket", "value")
    centres = PendingCentres.of(kept.unionByName(fresh), work.parts)
    return centres, work.norms(centres)


def learn_minibatch(fm: FeatureMatrix, r: int, iters: int = 10, batch_fraction: float = 0.1, lam=None, eps: float = 0.1, seed: int = 0, rate="running_mean", signs: str = "random", init: str = "columns") -> SketchModel:
    """As learn_full() on a fresh hash sample of columns each pass, batch_fraction of them; all columns are assigned at the end."""
    if not 0 < batch_fraction <= 1:
        raise ValueError("batch_fraction must be above 0 and at most 1")
    work = _Learner(fm, r, seed, signs, lam, eps)
    centres = work.start(init)
    norms = work.norms(centres)
    for turn in range(1, iters + 1):
        batch = work.assign(centres, norms, (batch_fraction, f"batch{turn}"))
        used = centres.rows
        centres, norms = work.step(centres, batch, rate, turn)
        if used is not None:
            drop(used)
        if fm.shared is not None:
            free(work.rows.sparkSession)
    fmap = work.assign(centres, norms)
    return work.model(centres, fmap, {"method": "learned_minibatch", "iters": iters, "batch_fraction": batch_fraction})
