"""The experiments: seven methods on the given tables, by accuracy, zeros and time, as width, ball and seed vary.

Each experiment makes its sketches, from parallel threads where no time is measured, and fits the linear models of all of
them, for all folds and costs, in one loop over the rows.
"""

from __future__ import annotations

import threading
import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from typing import NamedTuple

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures as A
from ..operators import adaptive as K
from ..operators import oblivious as O
from ..session import drop, free, kept, ship, small_batches
from ..sources import blocks as B
from ..sources import matrix as M
from . import linear
from . import solve as V

METRICS = "dataset string, method string, r int, lam double, seed long, metric string, value double"
METHODS = ["gaussian", "ternary", "countsketch", "hadamard", "hadamard_topr", "learned_full", "learned_minibatch"]
#: The ball of learned sketches where none is given, a share of the mean L1 norm of the columns.
BALL = ("relative", 0.2)
#: Costs that a comparison tries, of which it reports the best; the full published grid is that of tuning().
COSTS = (0.1, 10.0, 1e3, 1e5)
#: Sketches that are made at a time where no time is measured: of matrices up to SMALL entries, and of larger ones, whose
#: jobs fill the cores and whose files would lie on disk together, or in lists, whose maps lie on the driver together.
THREADS, FEW, SMALL = 6, 2, 2_000_000


class Config(NamedTuple):
    method: str
    r: int
    seed: int = 42
    lam: object = None
    label: str = ""
    options: tuple = ()  # (name, value) pairs for the learner

    def name(self) -> str:
        return f"{self.label or self.method}/{self.r}/{self.seed}/{self.lam}"

    def at(self, dataset: str) -> tuple:
        lam = self.lam if self.lam is not None else BALL
        size = float(lam[1] if isinstance(lam, tuple) else lam) if self.method.startswith("learned") else 0.0
        return dataset, self.label or self.method, self.r, size, self.seed


def _length_quartile(docs: DataFrame) -> F.Column:
    """0 to 3 by the length of the text; the bounds are three figures."""
    bounds = docs.agg(F.percentile_approx(F.length("text"), F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), 10_000)).first()[0] or [0, 0, 0]
    size = F.coalesce(F.length("text"), F.lit(0))
    return sum(((size > b).cast("int") for b in bounds[1:]), (size > bounds[0]).cast("int"))


def _language(docs: DataFrame) -> F.Column:
    return F.when(F.col("lang") == "en", 0).when(F.col("lang") == "fr", 1).when(F.col("lang") == "de", 2).otherwise(3)


def _labelled(docs: DataFrame, label) -> DataFrame:
    """(row_id, label, key): rows with the same text share their key, and so their fold."""
    return docs.select(F.col("doc_id").alias("row_id"), label.cast("int").alias("label"), F.md5(F.lower(F.coalesce("text", F.lit("")))).alias("key"))


def _bigram(spark: SparkSession, d: str):
    docs = M.table(spark, d, "documents", ["doc_id", "text", "lang"])
    return M.from_ngrams(docs, "doc_id", F.col("text")), _labelled(docs, 4 * _language(docs) + _length_quartile(docs))


def _quality(spark: SparkSession, d: str) -> DataFrame:
    return M.table(spark, d, "labels", ["doc_id", "quality"]).where("quality is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))


def _bow(spark: SparkSession, d: str, wanted: str):
    docs = M.table(spark, d, "documents", ["doc_id", "text", "lang"])
    fm = M.from_tokens(docs, "doc_id", F.col("text"), min_df=3)
    if wanted == "quality":
        labels = _labelled(docs.join(_quality(spark, d), "doc_id"), F.col("quality"))
        inside = labels.select("row_id").distinct()
        return M.FeatureMatrix(fm.entries.join(inside, "row_id", "left_semi"), fm.rows.join(inside, "row_id", "left_semi")), labels
    return fm, _labelled(docs, (F.col("lang") == "en") if wanted == "en" else 4 * _language(docs) + _length_quartile(docs))


def _emb(spark: SparkSession, d: str, squares: bool = False):
    """Embeddings with planted labels, as their own have no signal: the largest of the first ten coordinates."""
    fm = M.embeddings(spark, d)
    best = fm.entries.where("feature_id < 10").groupBy("row_id").agg(F.max(F.struct("value", (-F.col("feature_id")).alias("place")))["place"].alias("k"))
    label = -F.col("k")
    labels = best.select("row_id", ((label < 5) if squares else label).cast("int").alias("label"), F.col("row_id").cast("string").alias("key"))
    return M.min_max(M.quadratic(fm, 64) if squares else fm), labels


DATASETS: dict[str, Callable] = {
    "emb10": _emb,
    "bigram": _bigram,
    "embquad": lambda s, d: _emb(s, d, True),
    "bow_quality": lambda s, d: _bow(s, d, "quality"),
    "bow_en": lambda s, d: _bow(s, d, "en"),
    "bow_multi": lambda s, d: _bow(s, d, "multi"),
}


def _given(spark: SparkSession, d: str, name: str, k: int) -> M.FeatureMatrix | None:
    """The texts' matrix in lists, with columns label and fold, made where each text is; None if a doc_id is missing or repeated."""
    docs = M.table(small_batches(ship(spark)), d, "documents", ["doc_id", "text", "lang"])
    n, ids = docs.agg(F.count("*"), F.countDistinct("doc_id")).first()
    if n != ids:
        return None
    label, whole = 4 * _language(docs) + _length_quartile(docs), docs
    if name == "bow_en":
        label = F.col("lang") == "en"
    if name == "bow_quality":
        label = F.col("quality")
        whole = docs.join(_quality(spark, d), "doc_id", "left")
    key = F.md5(F.lower(F.coalesce("text", F.lit(""))))
    whole = V.folds(whole.select(F.col("doc_id").cast("long").alias("row_id"), label.cast("int").alias("label"), key.alias("key"), F.lower("text").alias("t")), "key", k)
    wanted = F.col("label").isNotNull() if name == "bow_quality" else F.lit(True)
    found = M.text_lists(whole.select("row_id", "label", "fold", "t", wanted.alias("wanted")), 2 if name == "bigram" else None)
    if found is None:
        return None
    out = M.FeatureMatrix.of_lists(*found)
    out.entries._kept_at = found[0]._kept_at
    out.shared, out.packed, out.opened = {}, kept(out.lists.select("row_id", "fold", "idx", "val").mapInArrow(B.pack, B.PACKED)), B.unpacked
    return out


def _given_squares(spark: SparkSession, d: str, k: int) -> tuple[M.FeatureMatrix, DataFrame] | None:
    """As load(), of embeddings and their products, which are made where a row is read; None if a vec_id is missing or repeated,
    an array is long or has figures that are not finite, or a row has no label."""
    t = M.table(small_batches(ship(spark)), d, "embeddings", ["vec_id", "embedding"])
    x, first = F.col("embedding").cast("array<double>"), F.slice(F.col("embedding").cast("array<double>"), 1, 10)
    label = F.array_position(first, F.array_max(F.filter(first, lambda v: v != 0))) - 1
    wrong = F.exists(x, lambda v: F.isnan(v) | (F.abs(v) == float("inf")))
    n, ids, most, bad, known = t.agg(F.count("*"), F.countDistinct("vec_id"), F.max(F.size(x)), F.max(F.coalesce(wrong, F.lit(False))), F.count(label)).first()
    if not n or not n == ids == known or most > 64 or bad:
        return None
    key = F.col("row_id").cast("string")
    base = kept(V.folds(t.select(F.col("vec_id").cast("long").alias("row_id"), (label < 5).cast("int").alias("label"), "embedding").withColumn("key", key), "key", k).select("row_id", "label", "fold", F.col("embedding").alias("x")))
    fm = M.scaled_squares(base, 64)
    fm.entries._kept_at, fm.shared = base._kept_at, {}
    rows = base.select("row_id", "label", "fold")
    rows._kept_at = base._kept_at  # the same files
    free(spark)
    return fm, rows


def load(spark: SparkSession, d: str, name: str, k: int = 5) -> tuple[M.FeatureMatrix, DataFrame]:
    """The matrix with dense feature ids, cut so that no method pays for building it, and (row_id, label, fold)."""
    fm = _given(spark, d, name, k) if name == "bigram" or name.startswith("bow") else None
    if fm is not None:
        rows = fm.lists.select("row_id", "label", "fold")
        rows._kept_at = fm.entries._kept_at  # the same files
        free(spark)
        return fm, rows
    squares = _given_squares(spark, d, k) if name == "embquad" else None
    if squares is not None:
        return squares
    fm, labels = DATASETS[name](spark, d)
    given, held = M.FeatureMatrix(kept(fm.entries), kept(fm.rows)), fm.held
    del fm
    drop(*held)
    free(spark)
    dense, _ = M.dense_ids(given)
    # Entries of a row lie together, so that their ids take few bytes.
    out = M.FeatureMatrix(kept(dense.entries.sortWithinPartitions("row_id", "feature_id")), given.rows, dense.d, shared={})
    rows = kept(V.folds(labels, "key", k).select("row_id", "label", "fold"))
    del dense, labels
    drop(given.entries)
    free(spark)
    return out, rows


def _done(fm: M.FeatureMatrix, *tables: DataFrame) -> None:
    """Deletes what load() and learners have stored of a matrix, and other tables."""
    drop(*[x for _, x in fm.energies.values()])
    drop(*([fm.entries] if fm.lists is not None else [fm.entries, fm.rows]), *([] if fm.packed is None else [fm.packed]), *[x[0] for x in (fm.shared or {}).values()], *tables)
    free(fm.entries.sparkSession)


class Fitted(NamedTuple):
    """What a method learned from a matrix: the sketch of new rows, that of the matrix itself, and a learned model."""

    apply: Callable
    training: DataFrame
    model: object = None


def fit(fm: M.FeatureMatrix, c: Config, iters: int = 3, batch_fraction: float = 0.2) -> Fitted:
    """Only the learned methods and the top coordinates look at the matrix they are fitted on."""
    r, seed, d = c.r, c.seed, fm.d
    more = dict(c.options)
    if c.method in ("learned_full", "learned_minibatch"):
        lam, eps = c.lam if c.lam is not None else BALL, more.pop("eps", 0.1)
        steps, shrink, part = more.pop("iters", iters), more.pop("shrink", None), more.pop("batch_fraction", batch_fraction)
        model = K.learn_full(fm, r, steps, lam, eps, seed, **more) if c.method == "learned_full" else K.learn_minibatch(fm, r, steps, part, lam, eps, seed, **more)
        return Fitted(lambda x: model.transform(x, shrink or "theta"), model.transform(fm, shrink) if shrink else model.training_sketch(), model)
    if c.method == "hadamard_topr":
        at = O.top_coordinates(fm, d, r, seed) if fm.lists is None else _top(fm, c)
        apply = lambda x: O.hadamard_at(x, d, seed, at)
    else:
        apply = {
            "gaussian": lambda x: O.gaussian(x, r, seed, "per_r", d, "hash64"),
            "ternary": lambda x: O.ternary(x, r, seed, family="hash64"),
            "countsketch": lambda x: O.countsketch(x, r, seed),
            "hadamard": lambda x: O.hadamard(x, d, r, seed),
            "identity": O.identity,
        }[c.method]
    return Fitted(apply, apply(fm))


#: One method at a time makes the energies that others wait for.
_MAKING = threading.Lock()


def _top(fm: M.FeatureMatrix, c: Config, without: int | None = None) -> np.ndarray:
    """The top coordinates of a matrix in lists, or of its rows outside a fold, from one pass over the pairs of its entries."""
    with _MAKING:
        if c.seed not in fm.energies:
            folds = sorted(x.fold for x in fm.lists.select("fold").distinct().collect())
            fm.energies[c.seed] = folds, kept(O.energies(fm.lists, fm.d, c.seed, folds))
    folds, parts = fm.energies[c.seed]
    return O.top_without(parts, None if without is None else folds.index(without), c.r)


def _width(fm: M.FeatureMatrix, c: Config) -> int:
    return fm.d if c.method == "identity" else c.r


def _in_threads(fm: M.FeatureMatrix, jobs: list[Callable]) -> list:
    spark = fm.entries.sparkSession
    with ThreadPoolExecutor(FEW if fm.lists is not None or fm.entries.count() > SMALL else THREADS) as pool:
        return [f.result() for f in [pool.submit(inheritable_thread_target(spark)(j)) for j in jobs]]


def _unshared(fm: M.FeatureMatrix) -> None:
    """The next learner writes the matrix for itself, as its time counts."""
    drop(*[x[0] for x in fm.shared.values()])
    fm.shared.clear()
    fm.profile = None


def _stored(f: Fitted, sketch: DataFrame) -> DataFrame:
    """The sketch, after which the fitted model is not read any more."""
    out = kept(sketch)
    if f.model is not None:
        drop(*f.model.held)
    return out


def _sketches(fm: M.FeatureMatrix, configs: list[Config]) -> list[DataFrame]:
    def one(c: Config) -> DataFrame:
        f = fit(fm, c)
        return _stored(f, f.training)

    out = _in_threads(fm, [lambda c=c: one(c) for c in configs])
    free(fm.entries.sparkSession)
    return out


def _zeros(fm: M.FeatureMatrix, sketches: list[DataFrame], configs: list[Config]) -> list[float]:
    """Shares of zeros by one pass over all sketches."""
    every = None
    for k, s in enumerate(sketches):
        one = s.where("value != 0").agg(F.count("*").alias("filled")).select(F.lit(k).alias("k"), "filled")
        every = one if every is None else every.unionByName(one)
    n, filled = fm.rows.count(), {x.k: x.filled for x in every.collect()}
    return [1 - filled[k] / max(1, n * _width(fm, c)) for k, c in enumerate(configs)]


def _scored(dataset: str, fm: M.FeatureMatrix, rows: DataFrame, configs: list[Config], sketches: list[DataFrame], costs: tuple[float, ...]) -> list[tuple]:
    models = linear.Models({c.name(): linear.Sketched(s, _width(fm, c)) for c, s in zip(configs, sketches, strict=True)}, rows, costs).fit()
    scores, out = models.scores(), []
    models.close()
    for c, zeros in zip(configs, _zeros(fm, sketches, configs), strict=True):
        cost, s = max(((x, scores[c.name(), x]) for x in costs), key=lambda p: p[1]["accuracy"])
        out += [(*c.at(dataset), m, float(v)) for m, v in (("best_c", cost), ("accuracy", s["accuracy"]), ("accuracy_sd", s["sd"]), ("balanced_accuracy", s["balanced"]), ("majority", s["majority"]), ("zeros", zeros))]
    return out


def compare(spark: SparkSession, d: str, dataset: str, widths: Iterable[int], methods: Iterable[str] = METHODS, seeds: Iterable[int] = (42,), lams=(None,), costs: tuple[float, ...] = COSTS) -> DataFrame:
    """Accuracy and zeros of each method, width, ball and seed; balls matter to learned methods only."""
    fm, rows = load(spark, d, dataset)
    configs = [Config(m, r, seed, lam) for r in widths for m in methods for lam in (lams if m.startswith("learned") else (None,)) for seed in seeds]
    sketches = _sketches(fm, configs)
    out = _scored(dataset, fm, rows, configs, sketches, costs)
    _done(fm, rows, *sketches)
    return spark.createDataFrame(out, METRICS)


def methods(spark: SparkSession, d: str, dataset: str, r: int, names: Iterable[str] = METHODS, costs: tuple[float, ...] = COSTS, seed: int = 42) -> DataFrame:
    """All measures of each method at one width: accuracy when the sketch is made from all rows and when it is learned on
    the training folds alone, zeros, seconds to embed, milliseconds to project and to classify one fold, the share of the
    energy that is lost, and how far the map of new rows is from the training sketch."""
    fm, rows = load(spark, d, dataset)
    configs, fitted, sketches, out = [Config(m, r, seed) for m in names], [], [], []
    for c in configs:
        _unshared(fm)
        start = time.perf_counter()
        f = fit(fm, c)
        sketches.append(kept(f.training))
        fitted.append(f)
        out.append((*c.at(dataset), "embed_s", time.perf_counter() - start))
    out += _scored(dataset, fm, rows, configs, sketches, costs)
    out += _inductive(dataset, fm, rows, configs, sketches, costs)
    for c, f, s in zip(configs, fitted, sketches, strict=True):
        projection, classification = prediction_ms(fm, rows, f, s, c.r)
        out += [(*c.at(dataset), "projection_ms", projection), (*c.at(dataset), "classification_ms", classification)]
        if c.method == "countsketch":
            out.append((*c.at(dataset), "error_share", A.reconstruction_error(fm, O.feature_map(fm.features(), r, seed)).first()["relative"] or 0.0))
        if f.model is not None:
            out += [(*c.at(dataset), "error_share", A.reconstruction_error(fm, f.model.feature_map).first()["relative"] or 0.0), (*c.at(dataset), "theta_gap", theta_gap(f.apply(fm), s))]
    _done(fm, rows, *sketches, *[x for f in fitted if f.model is not None for x in f.model.held])
    return spark.createDataFrame(out, METRICS)


def _inductive(dataset: str, fm: M.FeatureMatrix, rows: DataFrame, configs: list[Config], sketches: list[DataFrame], costs: tuple[float, ...]) -> list[tuple]:
    """Accuracy of the methods that look at data, learned for each fold on the others; other methods are alike in both."""
    folds = sorted(x.fold for x in rows.select("fold").distinct().collect())

    def one(part: M.FeatureMatrix, c: Config) -> DataFrame:
        f = fit(part, c)
        return _stored(f, f.apply(fm))

    looking = [c for c in configs if c.method in ("hadamard_topr", "learned_full", "learned_minibatch")]
    if not looking:
        return []
    jobs, made = [], []
    if fm.lists is not None:  # a fold's training rows are read from the lists of all, so nothing is stored and folds run together
        parts = {f: fm.outside(f) for f in folds}
        jobs = [(c, f) for f in folds for c in looking]

        def read(c: Config, f: int) -> DataFrame:
            if c.method != "hadamard_topr":
                return one(parts[f], c)
            return kept(O.hadamard_at(fm, fm.d, c.seed, _top(fm, c, f)))

        made, folds = _in_threads(fm, [lambda c=c, f=f: read(c, f) for c, f in jobs]), []
    for f in folds:  # the rows of one fold's training are stored at a time, once for all methods
        inside = rows.where(F.col("fold") != f).select("row_id")
        part = M.FeatureMatrix(kept(fm.entries.join(inside, "row_id", "left_semi")), kept(fm.rows.join(inside, "row_id", "left_semi")), fm.d, shared={})
        made += _in_threads(part, [lambda c=c, part=part: one(part, c) for c in looking])
        jobs += [(c, f) for c in looking]
        _done(part)
    models = linear.Models({f"{c.name()}/{f}": linear.Sketched(s, c.r, (f,)) for (c, f), s in zip(jobs, made, strict=True)}, rows, costs).fit()
    scores = models.scores()
    models.close()
    drop(*made)
    out = []
    for c in configs:
        mine = [[scores[f"{c.name()}/{f}", cost]["accuracy"] for x, f in jobs if x == c] for cost in costs]
        if mine[0]:
            out.append((*c.at(dataset), "accuracy_inductive", max(sum(x) / len(x) for x in mine)))
    return out


def prediction_ms(fm: M.FeatureMatrix, rows: DataFrame, fitted: Fitted, sketch: DataFrame, r: int) -> tuple[float, float]:
    """Milliseconds to sketch the rows of the first fold, and to multiply their sketches by a weight a column."""
    test = rows.where("fold = 0").select("row_id")
    if fm.lists is not None:
        stored = K.cut(fm.lists.where("fold = 0").select("row_id", "idx", "val"))
        part = M.FeatureMatrix.of_lists(stored, fm.d)
    else:
        stored = K.cut(fm.entries.join(test, "row_id", "left_semi"))
        part = M.FeatureMatrix(stored, test, fm.d)
    mine = K.cut(sketch.join(test, "row_id", "left_semi"))
    weights = F.broadcast(fm.entries.sparkSession.range(r).select(F.col("id").cast("int").alias("bucket"), (F.col("id") % 7 - 3).cast("double").alias("w")))  # r rows
    out = A.timed(fitted.apply(part), 1), A.timed(mine.join(weights, "bucket").groupBy("row_id").agg(F.sum(F.col("value") * F.col("w")).alias("score")), 1)
    drop(stored, mine)
    return out


def theta_gap(mapped: DataFrame, training: DataFrame) -> float:
    """Norm of the difference of two sketches over the norm of the second."""
    both = mapped.select("row_id", "bucket", F.col("value").alias("a"), F.lit(0.0).alias("b")).unionByName(training.select("row_id", "bucket", F.lit(0.0).alias("a"), F.col("value").alias("b")))
    both = both.groupBy("row_id", "bucket").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    return both.agg(F.try_divide(F.sqrt(F.sum((F.col("a") - F.col("b")) ** 2)), F.sqrt(F.sum(F.col("b") ** 2)))).first()[0] or 0.0


def embedding_time(spark: SparkSession, d: str, dataset: str, r: int, seed: int = 42) -> DataFrame:
    """(method, seconds) to make the training sketch, count-sketch against both learned ones."""
    fm, rows = load(spark, d, dataset)
    drop(kept(fit(fm, Config("countsketch", r, seed)).training))  # the first job of a kind is not measured
    out = []
    for method in ("countsketch", "learned_full", "learned_minibatch"):
        _unshared(fm)
        start = time.perf_counter()
        f = fit(fm, Config(method, r, seed))
        sketch = kept(f.training)
        out.append((dataset, method, r, time.perf_counter() - start))
        drop(sketch, *(f.model.held if f.model is not None else []))
        free(spark)
    _done(fm, rows)
    return spark.createDataFrame(out, "dataset string, method string, r int, seconds double")


def prediction_cost(fm: M.FeatureMatrix, sketches: dict[str, DataFrame], r: int, d: int) -> DataFrame:
    """(method, projection, classification): operations for all rows, by the cost model."""
    out = None
    for method, sketch in sketches.items():
        one = A.prediction_ops(fm, sketch, method, r, d).agg(F.sum("projection").alias("projection"), F.sum("classification").alias("classification")).select(F.lit(method).alias("method"), "projection", "classification")
        out = one if out is None else out.unionByName(one)
    return out


def stability(spark: SparkSession, d: str, dataset: str, r: int, seeds: Iterable[int] = range(10), methods=("countsketch", "learned_full"), **more) -> DataFrame:
    runs = compare(spark, d, dataset, [r], methods, seeds, **more).where("metric = 'accuracy'")
    return A.stability(runs.select("method", "seed", F.col("value").alias("accuracy")))


def tuning(spark: SparkSession, d: str, dataset: str, r: int, cs=tuple(10.0**k for k in range(-5, 6)), lams=(10.0, 20.0, 30.0, 40.0)) -> DataFrame:
    """(lam, c, accuracy) of the full-batch sketch over both grids, all models in one loop."""
    fm, rows = load(spark, d, dataset)
    configs = [Config("learned_full", r, 42, lam) for lam in lams]
    sketches = _sketches(fm, configs)
    models = linear.Models({c.name(): linear.Sketched(s, r) for c, s in zip(configs, sketches, strict=True)}, rows, cs).fit()
    scores = models.scores()
    models.close()
    _done(fm, rows, *sketches)
    return spark.createDataFrame([(float(c.lam), float(x), scores[c.name(), float(x)]["accuracy"]) for c in configs for x in cs], "lam double, c double, accuracy double")


#: One choice changed at a time; the label names it.
CHANGES: dict[str, dict] = {
    "default": {},
    "signs=identity": {"signs": "identity"},
    "signs=learned": {"signs": "learned"},
    "init=oblivious_groups": {"init": "oblivious_groups"},
    "rate=decay": {"rate": ("decay", 1e-3)},
    "shrink=theta": {"shrink": "theta"},
    "shrink=none": {"shrink": "none"},
    "eps=0": {"eps": 0.0},
    "reseed_empty": {"reseed_empty": True},
    "row_sketch=256": {"row_sketch": 256},
}


def ablations(spark: SparkSession, d: str, dataset: str, r: int, costs: tuple[float, ...] = COSTS) -> DataFrame:
    """The full-batch sketch with one choice changed at a time, and mini-batches of several shares (extension)."""
    fm, rows = load(spark, d, dataset)
    configs = [Config("learned_full", r, 42, None, name, tuple(change.items())) for name, change in CHANGES.items()]
    configs += [Config("learned_minibatch", r, 42, None, f"batch={x}", (("batch_fraction", x),)) for x in (0.1, 0.2, 0.5)]
    sketches = _sketches(fm, configs)
    out = _scored(dataset, fm, rows, configs, sketches, costs)
    _done(fm, rows, *sketches)
    return spark.createDataFrame(out, METRICS)


def scale_out(spark: SparkSession, dirs: Iterable[str], r: int = 16) -> DataFrame:
    """(sf, entries, seconds) of the count-sketch of customers x parts at each size (extension)."""
    out = []
    for d in dirs:
        fm = M.custpart(spark, d)
        out.append((d.rstrip("/").rpartition("/")[2], fm.entries.count(), A.timed(O.countsketch(fm, r, 42), 1) / 1000))
    return spark.createDataFrame(out, "sf string, entries long, seconds double")
