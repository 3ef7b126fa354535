"""Projection of centres onto an L1 ball, exactly or to within a factor 1 + eps, by one soft threshold for each centre.

Bisection only visits thresholds that are dyadic fractions of the largest magnitude, so one histogram of CELLS cells a
centre replays 12 halvings without another pass; a centre that needs more zooms into the cell that is left, whose values
are then the only ones read. lam > 0 is required; eps = 0 goes to the exact form. An empty centre or table has no
threshold; a centre inside the ball has threshold 0.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CELLS = 4096
#: Halvings after which the upper threshold is taken, as its interval is then below the precision of doubles.
MOST_HALVINGS = 64
_THETA = "bucket int, theta double, l1 double, halvings int, sq double"


def soft(value: Column, theta: Column | float) -> Column:
    return F.signum(value) * F.greatest(F.lit(0.0), F.abs(value) - theta)


def _checked(lam: float) -> None:
    if not lam > 0:
        raise ValueError("the radius must be positive")


def bisect(magnitudes: np.ndarray, lam: float, eps: float, steps: int = MOST_HALVINGS) -> float:
    """The threshold for one vector; 0 where it lies inside the ball. The loop's only state is the interval."""
    _checked(lam)
    a = np.abs(magnitudes)
    if a.sum() <= lam * (1 + eps):
        return 0.0
    low, high = 0.0, float(a.max())
    for _ in range(steps):
        theta = (low + high) / 2
        left = np.maximum(a - theta, 0).sum()
        if lam <= left <= lam * (1 + eps):
            return theta
        low, high = (theta, high) if left > lam else (low, theta)
    return high


def exact_threshold(magnitudes: np.ndarray, lam: float) -> float:
    a = np.sort(np.abs(magnitudes))[::-1]
    if a.sum() <= lam:
        return 0.0
    spare = (np.cumsum(a) - lam) / np.arange(1, len(a) + 1)
    return float(spare[np.flatnonzero(a > spare)[-1]])


def stats(centres: DataFrame) -> DataFrame:
    v = F.col("value")
    return centres.groupBy("bucket").agg(F.sum(F.abs(v)).alias("l1"), F.max(F.abs(v)).alias("linf"), F.sum(v * v).alias("sq"))


def figures(centres) -> list:
    """The rows of stats(), r of them. Here and in solved(), centres may be an object with figures() and cells() of its own."""
    return stats(centres).collect() if isinstance(centres, DataFrame) else centres.figures()


class _Search(NamedTuple):
    """What is known of a centre: its threshold lies in [low, high]; n, total and sq are of the magnitudes from high on."""

    bucket: int
    low: float
    high: float
    n: int
    total: float
    sq: float
    halvings: int
    l1: float


def _histogram(centres: DataFrame, search: list[_Search]) -> DataFrame:
    """(bucket, cell, n, total, sq) of the magnitudes between the bounds of each search."""
    if not isinstance(centres, DataFrame):
        return centres.cells(search)
    known = centres.sparkSession.createDataFrame([(s.bucket, s.low, s.high, s.n == 0) for s in search], "bucket int, low double, high double, top boolean")
    a = centres.join(F.broadcast(known), "bucket").select("bucket", "low", "high", "top", F.abs("value").alias("a"))  # a row for each centre
    a = a.where((F.col("a") >= F.col("low")) & ((F.col("a") < F.col("high")) | F.col("top")))
    cell = F.least(F.floor((F.col("a") - F.col("low")) / (F.col("high") - F.col("low")) * CELLS), F.lit(CELLS - 1)).cast("int")
    return a.groupBy("bucket", cell.alias("cell")).agg(F.count("*").alias("n"), F.sum("a").alias("total"), F.sum(F.col("a") * F.col("a")).alias("sq"))


def _suffixes(cells: np.ndarray, figures: tuple[np.ndarray, ...], s: _Search) -> tuple[np.ndarray, ...]:
    """At each edge between cells, the number, the sum and the sum of squares of the magnitudes from there on."""
    out = []
    for column, beyond in zip(figures, (s.n, s.total, s.sq), strict=True):
        x = np.zeros(CELLS + 1)
        x[cells] = column
        x[CELLS] = beyond
        out.append(x[::-1].cumsum()[::-1])
    return tuple(out)


_FOUND = pa.schema([("bucket", pa.int32()), ("low", pa.float64()), ("high", pa.float64()), ("n", pa.int64()), ("total", pa.float64()), ("sq", pa.float64()), ("halvings", pa.int32()), ("l1", pa.float64()), ("theta", pa.float64())])
#: Centres whose histograms, CELLS rows each at most, are replayed in one task.
TOGETHER = 256


def _narrowed(centres: DataFrame, search: list[_Search], replay) -> list[tuple]:
    """replay(suffixes, search) for each centre, where its cells are; the figures of r rows reach the driver."""
    by = {s.bucket: s for s in search}

    def run(table: pa.Table) -> pa.Table:
        bucket = np.asarray(table.column("bucket"))
        order = np.argsort(bucket, kind="stable")
        cell, *figures = (np.asarray(table.column(c))[order] for c in ("cell", "n", "total", "sq"))
        bucket, out = bucket[order], []
        for b in np.unique(bucket).tolist():
            x, y = np.searchsorted(bucket, [b, b + 1])
            out.append(replay(_suffixes(cell[x:y], tuple(f[x:y] for f in figures), by[b]), by[b]))
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out, strict=True), _FOUND.types, strict=True)], schema=_FOUND)

    # A group has TOGETHER x CELLS rows at most, whatever the number of rows of the matrix.
    cells = _histogram(centres, search)
    if isinstance(cells, pa.Table):
        found = [tuple(r.values()) for r in run(cells).to_pylist()] if len(cells) else []
    else:
        rows = cells.groupBy(F.floor(F.col("bucket") / TOGETHER)).applyInArrow(run, "bucket int, low double, high double, n long, total double, sq double, halvings int, l1 double, theta double")
        found = [tuple(r) for r in rows.collect()]
    # Between the bounds of the others no magnitude lies: what is left is linear there.
    nothing, met = np.zeros(0, int), {r[0] for r in found}
    return found + [replay(_suffixes(nothing, (nothing,) * 3, s), s) for b, s in by.items() if b not in met]


def _starts(centres: DataFrame, most: float) -> tuple[list, list[_Search]]:
    """(rows inside the ball, searches of the others)."""
    found = [r for r in figures(centres) if r.bucket is not None]  # r rows
    inside = [(r.bucket, 0.0, r.l1, 0, r.sq) for r in found if r.l1 <= most]
    return inside, [_Search(r.bucket, 0.0, r.linf, 0, 0.0, 0.0, 0, r.l1) for r in found if r.l1 > most]


def solved(centres: DataFrame, lam: float, eps: float = 0.1) -> list[tuple[int, float, float, int, float]]:
    """(bucket, theta, l1, halvings, sq) of each centre, sq being the squared norm after the projection; r rows on the driver."""
    _checked(lam)
    if eps == 0:
        return [tuple(r) for r in _exact(centres if isinstance(centres, DataFrame) else centres.raw(), lam).collect()]
    done, search = _starts(centres, lam * (1 + eps))

    def replay(sums: tuple[np.ndarray, ...], s: _Search) -> tuple:
        n, total, sq = sums
        width = (s.high - s.low) / CELLS
        low, high, k = 0, CELLS, s.halvings
        while high - low > 1 and k < MOST_HALVINGS:
            k += 1
            at = (low + high) // 2
            theta = s.low + at * width
            left = total[at] - theta * n[at]
            if lam <= left <= lam * (1 + eps):
                return s.bucket, theta, theta, 0, 0.0, sq[at] - 2 * theta * total[at] + theta * theta * n[at], k, s.l1, theta
            low, high = (at, high) if left > lam else (low, at)
        top = s.low + high * width
        if k >= MOST_HALVINGS or s.low + low * width >= top:
            return s.bucket, top, top, 0, 0.0, sq[high] - 2 * top * total[high] + top * top * n[high], k, s.l1, top
        return s.bucket, s.low + low * width, top, int(n[high]), total[high], sq[high], k, s.l1, None

    while search:
        rows = _narrowed(centres, search, replay)
        done += [(r[0], float(r[8]), r[7], int(r[6]), max(0.0, float(r[5]))) for r in rows if r[8] is not None]
        search = [_Search(*r[:8]) for r in rows if r[8] is None]
    return done


def _exact(centres: DataFrame, lam: float) -> DataFrame:
    """As solved(): one histogram brackets the threshold, and only the distinct magnitudes of that cell are sorted."""
    spark = centres.sparkSession
    done, search = _starts(centres, lam)
    inside = spark.createDataFrame(done, _THETA)
    if not search:
        return inside

    def replay(sums: tuple[np.ndarray, ...], s: _Search) -> tuple:
        n, total, sq = sums
        edges = s.high * np.arange(CELLS + 1) / CELLS
        at = int(np.flatnonzero(total - edges * n > lam)[-1])  # the last edge at which too much is left
        return s.bucket, edges[at], edges[at + 1], int(n[at + 1]), total[at + 1], sq[at + 1], 0, s.l1, None

    rows = [(r[0], *map(float, r[1:3]), int(r[3]), *map(float, r[4:6]), 0, r[7]) for r in _narrowed(centres, search, replay)]
    cell = F.broadcast(spark.createDataFrame([(*r[:6], r[7]) for r in rows], "bucket int, low double, high double, n0 long, t0 double, q0 double, l1 double"))
    a = centres.join(cell, "bucket").select("bucket", "low", "high", "n0", "t0", "q0", "l1", F.abs("value").alias("a"))
    # The upper edge counts as a magnitude without occurrences, as the threshold may lie above all values of the cell.
    own = a.where((F.col("a") >= F.col("low")) & ((F.col("a") < F.col("high")) | (F.col("n0") == 0))).groupBy("bucket", "a").agg(F.count("*").alias("n")).withColumn("edge", F.lit(False))
    own = own.unionByName(cell.where("n0 > 0").select("bucket", F.col("high").alias("a"), F.lit(0).cast("long").alias("n"), F.lit(True).alias("edge"))).join(cell, "bucket")
    run = "over (partition by bucket order by a desc rows unbounded preceding)"
    cum = own.selectExpr("bucket", "a", "edge", "l1", f"n0 + sum(n) {run} as k", f"t0 + sum(a * n) {run} as cum", f"q0 + sum(a * a * n) {run} as q").withColumn("theta", (F.col("cum") - lam) / F.col("k"))
    # At the edge what is left is at most lam, so it always bounds the threshold from above, if only by being it.
    last = cum.where("a >= theta or edge").groupBy("bucket").agg(F.max_by(F.struct("theta", "l1", "k", "cum", "q"), "k").alias("b")).select("bucket", "b.*")
    theta = F.greatest("theta", F.lit(0.0))
    return inside.unionByName(last.select("bucket", theta.alias("theta"), "l1", F.lit(0).alias("halvings"), (F.col("q") - 2 * theta * F.col("cum") + theta * theta * F.col("k")).alias("sq")))


def exact_thresholds(centres: DataFrame, lam: float) -> DataFrame:
    """(bucket, theta) by sorted cumulative sums within the bracketing cell."""
    _checked(lam)
    return _exact(centres, lam).select("bucket", "theta")


def thresholds(centres: DataFrame, lam: float, eps: float = 0.1) -> DataFrame:
    """(bucket, theta, l1, halvings), a row for each centre."""
    return centres.sparkSession.createDataFrame(solved(centres, lam, eps), _THETA).drop("sq")


def project(centres: DataFrame, lam: float, eps: float = 0.1) -> DataFrame:
    return shrunk(centres, thresholds(centres, lam, eps))


def shrunk(centres: DataFrame, theta: DataFrame) -> DataFrame:
    t = F.broadcast(theta.select("bucket", "theta"))  # one row for each centre
    return centres.join(t, "bucket", "left").select("row_id", "bucket", soft(F.col("value"), F.coalesce("theta", F.lit(0.0))).alias("value")).where("value != 0")


def residual(centres: DataFrame, theta: DataFrame) -> DataFrame:
    t = centres.join(F.broadcast(theta.select("bucket", "theta")), "bucket")
    return t.groupBy("bucket").agg(F.sum(F.greatest(F.lit(0.0), F.abs("value") - F.col("theta"))).alias("left"))


def project_array(values: list[float], lam: float, eps: float) -> list[float]:
    """One vector held in a cell."""
    v = np.asarray(values, float)
    t = exact_threshold(v, lam) if eps == 0 else bisect(v, lam, eps)
    return (np.sign(v) * np.maximum(np.abs(v) - t, 0)).tolist()
