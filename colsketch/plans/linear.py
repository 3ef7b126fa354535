"""Linear models on sketches, all folds, costs, classes and sketches in one loop over the rows.

The rows of all sketches are written once, in lists. A pass sends the weights of all models to the tasks and gets back
each model's loss and gradient, summed by task and then by slots of tasks; the driver keeps the weights and takes steps by
a limited-memory quasi-Newton method with halving. So the number of jobs does not grow with folds x costs x classes.

A model minimises mean loss + |w|^2 / (2 C n) over the rows outside its fold, with a free constant. Losses: squared hinge,
logistic, squared. Two classes need one model, more of them one against the rest; ties go to the class of least value.
Rows without a label are left out; rows without entries have the constant alone.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import drop, kept

#: Cells of a dense block of rows, and sketches up to which width rows become dense.
CELLS, WIDEST = 2_000_000, 8_192
MOST_CLASSES = 1_000
#: Margins of a block of rows by models, whose figures stay near a core.
NEAR = 100_000
MEMORY = 10
LOSSES = ("squared_hinge", "logistic", "squared")


class Sketched(NamedTuple):
    sketch: DataFrame  # row_id, bucket, value
    width: int
    folds: tuple[int, ...] | None = None  # the folds it is to be tested on, all if None


def losses(margin: np.ndarray, y: np.ndarray, loss: str) -> tuple[np.ndarray, np.ndarray]:
    """Loss and its derivative by the margin; y is -1 or 1."""
    z = margin * y
    if loss == "squared_hinge":
        gap = np.maximum(1 - z, 0)
        return gap * gap, -2 * gap * y
    if loss == "logistic":
        return np.logaddexp(0, -z), -y / (1 + np.exp(np.minimum(z, 500)))
    return (margin - y) ** 2, 2 * (margin - y)


class _Block:
    """Rows of one sketch in a batch, times weights and back, dense or in lists by width."""

    def __init__(self, batch: pa.RecordBatch, width: int):
        sizes = np.asarray(batch.column("idx").value_lengths().fill_null(0))
        self.n, self.width = batch.num_rows, width
        self.row, self.idx, self.val = np.repeat(np.arange(self.n), sizes), np.asarray(batch.column("idx").flatten()), np.asarray(batch.column("val").flatten())
        self.fold, self.label = np.asarray(batch.column("fold")), np.asarray(batch.column("label"))
        self.dense = None
        if width <= WIDEST:
            self.dense = np.zeros((self.n, width + 1))
            self.dense[self.row, self.idx] = self.val
            self.dense[:, width] = 1

    def margins(self, w: np.ndarray) -> np.ndarray:
        """Rows x models, for weights models x (width + 1)."""
        if self.dense is not None:
            return self.dense @ w.T
        out = np.tile(w[:, -1], (self.n, 1))
        for k in range(len(w)):
            out[:, k] += np.bincount(self.row, self.val * w[k, self.idx], minlength=self.n)
        return out

    def back(self, slope: np.ndarray) -> np.ndarray:
        if self.dense is not None:
            return slope.T @ self.dense
        out = np.empty((slope.shape[1], self.width + 1))
        for k in range(slope.shape[1]):
            out[k, :-1] = np.bincount(self.idx, self.val * slope[self.row, k], minlength=self.width)
            out[k, -1] = slope[:, k].sum()
        return out

    def squares(self) -> np.ndarray:
        return np.append(np.bincount(self.idx, self.val**2, minlength=self.width), self.n)


def _blocks(batches: Iterator[pa.RecordBatch], widths: list[int], models: list[int] | None = None) -> Iterator[tuple[int, _Block, pa.RecordBatch]]:
    """(sketch, block, its rows); partitions are sorted by sketch."""
    for batch in batches:
        tags = np.asarray(batch.column("tag"))
        cuts = [0, *(np.flatnonzero(tags[1:] != tags[:-1]) + 1).tolist(), len(tags)]
        for a, z in zip(cuts, cuts[1:], strict=False):
            if z > a:
                width = widths[tags[a]]
                step = max(1, CELLS // min(width + 1, WIDEST))
                if models is not None:
                    step = min(step, max(64, NEAR // max(1, models[tags[a]])))
                for x in range(a, z, step):
                    part = batch.slice(x, min(step, z - x))
                    yield int(tags[a]), _Block(part, width), part


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of a batch as bytes, a row for each of its sketches; a pass moves no list from the JVM."""
    for batch in batches:
        tags = np.asarray(batch.column("tag"))
        cuts = [0, *(np.flatnonzero(tags[1:] != tags[:-1]) + 1).tolist(), len(tags)]
        for a, z in zip(cuts, cuts[1:], strict=False):
            if z > a:
                part = batch.slice(a, z - a)
                lists = part.column("idx").value_lengths().fill_null(0), part.column("idx").flatten(), part.column("val").flatten()
                figures = [np.asarray(x).astype(t) for x, t in zip((part.column("row_id"), part.column("fold"), part.column("label"), *lists), _KINDS.values(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(tags[a : a + 1]), *(pa.array([x.tobytes()], pa.binary()) for x in figures)], names=["tag", *_KINDS])


_KINDS = {"row_id": np.int64, "fold": np.int32, "label": np.int32, "sizes": np.int32, "idx": np.int32, "val": np.float64}
PACKED = "tag int, " + ", ".join(f"{x} binary" for x in _KINDS)


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (tag, row_id, fold, label, idx, val) of _packed()."""
    for batch in batches:
        for k in range(batch.num_rows):
            x = {c: np.frombuffer(batch.column(c)[k].as_buffer(), t) for c, t in _KINDS.items()}
            ends = pa.array(np.append(0, np.cumsum(x["sizes"])).astype(np.int32))
            tag = np.full(len(x["row_id"]), batch.column("tag")[k].as_py(), np.int32)
            lists = [pa.ListArray.from_arrays(ends, pa.array(x[c])) for c in ("idx", "val")]
            yield pa.RecordBatch.from_arrays([pa.array(tag), *(pa.array(x[c]) for c in ("row_id", "fold", "label")), *lists], names=["tag", "row_id", "fold", "label", "idx", "val"])


def _summed(table: pa.Table) -> pa.Table:
    data = table.column("data").combine_chunks()
    total = sum(np.frombuffer(x.as_buffer(), np.float64) for x in data)
    return pa.table({"tag": table.column("tag")[:1], "data": pa.array([total.tobytes()], pa.binary())})


class Models:
    """Every model of sketches by name, for rows (row_id, label, fold) and costs cs."""

    def __init__(self, sketches: dict[str, Sketched], rows: DataFrame, cs: Sequence[float], loss: str = "squared_hinge"):
        if loss not in LOSSES:
            raise ValueError(f"unknown loss {loss!r}")
        spark = rows.sparkSession
        rows = rows.where("label is not null").select("row_id", "label", "fold")
        self.loss, self.cs, self.names = loss, tuple(map(float, cs)), list(sketches)
        counts = rows.groupBy("label", "fold").agg(F.count("*").alias("n")).limit(MOST_CLASSES * 1000).collect()
        self.classes = sorted({r.label for r in counts})
        if len(self.classes) > MOST_CLASSES:
            raise ValueError(f"more than {MOST_CLASSES} classes")
        self.folds = sorted({r.fold for r in counts})
        self.majority = 100 * max((sum(r.n for r in counts if r.label == x) for x in self.classes), default=0) / max(1, sum(r.n for r in counts))
        n = sum(r.n for r in counts)
        outside = {f: n - sum(r.n for r in counts if r.fold == f) for f in self.folds}
        self.widths = [sketches[x].width for x in self.names]
        heads = [1] if len(self.classes) <= 2 else list(range(len(self.classes)))
        # The models of each sketch: (fold, cost, positive class), as columns of figures.
        self.plan = []
        for x in self.names:
            mine = [f for f in self.folds if (sketches[x].folds is None or f in sketches[x].folds) and outside[f]]
            self.plan.append(np.array([(f, c, h, outside[f]) for f in mine for c in self.cs for h in heads], float).reshape(-1, 4))
        self.heads = len(heads)
        every = None
        for tag, x in enumerate(self.names):
            one = sketches[x].sketch.select(F.lit(tag).alias("tag"), "row_id", F.col("bucket").cast("int").alias("bucket"), F.col("value").cast("double").alias("value"))
            every = one if every is None else every.unionByName(one)
        lists = every.groupBy("tag", "row_id").agg(F.collect_list("bucket").alias("idx"), F.collect_list("value").alias("val"))
        tags = F.broadcast(spark.createDataFrame([(k,) for k in range(len(self.names))], "tag int"))
        code = F.array_position(F.array(*[F.lit(x) for x in self.classes]), F.col("label")) - 1 if self.classes else F.lit(0)
        whole = rows.select("row_id", "fold", code.cast("int").alias("label")).crossJoin(tags).join(lists, ["tag", "row_id"], "left")  # a row for each row and sketch
        self.data = kept(whole.sortWithinPartitions("tag").mapInArrow(_packed, PACKED))
        self.parts = self.data.rdd.getNumPartitions()
        self.weights = [np.zeros((len(p), w + 1)) for p, w in zip(self.plan, self.widths, strict=True)]

    def _pass(self, kernel) -> list[np.ndarray | None]:
        """kernel(tag, block) gives an array for each block; their sums by sketch. Beyond 32 tasks they are summed in slots first."""
        widths, models = self.widths, [len(p) for p in self.plan]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            total: dict[int, np.ndarray] = {}
            for tag, block, _ in _blocks(_unpacked(batches), widths, models):
                x = kernel(tag, block)
                total[tag] = total[tag] + x if tag in total else x
            slot = TaskContext.get().partitionId() % 32
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([slot] * len(total), pa.int32()), pa.array([x.tobytes() for x in total.values()], pa.binary())], names=["tag", "slot", "data"])

        rows = self.data.mapInArrow(run, "tag int, slot int, data binary")
        if self.parts > 32:
            rows = rows.groupBy("tag", "slot").applyInArrow(_summed, "tag int, data binary")
        out: list[np.ndarray | None] = [None] * len(self.names)
        for r in rows.select("tag", "data").collect():  # figures of the models, from 32 slots at most
            x = np.frombuffer(r.data, np.float64)
            out[r.tag] = x if out[r.tag] is None else out[r.tag] + x
        return out

    def _values(self, weights: list[np.ndarray], live: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
        """(loss, gradient) of each model of each sketch that is live; others' are not to be used."""
        loss = self.loss
        weights, plan = [w[a] for w, a in zip(weights, live, strict=True)], [p[a] for p, a in zip(self.plan, live, strict=True)]
        sent = self.data.sparkSession.sparkContext.broadcast(weights)

        def kernel(tag: int, block: _Block) -> np.ndarray:
            p, w = plan[tag], sent.value[tag]
            if not len(p):
                return np.zeros(0)
            out, slope = block_losses(block, p, w, loss)
            return np.concatenate([out.sum(axis=0), block.back(slope).ravel()])

        found = self._pass(kernel)
        sent.destroy()
        out = []
        for p, w, x, a in zip(plan, weights, found, live, strict=True):
            x = np.zeros(len(p) * (1 + w.shape[1])) if x is None else x
            ridge = w.copy()
            ridge[:, -1] = 0
            by = p[:, 1] * p[:, 3]  # C n
            value = x[: len(p)] / p[:, 3] + (ridge**2).sum(axis=1) / (2 * by)
            whole, slopes = np.zeros(len(a)), np.zeros((len(a), w.shape[1]))
            whole[a], slopes[a] = value, x[len(p) :].reshape(w.shape) / p[:, 3:4] + ridge / by[:, None]
            out.append((whole, slopes))
        return out

    def close(self) -> None:
        """Deletes the stored rows, after the last pass."""
        drop(self.data)

    def fit(self, passes: int = 40, tol: float = 1e-3) -> Models:
        """passes: most passes over the rows; a model is done when its gradient has shrunk to the share tol."""
        squares = self._pass(lambda tag, block: block.squares())
        state = [_Descent(w, p, s) for w, p, s in zip(self.weights, self.plan, squares, strict=True)]
        for _ in range(passes):
            for s, (value, slope) in zip(state, self._values([s.trial for s in state], [~s.done for s in state]), strict=True):
                s.tell(value, slope, tol)
            if all(s.done.all() for s in state):
                break
        self.weights = [s.w for s in state]
        return self

    def _guessed(self, rows: str, columns: str) -> DataFrame:
        """A row for each row, sketch and cost that was tested: rows 'each' or 'sums'."""
        plan, widths, heads, cs = self.plan, self.widths, self.heads, self.cs
        sent = self.data.sparkSession.sparkContext.broadcast(self.weights)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for tag, block, part in _blocks(_unpacked(batches), widths):
                if not len(plan[tag]):
                    continue
                margin = block.margins(sent.value[tag])
                for f in np.unique(block.fold):
                    mine = np.flatnonzero(plan[tag][:, 0] == f)
                    at = np.flatnonzero(block.fold == f)
                    if not len(mine):
                        continue
                    for k, c in enumerate(cs):
                        m = margin[np.ix_(at, mine[k * heads : (k + 1) * heads])]
                        guess = (m[:, 0] > 0).astype(np.int32) if heads == 1 else m.argmax(axis=1).astype(np.int32)
                        n = len(at)
                        fixed = [pa.array(np.full(n, tag, np.int32)), pa.array(np.full(n, c)), pa.array(np.full(n, f, np.int32)), pa.array(block.label[at].astype(np.int32)), pa.array(guess)]
                        if rows == "each":
                            yield pa.RecordBatch.from_arrays([part.column("row_id").take(pa.array(at)), *fixed], names=["row_id", "tag", "c", "fold", "l", "g"])
                        else:
                            both, count = np.unique(block.label[at].astype(np.int64) * 100_000 + guess, return_counts=True)
                            yield pa.RecordBatch.from_arrays([pa.array(count), *(x.slice(0, len(both)) for x in fixed[:3]), pa.array((both // 100_000).astype(np.int32)), pa.array((both % 100_000).astype(np.int32))], names=["n", "tag", "c", "fold", "l", "g"])

        return self.data.mapInArrow(run, f"{columns}, tag int, c double, fold int, l int, g int")

    def _class(self, code: str):
        return F.element_at(F.array(*[F.lit(x) for x in self.classes]), F.col(code) + 1)

    def predictions(self) -> DataFrame:
        """(name, c, row_id, fold, label, predicted) of each row outside the rows that its models were fitted on."""
        name = F.element_at(F.array(*map(F.lit, self.names)), F.col("tag") + 1)
        return self._guessed("each", "row_id long").select(name.alias("name"), "c", "row_id", "fold", self._class("l").cast("int").alias("label"), self._class("g").cast("int").alias("predicted"))

    def scores(self) -> dict[tuple[str, float], dict[str, float]]:
        """By (name, c): accuracy (mean by fold, percent), sd, balanced accuracy, and the share of the largest class."""
        rows = self._guessed("sums", "n long").groupBy("tag", "c", "fold", "l", "g").agg(F.sum("n").alias("n")).collect()  # confusion matrices
        out = {}
        for tag, name in enumerate(self.names):
            for c in self.cs:
                mine = [r for r in rows if r.tag == tag and r.c == c]
                by = [100 * sum(r.n for r in mine if r.fold == f and r.l == r.g) / sum(r.n for r in mine if r.fold == f) for f in sorted({r.fold for r in mine})]
                recall = [sum(r.n for r in mine if r.l == x == r.g) / sum(r.n for r in mine if r.l == x) for x in sorted({r.l for r in mine})]
                out[name, c] = {"accuracy": float(np.mean(by)) if by else 0.0, "sd": float(np.std(by, ddof=1)) if len(by) > 1 else 0.0, "balanced": 100 * float(np.mean(recall)) if recall else 0.0, "majority": self.majority}
        return out


def block_losses(block: _Block, plan: np.ndarray, w: np.ndarray, loss: str) -> tuple[np.ndarray, np.ndarray]:
    """Losses and slopes, rows x models; a model's own fold has none."""
    y = np.where(block.label[:, None] == plan[None, :, 2], 1.0, -1.0)
    out, slope = losses(block.margins(w), y, loss)
    inside = block.fold[:, None] != plan[None, :, 0]
    return out * inside, slope * inside


class _Descent:
    """Limited-memory quasi-Newton steps of all models of a sketch at once; a step that does not descend is halved."""

    def __init__(self, w: np.ndarray, plan: np.ndarray, squares: np.ndarray | None):
        self.w, self.trial, n = w, w.copy(), max(1.0, float(plan[:, 3].max()) if len(plan) else 1.0)
        second = np.zeros(w.shape[1]) if squares is None else squares
        total = second[-1] if second[-1] else 1.0
        by = (plan[:, 1] * plan[:, 3])[:, None] if len(plan) else np.ones((0, 1))
        self.scale = 1 / (2 * second[None, :] / total + 1 / by + 1e-12 * (1 + n))
        self.value = self.slope = self.move = None
        self.size, self.first = np.ones(len(w)), np.ones(len(w))
        self.done = np.zeros(len(w), bool)
        self.past: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def _direction(self) -> np.ndarray:
        q, kept = self.slope.copy(), []
        for s, y, rho in reversed(self.past):
            a = rho * (s * q).sum(axis=1)
            kept.append(a)
            q -= a[:, None] * y
        q *= self.scale
        if self.past:
            s, y, rho = self.past[-1]
            with np.errstate(all="ignore"):
                size = np.where(rho > 0, (s * y).sum(axis=1) / (y * y * self.scale).sum(axis=1), 1.0)
            q *= np.where(np.isfinite(size) & (size > 0), size, 1.0)[:, None]
        for (s, y, rho), a in zip(self.past, reversed(kept), strict=True):
            q += (a - rho * (y * q).sum(axis=1))[:, None] * s
        down = (q * self.slope).sum(axis=1) > 0
        return -np.where(down[:, None], q, self.slope * self.scale)

    def tell(self, value: np.ndarray, slope: np.ndarray, tol: float) -> None:
        """The loss and the gradient at the trial point; sets the next one."""
        if self.value is None:
            good = np.ones(len(self.w), bool)
            self.first = np.sqrt((slope**2 * self.scale).sum(axis=1)) + 1e-300
            self.value, self.slope = value, slope
        else:
            fall = (self.move * self.slope).sum(axis=1) * self.size
            good = (value <= self.value + 1e-4 * fall) & ~self.done
            slope = np.where(self.done[:, None], self.slope, slope)
            s, y = (self.trial - self.w) * good[:, None], (slope - self.slope) * good[:, None]
            sy = (s * y).sum(axis=1)
            with np.errstate(all="ignore"):
                rho = np.where(sy > 1e-12 * (y * y).sum(axis=1), 1 / sy, 0.0)
            self.past = [*self.past, (s, y, np.where(np.isfinite(rho), rho, 0.0))][-MEMORY:]
            self.w = np.where(good[:, None], self.trial, self.w)
            self.value, self.slope = np.where(good, value, self.value), np.where(good[:, None], slope, self.slope)
        left = np.sqrt((self.slope**2 * self.scale).sum(axis=1))
        stuck = ~good & (self.size < 1e-6)
        self.done = self.done | (left <= tol * self.first) | stuck
        new = self._direction()
        self.move = new if self.move is None else np.where(good[:, None], new, self.move)
        self.size = np.where(good, 1.0, self.size / 2)
        self.trial = np.where(self.done[:, None], self.w, self.w + self.size[:, None] * self.move)
