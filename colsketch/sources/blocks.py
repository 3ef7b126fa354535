"""Rows of a matrix in blocks of byte arrays, so that a pass moves a few arrays between the JVM and Python and not a figure an entry.

A block has the entries of up to ROWS rows in the order of features, and each feature once with the number of its entries.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

#: kinds are the types of row and val, the smallest that hold a block's figures.
PACKED = "kinds string, ids binary, fold binary, met binary, many binary, row binary, val binary"
#: Rows and, about, entries of a block at most.
ROWS, ENTRIES = 8_192, 3_000_000
#: Rows of a batch that are taken at a time.
SOME = 1_024


class Block(NamedTuple):
    ids: np.ndarray  # by row
    row: np.ndarray  # of each entry, below len(ids)
    f: np.ndarray  # ascending
    v: np.ndarray

    def only(self, rows: np.ndarray) -> Block:
        """The rows that a mask has."""
        keep = rows[self.row]
        return Block(self.ids[rows], (np.cumsum(rows) - 1)[self.row[keep]], self.f[keep], self.v[keep])


def _least(x: np.ndarray) -> np.ndarray:
    """Whole numbers in the fewest bytes."""
    if x.dtype.kind == "f" or not len(x) or x.min() < 0:
        return x
    return x.astype(np.min_scalar_type(x.max()))


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """PACKED blocks of rows (row_id, fold, idx, val)."""
    held, rows, entries = [], 0, 0

    def packed() -> pa.RecordBatch:
        ids, fold, sizes, f, v = (np.concatenate(x) for x in zip(*held, strict=True))
        order = np.argsort(f, kind="stable")
        f, row, v = f[order], _least(np.repeat(np.arange(len(sizes)), sizes)[order]), _least(v[order])
        edge = np.flatnonzero(np.append(True, f[1:] != f[:-1])) if len(f) else np.zeros(0, int)
        many = np.diff(np.append(edge, len(f)))
        figures = ids.astype(np.int64), fold.astype(np.int32), f[edge].astype(np.int64), many.astype(np.int32), row, v
        names = [x.split()[0] for x in PACKED.split(", ")]
        return pa.RecordBatch.from_arrays([pa.array([f"{row.dtype.str} {v.dtype.str}"]), *(pa.array([x.tobytes()], pa.binary()) for x in figures)], names=names)

    for batch in batches:
        for a in range(0, batch.num_rows, SOME):
            part = batch.slice(a, SOME)
            one = [np.asarray(x) for x in (part.column("row_id"), part.column("fold"), part.column("idx").value_lengths(), part.column("idx").flatten(), part.column("val").flatten())]
            if held and (rows + len(one[0]) > ROWS or entries + len(one[3]) > ENTRIES):
                yield packed()
                held, rows, entries = [], 0, 0
            held.append(one)
            rows, entries = rows + len(one[0]), entries + len(one[3])
    if held:
        yield packed()


def unpacked(batches: Iterator[pa.RecordBatch], without: int | None = None) -> Iterator[Block]:
    """The blocks of PACKED rows, but for the rows of a fold."""
    for batch in batches:
        for k in range(batch.num_rows):
            kinds, *found = (batch.column(c)[k] for c in batch.schema.names)
            types = [np.int64, np.int32, np.int64, np.int32, *kinds.as_py().split()]
            ids, fold, met, many, row, val = (np.frombuffer(x.as_buffer(), t) for x, t in zip(found, types, strict=True))
            block = Block(ids, row.astype(np.int64), np.repeat(met, many), val.astype(np.float64))
            yield block if without is None else block.only(fold != without)
