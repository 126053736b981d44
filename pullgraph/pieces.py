"""Edges shuffled as arrays: a row is a piece, the edges of one key among some 2^20 that a task has read."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import ship

#: Edges that a task cuts into pieces at a time.
READ_EDGES = 1 << 20
PIECE = "key long, src binary, dst binary, w binary"


def binaries(values: np.ndarray, start: np.ndarray) -> pa.Array:
    """A binary for each stretch of values; start: where stretches begin, and the end."""
    return pa.Array.from_buffers(pa.binary(), len(start) - 1, [None, pa.py_buffer((start * values.itemsize).astype(np.int32).tobytes()), pa.py_buffer(np.ascontiguousarray(values))])


def read(it, size: int = READ_EDGES) -> Iterator[list[np.ndarray]]:
    """The columns of Arrow batches as arrays of `size` rows or little more."""
    held, rows = [], 0
    for b in it:
        if b.num_rows:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            rows += b.num_rows
        if rows >= size:
            yield [np.concatenate(x) for x in zip(*held, strict=True)]
            held, rows = [], 0
    if rows:
        yield [np.concatenate(x) for x in zip(*held, strict=True)]


def by_key(key: np.ndarray, keys: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows by key, and where each of the keys that are there begins, and the end."""
    order = np.argsort(key.astype(np.int16) if keys <= 1 << 15 else key, kind="stable")
    return order, np.concatenate([[0], np.flatnonzero(np.diff(key[order])) + 1, [len(key)]])


def deal(edges: DataFrame, keys: int, parts: int, extra: DataFrame | None = None) -> DataFrame:
    """edges (key, src, dst, w), keys 0..keys-1, as pieces, in partition key mod parts.  extra: pieces to add."""
    ship(edges.sparkSession)

    def run(it):
        for key, src, dst, w in read(it):
            order, start = by_key(key, keys)
            yield pa.RecordBatch.from_arrays([pa.array(key[order[start[:-1]]], pa.int64()), *(binaries(x[order], start) for x in (src, dst, w))], ["key", "src", "dst", "w"])

    cut = edges.mapInArrow(run, PIECE)
    return (cut if extra is None else cut.unionAll(extra)).repartitionById(parts, F.pmod("key", F.lit(parts)).cast("int"))


def edges_of(it) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(key, src, dst, w) of each key, from pieces that stand together by key."""
    now, held = None, []
    for b in it:
        for k in range(b.num_rows):
            key = b.column(0)[k].as_py()
            if key != now and held:
                yield now, *(np.concatenate(x) for x in zip(*held, strict=True))
                held = []
            now = key
            # Copied, as the batch is given up.
            held.append(tuple(np.frombuffer(b.column(c)[k].as_buffer(), kind).copy() for c, kind in ((1, "<i8"), (2, "<i8"), (3, "<f8"))))
    if held:
        yield now, *(np.concatenate(x) for x in zip(*held, strict=True))
