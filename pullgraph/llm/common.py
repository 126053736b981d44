"""Shared pieces of the text operators: table access, Arrow plumbing, and identities of words and runs of words."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship

U64 = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_INVERSE = pow(_BASE, -1, 1 << 64)
#: Bytes of the six ASCII white space characters that end a word: \x20 and \x09-\x0D.
SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: What a side may hold that is broadcast, counted first: rows, and elements of its lists (48 bytes each at most).  Beyond
#: either, both sides are shuffled.
SMALL_ROWS, SMALL_ELEMENTS = 100_000, 1_000_000


#: Functions whose caches a worker holds for tasks to come, by module.
_HELD: dict[str, list] = {}


def held_by(module: str) -> Callable:
    """For a function with a cache: what it holds is given up when a worker runs another module's task."""

    def register(fn):
        _HELD.setdefault(module, []).append(fn)
        return fn

    return register


def _give_up(but: str) -> None:
    for module, fns in _HELD.items():
        if module != but:
            for fn in fns:
                fn.cache_clear()


def _give_back() -> None:
    """Return freed memory to the system: workers are reused, and what one task freed would count for the next."""
    POWERS.drop()
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def arrow_map(df: DataFrame, fn: Callable, schema: str) -> DataFrame:
    """mapInArrow with the package shipped to the workers first, and memory given back after each task; what the tasks of
    other modules left in the worker is given up before."""
    ship(df.sparkSession)
    module = fn.__module__

    def run(it):
        _give_up(module)
        try:
            yield from fn(it)
        finally:
            _give_back()

    return df.mapInArrow(run, schema)


def join_texts(docs: DataFrame, asked: DataFrame, lists: str) -> DataFrame:
    """docs with the columns of asked (one row per doc_id, with one column of lists): few rows with few list elements, both
    counted, go to the texts; otherwise the two meet in a shuffle."""
    rows, elements = asked.agg(F.count("*"), F.coalesce(F.sum(F.size(lists)), F.lit(0))).first()
    few = rows <= SMALL_ROWS and elements <= SMALL_ELEMENTS
    return docs.join(asked.hint("broadcast" if few else "shuffle_hash"), "doc_id")


def documents_of(df: DataFrame, *more: str | Column) -> DataFrame:
    """doc_id as long, text as string, and the named extra columns; whatever else the input has is dropped."""
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *more)


def unused(names: list[str], base: str) -> str:
    """A column name that none of names is, in any case of letters."""
    taken = {n.lower() for n in names}
    while base.lower() in taken:
        base += "_"
    return base


def batches(it: Iterator[pa.RecordBatch], most_bytes: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of the incoming batches holding about most_bytes of text at most (one row at least)."""
    for b in it:
        n, at = b.num_rows, 0
        if n == 0:
            continue
        per = max(1, int(n * most_bytes / max(1, b.nbytes)))
        while at < n:
            yield b.slice(at, per)
            at += per


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads each 64-bit value over all bits."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


class Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand and dropped when a task ends."""

    def __init__(self) -> None:
        self.drop()

    def drop(self) -> None:
        self.up = np.ones(1, U64)
        self.down = np.ones(1, U64)

    def need(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up), 1 << 16)
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.concatenate([np.ones(1, U64), np.full(size - 1, _BASE & _MASK, U64)]), dtype=U64)
                self.down = np.cumprod(np.concatenate([np.ones(1, U64), np.full(size - 1, _INVERSE, U64)]), dtype=U64)
        return self.up[:n], self.down[:n]


POWERS = Powers()


def prefix_hash(values: np.ndarray) -> np.ndarray:
    """P with P[i] = sum of values[j] * base**j for j < i, so that any slice has a key in constant time.

    Equal slices have equal keys, but patterns exist for which different ones have too: for finding candidates alone,
    never for telling things apart.
    """
    up, _ = POWERS.need(len(values) + 1)
    out = np.zeros(len(values) + 1, U64)
    with np.errstate(over="ignore"):
        np.cumsum(values.astype(U64) * up[: len(values)], out=out[1:], dtype=U64)
    return out


def slice_hash(prefix: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """Key of values[start:stop], the same wherever the slice stands."""
    _, down = POWERS.need(len(prefix))
    with np.errstate(over="ignore"):
        return mix((prefix[stop] - prefix[start]) * down[start] + (stop - start).astype(U64) * U64(0xD6E8FEB86659FD93))


#: Odd factors and a start value for each of the two lanes of a slice's identity.
_LANES = ((0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x27D4EB2F165667C5), (0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB))
_EIGHTS = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [(1 << 64) - 1], U64)


def slice_identity(data: np.ndarray, start: np.ndarray, stop: np.ndarray, lane: int = 0) -> np.ndarray:
    """64 bits for each byte slice, from eight bytes at a time with a non-linear step between them.

    Slices of eight bytes or less never share a value unless their lengths differ; longer ones do so by chance alone, once
    in 2**64 pairs.  The two lanes are independent of each other and together make 128 bits.
    """
    a, b, seed = (U64(x) for x in _LANES[lane])
    n = stop - start
    wide = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray((len(data) + 1,), "<u8", wide, strides=(1,))
    with np.errstate(over="ignore"):
        out = mix(n.astype(U64) * a + seed)
        todo, at = np.flatnonzero(n > 0), 0
        while len(todo):
            x = eight[start[todo] + at] & _EIGHTS[np.minimum(n[todo] - at, 8)]
            out[todo] = mix((out[todo] ^ (x * b)) + a)
            at += 8
            todo = todo[n[todo] > at]
    return out


def numbered(data: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, pa.Array]:
    """(number of each slice among the distinct ones, those as bytes): told apart by their bytes.  Slices ascend, do not
    overlap and are not empty."""
    edge = np.zeros(len(data) + 1, np.int8)
    edge[start] = 1
    edge[stop] -= 1
    offsets = np.concatenate([[0], np.cumsum(stop - start)]).astype(np.int64)
    body = data[np.cumsum(edge[:-1], dtype=np.int8) > 0] if len(data) else data
    found = pa.Array.from_buffers(pa.large_binary(), len(start), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(body))]).dictionary_encode()
    return found.indices.to_numpy(zero_copy_only=False).astype(np.int64), found.dictionary


class Runs:
    """Identities of runs of neighbouring values, 64 bits each, whatever their length.

    Level k has one value for the 2**k values from each place, made from two of the level below by a step that is not
    linear; a run of any length is two overlapping runs of a level and its length.  So equal runs have equal identities
    wherever they stand, and no pattern of repeated values makes different ones collide.
    """

    def __init__(self, values: np.ndarray) -> None:
        self.levels = [values.astype(U64)]

    @staticmethod
    def _join(x: np.ndarray, y: np.ndarray, size: np.ndarray | int) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix(mix(x + U64(0x9E3779B97F4A7C15) * np.asarray(size).astype(U64)) * U64(0xC2B2AE3D27D4EB4F) + (y ^ (y >> U64(29))))

    def _level(self, k: int) -> np.ndarray:
        while len(self.levels) <= k:
            low, half = self.levels[-1], 1 << (len(self.levels) - 1)
            self.levels.append(self._join(low[: max(len(low) - half, 0)], low[half:], 2 * half))
        return self.levels[k]

    def of(self, start: np.ndarray, size: np.ndarray | int) -> np.ndarray:
        """Identities of the runs of size values from each start, which must lie inside."""
        size = np.broadcast_to(np.asarray(size, np.int64), start.shape)
        out = np.zeros(len(start), U64)
        if not len(start):
            return out
        level = np.frexp(size.astype(float))[1] - 1
        for k in np.unique(level).tolist():
            pick = np.flatnonzero(level == k)
            row, s, n = self._level(k), start[pick], size[pick]
            out[pick] = self._join(row[s], row[s + n - (1 << k)], n)
        return out


class Words:
    """Words `[^\\x20\\x09-\\x0D]+` of a batch of texts, laid end to end.

    data: the UTF-8 bytes of all texts, each followed by one line feed; start/stop: byte bounds of each word; first:
    index of each text's first word, with the total at the end; base: byte offset of each text, likewise; hash and hash2:
    the two lanes of each word's identity.
    """

    def __init__(self, texts: list[str | None], lower_ascii: bool = False) -> None:
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        buf = b"\n".join(raw) + b"\n" if raw else b""
        data = np.frombuffer(buf, np.uint8)
        if lower_ascii:
            data = np.where((data >= 65) & (data <= 90), data + np.uint8(32), data)
        self.data = data
        self.base = np.concatenate([[0], np.cumsum([len(r) + 1 for r in raw])]).astype(np.int64)
        inside = ~SPACE[data]
        edge = np.flatnonzero(np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8)))
        self.start, self.stop = edge[0::2], edge[1::2]
        self.first = np.searchsorted(self.start, self.base)
        self.n = np.diff(self.first)

    @cached_property
    def hash(self) -> np.ndarray:
        return slice_identity(self.data, self.start, self.stop, 0)

    @cached_property
    def hash2(self) -> np.ndarray:
        return slice_identity(self.data, self.start, self.stop, 1)

    @cached_property
    def number(self) -> np.ndarray:
        """Number of each word among the distinct words of the batch, by its bytes."""
        return numbered(self.data, self.start, self.stop)[0]
