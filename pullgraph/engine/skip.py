"""Which tiles have a source that changed: by Bloom filter, exactly, or all."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship

MODES = ("none", "exact", "bloom")


def _mix(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64)
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def bloom_size(n: int, fpp: float) -> tuple[int, int]:
    """(bits, hashes) for n members at a false positive rate of fpp; whole bytes."""
    if n == 0:
        return 0, 0
    bits = math.ceil(-n * math.log(fpp) / math.log(2) ** 2)
    return -(-bits // 8) * 8, max(1, round(bits / n * math.log(2)))


def _places(ids: np.ndarray, bits: int, hashes: int) -> np.ndarray:
    """Bit numbers (id x hash) by double hashing."""
    one = _mix(ids)
    two = _mix(one + np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
    with np.errstate(over="ignore"):
        return ((one[:, None] + two[:, None] * np.arange(hashes, dtype=np.uint64)) % np.uint64(bits)).astype(np.int64)


def tile_filters(tiles: DataFrame, fpp: float = 0.01) -> DataFrame:
    """(tile_id, m_bits, k_hash, bits): one filter per tile over its distinct sources."""
    ship(tiles.sparkSession)

    def run(it):
        for b in it:
            rows = []
            for tile_id, col in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = np.unique(col.values.to_numpy(zero_copy_only=False)) if col.is_valid and len(col.values) else np.zeros(0, np.int64)
                m, k = bloom_size(len(ids), fpp)
                bits = np.zeros(m, np.uint8)
                if m:
                    bits[_places(ids, m, k).ravel()] = 1
                rows.append((tile_id, m, k, np.packbits(bits).tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)], ["tile_id", "m_bits", "k_hash", "bits"]) if rows else pa.RecordBatch.from_pylist([], pa.schema([("tile_id", pa.int64()), ("m_bits", pa.int64()), ("k_hash", pa.int32()), ("bits", pa.binary())]))

    return tiles.select("tile_id", "col").mapInArrow(run, "tile_id long, m_bits long, k_hash int, bits binary")


def may_hold(bits: bytes, m: int, k: int, ids: np.ndarray, chunk: int = 4096) -> bool:
    """True if the filter answers yes for any id."""
    if m == 0:
        return False
    have = np.unpackbits(np.frombuffer(bits, np.uint8))
    return any(have[_places(ids[i : i + chunk], m, k)].all(axis=1).any() for i in range(0, len(ids), chunk))


def active_by_bloom(filters: DataFrame, changed_ids: np.ndarray) -> DataFrame:
    """(tile_id): tiles whose filter may hold a changed id.  The ids travel with the task, as full replication has them."""
    ship(filters.sparkSession)
    ids = filters.sparkSession.sparkContext.broadcast(changed_ids)

    def run(it):
        for b in it:
            keep = [may_hold(x["bits"], x["m_bits"], x["k_hash"], ids.value) for x in b.to_pylist()]
            yield b.select(["tile_id"]).filter(pa.array(keep, pa.bool_()))

    return filters.mapInArrow(run, "tile_id long")


def active_exact(tile_sources: DataFrame, changed: DataFrame) -> DataFrame:
    """(tile_id): tiles with a source among changed (id), by a semi join."""
    return tile_sources.join(changed.select(F.col("id").alias("src")), "src", "left_semi").select("tile_id").distinct()
