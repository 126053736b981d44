"""Tile cache: what is admitted under a capacity, and in which encoding tiles are kept."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from .exchange import compress, decompress

#: Encodings by mode number, and the compression ratio each is expected to reach.
MODES = {1: "none", 2: "snappy", 3: "zlib1", 4: "zlib3"}
GAMMAS = (1.0, 2.0, 4.0, 5.0)
ENCODED = "tile_id long, v_lo long, v_hi long, n_edges long, codec string, raw_bytes long, payload binary"


def choose_mode(total_bytes: float, capacity: float, gammas: tuple[float, ...] = GAMMAS, fallback: int = 4) -> int:
    """The cheapest encoding to decode whose expected total fits; the fallback if none does."""
    return next((i for i, g in enumerate(gammas, 1) if total_bytes / g <= capacity), fallback)


def tile_bytes(row: np.ndarray, col: np.ndarray, val: np.ndarray | None) -> bytes:
    return row.astype("<i8").tobytes() + col.astype("<i8").tobytes() + (val.astype("<f8").tobytes() if val is not None else b"")


def tile_arrays(raw: bytes, n_targets: int, n_edges: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    row = np.frombuffer(raw, "<i8", n_targets + 1)
    col = np.frombuffer(raw, "<i8", n_edges, 8 * (n_targets + 1))
    rest = 8 * (n_targets + 1 + n_edges)
    return row, col, np.frombuffer(raw, "<f8", n_edges, rest) if len(raw) > rest else None


def encode_tiles(tiles: DataFrame, codec: str) -> DataFrame:
    ship(tiles.sparkSession)

    def run(it):
        for b in it:
            out = []
            for k in range(b.num_rows):
                tile_id, lo, hi, n = (b.column(i)[k].as_py() for i in range(4))
                row, col = (b.column(i)[k].values.to_numpy(zero_copy_only=False) for i in (4, 5))
                val = b.column(6)[k].values
                raw = tile_bytes(row, col, None if val is None else val.to_numpy(zero_copy_only=False))
                out.append((tile_id, lo, hi, n, codec, len(raw), compress(raw, codec)))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.binary())
            cols = list(zip(*out, strict=True)) if out else [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["tile_id", "v_lo", "v_hi", "n_edges", "codec", "raw_bytes", "payload"])

    return tiles.select("tile_id", "v_lo", "v_hi", "n_edges", "row", "col", "val").mapInArrow(run, ENCODED)


def decode_payload(payload: bytes, codec: str, n_targets: int, n_edges: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    return tile_arrays(decompress(payload, codec), n_targets, n_edges)


def plan_cache(sizes: DataFrame, capacity: int, servers: int) -> DataFrame:
    """sizes (tile_id, bytes) with server_id, fill and cached.

    Tiles are met in order of their number, and each server admits them until one does not fit; then its cache is full,
    and nothing is given up again.
    """
    w = Window.partitionBy("server_id").orderBy("tile_id").rowsBetween(Window.unboundedPreceding, 0)
    out = sizes.withColumn("server_id", F.pmod("tile_id", F.lit(servers)).cast("int")).withColumn("fill", F.sum("bytes").over(w).cast("long"))
    return out.withColumn("cached", F.col("fill") <= F.lit(capacity))
