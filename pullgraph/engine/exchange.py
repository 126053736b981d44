"""Encoding of a tile's updates: dense, sparse or whichever suits, with an optional codec."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa

#: Share of unchanged vertices above which a message is sparse.
SPARSITY = 0.8
CODECS = ("none", "snappy", "zlib1", "zlib3")


def dense_bytes(n: int) -> int:
    return 8 * n + -(-n // 8)


def sparse_bytes(k: int) -> int:
    return 12 * k


def encode_dense(values: np.ndarray, flags: np.ndarray) -> bytes:
    """All values of a tile and one bit per value that says whether it changed."""
    return np.packbits(flags).tobytes() + np.where(flags, values, 0.0).astype("<f8").tobytes()


def encode_sparse(values: np.ndarray, flags: np.ndarray) -> bytes:
    """Offsets within the tile and values of what changed."""
    at = np.flatnonzero(flags)
    return at.astype("<u4").tobytes() + values[at].astype("<f8").tobytes()


def choose(n: int, k: int, threshold: float | str = SPARSITY) -> str:
    """dense or sparse for k changed of n: sparse if the unchanged share is above the threshold; `bytes` takes the shorter."""
    if threshold == "bytes":
        return "sparse" if sparse_bytes(k) < dense_bytes(n) else "dense"
    return "sparse" if n and (n - k) / n > threshold else "dense"


def encode(values: np.ndarray, flags: np.ndarray, mode: str = "hybrid", threshold: float | str = SPARSITY) -> tuple[str, bytes]:
    if mode == "hybrid":
        mode = choose(len(values), int(flags.sum()), threshold)
    return mode, (encode_dense if mode == "dense" else encode_sparse)(values, flags)


def decode(payload: bytes, mode: str, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, values) of what changed in a tile of n vertices."""
    if mode == "dense":
        flag_bytes = -(-n // 8)
        at = np.flatnonzero(np.unpackbits(np.frombuffer(payload, np.uint8, flag_bytes), count=n))
        return at, np.frombuffer(payload, "<f8", n, flag_bytes)[at]
    k = len(payload) // 12
    return np.frombuffer(payload, "<u4", k).astype(np.int64), np.frombuffer(payload, "<f8", k, 4 * k)


def compress(payload: bytes, codec: str = "snappy") -> bytes:
    if codec == "none":
        return payload
    if codec == "snappy":
        return len(payload).to_bytes(8, "little") + pa.compress(payload, codec="snappy", asbytes=True)
    if codec in ("zlib1", "zlib3"):
        return zlib.compress(payload, int(codec[-1]))
    raise ValueError(f"unknown codec {codec}")


def decompress(payload: bytes, codec: str) -> bytes:
    if codec == "none":
        return payload
    if codec == "snappy":
        return pa.decompress(payload[8:], decompressed_size=int.from_bytes(payload[:8], "little"), codec="snappy", asbytes=True)
    return zlib.decompress(payload)
