"""Vertex programs: what a vertex gathers from its in-edges and how it applies the result."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class VertexProgram:
    """A program in two forms: column expressions for the relational path, NumPy functions for the tile kernel.

    init(id, n): start value.  message(value, d_out, w): what an in-edge brings.  gather: sum, min or max.
    apply(id, old, accum, n): new value.  components: state columns besides value that messages need.
    apply_without_input: apply must run once for vertices whose inputs never change (its first superstep loads all).
    idempotent: gathering a message twice changes nothing, so only changed sources need to send.
    """

    name: str
    gather: str
    init: Callable[[Column, int], Column]
    message: Callable[[Column, Column, Column], Column]
    apply: Callable[[Column, Column, Column, int], Column]
    np_init: Callable[[int], np.ndarray]
    np_message: Callable[[np.ndarray, np.ndarray | None, np.ndarray | None], np.ndarray]
    np_apply: Callable[[np.ndarray, np.ndarray, np.ndarray, int], np.ndarray]
    components: tuple[str, ...] = ()
    apply_without_input: bool = True
    start: int | None = None
    #: The value of vertices without out-edges is shared among all vertices (tile kernel with full replication only).
    spread: bool = False
    #: Messages need the edge's weight; without, the baselines over arrays do not read it.
    weights: bool = True

    @property
    def neutral(self) -> float:
        return {"sum": 0.0, "min": float("inf"), "max": float("-inf")}[self.gather]

    @property
    def idempotent(self) -> bool:
        return self.gather != "sum"

    def fold(self, messages: Column) -> Column:
        return {"sum": F.sum, "min": F.min, "max": F.max}[self.gather](messages)

    def np_fold(self, messages: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Fold messages per row of offsets; rows without messages get the neutral value."""
        op = {"sum": np.add, "min": np.minimum, "max": np.maximum}[self.gather]
        out = np.full(len(row) - 1, self.neutral)
        full = np.flatnonzero(row[1:] > row[:-1])
        if len(full):
            out[full] = op.reduceat(messages, row[full])
        return out


@dataclass(frozen=True)
class StopRule:
    """Stop after max_supersteps, or when no value moved by more than tol (0: when none changed at all).

    With tol > 0 a suppressed change is measured against the value last published, so small drifts add up until sent.
    """

    max_supersteps: int | None = None
    tol: float = 0.0


def changed(new: Column, old: Column, tol: float = 0.0) -> Column:
    """Published change: null- and NaN-safe, infinity equals itself."""
    if tol:
        return ~new.eqNullSafe(old) & ~(F.abs(new - old) <= tol)
    return ~new.eqNullSafe(old)


def np_changed(new: np.ndarray, old: np.ndarray, tol: float = 0.0) -> np.ndarray:
    differ = ~((new == old) | (np.isnan(new) & np.isnan(old)))
    if tol:
        with np.errstate(invalid="ignore"):
            differ &= ~(np.abs(new - old) <= tol)
    return differ
