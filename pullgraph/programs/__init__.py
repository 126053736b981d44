"""PageRank, shortest paths and further programs on the same interface."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..engine.program import VertexProgram

DAMPING = 0.85


def pagerank(damping: float = DAMPING, dangling: str = "ignore") -> VertexProgram:
    """Rank (1 - damping) / n + damping * sum of value / out-degree.

    dangling: the mass of vertices without out-edges is lost (ignore), or, as an extension, shared by all (spread).
    """
    if dangling not in ("ignore", "spread"):
        raise ValueError("dangling is ignore or spread")
    return VertexProgram(
        "pagerank", "sum",
        init=lambda _, n: F.lit(1.0 / n),
        message=lambda value, d_out, _: value / d_out,
        apply=lambda _, __, accum, n: F.lit((1.0 - damping) / n) + F.lit(damping) * accum,
        np_init=lambda n: np.full(n, 1.0 / n),
        np_message=lambda value, d_out, _: value / d_out,
        np_apply=lambda _, __, accum, n: (1.0 - damping) / n + damping * accum,
        components=("d_out",), spread=dangling == "spread", weights=False,
    )


def sssp(source: int = 0, weighted: bool = True) -> VertexProgram:
    """Shortest distance from source; hops if not weighted; infinity where no path leads."""
    step = (lambda w: F.coalesce(w, F.lit(1.0))) if weighted else (lambda w: F.lit(1.0))
    np_step = (lambda w: 1.0 if w is None else w) if weighted else (lambda w: 1.0)

    def start(n: int) -> np.ndarray:
        if not 0 <= source < n:
            raise ValueError(f"source {source} is no vertex of 0..{n - 1}")
        out = np.full(n, np.inf)
        out[source] = 0.0
        return out

    def init(i, n):
        if not 0 <= source < n:
            raise ValueError(f"source {source} is no vertex of 0..{n - 1}")
        return F.when(i == source, F.lit(0.0)).otherwise(F.lit(float("inf")))

    return VertexProgram(
        "sssp" if weighted else "sssp_unit", "min",
        init=init,
        message=lambda value, _, w: value + step(w),
        apply=lambda _, old, accum, __: F.least(old, accum),
        np_init=start,
        np_message=lambda value, _, w: value + np_step(w),
        np_apply=lambda _, old, accum, __: np.minimum(old, accum),
        apply_without_input=False, start=source, weights=weighted,
    )


def components() -> VertexProgram:
    """Extension: smallest id that reaches a vertex; connected components on a symmetrised graph."""
    return VertexProgram(
        "components", "min",
        init=lambda i, _: i.cast("double"),
        message=lambda value, _, __: value,
        apply=lambda _, old, accum, __: F.least(old, accum),
        np_init=lambda n: np.arange(n, dtype=float),
        np_message=lambda value, _, __: value,
        np_apply=lambda _, old, accum, __: np.minimum(old, accum),
    )


def reachable(source: int = 0) -> VertexProgram:
    """Extension: 1 for vertices that a path from source leads to, else 0."""
    return VertexProgram(
        "reachable", "max",
        init=lambda i, _: F.when(i == source, F.lit(1.0)).otherwise(F.lit(0.0)),
        message=lambda value, _, __: value,
        apply=lambda _, old, accum, __: F.greatest(old, accum),
        np_init=lambda n: (np.arange(n) == source).astype(float),
        np_message=lambda value, _, __: value,
        np_apply=lambda _, old, accum, __: np.maximum(old, accum),
        apply_without_input=False, start=source,
    )


def personalised_pagerank(source: int, damping: float = DAMPING) -> VertexProgram:
    """Extension: PageRank that restarts at one vertex."""
    return VertexProgram(
        f"personalised_pagerank_{source}", "sum",
        init=lambda i, _: F.when(i == source, F.lit(1.0)).otherwise(F.lit(0.0)),
        message=lambda value, d_out, _: value / d_out,
        apply=lambda i, _, accum, __: F.when(i == source, F.lit(1.0 - damping)).otherwise(F.lit(0.0)) + F.lit(damping) * accum,
        np_init=lambda n: (np.arange(n) == source).astype(float),
        np_message=lambda value, d_out, _: value / d_out,
        np_apply=lambda i, _, accum, __: np.where(i == source, 1.0 - damping, 0.0) + damping * accum,
        components=("d_out",),
    )


def in_degree() -> VertexProgram:
    """Extension: number of in-edges, in one superstep."""
    return VertexProgram(
        "in_degree", "sum",
        init=lambda _, __: F.lit(1.0),
        message=lambda value, _, __: F.lit(1.0) + value * 0,
        apply=lambda _, __, accum, ___: accum,
        np_init=lambda n: np.ones(n),
        np_message=lambda value, _, __: np.ones(len(value)),
        np_apply=lambda _, __, accum, ___: accum,
    )
