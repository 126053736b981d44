"""The compared engines over arrays, for graphs whose vertex states fit every worker, as pull's tile kernel has them.

Same methods, activity rules and results as in `engines`, which serves any number of vertices by tables.  Edges are laid
out by target once, as arrays, and from that once per cut, in blocks: those of one part (worker, server, streaming partition) for one chunk of targets, by target,
with the sources that the part has a replica of.  The vertices of a chunk are those with one remainder of the id, so hubs
with neighbouring ids are spread.  A superstep moves values to the blocks by broadcast and messages to the chunks by a
shuffle; the chunks fold and apply, and what changed comes to the driver, which is the barrier.

Blocks of one part and chunk are not cut, so what a block combines is all that its part has for a target.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..engine.program import StopRule, VertexProgram, np_changed
from ..engine.relational import Result
from ..engine.replica import Replicas
from ..engine.tilepath import _result_limit, degrees_everywhere, values_frame
from ..graphs import Graph
from ..partition.cuts import hybrid_place, random_cut, random_place, source_place, streaming_partitions  # noqa: F401
from ..partition.tiles import Prepared
from ..pieces import binaries, by_key, deal, edges_of, read
from ..session import collect_garbage, materialize, release, ship

#: Vertices up to which every Python worker holds values, degrees and flags: 17 bytes each.
ARRAY_VERTICES = 1 << 23
#: Edges of a chunk, 4 MB of a row, as readers and writers hold pages of whole rows; small graphs have as many chunks as
#: keep the cores busy.
CHUNK_EDGES = 1 << 18
#: Edges whose messages a task folds.
TASK_EDGES = 1 << 21
#: Edges of a file of chunks or blocks.
FILE_EDGES = 1 << 19
STREAMING_PARTS = 36
#: Edges that a task deals out to the streaming partitions at a time.
STREAM_EDGES = 1 << 20

CHUNK = "chunk int, src binary, dst binary, row binary, w binary"
BLOCK = "part int, chunk int, ids binary, src binary, dst binary, row binary, w binary"
MESSAGE = "part int, chunk int, at binary, m binary"
_KINDS = {"int": pa.int32(), "binary": pa.binary()}


def fits(g: Graph) -> bool:
    """Whether states fit every worker, and 12 bytes for each vertex into half of what the driver may receive at once."""
    return 0 < g.n_vertices <= min(ARRAY_VERTICES, _result_limit(g.spark) // 24)


def _batch(schema: str, *row) -> pa.RecordBatch:
    names, kinds = zip(*(c.split() for c in schema.split(", ")), strict=True)
    return pa.RecordBatch.from_arrays([pa.array([x.tobytes() if isinstance(x, np.ndarray) else x], _KINDS[k]) for x, k in zip(row, kinds, strict=True)], list(names))


def _rows(it, *kinds: str | None) -> Iterator[list]:
    """The rows of Arrow batches; binaries as arrays of the kinds named, or None."""
    for b in it:
        for k in range(b.num_rows):
            yield [c[k].as_py() if kind is None else np.frombuffer(c[k].as_buffer(), kind) if c[k].is_valid else None for c, kind in zip(b.columns, kinds, strict=True)]


@dataclass
class Layout:
    """Blocks in files of the shared folder, of `parts` parts, the number of chunks of targets, and of tasks for them."""

    blocks: DataFrame
    parts: int
    chunks: int
    tasks: int

    def drop(self) -> None:
        release(self.blocks)


def _by_target(prep: Prepared) -> tuple[DataFrame, int, int]:
    """The edges by chunk of targets, from which each cut is made without another shuffle, and the numbers of chunks and
    of tasks for them.

    A row has the edges of a chunk: the targets, where each one's edges begin, the edges' sources and weights.
    """
    g, spark = prep.graph, prep.graph.spark
    chunks, tasks = (max(spark.sparkContext.defaultParallelism, -(-g.n_edges // k)) for k in (CHUNK_EDGES, TASK_EDGES))
    rows = g.edges.select(F.pmod("dst", F.lit(chunks)).alias("key"), "src", "dst", F.coalesce("w", F.lit(1.0)).alias("w"))
    # Every chunk has a row, as its vertices apply whether a message comes or not.
    nothing = F.lit(b"").cast("binary")
    dealt = deal(rows, chunks, tasks, spark.range(chunks).select(F.col("id").alias("key"), nothing.alias("src"), nothing.alias("dst"), nothing.alias("w")))

    def run(it):
        for chunk, src, dst, w in edges_of(it):
            order = np.lexsort((src, dst))
            dst = (dst[order] // chunks).astype(np.int32)
            row = np.flatnonzero(np.diff(dst, prepend=-1))
            yield _batch(CHUNK, chunk, src[order].astype(np.int32), dst[row], row.astype(np.int32), w[order])

    return materialize(dealt.sortWithinPartitions("key").mapInArrow(run, CHUNK), "chunks", codec="zstd", file_rows=FILE_EDGES // CHUNK_EDGES), chunks, tasks


def _block(part: int, chunk: int, src: np.ndarray, dst: np.ndarray, row: np.ndarray, w: np.ndarray) -> pa.RecordBatch:
    ids, local = np.unique(src, return_inverse=True)
    return _batch(BLOCK, part, chunk, ids.astype(np.int64), local.astype(np.int32), dst, row.astype(np.int32), w)


def _placed(place: Callable, parts: int, chunks: int) -> Callable:
    """Blocks of the parts that `place` deals the edges of _by_target() to; a chunk has all in-edges of its targets."""

    def run(it):
        for chunk, src, dst, row, w in _rows(it, None, "<i4", "<i4", "<i4", "<f8"):
            d_in = np.diff(row, append=len(src))
            at, src = np.repeat(dst, d_in), src.astype(np.int64)
            part = place(src, at.astype(np.int64) * chunks + chunk, np.repeat(d_in, d_in), parts)
            order, start = by_key(part, parts)
            part, src, at, w = part[order], src[order], at[order], w[order]
            for a, z in zip(start[:-1], start[1:], strict=True):
                first = np.flatnonzero(np.diff(at[a:z], prepend=-1))
                yield _block(int(part[a]) if z > a else 0, chunk, src[a:z], at[a:z][first], first, w[a:z])

    return run


def _streamed(parts: int) -> Callable:
    """Blocks of one part for all targets, where dst are ids, of edges (part, src, dst, w) as they are read, in no order."""

    def run(it):
        for part, src, dst, w in read(it, STREAM_EDGES):
            order, start = by_key(part, parts)
            part, src, dst, w = part[order], src[order], dst[order], w[order]
            for a, z in zip(start[:-1], start[1:], strict=True):
                have = src[a:z] >= 0
                yield _block(int(part[a]), 0, src[a:z][have], dst[a:z][have], start[:0], w[a:z][have])

    return run


def _pack(edges: DataFrame, blocks: Callable, parts: int, chunks: int, tasks: int) -> Layout:
    """Blocks of `parts` parts, which `blocks` makes of some 2^18 edges or more at a time."""
    return Layout(materialize(edges.mapInArrow(blocks, BLOCK), "blocks", file_rows=FILE_EDGES // CHUNK_EDGES * parts), parts, chunks, tasks)


def _stream_edges(prep: Prepared, servers: int) -> DataFrame:
    ship(prep.graph.spark)
    rows = streaming_partitions(prep.graph, STREAMING_PARTS, servers).select("part", "src", "dst", F.coalesce("w", F.lit(1.0)).alias("w"))
    # One row without an edge, as vertices apply in a graph without edges too.
    return rows.unionAll(prep.graph.spark.sql("SELECT 0L AS part, -1L AS src, -1L AS dst, 0D AS w"))


#: How each engine's edges are cut.
PLACE: dict[str, Callable] = {"worker": source_place, "random": random_place, "hybrid": hybrid_place}
ENGINE_CUT = {"msg_mem": "worker", "msg_disk": "worker", "msg_hadoop": "worker", "gas_vcut": "random", "gas_hybrid": "hybrid", "edge_stream": "stream"}


def layout(prep: Prepared, engine: str, servers: int) -> Layout:
    """Made once for each cut and number of servers; on one server all cuts but the streaming partitions are the same."""
    cut = ENGINE_CUT[engine]
    by_target, chunks, tasks = prep.once("by-target", lambda: _by_target(prep))
    if cut == "stream":
        return prep.once("blocks-stream", lambda: _pack(_stream_edges(prep, servers), _streamed(STREAMING_PARTS), STREAMING_PARTS, chunks, tasks))
    return prep.once(f"blocks-{'worker' if servers == 1 else cut}-{servers}", lambda: _pack(by_target, _placed(PLACE[cut], servers, chunks), servers, chunks, tasks))


def drop_layouts(prep: Prepared, but: str = "") -> None:
    """All of them, or all but the one named; the edges by target stay."""
    for name in [k for k in prep.kept if k.startswith("blocks-") and k != but]:
        prep.kept.pop(name).drop()


def _sources(program: VertexProgram, value: Replicas, d_out: Replicas | None, ids: np.ndarray, src: np.ndarray, w: np.ndarray | None) -> np.ndarray:
    """A message for each edge, from the values of the part's replicas."""
    own, degree = value.at(ids), d_out.at(ids) if d_out else None
    if not program.weights:  # all edges of a source bring the same
        return program.np_message(own, degree, None)[src]
    return program.np_message(own[src], degree[src] if d_out else None, w)


def _send(program: VertexProgram, value: Replicas, d_out: Replicas | None, active: Replicas | None, combine: bool) -> Callable:
    """Messages along the out-edges of active sources (None: all), combined for each target or not."""

    def run(it):
        for part, chunk, ids, src, dst, row, w in _rows(it, None, None, "<i8", "<i4", "<i4", "<i4", "<f8"):
            sends = active.at(ids) if active else np.ones(len(ids), bool)
            if not sends.any():
                yield _batch(MESSAGE, part, chunk, dst[:0], np.zeros(0))
                continue
            m, to = _sources(program, value, d_out, ids, src, w), np.repeat(dst, np.diff(row, append=len(src)))
            if not sends.all():
                m, to = m[sends[src]], to[sends[src]]
            yield _batch(MESSAGE, part, chunk, *(_combined(program, to, m) if combine else (to, m)))

    return run


def _combined(program: VertexProgram, to: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One message for each of the targets, which are in order."""
    start = np.flatnonzero(np.diff(to, prepend=-1))
    return to[start], program.np_fold(m, np.append(start, len(m))) if len(start) else m


def _combine(program: VertexProgram) -> Callable:
    def run(it):
        for part, chunk, to, m in _rows(it, None, None, "<i4", "<f8"):
            yield _batch(MESSAGE, part, chunk, *_combined(program, to, m))

    return run


def _gather(program: VertexProgram, value: Replicas, d_out: Replicas | None, active: Replicas | None, chunks: int) -> Callable:
    """What a part's mirrors fold for each active target (None: all) from all its in-edges there."""

    def run(it):
        for part, chunk, ids, src, dst, row, w in _rows(it, None, None, "<i8", "<i4", "<i4", "<i4", "<f8"):
            takes = active.at(dst.astype(np.int64) * chunks + chunk) if active else np.ones(len(dst), bool)
            if not takes.any():
                yield _batch(MESSAGE, part, chunk, dst[:0], np.zeros(0))
                continue
            if not takes.all():
                size = np.diff(row, append=len(src))
                edge = np.repeat(takes, size)
                src, w, dst, row = src[edge], None if w is None else w[edge], dst[takes], np.cumsum(size[takes]) - size[takes]
            yield _batch(MESSAGE, part, chunk, dst, program.np_fold(_sources(program, value, d_out, ids, src, w), np.append(row, len(src))))

    return run


def _scatter(moved: Replicas) -> Callable:
    """Targets with a source that moved, as bits over the chunk."""

    def run(it):
        for part, chunk, ids, src, dst, row, _ in _rows(it, None, None, "<i8", "<i4", "<i4", "<i4", "<f8"):
            sends = moved.at(ids)
            if sends.any():
                to = np.zeros(int(dst[-1]) + 1, bool)
                to[dst] = np.logical_or.reduceat(sends[src], row)
                yield _batch(MESSAGE, part, chunk, np.packbits(to), np.zeros(0))

    return run


def _stream(program: VertexProgram, value: Replicas, d_out: Replicas | None, chunks: int) -> Callable:
    """A message for every edge, dealt out to its target's chunk."""

    def run(it):
        for part, _, ids, src, dst, _, w in _rows(it, None, None, "<i8", "<i4", "<i8", "<i4", "<f8"):
            m, chunk = _sources(program, value, d_out, ids, src, w), dst % chunks
            order, _ = by_key(chunk, chunks)
            start = np.searchsorted(chunk[order], np.arange(chunks + 1))
            columns = [pa.array(np.full(chunks, part, np.int32)), pa.array(np.arange(chunks, dtype=np.int32)), binaries((dst // chunks)[order].astype(np.int32), start), binaries(m[order], start)]
            yield pa.RecordBatch.from_arrays(columns, ["part", "chunk", "at", "m"])

    return run


def _apply(program: VertexProgram, n: int, chunks: int, value: Replicas, only: Replicas | None, tol: float) -> Callable:
    """Chunks fold what came for their vertices and apply it; out go the values that changed.  only: which vertices apply."""
    op = {"sum": np.add, "min": np.minimum, "max": np.maximum}[program.gather]

    def run(it):
        folded: dict[int, np.ndarray] = {}
        for _, chunk, to, m in _rows(it, None, None, "<i4", "<f8"):
            if chunk not in folded:
                folded[chunk] = np.full(len(range(chunk, n, chunks)), program.neutral)
            op.at(folded[chunk], to, m)
        for chunk, accum in folded.items():
            ids = np.arange(chunk, n, chunks)
            old = value.at(ids)
            new = program.np_apply(ids, old, accum, n)
            if only is not None:
                new = np.where(only.at(ids), new, old)
            at = np.flatnonzero(np_changed(new, old, tol)).astype(np.int32)
            yield _batch(MESSAGE, 0, chunk, at, new[at])

    return run


def run(engine: str, prep: Prepared, program: VertexProgram, stop: StopRule, servers: int = 9) -> Result:
    """One of the engines of ENGINE_CUT, until its rule says stop."""
    g, spark, n = prep.graph, prep.graph.spark, prep.graph.n_vertices
    laid = layout(prep, engine, servers)
    gas, stream, spooled = engine.startswith("gas"), engine == "edge_stream", engine in ("msg_disk", "msg_hadoop", "edge_stream")
    blocks = laid.blocks if program.weights else laid.blocks.withColumn("w", F.lit(None).cast("binary"))
    if not spooled:
        # A plan of its own: persist() is of plans, and another engine reads the same files each time.
        kept = spark.read.schema(laid.blocks.schema).parquet(laid.blocks._scratch_path)
        blocks = (kept if program.weights else kept.withColumn("w", F.lit(None).cast("binary"))).persist(StorageLevel.MEMORY_AND_DISK)
    d_out = degrees_everywhere(prep)[1] if "d_out" in program.components else None
    values = program.np_init(n)
    moved = np.ones(n, bool) if program.start is None else np.arange(n) == program.start
    takes: np.ndarray | None = None
    chunks, log, done = laid.chunks, [], 0

    def activated() -> np.ndarray:
        share, out = Replicas(spark, moved), np.zeros(n, bool)
        for r in blocks.mapInArrow(_scatter(share), MESSAGE).collect():
            bits = np.unpackbits(np.frombuffer(r["at"], np.uint8))
            out[np.flatnonzero(bits) * chunks + r["chunk"]] = True
        share.drop()
        return out

    def one(value: Replicas, active: Replicas | None) -> tuple[DataFrame, DataFrame | None]:
        """The messages for the chunks, and the files they are in, if they are."""
        if gas:
            return blocks.mapInArrow(_gather(program, value, d_out, active, chunks), MESSAGE), None
        sent = blocks.mapInArrow(_stream(program, value, d_out, chunks) if stream else _send(program, value, d_out, active, not spooled), MESSAGE)
        if not spooled:
            return sent, None
        files = materialize(sent, "spool")
        return files.mapInArrow(_combine(program), MESSAGE) if engine == "msg_disk" else files, files

    if gas and program.idempotent and program.start is not None:
        takes = activated()
    while stop.max_supersteps is None or done < stop.max_supersteps:
        began, value = time.time(), Replicas(spark, values)
        flags = takes if gas else moved if program.idempotent and not stream else None
        active = None if flags is None else Replicas(spark, flags)
        messages, files = one(value, active)
        applied = messages.repartitionById(laid.tasks, F.pmod("chunk", F.lit(laid.tasks)).cast("int")).mapInArrow(_apply(program, n, chunks, value, active if gas else None, stop.tol), MESSAGE)
        values, moved = values.copy(), np.zeros(n, bool)
        for r in applied.collect():
            at = np.frombuffer(r["at"], "<i4").astype(np.int64) * chunks + r["chunk"]
            values[at], moved[at] = np.frombuffer(r["m"], "<f8"), True
        if files is not None:
            release(files)
            del messages, applied
            collect_garbage(spark)  # a superstep's shuffle files are as large as its messages
        for x in (value, active):
            if x is not None:
                x.drop()
        done += 1
        if gas and program.idempotent:
            takes = activated()
        k = int(moved.sum())
        log.append({"superstep": done, "wall_s": time.time() - began, "changed": k, "update_ratio": k / n})
        if not k:
            break
    if not spooled:
        blocks.unpersist()
    return Result(values_frame(spark, values), done, log)
