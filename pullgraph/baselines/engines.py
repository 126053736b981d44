"""The engines that the pull model is compared with, on the same substrate and with counted costs.

All return the same values as the pull engine.  Sum programs run a fixed number of supersteps with all vertices active;
programs with an idempotent gather follow each engine's own activity rule and stop when no vertex is active.

Edges are laid out once, by the key that each engine's superstep joins them on and sorted by it: in blocks of memory for
in-memory engines, of disk for out-of-core ones.  So a superstep moves values and messages, as the methods mean it, and
reads edges where they are.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..engine.program import StopRule, VertexProgram, changed
from ..engine.relational import BROADCAST_VERTICES, Result
from ..graphs import Graph, degrees
from ..partition.cuts import CUTS, hash_edge_cut, replicas, streaming_partitions
from ..session import materialize, release


#: Edges that a task of a superstep reads, where the session's number of partitions would give it fewer.
TASK_EDGES = 1 << 17


def _laid_out(edges: DataFrame, n_edges: int, *keys: str, on_disk: bool = False) -> DataFrame:
    """Every superstep has a task for each partition, so small graphs have no more of them than keep the cores busy."""
    spark = edges.sparkSession
    n = min(int(spark.conf.get("spark.sql.shuffle.partitions")), max(spark.sparkContext.defaultParallelism, -(-n_edges // TASK_EDGES)))
    return edges.repartition(n, *keys).sortWithinPartitions(*keys).persist(StorageLevel.DISK_ONLY if on_disk else StorageLevel.MEMORY_AND_DISK)


def _start(g: Graph, program: VertexProgram) -> DataFrame:
    n = g.n_vertices
    first = F.lit(True) if program.start is None else F.col("id") == F.lit(program.start)
    return materialize(degrees(g).select("id", program.init(F.col("id"), n).alias("value"), "d_out", first.alias("active")), "state")


def _sent_out(state: DataFrame, n: int) -> DataFrame:
    """The state as the side of a join that travels: broadcast where the pull engine's is, else shuffled."""
    return F.broadcast(state) if n <= BROADCAST_VERTICES else state


def _commit(state: DataFrame, messages: DataFrame, program: VertexProgram, n: int, tol: float, only: DataFrame | None = None) -> DataFrame:
    """Fold messages (id, accum) and apply them to the state; `only` (id) limits which vertices apply.  active: the value
    changed.

    Each vertex has its old state as one more row among the messages, so one aggregation folds and finds it.
    """
    own = state.select("id", F.lit(None).cast("double").alias("accum"), "value", "d_out", F.lit(True).alias("own"), F.lit(None).cast("boolean").alias("applies"))
    rows = own.unionByName(messages.select("id", "accum"), allowMissingColumns=True)
    if only is not None:
        rows = rows.unionByName(only.select("id", F.lit(True).alias("applies")), allowMissingColumns=True)
    s = rows.groupBy("id").agg(program.fold(F.col("accum")).alias("accum"), F.max("value").alias("value"), F.max("d_out").alias("d_out"), F.max("own").alias("own"), F.max("applies").alias("applies")).filter("own")
    new = program.apply(F.col("id"), F.col("value"), F.coalesce("accum", F.lit(program.neutral)), n)
    if only is not None:
        new = F.when(F.col("applies"), new).otherwise(F.col("value"))
    s = s.withColumn("new", new).withColumn("sent", changed(F.col("new"), F.col("value"), tol))
    return s.select("id", F.when(F.col("sent"), F.col("new")).otherwise(F.col("value")).alias("value"), "d_out", F.col("sent").alias("active"))


def _loop(g: Graph, program: VertexProgram, stop: StopRule, one: Callable[[DataFrame, int, dict], DataFrame], after: Callable[[DataFrame, dict], None] | None = None) -> Result:
    """one: the plan of the next state; after: what else a superstep does once that state is written."""
    state, done, log = _start(g, program), 0, []
    n = g.n_vertices
    while stop.max_supersteps is None or done < stop.max_supersteps:
        began, entry, seen = time.time(), {"superstep": done + 1}, Observation()
        # Changes are counted while the state is written, which saves a job a superstep.
        kept = materialize(one(state, done, entry).observe(seen, F.count_if("active").alias("moved")), "state")
        release(state)
        release(entry.pop("spool", None))
        state, done = kept, done + 1
        if after is not None:
            after(state, entry)
        moved = seen.get["moved"]
        log.append(entry | {"wall_s": time.time() - began, "changed": moved, "update_ratio": moved / max(n, 1)})
        if not moved:
            break
    return Result(state.select("id", "value"), done, log)


def msg_mem(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, combine: bool = True, on_disk: bool = False, count: bool = False) -> Result:
    """Vertex messages over a hash edge-cut.

    Active vertices send along their out-edges; messages of one worker for one target are combined before they leave it
    (combine), then folded at the target.  In an idempotent program a vertex halts until a message improves it.  on_disk:
    edges and uncombined messages are files, as in the out-of-core engine.
    """
    out = _laid_out(hash_edge_cut(g, servers), g.n_edges, "src", on_disk=on_disk)
    n = g.n_vertices

    def one(state: DataFrame, done: int, entry: dict) -> DataFrame:
        sending = state.filter("active") if program.idempotent else state
        sent = out.join(_sent_out(sending.select(F.col("id").alias("src"), "value", "d_out"), n), "src").select("worker", "dst", program.message(F.col("value"), F.col("d_out"), F.col("w")).alias("m"))
        if on_disk:
            sent = entry["spool"] = materialize(sent, "spool")
        combined = sent.groupBy("worker", "dst").agg(program.fold(F.col("m")).alias("m")) if combine else sent
        if count:
            entry |= {"msg_raw": sent.count(), "msg_count": combined.count()}
        return _commit(state, combined.select(F.col("dst").alias("id"), F.col("m").alias("accum")), program, n, stop.tol)

    result = _loop(g, program, stop, one)
    out.unpersist()
    return result


def msg_disk(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, count: bool = False) -> Result:
    return msg_mem(g, program, stop, servers, True, True, count)


def msg_hadoop(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, count: bool = False) -> Result:
    """Stand-in for a vertex-message engine on a general-purpose stack: no combiner, everything rewritten each superstep."""
    return msg_mem(g, program, stop, servers, False, True, count)


def gas(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, cut: str = "random", count: bool = False) -> Result:
    """Gather, apply, scatter over a vertex-cut.

    Mirrors fold the in-edges of their part, masters fold the partial results and apply, new values go to the mirrors, and
    changed vertices activate their out-neighbours, which alone gather next time.
    """
    n, all_active = g.n_vertices, not program.idempotent
    edges = _laid_out(CUTS[cut](g, servers), g.n_edges, "part", "src")
    # Where values are broadcast to the mirrors, these lie as the edges they are joined with; else as the values do.
    places = _laid_out(replicas(edges), g.n_edges, *(("part", "id") if n <= BROADCAST_VERTICES else ("id",)))
    active_next: list[DataFrame | None] = [None]
    folds: list[DataFrame] = []

    def targets(moved: DataFrame) -> DataFrame:
        return edges.join(_sent_out(moved.select(F.col("id").alias("src")), n), "src", "left_semi").select(F.col("dst").alias("id")).distinct()

    def one(state: DataFrame, done: int, entry: dict) -> DataFrame:
        if done == 0 and program.start is not None:
            active_next[0] = materialize(targets(state.filter("active")), "active")
        active = active_next[0]
        mirrors = places.join(_sent_out(state.select("id", "value", "d_out"), n), "id").select("part", F.col("id").alias("src"), "value", "d_out")
        local = edges if active is None else edges.join(_sent_out(active.select(F.col("id").alias("dst")), n), "dst", "left_semi")
        partial = local.join(mirrors, ["part", "src"]).groupBy("part", "dst").agg(program.fold(program.message(F.col("value"), F.col("d_out"), F.col("w"))).alias("m"))
        if count:
            partial = materialize(partial, "partial")
            folds.append(partial)
        return _commit(state, partial.select(F.col("dst").alias("id"), F.col("m").alias("accum")), program, n, stop.tol, active)

    def after(new: DataFrame, entry: dict) -> None:
        old, moved = active_next[0], new.filter("active")
        if count:
            partial = folds.pop()
            up = partial.select("part", F.col("dst").alias("id")).join(places.filter("NOT is_master"), ["part", "id"], "left_semi").count()
            down = places.filter("NOT is_master").join(moved, "id", "left_semi").count()
            entry |= {"msg_up": up, "msg_down": down, "msg_count": up + down, "op_gather": partial.count(), "op_apply": n if old is None else old.count(), "op_scatter": edges.join(moved.select(F.col("id").alias("src")), "src", "left_semi").select("part", "src").distinct().count()}
            release(partial)
        if not all_active:
            active_next[0] = materialize(targets(moved), "active")
            release(old)

    result = _loop(g, program, stop, one, after)
    release(active_next[0])
    edges.unpersist()
    places.unpersist()
    return result


def gas_vcut(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, count: bool = False) -> Result:
    return gas(g, program, stop, servers, "random", count)


def gas_hybrid(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, count: bool = False) -> Result:
    return gas(g, program, stop, servers, "hybrid", count)


def edge_stream(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, parts: int = 36, count: bool = False) -> Result:
    """Edge-centric gather, apply, scatter over streaming partitions.

    Every superstep reads every edge and writes one message per edge to its target's partition; a second pass folds the
    messages; a third applies.  Nothing is combined and no edge is left out.
    """
    edges = _laid_out(streaming_partitions(g, parts, servers), g.n_edges, "src", on_disk=True)
    n = g.n_vertices

    def one(state: DataFrame, done: int, entry: dict) -> DataFrame:
        sent = edges.join(_sent_out(state.select(F.col("id").alias("src"), "value", "d_out"), n), "src")
        spool = entry["spool"] = materialize(sent.select(F.pmod("dst", F.lit(parts)).alias("part"), "dst", program.message(F.col("value"), F.col("d_out"), F.col("w")).alias("m")), "inbox")
        if count:
            k = spool.count()
            entry |= {"msg_raw": k, "msg_count": k}
        return _commit(state, spool.select(F.col("dst").alias("id"), F.col("m").alias("accum")), program, n, stop.tol)

    result = _loop(g, program, stop, one)
    edges.unpersist()
    return result


def triplets(g: Graph, program: VertexProgram, stop: StopRule, servers: int = 9, count: bool = False) -> Result:
    """General-purpose dataflow: vertices join edges join vertices, then messages are aggregated at the target."""
    n = g.n_vertices

    def one(state: DataFrame, done: int, entry: dict) -> DataFrame:
        s = state.select(F.col("id").alias("src"), F.col("value").alias("sv"), "d_out")
        t = state.select(F.col("id").alias("dst"), F.col("value").alias("tv"))
        rows = g.edges.join(_sent_out(s, n), "src").join(_sent_out(t, n), "dst")
        if count:
            entry |= {"msg_count": rows.count()}
        return _commit(state, rows.select(F.col("dst").alias("id"), program.message(F.col("sv"), F.col("d_out"), F.col("w")).alias("accum")), program, n, stop.tol)

    return _loop(g, program, stop, one)


ENGINES: dict[str, Callable[..., Result]] = {f.__name__: f for f in (msg_mem, msg_disk, msg_hadoop, gas_vcut, gas_hybrid, edge_stream, triplets)}
