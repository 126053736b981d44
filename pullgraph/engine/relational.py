"""Pull supersteps as joins and aggregations.

Every vertex has one more row among the edges, which brings its own old value; so a superstep reads the state once, in
one join, and one aggregation gives both the gathered value and the old one.  A chain of supersteps is then a chain of
plans, not a tree, and needs a table in the shared folder only every few supersteps.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graphs import Graph
from ..session import materialize, release
from .program import StopRule, VertexProgram, changed

#: The state is broadcast up to so many vertices (16 bytes each); beyond, both sides of the join are shuffled.
BROADCAST_VERTICES = 2_000_000


@dataclass
class Result:
    """values (id, value); one log entry per superstep or, without logging, per written table."""

    values: DataFrame
    supersteps: int
    log: list[dict] = field(default_factory=list)


def augmented(g: Graph, program: VertexProgram) -> DataFrame:
    """(src, dst, w, d_out, own): the edges with what messages need, and one row per vertex for itself."""
    edges = g.edges.select("src", "dst", "w")
    if "d_out" in program.components:
        # Every source has out-edges, so the degree is a count of its rows.
        edges = edges.join(g.edges.groupBy("src").agg(F.count("*").alias("d_out")), "src")
    else:
        edges = edges.withColumn("d_out", F.lit(None).cast("long"))
    own = g.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(None).cast("double").alias("w"), F.lit(None).cast("long").alias("d_out"), F.lit(True).alias("own"))
    return edges.select("src", "dst", "w", "d_out", F.lit(False).alias("own")).unionByName(own)


def step(rows: DataFrame, state: DataFrame, program: VertexProgram, n: int, tol: float = 0.0, frontier: bool = False, broadcast: bool | None = None) -> DataFrame:
    """The next state (id, value, changed)."""
    s = state.select(F.col("id").alias("src"), "value", "changed")
    if broadcast if broadcast is not None else n <= BROADCAST_VERTICES:
        s = F.broadcast(s)
    joined = rows.join(s, "src")
    if frontier:
        joined = joined.filter("own OR changed")
    message = F.when(~F.col("own"), program.message(F.col("value"), F.col("d_out"), F.col("w")))
    folded = joined.groupBy("dst").agg(program.fold(message).alias("accum"), F.max(F.when(F.col("own"), F.col("value"))).alias("old"))
    new = program.apply(F.col("dst"), F.col("old"), F.coalesce("accum", F.lit(program.neutral)), n)
    out = folded.select(F.col("dst").alias("id"), new.alias("new"), "old")
    sent = changed(F.col("new"), F.col("old"), tol)
    return out.select("id", F.when(sent, F.col("new")).otherwise(F.col("old")).alias("value"), sent.alias("changed"))


def run(g: Graph, program: VertexProgram, stop: StopRule = StopRule(), cut_every: int = 5, frontier: bool = False, log: bool = False, broadcast: bool | None = None) -> Result:
    """Supersteps until the rule says stop; frontier: only changed sources send (idempotent gathers only).

    Without a bound, the number of supersteps is rounded up to a multiple of cut_every, which changes nothing at a fixed
    point.
    """
    if frontier and not program.idempotent:
        raise ValueError("a sum must gather all in-edges again; only idempotent gathers can follow a frontier")
    if program.spread:
        raise ValueError("dangling mass is known only where all values are; use the tile kernel")
    n = g.n_vertices
    if n == 0:
        return Result(g.vertices.select("id", F.lit(None).cast("double").alias("value")), 0)
    state = g.vertices.select("id", program.init(F.col("id"), n).alias("value"), F.lit(True).alias("changed"))
    rows = materialize(augmented(g, program), "augmented")
    by_source = not (broadcast if broadcast is not None else n <= BROADCAST_VERTICES)
    if by_source:
        # Both sides of the join are laid out by vertex: the rows once, the state by the aggregation that made it.
        rows = rows.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), "src").persist(StorageLevel.DISK_ONLY)
    every = 1 if log else cut_every
    entries, done, held = [], 0, None
    while stop.max_supersteps is None or done < stop.max_supersteps:
        k = every if stop.max_supersteps is None else min(every, stop.max_supersteps - done)
        for _ in range(k):
            state = step(rows, state, program, n, stop.tol, frontier, broadcast)
        done += k
        if not by_source and not log and stop.max_supersteps is not None and done == stop.max_supersteps and done <= cut_every:
            break
        state = materialize(state, "state")
        release(held)
        held = state
        if log or stop.max_supersteps is None:
            moved = state.filter("changed").count()
            entries.append({"superstep": done, "changed": moved, "update_ratio": moved / n})
            if moved == 0:
                break
    if by_source:
        rows.unpersist()
    return Result(state.select("id", "value"), done, entries)
