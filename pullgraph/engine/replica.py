"""Replication of vertex state: everywhere (dense arrays) or on demand (routing table)."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..partition.tiles import Prepared, sources
from ..session import materialize, release, ship
from .program import StopRule, VertexProgram, np_changed
from .relational import Result

#: A broadcast array is cut into chunks of so many numbers.
CHUNK = 1 << 27


class Replicas:
    """A dense array on every worker, in chunks; the position of a vertex is its id."""

    def __init__(self, spark: SparkSession, values: np.ndarray) -> None:
        self.parts = [spark.sparkContext.broadcast(values[i : i + CHUNK]) for i in range(0, max(len(values), 1), CHUNK)]

    def at(self, ids: np.ndarray) -> np.ndarray:
        if len(self.parts) == 1:
            return self.parts[0].value[ids]
        out, chunk = np.empty(len(ids), self.parts[0].value.dtype), ids // CHUNK
        for k in np.unique(chunk):
            mine = chunk == k
            out[mine] = self.parts[k].value[ids[mine] - k * CHUNK]
        return out

    def drop(self) -> None:
        for p in self.parts:
            p.unpersist()


def gather_tile(program: VertexProgram, n: int, v_lo: int, row: np.ndarray, col: np.ndarray, val: np.ndarray | None, old: np.ndarray, value, d_out, shared: float = 0.0) -> np.ndarray:
    """Candidate values of a tile's targets; value and d_out are functions from source ids to numbers, shared is added to
    what every target gathers."""
    degree = d_out(col) if "d_out" in program.components and len(col) else None
    messages = program.np_message(value(col), degree, val) if len(col) else np.zeros(0)
    return program.np_apply(np.arange(v_lo, v_lo + len(old)), old, program.np_fold(messages, row) + shared, n)


def vertices_of_tiles(tiles: DataFrame) -> DataFrame:
    """(tile_id, id): sources and targets of each tile: the routing table of on-demand replication."""
    own = F.sequence(F.col("v_lo"), F.col("v_hi") - 1)
    return tiles.filter("v_hi > v_lo").select("tile_id", F.explode(F.array_union("col", own)).alias("id"))


def run_on_demand(prep: Prepared, program: VertexProgram, stop: StopRule) -> Result:
    """Supersteps in which each tile gets only the values of the vertices it touches.

    State stays a table: it is routed to tiles by a shuffle join with the routing table, each tile gathers on its own, and
    updates come back as rows.  No array of all vertices exists anywhere, so this is the path for graphs whose state does
    not fit into one machine.
    """
    if program.spread:
        raise ValueError("dangling mass is known only where all values are; use full replication")
    spark, n = prep.tiles.sparkSession, prep.graph.n_vertices
    ship(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # Laid out once, in blocks on the executors' disks that are made again if one is lost: tiles by tile, the routing table
    # and the sources by vertex.  What travels in a superstep is values alone.
    lay = lambda df, key: df.repartition(parts, key).persist(StorageLevel.DISK_ONLY)
    placed = prep.once("placed", lambda: lay(prep.tiles, "tile_id"))
    route = prep.once("routing", lambda: lay(materialize(vertices_of_tiles(prep.tiles), "routing"), "id"))
    tile_src = prep.once("sources-by-vertex", lambda: lay(materialize(sources(prep.tiles), "tile-sources"), "src"))
    state = materialize(prep.degrees.select("id", program.init(F.col("id"), n).alias("value"), "d_out", F.lit(True).alias("changed")), "state")
    tol = stop.tol

    def kernel(tiles: pd.DataFrame, states: pd.DataFrame) -> pd.DataFrame:
        out = []
        order = states.sort_values("id")
        ids, values, degree = order["id"].to_numpy(), order["value"].to_numpy(float), order["d_out"].to_numpy(float)
        for t in tiles.itertuples(index=False):
            old = values[np.searchsorted(ids, np.arange(t.v_lo, t.v_hi))]
            row, col = np.asarray(t.row), np.asarray(t.col, np.int64)
            val = None if t.val is None else np.asarray(t.val)
            new = gather_tile(program, n, t.v_lo, row, col, val, old, lambda c: values[np.searchsorted(ids, c)], lambda c: degree[np.searchsorted(ids, c)])
            flags = np_changed(new, old, tol)
            out.append(pd.DataFrame({"id": np.arange(t.v_lo, t.v_hi)[flags], "new": new[flags]}))
        return pd.concat(out) if out else pd.DataFrame({"id": np.zeros(0, np.int64), "new": np.zeros(0)})

    log, done, active = [], 0, None
    while stop.max_supersteps is None or done < stop.max_supersteps:
        began, tiles = time.time(), placed
        if done or not program.apply_without_input:
            moved = state.filter("changed" if done else F.col("id") == F.lit(program.start)).select(F.col("id").alias("src"))
            active = materialize(tile_src.join(moved, "src", "left_semi").select("tile_id").distinct(), "active")
            tiles = tiles.join(active, "tile_id", "left_semi")
        routed = route.join(state, "id").select("tile_id", "id", "value", "d_out")
        updates = tiles.groupBy("tile_id").cogroup(routed.groupBy("tile_id")).applyInPandas(kernel, "id long, new double")
        new = state.drop("changed").join(updates, "id", "left").select("id", F.coalesce("new", "value").alias("value"), "d_out", F.col("new").isNotNull().alias("changed"))
        kept = materialize(new, "state")
        release(state)
        state, done = kept, done + 1
        moved = state.filter("changed").count()
        log.append({"superstep": done, "wall_s": time.time() - began, "changed": moved, "update_ratio": moved / max(n, 1)})
        release(active)
        active = None
        if not moved:
            break
    return Result(state.select("id", "value"), done, log)
