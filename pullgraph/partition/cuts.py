"""Partitioning of the baselines: hash edge-cut, vertex-cuts, streaming partitions.

`arithmetic` hashes are plain integer formulas that any SQL engine repeats; xxhash64 is the production choice.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graphs import Graph, degrees


def _hash(n: int, *cols: str) -> Column:
    return F.pmod(F.xxhash64(*cols), F.lit(n)).cast("long")


# Where the compared engines' cuts place an edge, over columns or arrays; ids are 0 or more.


def source_place(src, dst, d_in, servers: int):
    """A vertex and its out-edges together."""
    return src % servers


def random_place(src, dst, d_in, servers: int):
    """By a hash of both ends."""
    return (src * 31 + dst * 17) % servers


def hybrid_place(src, dst, d_in, servers: int, theta: int = 100):
    """In-edges of targets with theta in-edges or fewer together; those of larger targets by their source."""
    few = d_in <= theta
    return (F.when(few, dst).otherwise(src) if isinstance(few, Column) else np.where(few, dst, src)) % servers


def hash_edge_cut(g: Graph, servers: int) -> DataFrame:
    """(worker, src, dst, w): a vertex and its out-edges live on worker id mod servers."""
    return g.edges.select(source_place(F.col("src"), None, None, servers).cast("long").alias("worker"), "src", "dst", "w")


def random_cut(g: Graph, servers: int, arithmetic: bool = True) -> DataFrame:
    """(part, src, dst, w): each edge on a server by a hash of both ends."""
    at = random_place(F.col("src"), F.col("dst"), None, servers).cast("long") if arithmetic else _hash(servers, "src", "dst")
    return g.edges.select(at.alias("part"), "src", "dst", "w")


def grid_cut(g: Graph, servers: int, arithmetic: bool = True) -> DataFrame:
    """Edges on a grid of servers: the source picks the row, the target the column; a vertex meets one row and one column."""
    rows = max(d for d in range(1, math.isqrt(servers) + 1) if servers % d == 0)
    cols = servers // rows
    r = F.pmod("src", F.lit(rows)) if arithmetic else F.pmod(F.xxhash64("src"), F.lit(rows))
    c = F.pmod("dst", F.lit(cols)) if arithmetic else F.pmod(F.xxhash64("dst"), F.lit(cols))
    return g.edges.select((r * cols + c).cast("long").alias("part"), "src", "dst", "w")


def degree_cut(g: Graph, servers: int) -> DataFrame:
    """Each edge goes by its end of smaller degree, so that few vertices are mirrored often."""
    d = degrees(g).select("id", (F.col("d_in") + F.col("d_out")).alias("d"))
    e = g.edges.join(d.select(F.col("id").alias("src"), F.col("d").alias("ds")), "src").join(d.select(F.col("id").alias("dst"), F.col("d").alias("dd")), "dst")
    low = F.when((F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") <= F.col("dst"))), F.col("src")).otherwise(F.col("dst"))
    return e.select(F.pmod(low, F.lit(servers)).cast("long").alias("part"), "src", "dst", "w")


def hybrid_cut(g: Graph, servers: int, theta: int = 100, deg: DataFrame | None = None) -> DataFrame:
    """In-edges of targets with theta in-edges or fewer stay together; those of larger targets go by their source.  deg: the
    degrees, if they are there already."""
    d = (degrees(g) if deg is None else deg).select(F.col("id").alias("dst"), "d_in")
    at = hybrid_place(F.col("src"), F.col("dst"), F.col("d_in"), servers, theta)
    return g.edges.join(d, "dst").select(at.cast("long").alias("part"), "src", "dst", "w")


def refined_hybrid_cut(g: Graph, servers: int, theta: int = 100) -> DataFrame:
    """Approximation of a greedy hybrid cut: a small target moves, in one round, to the part where most of its sources are.

    Sources are placed by id.  Parts are weighed by the edges they would have without the round, so that of parts with as
    many sources the emptier one wins; ties go to the smaller part number.
    """
    d = degrees(g).select(F.col("id").alias("dst"), "d_in")
    e = g.edges.join(d, "dst").withColumn("home", F.pmod("src", F.lit(servers)).cast("long"))
    load = e.groupBy("home").agg(F.count("*").alias("load"))  # one row per server
    votes = e.filter(F.col("d_in") <= theta).groupBy("dst", "home").count().join(F.broadcast(load), "home")
    best = votes.groupBy("dst").agg(F.min_by("home", F.struct(-(F.col("count") / F.col("load")), "home")).alias("best"))
    return e.join(best, "dst", "left").select(F.coalesce("best", "home").alias("part"), "src", "dst", "w")


CUTS = {"random": random_cut, "grid": grid_cut, "degree": degree_cut, "hybrid": hybrid_cut, "refined_hybrid": refined_hybrid_cut}


def replicas(cut: DataFrame) -> DataFrame:
    """(part, id, is_master): where a vertex has edges; the smallest part number holds its master."""
    ends = cut.select("part", F.explode(F.array("src", "dst")).alias("id")).distinct()
    master = ends.groupBy("id").agg(F.min("part").alias("master"))
    return ends.join(master, "id").select("part", "id", (F.col("part") == F.col("master")).alias("is_master"))


def streaming_partitions(g: Graph, parts: int, servers: int) -> DataFrame:
    """(part, server, src, dst, w): unsorted out-edges by source partition; data lie on servers without regard to parts."""
    return g.edges.select(F.pmod("src", F.lit(parts)).cast("long").alias("part"), F.pmod(F.xxhash64("src", "dst"), F.lit(servers)).cast("long").alias("server"), "src", "dst", "w")
