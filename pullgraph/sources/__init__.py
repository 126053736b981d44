"""Readers of edge lists, tables and saved tiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graphs import EDGE_SCHEMA, Graph
from ..partition.tiles import TILE, Prepared


def read_edge_list(spark: SparkSession, path: str, sep: str = ",", weighted: bool = True, header: bool = False) -> DataFrame:
    """(src, dst, w) from delimited text with an explicit schema; an unweighted list gets weight 1.  Lines that do not
    parse are dropped by the reader's mode."""
    schema = EDGE_SCHEMA if weighted else "src long, dst long"
    rows = spark.read.schema(schema).csv(path, sep=sep, header=header, mode="DROPMALFORMED", comment="#")
    return rows if weighted else rows.withColumn("w", F.lit(1.0))


def read_json_edges(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(EDGE_SCHEMA).json(path).select("src", "dst", F.coalesce("w", F.lit(1.0)).alias("w"))


def graph_of(edges: DataFrame, n_vertices: int | None = None, name: str = "graph") -> Graph:
    """A graph over dense ids; without a number of vertices, the largest id decides."""
    if n_vertices is None:
        n_vertices = (edges.agg(F.max(F.greatest("src", "dst"))).first()[0] or -1) + 1
    return Graph(edges.select("src", "dst", "w"), n_vertices, name)


def load_tiles(spark: SparkSession, path: str) -> Prepared:
    """What sinks.save_tiles() wrote."""
    meta = spark.read.json(f"{path}/meta").first()
    deg, splitter = spark.read.parquet(f"{path}/degrees"), spark.read.parquet(f"{path}/splitter")
    tiles = spark.read.schema(TILE + ", server_id int").parquet(f"{path}/tiles").drop("server_id")
    g = Graph(spark.read.schema(EDGE_SCHEMA).parquet(f"{path}/edges"), meta["n_vertices"], meta["name"])
    return Prepared(g, deg, splitter, tiles, meta["n_tiles"], meta["weighted"], meta["tile_edges"])
