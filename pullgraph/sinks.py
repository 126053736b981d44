"""Writers of tiles, degrees and results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .partition.tiles import Prepared, assign_servers


def save_tiles(prep: Prepared, path: str, servers: int = 9, compression: str = "zstd") -> None:
    """Tiles by server, sorted by tile, with degrees, boundaries, edges and a description; reused by any program."""
    spark = prep.tiles.sparkSession
    placed = assign_servers(prep.tiles, servers)
    placed.repartition(servers, "server_id").sortWithinPartitions("server_id", "tile_id").write.partitionBy("server_id").option("compression", compression).mode("overwrite").parquet(f"{path}/tiles")
    prep.degrees.write.mode("overwrite").parquet(f"{path}/degrees")
    prep.splitter.write.mode("overwrite").parquet(f"{path}/splitter")
    prep.graph.edges.write.mode("overwrite").parquet(f"{path}/edges")
    meta = [(prep.graph.name, prep.graph.n_vertices, prep.n_tiles, prep.weighted, prep.tile_edges)]
    spark.createDataFrame(meta, "name string, n_vertices long, n_tiles long, weighted boolean, tile_edges long").coalesce(1).write.mode("overwrite").json(f"{path}/meta")


def save_values(values: DataFrame, path: str, fmt: str = "parquet", unreached: str = "inf") -> None:
    """(id, value) as parquet, csv or json; infinite values kept, made null, or dropped."""
    far = F.abs("value") == F.lit(float("inf"))
    if unreached == "drop":
        values = values.filter(~far)
    elif unreached == "null":
        values = values.withColumn("value", F.when(~far, F.col("value")))
    values.write.mode("overwrite").format(fmt).save(path)


def save_bucketed(edges: DataFrame, table: str, buckets: int, key: str = "dst") -> None:
    """Edges as a table bucketed and sorted by one end, so that joins and aggregations on it need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
