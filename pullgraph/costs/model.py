"""Analytic cost and memory models: plain formulas, and the same as tables."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of a vertex state with its message when replicated everywhere, and of one with its id on demand.
BYTES_ALL, BYTES_ON_DEMAND = 20, 24
#: Vertices, edges, average degree of the four published graphs.
PUBLISHED = (("D1", 42_000_000, 1_500_000_000, 35.3), ("D2", 134_000_000, 5_500_000_000, 41.2), ("D3", 788_000_000, 47_600_000_000, 60.4), ("D4", 1_100_000_000, 91_800_000_000, 85.7))
#: Published cluster memory in GB, PageRank on D2 with 9 servers.
MEMORY_GB = (("msg_hadoop", 795.0), ("gas_dataflow", 685.0), ("gas_vcut", 357.0), ("gas_hybrid", 511.0), ("msg_mem", 281.0), ("msg_disk", 73.0), ("edge_stream", 26.0))


def expected_od(n_v: int, d_avg: float, servers: int) -> float:
    """Vertices a server meets on demand: expected distinct sources of its tiles, and its own targets."""
    return (1 - (1 - d_avg / n_v) ** (n_v / servers)) * n_v + n_v / servers


def expected_od_limit(n_v: int, d_avg: float, servers: int) -> float:
    """The same for very large graphs; an upper bound that can exceed n_v."""
    return (1 - math.exp(-d_avg / servers)) * n_v + n_v / servers


def m_aa(n_v: int, tile_bytes: float = 0.0, workers: int = 0, vertex_bytes: int = BYTES_ALL) -> float:
    """Bytes per server with full replication."""
    return vertex_bytes * n_v + tile_bytes * workers


def m_od(n_v: int, d_avg: float, servers: int, tile_bytes: float = 0.0, workers: int = 0, vertex_bytes: int = BYTES_ON_DEMAND, capped: bool = False) -> float:
    """Bytes per server on demand."""
    held = expected_od_limit(n_v, d_avg, servers)
    return vertex_bytes * (min(held, n_v) if capped else held) + tile_bytes * workers


def choose_replication(n_v: int, d_avg: float, servers: int) -> str:
    return "all" if m_aa(n_v) <= m_od(n_v, d_avg, servers) else "on_demand"


def crossover(d_avg: float, n_v: int = 1_000_000, most: int = 10_000) -> int | None:
    """The first number of servers at which on demand is cheaper."""
    return next((n for n in range(1, most) if choose_replication(n_v, d_avg, n) == "on_demand"), None)


def eta(d_avg: float, workers: int) -> float:
    """Expected ratio of combined to raw messages with `workers` combining workers."""
    return (1 - math.exp(-d_avg / workers)) * workers / d_avg


def load_rate(workers: int, mb_per_s: float, disk_mb_per_s: float = 310.0) -> dict[str, float]:
    """Tile loading: decoding by all workers against reading from disk, MB/s."""
    return {"decode_mb_s": workers * mb_per_s, "disk_mb_s": disk_mb_per_s, "ratio": workers * mb_per_s / disk_mb_per_s}


def explosion(memory: float, input_size: float) -> float:
    return memory / input_size


#: Per superstep, what each system holds and moves; counts of values.
COSTS = ("ram_vertex", "ram_edge", "ram_msg", "network", "disk_read", "disk_write")


def cost_rows(n_v: float, n_e: float, servers: int, tiles: int, replication: float, combine: float, beta: float) -> list[tuple]:
    """(system, costs in the order of COSTS) of one PageRank superstep."""
    v, e, n, p, m, h = float(n_v), float(n_e), servers, tiles, replication, combine
    return [
        ("msg_mem", v, e, h * e + v, h * e, 0.0, 0.0),
        ("gas_vcut", m * v, 2 * e, m * v, 2 * m * v, 0.0, 0.0),
        ("msg_disk", v, 1.0, 1.0, h * e, 2 * e, e),
        ("edge_stream", n * v / p, 1.0, 1.0, 3 * e + 3 * v, 2 * e + 2 * v, e + v),
        ("pull", n * v, n * e / p, n * v, n * v, beta * e, 0.0),
    ]


def cost_table(spark: SparkSession, n_v: int, n_e: int, servers: int, tiles: int, replication: float, combine: float, beta: float) -> DataFrame:
    return spark.createDataFrame(cost_rows(n_v, n_e, servers, tiles, replication, combine, beta), "system string, " + ", ".join(f"{c} double" for c in COSTS))


def od_column(n_v: Column, d_avg: Column, servers: Column) -> Column:
    return (F.lit(1.0) - F.exp(-d_avg / servers)) * n_v + n_v / servers


def replication_sweep(graphs: DataFrame, most: int = 64, workers: int = 0) -> DataFrame:
    """Memory per server of both policies for 1..most servers; graphs (graph, n_v, d_avg), a few rows.

    With workers, graphs also has tile_b, and a server holds a tile of that size for each worker.
    """
    n = graphs.sparkSession.range(1, most + 1).select(F.col("id").alias("servers"))
    rows = graphs.crossJoin(n)
    held = F.col("tile_b") * F.lit(workers) if workers else F.lit(0)
    aa = F.col("n_v") * F.lit(float(BYTES_ALL)) + held
    od = od_column(F.col("n_v"), F.col("d_avg"), F.col("servers")) * F.lit(float(BYTES_ON_DEMAND)) + held
    return rows.select("graph", "servers", F.round(aa, 0).cast("long").alias("aa_bytes"), F.round(od, 0).cast("long").alias("od_bytes"), F.when(aa <= od, F.lit("all")).otherwise(F.lit("on_demand")).alias("cheaper"))


def od_expected(graphs: DataFrame, most: int = 64) -> DataFrame:
    """Share of the vertices that a server meets on demand, for the graph's own size and in the limit, 1..most servers."""
    n = graphs.sparkSession.range(1, most + 1).select(F.col("id").alias("servers"))
    v, d, k = F.col("n_v"), F.col("d_avg"), F.col("servers")
    finite = F.lit(1.0) - F.pow(F.lit(1.0) - d / v, v / k) + F.lit(1.0) / k
    return graphs.crossJoin(n).select("graph", "servers", F.round(finite, 5).alias("finite"), F.round(od_column(v, d, k) / v, 5).alias("limit"))


def published(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(g, float(v), d) for g, v, _, d in PUBLISHED], "graph string, n_v double, d_avg double")
