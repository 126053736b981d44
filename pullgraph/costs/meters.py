"""Measured counterparts of the models: what partitions, messages, caches and codecs really cost."""

from __future__ import annotations

import time
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..engine.cache import tile_bytes
from ..engine.exchange import CODECS, SPARSITY, compress, decompress
from ..graphs import Graph
from ..partition.cuts import replicas
from ..session import ship


def log_frame(spark: SparkSession, log: list[dict], **labels: str) -> DataFrame:
    """A step log as a table, one row per superstep, with label columns; what no superstep measured is left out."""
    import pandas as pd

    return spark.createDataFrame(pd.DataFrame([{**labels, **e} for e in log]).dropna(axis=1, how="all"))


def mean_step_time(log: list[dict], skip: int = 1) -> float:
    """Mean seconds per superstep after the first `skip`."""
    kept = [e["wall_s"] for e in log[skip:]]
    return sum(kept) / len(kept) if kept else float("nan")


def speedup(base: list[dict], ours: list[dict], skip: int = 1) -> float:
    return mean_step_time(base, skip) / mean_step_time(ours, skip)


def replication_factor(cut: DataFrame, n_vertices: int) -> DataFrame:
    """One row: replicas, vertices, replicas per vertex."""
    return replicas(cut).agg(F.count("*").alias("n_replicas")).select("n_replicas", F.lit(n_vertices).cast("long").alias("n_vertices"), F.round(F.col("n_replicas") / F.lit(n_vertices), 6).alias("factor"))


def eta(g: Graph, workers: int) -> DataFrame:
    """One row: messages before and after combining within workers (source id mod workers), and their ratio."""
    pairs = g.edges.groupBy(F.pmod("src", F.lit(workers)).alias("worker"), "dst").agg(F.count("*").alias("n"))
    return pairs.agg(F.sum("n").cast("long").alias("raw"), F.count("*").alias("combined"), F.round(F.count("*") / F.sum("n"), 6).alias("eta"))


def edgecut_balance(g: Graph, servers: int) -> DataFrame:
    """Edges per server of a hash edge-cut."""
    return g.edges.groupBy(F.pmod("src", F.lit(servers)).cast("long").alias("server")).agg(F.count("*").alias("n_edges"))


def balance(splitter: DataFrame, tile_edges: int) -> DataFrame:
    """One row: number of tiles, their sizes, largest and smallest against the size asked for."""
    return splitter.agg(
        F.count("*").alias("n_tiles"), F.min("n_edges").alias("min_edges"), F.max("n_edges").alias("max_edges"),
        F.round(F.avg("n_edges"), 6).alias("avg_edges"), F.round(F.stddev_pop("n_edges"), 6).alias("std_edges"),
        F.round(F.max("n_edges") / F.lit(tile_edges), 6).alias("max_ratio"), F.round(F.min("n_edges") / F.lit(tile_edges), 6).alias("min_ratio"),
    )


def od_vertices(g: Graph, splitter: DataFrame, servers: int) -> DataFrame:
    """Distinct vertices that a server's tiles touch, tiles going round the servers; targets count with their intervals."""
    tile = F.broadcast(splitter.select("tile_id", "v_lo", "v_hi"))  # one row per tile
    e = g.edges.join(tile, (F.col("dst") >= F.col("v_lo")) & (F.col("dst") < F.col("v_hi"))).select(F.pmod("tile_id", F.lit(servers)).alias("server"), F.col("src").alias("id"))
    own = g.vertices.join(tile, (F.col("id") >= F.col("v_lo")) & (F.col("id") < F.col("v_hi"))).select(F.pmod("tile_id", F.lit(servers)).alias("server"), "id")
    return e.unionByName(own).distinct().groupBy("server").agg(F.count("*").alias("n_vertices")).select(F.col("server").cast("long").alias("server"), "n_vertices")


def traffic_rows(changes: DataFrame, splitter: DataFrame, threshold: float = SPARSITY) -> DataFrame:
    """(superstep, tile_id, n, k, dense_b, sparse_b, hybrid_b, bytes_b): encoded bytes of each tile's message, the last by
    whichever encoding is shorter.

    changes (superstep, id): the vertices that changed.  A tile without changes has k = 0.
    """
    t = F.broadcast(splitter.select("tile_id", "v_lo", "v_hi"))
    k = changes.join(t, (F.col("id") >= F.col("v_lo")) & (F.col("id") < F.col("v_hi"))).groupBy("superstep", "tile_id").agg(F.count("*").alias("k"))
    steps = changes.select("superstep").distinct()
    rows = steps.crossJoin(splitter.select("tile_id", (F.col("v_hi") - F.col("v_lo")).alias("n"))).join(k, ["superstep", "tile_id"], "left").withColumn("k", F.coalesce("k", F.lit(0)))
    dense, sparse = 8 * F.col("n") + F.ceil(F.col("n") / 8), 12 * F.col("k")
    hybrid = F.when((F.col("n") - F.col("k")) / F.col("n") > threshold, sparse).otherwise(dense)
    return rows.select("superstep", "tile_id", "n", "k", dense.cast("long").alias("dense_b"), sparse.cast("long").alias("sparse_b"), hybrid.cast("long").alias("hybrid_b"), F.least(dense, sparse).cast("long").alias("bytes_b"))


def sparsity(rows: DataFrame) -> DataFrame:
    """Per superstep, least, mean and largest share of unchanged vertices over the tiles of traffic_rows()."""
    share = (F.col("n") - F.col("k")) / F.col("n")
    return rows.filter("n > 0").groupBy("superstep").agg(F.round(F.min(share), 6).alias("least"), F.round(F.avg(share), 6).alias("mean"), F.round(F.max(share), 6).alias("most"))


def traffic(log: list[dict], servers: int) -> list[dict]:
    """Network bytes per superstep: every message goes to all other servers."""
    return [{"superstep": e["superstep"], **{k: e[k] * (servers - 1) for k in ("msg_dense_b", "msg_sparse_b", "msg_hybrid_b", "msg_compressed_b")}} for e in log]


def messages(log: list[dict]) -> int:
    """Messages that were sent, where the engine counts them."""
    return sum(e["msg_count"] for e in log)


def gas_messages(cut: DataFrame) -> DataFrame:
    """One row: messages of a superstep with all vertices active, mirrors to masters and masters to mirrors."""
    mirrors = replicas(cut).filter("NOT is_master").select("part", "id")
    up = cut.select("part", F.col("dst").alias("id")).distinct().join(mirrors, ["part", "id"], "left_semi")
    return up.unionAll(mirrors).agg(F.count("*").alias("messages"))


def stored_bytes(df: DataFrame) -> int:
    """Bytes that a table takes when it is held in executors."""
    sc = df.sparkSession.sparkContext._jsc.sc()
    size = lambda: sum(i.memSize() + i.diskSize() for i in sc.getRDDStorageInfo())
    before = size()
    df.persist()
    df.count()
    out = size() - before
    df.unpersist(blocking=True)
    return out


def hit_ratio(log: list[dict]) -> float:
    loads = sum(e["tiles_loaded"] for e in log)
    return sum(e["cache_hits"] for e in log) / loads if loads else 0.0


def disk(log: list[dict]) -> int:
    """Bytes read from and written to disk."""
    return sum(e["disk_read_b"] + e["disk_write_b"] for e in log)


def skips(log: list[dict]) -> list[dict]:
    return [{k: e[k] for k in ("superstep", "tiles_total", "tiles_loaded", "tiles_skipped", "tiles_fp")} for e in log]


def codec_stats(tiles: DataFrame) -> DataFrame:
    """(codec, tiles, raw_bytes, packed_bytes, ratio, decode_mb_s): each tile packed and unpacked with each codec."""
    ship(tiles.sparkSession)

    def run(it):
        for b in it:
            out = []
            for k in range(b.num_rows):
                val = b.column(2)[k].values
                raw = tile_bytes(*(b.column(i)[k].values.to_numpy(zero_copy_only=False) for i in (0, 1)), None if val is None else val.to_numpy(zero_copy_only=False))
                for codec in CODECS:
                    packed = compress(raw, codec)
                    t = time.perf_counter_ns()
                    decompress(packed, codec)
                    out.append((codec, len(raw), len(packed), time.perf_counter_ns() - t))
            cols = list(zip(*out, strict=True)) if out else [[]] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.string(), pa.int64(), pa.int64(), pa.int64()), strict=True)], ["codec", "raw", "packed", "ns"])

    rows = tiles.select("row", "col", "val").mapInArrow(run, "codec string, raw long, packed long, ns long")
    return rows.groupBy("codec").agg(
        F.count("*").alias("tiles"), F.sum("raw").cast("long").alias("raw_bytes"), F.sum("packed").cast("long").alias("packed_bytes"),
        F.round(F.sum("raw") / F.sum("packed"), 3).alias("ratio"), F.round(F.sum("raw") / F.greatest(F.sum("ns"), F.lit(1)) * 1000, 1).alias("decode_mb_s"),
    )


def csv_bytes(g: Graph, weighted: bool = True) -> int:
    """Bytes of the edge list as text."""
    return format_sizes(g, None, weighted).filter("format = 'csv_edge_list'").first()["bytes"]


def format_sizes(g: Graph, tiles: DataFrame | None, weighted: bool = True) -> DataFrame:
    """(format, bytes): edge list as text, adjacency text, binary edges, tiles with degree arrays."""
    sign = F.length(F.col("src").cast("string")) + F.length(F.col("dst").cast("string")) + 2
    csv = g.edges.select(F.lit("csv_edge_list").alias("format"), (sign + (F.length(F.col("w").cast("string")) + 1 if weighted else 0)).alias("b"))
    lists = g.edges.groupBy("src").agg(F.sum(F.length(F.col("dst").cast("string")) + 1).alias("b")).select(F.lit("adjacency_text").alias("format"), (F.col("b") + F.length(F.col("src").cast("string")) + 1).alias("b"))
    binary = g.edges.select(F.lit("binary_edges").alias("format"), F.lit(16 if weighted else 8).alias("b"))
    parts = [csv, lists, binary]
    if tiles is not None:
        # What the engine stores: 8 bytes a number in tiles, and both degrees of every vertex.
        parts.append(tiles.select(F.lit("tiles").alias("format"), (8 * (F.size("row") + F.size("col") + F.coalesce(F.size("val"), F.lit(0))) + 16 * (F.col("v_hi") - F.col("v_lo"))).alias("b")))
    return reduce(DataFrame.unionAll, [x.select("format", F.col("b").cast("long")) for x in parts]).groupBy("format").agg(F.sum("b").cast("long").alias("bytes"))


def agree(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: largest and summed difference of two results (id, value), infinity equal to itself, and ids in one only."""
    x = a.select("id", F.col("value").alias("x")).join(b.select("id", F.col("value").alias("y")), "id", "full")
    d = F.when(F.col("x").eqNullSafe(F.col("y")), F.lit(0.0)).otherwise(F.abs(F.col("x") - F.col("y")))
    return x.agg(F.coalesce(F.max(d), F.lit(0.0)).alias("max_diff"), F.coalesce(F.sum(d), F.lit(0.0)).alias("l1_diff"), F.sum((F.col("x").isNull() | F.col("y").isNull()).cast("long")).alias("unmatched"))


def op_counts(spark: SparkSession, logs: dict[str, list[dict]]) -> DataFrame:
    """(engine, gathers, applies, scatters, messages) of the last superstep of each engine's log, as the engine counted them.

    A gather is a fold of the in-edges of a vertex in one place, so the pull engine gathers where it applies.
    """
    rows = []
    for engine, log in logs.items():
        e = log[-1]
        rows.append((engine, e["op_apply"] if engine == "pull" else e["op_gather"], e["op_apply"], e.get("op_scatter", 0), e["op_broadcast"] if engine == "pull" else e["msg_count"]))
    return spark.createDataFrame(rows, "engine string, gathers long, applies long, scatters long, messages long")


def update_trend(log: DataFrame) -> DataFrame:
    """A step log (superstep, update_ratio) with its change from the step before and its mean over five steps."""
    w = Window.orderBy("superstep")  # one row per superstep
    return log.withColumn("step_change", F.col("update_ratio") - F.lag("update_ratio").over(w)).withColumn("mean5", F.avg("update_ratio").over(w.rowsBetween(-4, 0)))
