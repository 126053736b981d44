"""The experiments, re-expressed on the derived graphs; each returns a table."""

from __future__ import annotations

import pickle
from functools import reduce
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import graphs, programs
from .baselines import arrays
from .baselines.engines import ENGINES
from .costs import meters, model
from .engine import relational, tilepath
from .engine.cache import GAMMAS, MODES, choose_mode
from .engine.program import StopRule, VertexProgram
from .graphs import Graph
from .partition import cuts, tiles
from .partition.cuts import CUTS, replicas
from .session import materialize, release

PROGRAMS = {"pagerank": programs.pagerank, "sssp": programs.sssp}


def datasets(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("trade", "skew", "word", "basket", "event", "link")) -> DataFrame:
    """Dataset table: statistics of each graph."""
    parts = [graphs.stats(graphs.build(spark, sf_dir, n)).withColumn("graph", F.lit(n)) for n in names]
    return reduce(DataFrame.unionByName, parts)


def changes(g: Graph, program: VertexProgram, steps: int | None = None) -> DataFrame:
    """(superstep, id): which vertices changed in which superstep, until none does or `steps`, if given, are done."""
    n = g.n_vertices
    rows = materialize(relational.augmented(g, program), "augmented")
    state = g.vertices.select("id", program.init(F.col("id"), n).alias("value"), F.lit(True).alias("changed"))
    out = []
    for k in count(1) if steps is None else range(1, steps + 1):
        state = materialize(relational.step(rows, state, program, n), "state")
        moved = state.filter("changed").select(F.lit(k).alias("superstep"), "id")
        if not moved.limit(1).count():
            break
        out.append(moved)
    return reduce(DataFrame.union, out) if out else g.spark.createDataFrame([], "superstep int, id long")


#: Engines of the published comparison, and those on general-purpose stacks.
COMPARED = ("pull", "msg_mem", "gas_vcut", "gas_hybrid", "msg_disk", "edge_stream")
EVERY_ENGINE = (*COMPARED, "msg_hadoop", "triplets")
#: Edges up to which the baselines' layouts stay on the shared disk for the next program, some 16 bytes each and layout.
KEPT_EDGES = 1 << 24


def _run(engine: str, prep: tiles.Prepared, program: VertexProgram, stop: StopRule, servers: int) -> relational.Result:
    if engine == "pull":
        cfg = tilepath.EngineConfig(servers=servers, skip="bloom" if program.idempotent else "none", cache_mode=0)
        return tilepath.run(prep, program, stop, cfg)
    if engine in arrays.ENGINE_CUT and arrays.fits(prep.graph):
        return arrays.run(engine, prep, program, stop, servers)
    return ENGINES[engine](prep.graph, program, stop, servers=servers)


def compare_engines(spark: SparkSession, sf_dir: str, program: str, names=("trade",), engines: tuple[str, ...] = EVERY_ENGINE, servers: tuple[int, ...] = (1, 3, 6, 9), steps: int | None = 21, prepare=None) -> DataFrame:
    """Per graph, engine and number of servers: supersteps, mean seconds of those after the first, how many times as long as
    pull on as many servers, and the largest difference from pull's result on one server."""
    prepare = prepare or (lambda name: tiles.prepare(graphs.build(spark, sf_dir, name), n_tiles=32))
    out = []
    for name in names:
        prep, p, stop = prepare(name), PROGRAMS[program](), StopRule(steps)
        first = None
        for n in servers:
            ours = _run("pull", prep, p, stop, n)
            if prep.graph.n_edges > KEPT_EDGES:
                tilepath.give_up_cache(prep)
            first = first or ours
            for e in engines:
                r = ours if e == "pull" else _run(e, prep, p, stop, n)
                diff = meters.agree(r.values, first.values).first()["max_diff"]
                out.append((name, program, e, n, r.supersteps, meters.mean_step_time(r.log), meters.speedup(r.log, ours.log), float(diff)))
            if prep.graph.n_edges > KEPT_EDGES:
                arrays.drop_layouts(prep, but="blocks-stream" if n != servers[-1] else "")
    return spark.createDataFrame(pd.DataFrame(out, columns=["graph", "program", "engine", "servers", "supersteps", "mean_step_s", "times_pull", "max_diff"]))


def messages_by_servers(g: Graph, servers: tuple[int, ...] = (1, 3, 6, 9)) -> DataFrame:
    """(engine, servers, messages) of a PageRank superstep in which every vertex changes, counted on each engine's layout."""
    n_e, parts = g.n_edges, []
    for n in servers:
        one = lambda df, e, n=n: df.select(F.lit(e).alias("engine"), F.lit(n).alias("servers"), F.col("messages").cast("long").alias("messages"))
        fixed = g.spark.createDataFrame([("pull", n, g.n_vertices * (n - 1)), ("msg_disk", n, n_e), ("edge_stream", n, n_e)], "engine string, servers int, messages long")
        parts += [fixed, one(meters.eta(g, n).withColumnRenamed("combined", "messages"), "msg_mem")]
        parts += [one(meters.gas_messages(CUTS[cut](g, n)), e) for e, cut in (("gas_vcut", "random"), ("gas_hybrid", "hybrid"))]
    return reduce(DataFrame.unionAll, parts)


def by_engine(results: DataFrame) -> DataFrame:
    """The comparison laid out with one column per engine."""
    return results.groupBy("graph", "program", "servers").pivot("engine").agg(F.first("mean_step_s"))


def report(results: DataFrame) -> DataFrame:
    """Mean step time over every combination of engine, graph and servers, and their totals."""
    return results.cube("engine", "graph", "servers").agg(F.avg("mean_step_s").alias("mean_step_s"), F.count("*").alias("runs"))


def costs(spark: SparkSession, g: Graph, servers: int = 9, n_tiles: int = 32, cut: str = "random", beta: float = 0.0) -> DataFrame:
    """Cost table of a graph with measured combining ratio and replication factor; whole numbers."""
    n_v, n_e = g.n_vertices, g.n_edges
    combine = meters.eta(g, servers).first()["eta"]
    m = meters.replication_factor(CUTS[cut](g, servers), n_v).first()["factor"]
    t = model.cost_table(spark, n_v, n_e, servers, n_tiles, m, combine, beta)
    return t.select("system", *(F.round(c, 0).cast("long").alias(c) for c in model.COSTS))


def memory(counted: dict[str, tuple[DataFrame, int]]) -> DataFrame:
    """(engine, memory_b, input_b, explosion): memory of the engines over several graphs and how many times their edge lists
    that is; counted: by graph, memory_counted() and the bytes of the edge list as text."""
    rows = reduce(DataFrame.unionByName, [m.select("engine", F.col("memory_b").cast("long").alias("m"), F.lit(b).cast("long").alias("b")) for m, b in counted.values()])
    return rows.groupBy("engine").agg(F.sum("m").alias("memory_b"), F.sum("b").alias("input_b")).withColumn("explosion", F.round(F.col("memory_b") / F.col("input_b"), 2))


def memory_counted(spark: SparkSession, g: Graph, servers: int = 9, n_tiles: int = 32) -> DataFrame:
    """(engine, memory_b, explosion): what each engine holds in a superstep by the cost table with the graph's own combining
    ratio and replication factor, at 24 bytes a vertex state, 16 an edge and 16 a message, and its ratio to the edge list."""
    text = meters.csv_bytes(g)
    held = 24 * F.col("ram_vertex") + 16 * F.col("ram_edge") + 16 * F.col("ram_msg")
    return costs(spark, g, servers, n_tiles).select(F.col("system").alias("engine"), held.alias("memory_b"), F.round(held / F.lit(text), 4).alias("explosion"))


def memory_measured(spark: SparkSession, prep: tiles.Prepared, servers: int = 9, workers: int = 24) -> DataFrame:
    """(engine, program, vertex_b, edge_b): bytes really taken, over all servers.

    pull: the arrays that are broadcast to every server and the tiles its workers hold, without a cache; the others: the
    tables that their layouts keep in executors.
    """
    g, n = prep.graph, prep.graph.n_vertices
    out = []
    for name in ("pagerank", "sssp"):
        arrays = 1 + len(PROGRAMS[name]().components)
        sent = sum(len(pickle.dumps(np.zeros(n), protocol=5)) for _ in range(arrays)) + 8 * n  # values, components, messages
        out.append(("pull", name, sent * servers, prep.largest_tile * min(workers * servers, prep.n_tiles)))
    state = graphs.degrees(g).withColumn("value", F.lit(0.0)).select("id", "value", "d_out")
    one_state = meters.stored_bytes(state)
    for e, edges, per_vertex in (("msg_mem", cuts.hash_edge_cut(g, servers), None), ("gas_vcut", CUTS["random"](g, servers), "random"), ("gas_hybrid", CUTS["hybrid"](g, servers), "hybrid")):
        places = meters.stored_bytes(replicas(CUTS[per_vertex](g, servers)).join(state, "id")) if per_vertex else one_state
        out.append((e, "pagerank", places, meters.stored_bytes(edges)))
    return spark.createDataFrame(out, "engine string, program string, vertex_b long, edge_b long")


def ops(spark: SparkSession, prep: tiles.Prepared, servers: int = 9) -> DataFrame:
    """Counted operations of a PageRank superstep: pull and the vertex-cut engines."""
    p, one = PROGRAMS["pagerank"](), StopRule(1)
    logs = {"pull": tilepath.run(prep, p, one, tilepath.EngineConfig(servers=servers)).log}
    logs |= {e: ENGINES[e](prep.graph, p, one, servers=servers, count=True).log for e in ("gas_vcut", "gas_hybrid")}
    return meters.op_counts(spark, logs)


def replication(prep: tiles.Prepared, most: int = 64, workers: int = 24) -> DataFrame:
    """Memory per server of both replication policies for a graph, with a tile for each worker."""
    g = prep.graph
    own = [(g.name, float(g.n_vertices), g.n_edges / max(g.n_vertices, 1), prep.largest_tile)]
    return model.replication_sweep(g.spark.createDataFrame(own, "graph string, n_v double, d_avg double, tile_b long"), most, workers)


def sizes(named: dict[str, Graph]) -> DataFrame:
    """(graph, n_v, d_avg): what the memory models need of graphs with vertices."""
    parts = [g.edges.agg(F.lit(n).alias("graph"), F.lit(float(g.n_vertices)).alias("n_v"), (F.count("*") / F.lit(float(g.n_vertices))).alias("d_avg")) for n, g in named.items() if g.n_vertices]
    return reduce(DataFrame.unionByName, parts)


def crossovers(own: DataFrame, most: int = 10_000) -> DataFrame:
    """First number of servers, of less than `most`, at which on demand needs less memory, per graph of sizes(); null if none."""
    n = own.sparkSession.range(1, most).select(F.col("id").alias("n"))
    all_b, od_b = F.lit(float(model.BYTES_ALL)) * F.col("n_v"), F.lit(float(model.BYTES_ON_DEMAND)) * model.od_column(F.col("n_v"), F.col("d_avg"), F.col("n"))
    return own.crossJoin(n).groupBy("graph").agg(F.min(F.when(all_b > od_b, F.col("n"))).cast("int").alias("servers"))


SIZES = (4, 16, 64, 256)


def tile_sizes(spark: SparkSession, g: Graph, parts: tuple[int, ...] = SIZES) -> DataFrame:
    """Balance of greedy tiles for several sizes."""
    deg = materialize(graphs.degrees(g), "degrees")
    n_e, out = g.n_edges, []
    for p in parts:
        s = max(1, -(-n_e // p))
        out.append(meters.balance(tiles.split_greedy(deg, s), s).withColumn("asked", F.lit(p)))
    return reduce(DataFrame.unionByName, out)


def tile_size_times(spark: SparkSession, g: Graph, parts: tuple[int, ...] = SIZES, steps: int = 4, workers: int = 24) -> DataFrame:
    """Step time of PageRank, tiles, and memory of a server's workers for several tile sizes.

    Few tiles of a large graph are hundreds of MB each, so they are kept in rows; the files of a size go before the next.
    """
    g, out = g.stored(), []
    deg = materialize(graphs.degrees(g), "degrees")
    for p in parts:
        prep = tiles.prepare(g, n_tiles=p, row_edges=tiles.ROW_EDGES, deg=deg)
        r = tilepath.run(prep, PROGRAMS["pagerank"](), StopRule(steps), tilepath.EngineConfig(cache_mode=1))
        out.append((p, prep.n_tiles, prep.largest_tile * workers, meters.mean_step_time(r.log)))
        prep.drop()
    release(deg)
    return spark.createDataFrame(out, "asked int, n_tiles long, workers_b long, mean_step_s double")


def codecs(spark: SparkSession, prepared: dict[str, tiles.Prepared]) -> DataFrame:
    """Compression ratio and speed of each codec on each graph's tiles without weights, as the published graphs have none."""
    bare = lambda p: p.tiles.withColumn("val", F.lit(None).cast("array<double>"))
    return reduce(DataFrame.unionByName, [meters.codec_stats(bare(p)).withColumn("graph", F.lit(n)) for n, p in prepared.items()])


def cache_modes(spark: SparkSession, prep: tiles.Prepared, capacities: tuple[int, ...], servers: tuple[int, ...] = (1, 3, 9), steps: int = 4, modes: tuple[int, ...] = (0, 1, 2, 3, 4)) -> DataFrame:
    """Hit ratio, hits, loads, bytes read from disk and step time per cache mode (0: chosen), capacity and servers."""
    out = []
    for n in servers:
        for c in capacities:
            for m in modes:
                r = tilepath.run(prep, programs.pagerank(), StopRule(steps), tilepath.EngineConfig(servers=n, cache_mode=m, cache_capacity=c))
                loads, hits = (sum(e[k] for e in r.log) for k in ("tiles_loaded", "cache_hits"))
                out.append((n, c, m, meters.hit_ratio(r.log), hits, loads, meters.disk(r.log), meters.mean_step_time(r.log)))
    return spark.createDataFrame(out, "servers int, capacity long, mode int, hit_ratio double, hits long, loads long, disk_read_b long, mean_step_s double")


def cache_study(spark: SparkSession, prep: tiles.Prepared, share: float = 0.5, steps: int = 4) -> DataFrame:
    """The cache modes where a server holds `share` of a third of the tiles: on three servers raw tiles do not fit and well
    compressed ones do, on nine all fit."""
    return cache_modes(spark, prep, (int(share * tilepath.raw_bytes(prep) / 3),), steps=steps)


def cache_choice(prep: tiles.Prepared, capacities: tuple[int, ...] = (100, 60, 30, 20, 19)) -> DataFrame:
    """Mode chosen for a graph's tiles per capacity, given in hundredths of their bytes, with the highest compression as the
    fallback, and with mode 3 as the other reading."""
    total = tilepath.raw_bytes(prep)
    rows = [(total * c / 100, choose_mode(total, total * c / 100), choose_mode(total, total * c / 100, GAMMAS, 3)) for c in capacities]
    return prep.tiles.sparkSession.createDataFrame(rows, "capacity double, mode int, mode_other_fallback int")


def communication(spark: SparkSession, prep: tiles.Prepared, steps: int = 200, servers: int = 9) -> DataFrame:
    """Per PageRank superstep: update ratio, and network bytes of dense, sparse, hybrid and compressed hybrid messages."""
    r = tilepath.run(prep, programs.pagerank(), StopRule(steps), tilepath.EngineConfig(servers=servers, cache_mode=0))
    ratio = pd.DataFrame(r.log)[["superstep", "update_ratio"]]
    return spark.createDataFrame(ratio.merge(pd.DataFrame(meters.traffic(r.log, servers)), on="superstep"))


def message_codecs(spark: SparkSession, prep: tiles.Prepared, steps: int = 50, servers: int = 9, codecs: tuple[str, ...] = ("none", "snappy", "zlib1", "zlib3")) -> DataFrame:
    """(codec, sent_b, reduction, mean_step_s) of hybrid messages over the first supersteps of PageRank."""
    out = []
    for codec in codecs:
        r = tilepath.run(prep, programs.pagerank(), StopRule(steps), tilepath.EngineConfig(servers=servers, codec=codec, cache_mode=0))
        sent = sum(e["msg_compressed_b"] for e in meters.traffic(r.log, servers))
        plain = sum(e["msg_hybrid_b"] for e in meters.traffic(r.log, servers))
        out.append((codec, sent, plain / max(sent, 1), meters.mean_step_time(r.log)))
    return spark.createDataFrame(out, "codec string, sent_b long, reduction double, mean_step_s double")


def skip_effect(spark: SparkSession, prep: tiles.Prepared, mode: str = "bloom", audit: bool = True) -> DataFrame:
    """Per superstep of shortest paths: tiles, those loaded and skipped, and those loaded in vain."""
    r = tilepath.run(prep, programs.sssp(0), StopRule(), tilepath.EngineConfig(skip=mode, audit=audit))
    return spark.createDataFrame(pd.DataFrame(meters.skips(r.log)).astype("int64"))


def single_node(prep: tiles.Prepared, steps: int = 21) -> relational.Result:
    """The pull engine on one logical server: nothing goes over the network, all tiles belong to it."""
    return tilepath.run(prep, programs.pagerank(), StopRule(steps), tilepath.EngineConfig(servers=1, cache_mode=0))


def load_rates(prep: tiles.Prepared) -> DataFrame:
    """Decode rate of all workers of a server against its disk, from the published codec speeds, and the milliseconds that
    a graph's tiles take at either rate."""
    speeds, b = {"snappy": 890.0, "zlib1": 62.0, "zlib3": 56.0}, tilepath.raw_bytes(prep)
    rates = [(c, *model.load_rate(22, s).values()) for c, s in speeds.items()]
    return prep.tiles.sparkSession.createDataFrame([(c, d, k, r, b, round(b / d / 1000, 3), round(b / k / 1000, 3)) for c, d, k, r in rates], "codec string, decode_mb_s double, disk_mb_s double, ratio double, tile_b long, decode_ms double, disk_ms double")


__all__ = [n for n in dir() if not n.startswith("_") and n not in {"annotations", "count", "reduce", "pickle", "np", "pd", "MODES"}]
