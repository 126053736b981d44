"""Registered graph queries: (spark, sf_dir) -> DataFrame, by name.

Prepared graphs are kept per session and folder, so that queries over one graph prepare it once.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import graphs, programs, sinks, sources, workloads
from .baselines.engines import ENGINES
from .costs import meters, model
from .engine import relational, tilepath
from .engine.cache import plan_cache
from .engine.program import StopRule
from .graphs import Graph
from .partition import tiles
from .partition.cuts import CUTS
from .session import scratch_root

GRAPHS = ("trade", "skew", "word", "basket", "event", "link")
#: The four graphs of the engine comparisons.
COMPARED = ("trade", "skew", "word", "basket")
#: PageRank supersteps of all engines, those of the timed sweeps over servers, and the number of tiles asked for.
STEPS, TIMED_STEPS, TILES = 21, 4, 32
SERVERS, WORKERS = 9, 24

_KEPT: dict[tuple[str, str, str, str], object] = {}
Query = Callable[[SparkSession, str], DataFrame]


def _keep(kind: str, spark: SparkSession, sf_dir: str, name: str, make: Callable[[], object]):
    key = (kind, spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return _keep("graph", spark, sf_dir, name, lambda: graphs.build(spark, sf_dir, name).stored())


def prepared(spark: SparkSession, sf_dir: str, name: str) -> tiles.Prepared:
    return _keep("tiles", spark, sf_dir, name, lambda: tiles.prepare(graph(spark, sf_dir, name), n_tiles=TILES))


def in_rows(spark: SparkSession, sf_dir: str, name: str) -> tiles.Prepared:
    """The same tiles for engines: those of a large graph are kept in rows, of which a worker has one at a time."""
    g = graph(spark, sf_dir, name)
    if g.n_edges <= TILES * tiles.ROW_EDGES:
        return prepared(spark, sf_dir, name)
    return _keep("rows", spark, sf_dir, name, lambda: tiles.prepare(g, n_tiles=TILES, row_edges=tiles.ROW_EDGES))


def ranks(values: DataFrame) -> DataFrame:
    return values.select("id", F.round(F.col("value") * 1e9).cast("long").alias("rank_e9"))


def distances(values: DataFrame) -> DataFrame:
    return values.filter(F.col("value") < float("inf")).select("id", F.col("value").cast("long").alias("distance"))


def _changed(spark: SparkSession, d: str, g: str) -> DataFrame:
    return _keep("changes", spark, d, g, lambda: workloads.changes(graph(spark, d, g), programs.sssp(0)))


def _skips(spark: SparkSession, d: str, g: str, mode: str) -> DataFrame:
    return _keep(f"skips-{mode}", spark, d, g, lambda: workloads.skip_effect(spark, prepared(spark, d, g), mode))


def _active(spark: SparkSession, d: str, g: str, mode: str) -> DataFrame:
    return _skips(spark, d, g, mode).filter("tiles_loaded > 0").select("superstep", F.col("tiles_loaded").alias("tiles"))


def _traffic(spark: SparkSession, d: str, g: str, mode: str) -> DataFrame:
    rows = meters.traffic_rows(_changed(spark, d, g), prepared(spark, d, g).splitter)
    return rows.groupBy(F.col("superstep").cast("long").alias("superstep")).agg(F.sum(f"{mode}_b").cast("long").alias("bytes"))


def _compared(spark: SparkSession, d: str, g: str, program: str) -> DataFrame:
    """The engines' runs over servers, once for the query of times and that of agreement."""
    servers = (1, SERVERS) if program == "pagerank" else (SERVERS,)
    make = lambda: workloads.compare_engines(spark, d, program, (g,), workloads.COMPARED, servers, TIMED_STEPS if program == "pagerank" else None, lambda name: in_rows(spark, d, name))
    return _keep(f"compared-{program}", spark, d, g, make)


def _agreement(spark: SparkSession, d: str, g: str) -> DataFrame:
    """Whether each engine came to pull's result, to 12 digits, on each number of servers."""
    both = _compared(spark, d, g, "pagerank").unionAll(_compared(spark, d, g, "sssp"))
    return both.select("program", "engine", F.col("servers").cast("long").alias("servers"), (F.col("max_diff") < 1e-12).alias("agrees"))


def _sizes(spark: SparkSession, d: str) -> DataFrame:
    return workloads.sizes({g: graph(spark, d, g) for g in COMPARED})


def _communication(spark: SparkSession, d: str, g: str) -> DataFrame:
    return _keep("communication", spark, d, g, lambda: workloads.communication(spark, prepared(spark, d, g)))


def _raw_cache(spark: SparkSession, d: str, g: str) -> DataFrame:
    """Hits of a cache of raw tiles that holds a third of the tiles, on one, three and nine servers."""
    prep = prepared(spark, d, g)
    third = tilepath.raw_bytes(prep) // 3
    return workloads.cache_modes(spark, prep, (third,), (1, 3, 9), TIMED_STEPS, (1,)).select("servers", "capacity", "hits", "loads", "disk_read_b")


def _reloaded(spark: SparkSession, d: str, g: str) -> DataFrame:
    path = f"{scratch_root(spark)}/saved-{g}-{uuid.uuid4().hex}"
    sinks.save_tiles(prepared(spark, d, g), path, SERVERS)
    return tiles.unpack(sources.load_tiles(spark, path).tiles)


def _edge_list(spark: SparkSession, d: str, g: str) -> DataFrame:
    path = f"{scratch_root(spark)}/edges-{g}-{uuid.uuid4().hex}"
    graph(spark, d, g).edges.write.csv(path)
    return sources.read_edge_list(spark, path)


def _events_windowed(spark: SparkSession, d: str) -> DataFrame:
    from .streaming.ingest import daily_edges

    return daily_edges(spark.read.parquet(f"{d}/events.parquet"))


def _degree_rollup(spark: SparkSession, d: str) -> DataFrame:
    n_c, n_p = spark.read.parquet(f"{d}/customer.parquet").count(), spark.read.parquet(f"{d}/part.parquet").count()
    kind = F.when(F.col("id") < n_c, "customer").when(F.col("id") < n_c + n_p, "part").otherwise("supplier")
    rolled = graphs.degrees(graph(spark, d, "trade")).withColumn("kind", kind).rollup("kind").agg(F.sum("d_in").cast("long").alias("d_in"), F.sum("d_out").cast("long").alias("d_out"), F.count("*").alias("n"))
    return rolled.select(F.coalesce("kind", F.lit("all")).alias("kind"), "d_in", "d_out", "n")


def _per_graph(g: str) -> dict[str, Query]:
    kernel = lambda p, stop, cfg=tilepath.EngineConfig(): lambda s, d: tilepath.run(prepared(s, d, g), p, stop, cfg).values
    rel = lambda p, stop: lambda s, d: relational.run(graph(s, d, g), p, stop).values
    then = lambda f, q: lambda s, d: f(q(s, d))
    return {
        f"graph_stats_{g}": lambda s, d: graphs.stats(graph(s, d, g)),
        f"out_degrees_{g}": lambda s, d: tiles.out_degrees(graph(s, d, g)),
        f"in_degrees_{g}": lambda s, d: tiles.in_degrees(graph(s, d, g)),
        f"tile_splitter_greedy_{g}": lambda s, d: prepared(s, d, g).splitter,
        f"tile_splitter_quota_{g}": lambda s, d: tiles.split_quota(prepared(s, d, g).degrees, prepared(s, d, g).tile_edges),
        f"tile_balance_{g}": lambda s, d: meters.balance(prepared(s, d, g).splitter, prepared(s, d, g).tile_edges),
        f"tile_servers_{g}": lambda s, d: tiles.assign_servers(prepared(s, d, g).tiles, SERVERS).groupBy("server_id").agg(F.count("*").alias("n_tiles"), F.sum("n_edges").cast("long").alias("n_edges")),
        f"tile_roundtrip_{g}": lambda s, d: tiles.unpack(prepared(s, d, g).tiles),
        f"tile_sources_{g}": lambda s, d: tiles.sources(prepared(s, d, g).tiles).groupBy("tile_id").agg(F.count("*").alias("n_sources")),
        f"pagerank_pull_{g}": then(ranks, rel(programs.pagerank(), StopRule(STEPS))),
        f"pagerank_tilekernel_{g}": then(ranks, kernel(programs.pagerank(), StopRule(STEPS))),
        f"sssp_pull_{g}": then(distances, rel(programs.sssp(0), StopRule())),
        f"sssp_tilekernel_{g}": then(distances, kernel(programs.sssp(0), StopRule())),
        f"sssp_unit_{g}": then(distances, kernel(programs.sssp(0, weighted=False), StopRule())),
        f"sssp_unreached_{g}": then(lambda v: v.filter(F.col("value") == float("inf")).select("id"), kernel(programs.sssp(0), StopRule())),
        f"combine_eta_{g}": lambda s, d: meters.eta(graph(s, d, g), 36),
    }


def _experiments(g: str) -> dict[str, Query]:
    """The experiments on each of the compared graphs."""
    out: dict[str, Query] = {
        f"messages_by_servers_{g}": lambda s, d: workloads.messages_by_servers(graph(s, d, g)),
        f"compare_pagerank_{g}": lambda s, d: _compared(s, d, g, "pagerank"),
        f"compare_sssp_{g}": lambda s, d: _compared(s, d, g, "sssp"),
        f"engine_agreement_{g}": lambda s, d: _agreement(s, d, g),
        f"engine_memory_{g}": lambda s, d: workloads.memory_counted(s, graph(s, d, g), SERVERS, TILES),
        f"input_sizes_{g}": lambda s, d: meters.format_sizes(graph(s, d, g), prepared(s, d, g).tiles),
        f"replication_memory_{g}": lambda s, d: workloads.replication(prepared(s, d, g), 64, WORKERS),
        f"cache_hits_raw_{g}": lambda s, d: _raw_cache(s, d, g),
        f"skip_effect_{g}": lambda s, d: _skips(s, d, g, "exact").select("superstep", "tiles_total", "tiles_loaded", "tiles_skipped"),
        f"skip_effect_bloom_{g}": lambda s, d: _skips(s, d, g, "bloom"),
        f"tile_size_sweep_{g}": lambda s, d: workloads.tile_sizes(s, graph(s, d, g)),
    }
    for e in workloads.COMPARED[1:] + (("msg_hadoop", "triplets") if g in ("trade", "skew") else ()):
        out[f"pagerank_{e}_{g}"] = lambda s, d, e=e: ranks(ENGINES[e](graph(s, d, g), programs.pagerank(), StopRule(STEPS)).values)
    for e in ("msg_mem", "msg_disk", "gas_vcut", "gas_hybrid", "edge_stream"):
        out[f"sssp_{e}_{g}"] = lambda s, d, e=e: distances(ENGINES[e](graph(s, d, g), programs.sssp(0), StopRule()).values)
    return out


def _measures(g: str) -> dict[str, Query]:
    out: dict[str, Query] = {
        f"update_ratio_sssp_{g}": lambda s, d: _changed(s, d, g).groupBy(F.col("superstep").cast("long").alias("superstep")).agg(F.count("*").alias("changed")),
        f"active_tiles_exact_{g}": lambda s, d: _active(s, d, g, "exact"),
        f"active_tiles_bloom_superset_{g}": lambda s, d: _active(s, d, g, "bloom"),
        f"bloom_misses_none_{g}": lambda s, d: _skips(s, d, g, "bloom").join(_skips(s, d, g, "exact").select("superstep", F.col("tiles_loaded").alias("needed")), "superstep").select("superstep", "needed", (F.col("tiles_loaded") - F.col("tiles_fp") == F.col("needed")).alias("all_loaded")),
        f"sparsity_{g}": lambda s, d: meters.sparsity(meters.traffic_rows(_changed(s, d, g), prepared(s, d, g).splitter)).withColumn("superstep", F.col("superstep").cast("long")),
        f"edgecut_balance_{g}": lambda s, d: meters.edgecut_balance(graph(s, d, g), SERVERS),
        f"od_vertices_measured_{g}": lambda s, d: meters.od_vertices(graph(s, d, g), prepared(s, d, g).splitter, SERVERS),
        f"cache_plan_{g}": lambda s, d: plan_cache(prepared(s, d, g).splitter.select("tile_id", (8 * (F.col("v_hi") - F.col("v_lo") + 1 + 2 * F.col("n_edges"))).alias("bytes")), 400_000, SERVERS),
        f"cost_table_{g}": lambda s, d: workloads.costs(s, graph(s, d, g), SERVERS, TILES),
        f"engine_ops_{g}": lambda s, d: workloads.ops(s, prepared(s, d, g), SERVERS),
        f"codec_stats_{g}": lambda s, d: meters.codec_stats(prepared(s, d, g).tiles),
        f"memory_measured_{g}": lambda s, d: workloads.memory_measured(s, prepared(s, d, g), SERVERS, WORKERS),
        f"pagerank_ondemand_{g}": lambda s, d: ranks(tilepath.run(prepared(s, d, g), programs.pagerank(), StopRule(STEPS), tilepath.EngineConfig(replication="on_demand")).values),
        f"sssp_ondemand_{g}": lambda s, d: distances(tilepath.run(prepared(s, d, g), programs.sssp(0), StopRule(), tilepath.EngineConfig(replication="on_demand")).values),
        f"sssp_skip_bloom_{g}": lambda s, d: distances(tilepath.run(prepared(s, d, g), programs.sssp(0), StopRule(), tilepath.EngineConfig(skip="bloom")).values),
        f"sssp_probe_{g}": lambda s, d: distances(tilepath.run(prepared(s, d, g), programs.sssp(0), StopRule(), tilepath.EngineConfig(skip="bloom", probe_below=0.05)).values),
        f"pagerank_partly_cached_{g}": lambda s, d: ranks(tilepath.run(prepared(s, d, g), programs.pagerank(), StopRule(STEPS), tilepath.EngineConfig(servers=3, cache_mode=2, cache_capacity=tilepath.raw_bytes(prepared(s, d, g)) // 8, codec="zlib1", message_mode="dense")).values),
        f"tiles_unweighted_{g}": lambda s, d: tiles.unpack(tiles.prepare(graph(s, d, g), n_tiles=TILES, weighted=False).tiles),
        f"tiles_reloaded_{g}": lambda s, d: _reloaded(s, d, g),
        f"edge_list_{g}": lambda s, d: _edge_list(s, d, g),
        f"sssp_frontier_{g}": lambda s, d: distances(relational.run(graph(s, d, g), programs.sssp(0), frontier=True).values),
        f"update_ratio_pagerank_{g}": lambda s, d: meters.update_trend(meters.log_frame(s, tilepath.run(prepared(s, d, g), programs.pagerank(), StopRule(20)).log).select("superstep", "update_ratio")),
    }
    for mode in ("dense", "sparse", "hybrid", "bytes"):
        out[f"traffic_{mode}_{g}"] = lambda s, d, mode=mode: _traffic(s, d, g, mode)
    for cut in ("random", "grid", "hybrid", "degree", "refined_hybrid"):
        out[f"replication_factor_{cut}_{g}"] = lambda s, d, cut=cut: meters.replication_factor(CUTS[cut](graph(s, d, g), SERVERS), graph(s, d, g).n_vertices)
    return out


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for g in GRAPHS:
        out |= _per_graph(g)
    for g in COMPARED:
        out |= _experiments(g)
    for g in ("trade", "skew"):
        out |= _measures(g)
    for g in ("trade", "word"):
        out[f"single_node_{g}"] = lambda s, d, g=g: ranks(workloads.single_node(prepared(s, d, g), STEPS).values)
    for g in ("geo", "dialog"):
        out[f"graph_stats_{g}"] = lambda s, d, g=g: graphs.stats(graphs.build(s, d, g))
    for g in ("trade", "word"):
        out[f"topk_rank_{g}"] = lambda s, d, g=g: ranks(tilepath.run(prepared(s, d, g), programs.pagerank(), StopRule(STEPS)).values).orderBy(F.desc("rank_e9"), "id").limit(10)
    return out | {
        "labels_subgraph_word": lambda s, d: graphs.stats(graphs.build(s, d, "word_labelled")),
        "csr_rows_trade": lambda s, d: prepared(s, d, "trade").tiles.select("tile_id", F.posexplode("row").alias("pos", "edges_through")),
        "csr_cols_trade": lambda s, d: prepared(s, d, "trade").tiles.select("tile_id", F.posexplode("col").alias("pos", "src")),
        "cache_mode_choice": lambda s, d: workloads.cache_choice(prepared(s, d, "trade")),
        "memory_aa_od_sweep": lambda s, d: model.replication_sweep(_sizes(s, d)),
        "od_crossover": lambda s, d: workloads.crossovers(_sizes(s, d)),
        "communication_word": lambda s, d: _communication(s, d, "word"),
        "message_codecs_word": lambda s, d: workloads.message_codecs(s, prepared(s, d, "word")),
        "cache_study_word": lambda s, d: workloads.cache_study(s, prepared(s, d, "word")),
        "compression_table": lambda s, d: workloads.codecs(s, {g: prepared(s, d, g) for g in COMPARED}),
        "tile_size_times_trade": lambda s, d: workloads.tile_size_times(s, graph(s, d, "trade")),
        "od_expected": lambda s, d: model.od_expected(_sizes(s, d)),
        "load_rates": lambda s, d: workloads.load_rates(prepared(s, d, "trade")),
        "explosion_factor": lambda s, d: workloads.memory({g: (workloads.memory_counted(s, graph(s, d, g), SERVERS, TILES), meters.csv_bytes(graph(s, d, g))) for g in COMPARED}),
        "components_link": lambda s, d: relational.run(graph(s, d, "link_both"), programs.components()).values.select("id", F.col("value").cast("long").alias("component")),
        "reachable_skew": lambda s, d: relational.run(graph(s, d, "skew"), programs.reachable(0)).values.agg(F.sum("value").cast("long").alias("reached")),
        "event_edges_windowed": _events_windowed,
        "degree_rollup_trade": _degree_rollup,
    }
