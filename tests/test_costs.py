import pytest

from pullgraph import graphs, workloads
from pullgraph.costs import meters, model
from pullgraph.engine import tilepath
from pullgraph.engine.program import StopRule
from pullgraph.graphs import of_rows
from pullgraph.partition import tiles
from tests.conftest import SF


def test_published_relations():
    assert [model.crossover(d) for *_, d in model.PUBLISHED] == [23, 27, 37, 51]
    assert all(model.choose_replication(v, d, n) == "all" for _, v, _, d in model.PUBLISHED for n in range(1, 16))
    assert model.choose_replication(model.PUBLISHED[3][1], 85.7, 60) == "on_demand"
    assert model.eta(85.7, 216) == pytest.approx(0.825, abs=0.001)
    for _, v, _, d in model.PUBLISHED:
        assert model.expected_od(v, d, 9) == pytest.approx(model.expected_od_limit(v, d, 9), rel=1e-4)
    assert model.m_aa(1_100_000_000) == 22e9
    assert model.m_od(10**6, 500, 2, capped=True) == 24e6
    assert model.load_rate(22, 56)["decode_mb_s"] == 1232


def test_cost_order():
    rows = {r[0]: dict(zip(model.COSTS, r[1:])) for r in model.cost_rows(3600, 159640, 9, 32, 8.97, 0.5, 0.0)}
    assert rows["pull"]["network"] == 32400 and rows["edge_stream"]["network"] == 3 * 159640 + 3 * 3600
    assert rows["pull"]["network"] < rows["gas_vcut"]["network"] < rows["msg_mem"]["network"] < rows["edge_stream"]["network"]


def test_workloads_run(spark):
    prep = tiles.prepare(graphs.build(spark, SF, "trade"), n_tiles=8)
    g = prep.graph
    assert workloads.datasets(spark, SF).count() == 6
    assert workloads.tile_sizes(spark, g, (2, 8)).count() == 2
    assert workloads.tile_size_times(spark, g, (2, 8), 2).count() == 2
    sweep = workloads.cache_modes(spark, prep, (0, 1 << 40), (3,), 2, (1, 3)).collect()
    assert {(r.capacity > 0, r.hit_ratio) for r in sweep} == {(False, 0.0), (True, 0.5)}
    study = workloads.cache_study(spark, prep, 0.6, 3).collect()
    hits = {(r.servers, r.mode): r.hit_ratio for r in study}
    assert hits[3, 1] < hits[3, 4] and hits[9, 1] == hits[9, 4] == 2 / 3
    talk = workloads.communication(spark, prep, 3).toPandas()
    assert len(talk) == 3 and (talk.msg_hybrid_b <= talk[["msg_dense_b", "msg_sparse_b"]].max(axis=1)).all()
    by = {r.codec: r for r in workloads.message_codecs(spark, prep, 3).collect()}
    assert by["none"].reduction == 1 and by["zlib3"].sent_b <= by["snappy"].sent_b * 1.1
    res = workloads.compare_engines(spark, SF, "sssp", ("skew",), ("pull", "msg_mem"), (1, 3), None)
    assert all(r.max_diff == 0 for r in res.collect()) and res.count() == 4
    assert set(workloads.by_engine(res).columns) == {"graph", "program", "servers", "pull", "msg_mem"}
    assert workloads.report(res).count() >= 5
    assert workloads.replication(prep, 4, 2).count() == 4
    assert workloads.load_rates(prep).count() == 3
    assert workloads.codecs(spark, {"trade": prep}).count() == 4
    skips = workloads.skip_effect(spark, prep, "bloom").collect()
    assert all(r.tiles_loaded + r.tiles_skipped == r.tiles_total and r.tiles_fp >= 0 for r in skips)
    held = {r.engine: r for r in workloads.memory_measured(spark, prep, 9, 2).filter("program = 'pagerank'").collect()}
    assert held["gas_vcut"].vertex_b > held["msg_mem"].vertex_b > 0 and held["pull"].edge_b == 8 * prep.largest_tile
    counted = {r.engine: r for r in workloads.ops(spark, prep).collect()}
    assert counted["pull"].gathers == counted["pull"].applies == g.n_vertices < counted["gas_vcut"].gathers


def test_update_ratio_and_traffic_of_a_long_run(spark):
    prep = tiles.prepare(graphs.build(spark, SF, "skew"), n_tiles=8)
    log = tilepath.run(prep, workloads.PROGRAMS["pagerank"](), StopRule(60), tilepath.EngineConfig(cache_mode=0)).log
    ratio = [e["update_ratio"] for e in log]
    assert ratio[0] > 0.9 and min(ratio) < 0.5
    dense_wins = [e["msg_dense_b"] < e["msg_sparse_b"] for e in log]
    assert dense_wins[0] and not dense_wins[ratio.index(min(ratio))], "sparse messages are shorter only late in a run"


def test_codec_stats_and_sizes(spark):
    prep = tiles.prepare(graphs.build(spark, SF, "trade"), n_tiles=8)
    by = {r.codec: r for r in meters.codec_stats(prep.tiles).collect()}
    assert by["none"].ratio == 1 and by["zlib3"].ratio >= by["zlib1"].ratio > by["snappy"].ratio > 1
    sizes = {r.format: r.bytes for r in meters.format_sizes(prep.graph, prep.tiles).collect()}
    assert set(sizes) == {"csv_edge_list", "adjacency_text", "binary_edges", "tiles"} and sizes["binary_edges"] == 16 * prep.graph.n_edges


def test_update_ratio_falls(spark):
    log = workloads.changes(graphs.build(spark, SF, "skew").stored(), workloads.PROGRAMS["sssp"](0), 30).groupBy("superstep").count().collect()
    assert len(log) == 7  # the eighth superstep changes nothing


def test_models_follow_the_graph_they_are_given(spark):
    few, many = (of_rows(spark, [(i, j, 1) for i in range(40) for j in range(k)], 40) for k in (2, 40))
    own = workloads.sizes({"few": few, "many": many})
    assert {r.graph: (r.n_v, r.d_avg) for r in own.collect()} == {"few": (40.0, 2.0), "many": (40.0, 40.0)}
    got = {r.graph: r.servers for r in workloads.crossovers(own).collect()}
    assert got == {"few": model.crossover(2.0), "many": model.crossover(40.0)} and got["few"] < got["many"]
    a, b = (workloads.cache_choice(tiles.prepare(g, n_tiles=2)).collect() for g in (few, many))
    assert [r.mode for r in a] == [r.mode for r in b] == [1, 2, 3, 4, 4] and a[0].capacity < b[0].capacity
