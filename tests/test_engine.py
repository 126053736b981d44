import numpy as np
import pytest

from pullgraph import graphs, programs, queries, workloads
from pullgraph.baselines import arrays
from pullgraph.baselines import engines as baselines
from pullgraph.baselines.engines import ENGINES
from pullgraph.costs import meters
from pullgraph.engine import cache, exchange, relational, skip, tilepath
from pullgraph.engine.program import StopRule
from pullgraph.graphs import of_rows
from pullgraph.partition import cuts, tiles
from tests.conftest import SF


def values(r):
    return r.values.toPandas().sort_values("id")["value"].to_numpy()


@pytest.fixture(scope="module")
def tiny(spark):
    return tiles.prepare(graphs.tiny8(spark), tile_edges=2)


@pytest.fixture(scope="module")
def skew(spark):
    return tiles.prepare(graphs.build(spark, SF, "skew"), n_tiles=12)


def reference_pagerank(g, steps):
    e = g.edges.toPandas()
    n = g.n_vertices
    out = np.bincount(e.src, minlength=n)
    v = np.full(n, 1 / n)
    for _ in range(steps):
        v = 0.15 / n + 0.85 * np.bincount(e.dst, weights=v[e.src] / out[e.src], minlength=n)
    return v


def test_worked_pagerank_step(tiny):
    want = [1 / 6, 0.0958333333, 0.2375, 1 / 6, 0.025, 1 / 6]
    got = values(tilepath.run(tiny, programs.pagerank(), StopRule(1)))
    assert np.allclose(got, want) and np.isclose(got.sum(), 1 - 0.85 / 6)


def test_worked_sssp_with_skipping(tiny):
    for mode in ("exact", "bloom"):
        r = tilepath.run(tiny, programs.sssp(0), StopRule(), tilepath.EngineConfig(skip=mode, audit=True))
        assert values(r).tolist() == [0, 1, 7, 3, np.inf, np.inf]
        assert [e["changed"] for e in r.log] == [2, 1, 0]
        assert all(e["tiles_fp"] >= 0 for e in r.log)
    assert [e["tiles_loaded"] for e in tilepath.run(tiny, programs.sssp(0), StopRule(), tilepath.EngineConfig(skip="exact")).log] == [2, 2, 2]


@pytest.mark.parametrize("steps", [1, 2, 10])
def test_pagerank_equals_reference_on_every_path(skew, steps):
    want = reference_pagerank(skew.graph, steps)
    for cfg in (tilepath.EngineConfig(), tilepath.EngineConfig(replication="on_demand"), tilepath.EngineConfig(skip="bloom", message_mode="dense", codec="zlib1")):
        assert np.allclose(values(tilepath.run(skew, programs.pagerank(), StopRule(steps), cfg)), want, atol=1e-12)
    assert np.allclose(values(relational.run(skew.graph, programs.pagerank(), StopRule(steps))), want, atol=1e-12)
    assert np.allclose(values(relational.run(skew.graph, programs.pagerank(), StopRule(steps), broadcast=False)), want, atol=1e-12)
    assert (want >= 0.15 / skew.graph.n_vertices - 1e-15).all()


@pytest.mark.parametrize("name", sorted(ENGINES))
def test_baselines_agree_with_pull(skew, name):
    ours = tilepath.run(skew, programs.pagerank(), StopRule(3))
    theirs = ENGINES[name](skew.graph, programs.pagerank(), StopRule(3))
    assert meters.agree(ours.values, theirs.values).first()["max_diff"] < 1e-12
    ours = tilepath.run(skew, programs.sssp(0), StopRule())
    theirs = ENGINES[name](skew.graph, programs.sssp(0), StopRule())
    assert meters.agree(ours.values, theirs.values).first()["max_diff"] == 0


def test_counted_messages(skew):
    g, n_e = skew.graph, skew.graph.n_edges
    combined = meters.eta(g, 9).first()["combined"]
    p, one = programs.pagerank(), StopRule(1)
    assert ENGINES["edge_stream"](g, p, one, count=True).log[0]["msg_count"] == n_e
    log = ENGINES["msg_mem"](g, p, one, count=True).log[0]
    assert (log["msg_raw"], log["msg_count"]) == (n_e, combined)
    m = meters.replication_factor(graphs_cut(g), g.n_vertices).first()["factor"]
    assert ENGINES["gas_vcut"](g, p, one, count=True).log[0]["msg_count"] <= 2 * m * g.n_vertices
    assert tilepath.run(skew, p, one).log[0]["changed"] <= g.n_vertices


def graphs_cut(g):
    from pullgraph.partition.cuts import random_cut

    return random_cut(g, 9)


def test_sssp_properties(skew):
    d = values(tilepath.run(skew, programs.sssp(0), StopRule()))
    e = skew.graph.edges.toPandas()
    assert d[0] == 0 and (d[e.dst] <= d[e.src] + e.w).all()
    assert (values(relational.run(skew.graph, programs.sssp(0), frontier=True)) == d).all()
    hops = values(tilepath.run(skew, programs.sssp(0, weighted=False), StopRule()))
    assert (np.isinf(hops) == np.isinf(d)).all()
    with pytest.raises(ValueError):
        tilepath.run(skew, programs.sssp(10**6), StopRule())
    with pytest.raises(ValueError):
        relational.run(skew.graph, programs.pagerank(), StopRule(2), frontier=True)


def test_a_chain_needs_one_superstep_per_hop(spark):
    p = tiles.prepare(of_rows(spark, [(i, i + 1, 1) for i in range(5)], 6), tile_edges=2)
    r = tilepath.run(p, programs.sssp(0), StopRule())
    assert r.supersteps == 6 and [e["changed"] for e in r.log] == [1, 1, 1, 1, 1, 0]


def test_the_change_log_runs_to_its_fixed_point(spark, monkeypatch):
    chain = of_rows(spark, [(i, i + 1, 1) for i in range(4)], 5)
    asked, made = [], workloads.changes
    monkeypatch.setattr(workloads, "changes", lambda g, p, *steps: asked.append(steps) or made(g, p, *steps))
    monkeypatch.setattr(queries, "graph", lambda *_: chain)
    monkeypatch.setattr(queries, "_KEPT", {})
    got = sorted((r.superstep, r.id) for r in queries._changed(spark, "none", "chain").collect())
    assert asked == [()] and got == [(k, k) for k in range(1, 5)]


def test_two_runs_are_identical(skew):
    a, b = (values(tilepath.run(skew, programs.pagerank(), StopRule(8))) for _ in range(2))
    assert (a == b).all()


def test_further_programs(spark):
    g = of_rows(spark, [(0, 1, 1), (1, 0, 1), (2, 3, 1), (3, 2, 1), (3, 4, 1), (4, 3, 1)], 6)
    p = tiles.prepare(g, tile_edges=2)
    assert values(tilepath.run(p, programs.components(), StopRule())).tolist() == [0, 0, 2, 2, 2, 5]
    assert values(relational.run(g, programs.components())).tolist() == [0, 0, 2, 2, 2, 5]
    assert values(tilepath.run(p, programs.in_degree(), StopRule(1))).tolist() == [1, 1, 1, 2, 1, 0]
    assert values(relational.run(g, programs.reachable(2))).tolist() == [0, 0, 1, 1, 1, 0]
    mine = values(tilepath.run(p, programs.personalised_pagerank(2), StopRule(60)))
    assert np.isclose(mine.sum(), 1) and mine[[0, 1, 5]].sum() < 1e-9
    assert np.allclose(values(relational.run(g, programs.personalised_pagerank(2), StopRule(60))), mine)


def test_tolerance_stops(skew):
    r = tilepath.run(skew, programs.pagerank(), StopRule(tol=1e-9))
    assert r.supersteps < 200 and np.abs(values(r) - reference_pagerank(skew.graph, 300)).sum() < 1e-5


def test_edge_cases(spark):
    one = tiles.prepare(of_rows(spark, [], 1), tile_edges=1)
    assert values(tilepath.run(one, programs.pagerank(), StopRule(3))).tolist() == [pytest.approx(0.15)]
    none = tiles.prepare(of_rows(spark, [], 0), tile_edges=1)
    assert tilepath.run(none, programs.pagerank(), StopRule(3)).values.count() == 0
    dangling = tiles.prepare(of_rows(spark, [(0, 1, 1)], 2), tile_edges=1)
    assert values(tilepath.run(dangling, programs.pagerank(), StopRule(2))).sum() < 1
    with pytest.raises(MemoryError):
        tilepath.run(dangling, programs.pagerank(), StopRule(1), tilepath.EngineConfig(memory_budget=1, replication="all"))
    assert len(values(tilepath.run(dangling, programs.pagerank(), StopRule(1), tilepath.EngineConfig(memory_budget=1, replication="auto")))) == 2


@pytest.mark.parametrize("n", [1, 8, 10, 13])
def test_messages_round_trip(n):
    rng = np.random.default_rng(n)
    for k in range(n + 1):
        flags = np.zeros(n, bool)
        flags[rng.permutation(n)[:k]] = True
        v = rng.random(n)
        for mode in ("dense", "sparse", "hybrid"):
            used, raw = exchange.encode(v, flags, mode)
            for codec in exchange.CODECS:
                at, got = exchange.decode(exchange.decompress(exchange.compress(raw, codec), codec), used, n)
                assert at.tolist() == np.flatnonzero(flags).tolist() and (got == v[flags]).all()


def test_message_sizes_and_threshold():
    assert exchange.dense_bytes(10) == 82 and exchange.sparse_bytes(1) == 12
    assert [exchange.choose(10, k) for k in (0, 1, 2, 10)] == ["sparse", "sparse", "dense", "dense"]
    assert exchange.choose(10, 2, "bytes") == "sparse" and exchange.choose(10, 7, "bytes") == "dense"


def test_bloom_filters_never_miss(skew):
    filters = skip.tile_filters(skew.tiles, 0.01).cache()
    src = tiles.sources(skew.tiles).toPandas()
    rng = np.random.default_rng(1)
    asked = false = 0
    for r in filters.collect():
        mine = set(src[src.tile_id == r.tile_id].src)
        for i in rng.permutation(skew.graph.n_vertices)[:50]:
            yes = skip.may_hold(r.bits, r.m_bits, r.k_hash, np.array([i]))
            assert yes or i not in mine
            asked += i not in mine
            false += yes and i not in mine
    assert false <= max(3, 0.03 * asked)


def test_cache_modes(skew):
    plain = values(tilepath.run(skew, programs.pagerank(), StopRule(3)))
    raw = tilepath.raw_bytes(skew)
    for mode in (0, 1, 2, 3, 4):
        r = tilepath.run(skew, programs.pagerank(), StopRule(3), tilepath.EngineConfig(servers=2, cache_mode=mode))
        # The first load of a tile comes from disk, the others from memory.
        assert (values(r) == plain).all() and meters.hit_ratio(r.log) == 2 / 3 and meters.disk(r.log) == raw
        assert [e["cache_hits"] for e in r.log] == [0, skew.n_tiles, skew.n_tiles]
    r = tilepath.run(skew, programs.pagerank(), StopRule(3), tilepath.EngineConfig(servers=2, cache_mode=1, cache_capacity=0))
    assert meters.hit_ratio(r.log) == 0 and meters.disk(r.log) == 3 * raw and (values(r) == plain).all()
    r = tilepath.run(skew, programs.pagerank(), StopRule(3), tilepath.EngineConfig(servers=2, cache_mode=1, cache_capacity=30_000))
    assert 0 < meters.hit_ratio(r.log) < 2 / 3 and (values(r) == plain).all()
    assert [cache.choose_mode(100, c) for c in (100, 60, 30, 20, 19)] == [1, 2, 3, 4, 4]
    assert cache.choose_mode(100, 19, fallback=3) == 3


def test_policy_follows_the_memory_model(skew):
    p, n = programs.pagerank(), skew.graph.n_vertices
    cfg = tilepath.EngineConfig(workers=2)
    everywhere, on_demand = tilepath.memory_needed(skew, p, cfg)
    assert everywhere == 24 * n + 2 * skew.largest_tile and on_demand > 2 * skew.largest_tile
    assert tilepath.policy(skew, p, tilepath.EngineConfig(workers=2, memory_budget=everywhere)) == "all"
    assert tilepath.policy(skew, p, tilepath.EngineConfig(workers=2, memory_budget=everywhere - 1)) == "on_demand"
    cheap = [tilepath.policy(skew, p, tilepath.EngineConfig(servers=k, replication="cheapest")) for k in (1, 1000)]
    assert cheap == ["all", "on_demand"]
    small = tilepath.EngineConfig(memory_budget=1)
    assert np.allclose(values(tilepath.run(skew, p, StopRule(3), small)), reference_pagerank(skew.graph, 3), atol=1e-12)
    assert (values(tilepath.run(skew, programs.sssp(0), StopRule(), small)) == values(tilepath.run(skew, programs.sssp(0), StopRule()))).all()


def test_messages_by_file_and_degrees_in_parts(skew, monkeypatch):
    want = values(tilepath.run(skew, programs.pagerank(), StopRule(3)))
    monkeypatch.setattr(tilepath, "_result_limit", lambda spark: 1)
    monkeypatch.setattr(tilepath, "FETCH", 37)
    skew.kept.pop("d_out"), skew.kept.pop("d_out_everywhere")
    assert (values(tilepath.run(skew, programs.pagerank(), StopRule(3))) == want).all()


def test_counted_operations(skew):
    log = tilepath.run(skew, programs.pagerank(), StopRule(2), tilepath.EngineConfig(servers=3, workers=2)).log
    n, n_e = skew.graph.n_vertices, skew.graph.n_edges
    assert all(e["op_gather"] == n_e and e["op_apply"] == n and e["op_broadcast"] == e["changed"] for e in log)
    assert log[0]["rounds"] == -(-max(sum(t % 3 == s for t in range(skew.n_tiles)) for s in range(3)) // 2)


def test_cached_tiles_beyond_the_listed_number(skew, monkeypatch):
    monkeypatch.setattr(tilepath, "LISTED", 2)
    cfg = tilepath.EngineConfig(servers=2, cache_mode=2, cache_capacity=31_000)
    assert np.allclose(values(tilepath.run(skew, programs.pagerank(), StopRule(2), cfg)), reference_pagerank(skew.graph, 2), atol=1e-12)


def test_a_superstep_of_a_baseline_writes_its_state_once(skew, monkeypatch):
    written = []
    keep = baselines.materialize
    monkeypatch.setattr(baselines, "materialize", lambda df, name="step", by=(): written.append(name) or keep(df, name, by))
    done = ENGINES["gas_vcut"](skew.graph, programs.sssp(0), StopRule(3)).supersteps
    assert done == 3 and written.count("state") == done + 1 and written.count("active") == done + 1 and len(written) == 2 * done + 2


def test_small_graphs_are_laid_out_in_few_partitions(spark):
    g = graphs.tiny8(spark)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        few = baselines._laid_out(g.edges, g.n_edges, "src")
        many = baselines._laid_out(g.edges, 1 << 40, "src")
        assert few.rdd.getNumPartitions() == min(64, spark.sparkContext.defaultParallelism)
        assert many.rdd.getNumPartitions() == 64
        assert few.count() == many.count() == g.n_edges
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_compared_engines_write_no_state_and_lay_out_a_cut_once(skew, monkeypatch):
    written = []
    keep, pack = baselines.materialize, arrays._pack
    monkeypatch.setattr(baselines, "materialize", lambda df, name="step", by=(): written.append(name) or keep(df, name, by))
    monkeypatch.setattr(arrays, "_pack", lambda *a: written.append("layout") or pack(*a))
    for e in ("msg_mem", "gas_vcut", "gas_hybrid", "msg_disk", "edge_stream"):
        for p, stop in ((programs.pagerank(), StopRule(2)), (programs.sssp(0), StopRule())):
            ours, theirs = tilepath.run(skew, p, stop), workloads._run(e, skew, p, stop, 3)
            assert meters.agree(ours.values, theirs.values).first()["max_diff"] < 1e-12
            assert [x["changed"] for x in ours.log] == [x["changed"] for x in theirs.log]
    assert written == ["layout"] * 4, "msg_mem and msg_disk share theirs"
    g, of = skew.graph, {e: arrays.layout(skew, e, 3).blocks.selectExpr("sum(length(src)) div 4", "sum(length(dst)) div 4").first() for e in arrays.ENGINE_CUT}
    assert {r[0] for r in of.values()} == {g.n_edges}
    # A block's targets are the messages that its worker or server sends when every vertex does.
    assert of["msg_mem"][1] == meters.eta(g, 3).first()["combined"]
    assert of["gas_vcut"][1] == arrays.random_cut(g, 3).select("part", "dst").distinct().count()
    arrays.drop_layouts(skew)


def test_chunks_without_edges_apply_too(spark):
    p = tiles.prepare(of_rows(spark, [(0, 8, 2), (8, 0, 1)], 9), tile_edges=1)
    for e in arrays.ENGINE_CUT:
        assert np.allclose(values(arrays.run(e, p, programs.pagerank(), StopRule(2), 2)), values(tilepath.run(p, programs.pagerank(), StopRule(2))))
    assert values(arrays.run("gas_vcut", p, programs.sssp(0), StopRule(), 2))[[0, 8]].tolist() == [0, 2]


def test_cuts_are_made_from_one_shuffle_of_the_edges(spark, monkeypatch):
    dealt, deal = [], arrays.deal
    monkeypatch.setattr(arrays, "deal", lambda *a: dealt.append(1) or deal(*a))
    monkeypatch.setattr(arrays, "CHUNK_EDGES", 300)
    p = tiles.prepare(graphs.build(spark, SF, "trade"), n_tiles=4)
    for e, cut in (("msg_mem", cuts.hash_edge_cut(p.graph, 3).withColumnRenamed("worker", "part")), ("gas_vcut", cuts.random_cut(p.graph, 3)), ("gas_hybrid", cuts.hybrid_cut(p.graph, 3))):
        laid = arrays.layout(p, e, 3)
        assert laid.chunks > laid.tasks, "a task has several chunks"
        blocks = laid.blocks.groupBy("part").agg({"src": "count"}).count(), {r[0]: r[1] for r in laid.blocks.selectExpr("part", "length(src) div 4 as n").groupBy("part").sum("n").collect()}
        assert blocks == (3, {r[0]: r[1] for r in cut.groupBy("part").count().collect()})
    assert len(dealt) == 1
    for e in ("msg_mem", "edge_stream"):
        assert np.allclose(values(arrays.run(e, p, programs.pagerank(), StopRule(2), 3)), values(tilepath.run(p, programs.pagerank(), StopRule(2))))


def test_compared_tiles_of_a_large_graph_are_kept_in_rows(spark, monkeypatch):
    whole = queries.prepared(spark, SF, "skew")
    assert queries.in_rows(spark, SF, "skew") is whole
    monkeypatch.setattr(tiles, "ROW_EDGES", 60)
    p = queries.in_rows(spark, SF, "skew")
    queries._KEPT.pop(("rows", spark.sparkContext.applicationId, SF, "skew"))
    assert p.n_tiles == whole.n_tiles and p.tiles.count() > p.n_tiles
    a, b = (workloads._run("pull", x, programs.sssp(0), StopRule(), 3) for x in (whole, p))
    assert np.array_equal(values(a), values(b)) and [x["tiles_loaded"] for x in a.log] == [x["tiles_loaded"] for x in b.log]
    tilepath.give_up_cache(p)
    assert not any(k.startswith("cache-") for k in p.kept)
    p.drop()
