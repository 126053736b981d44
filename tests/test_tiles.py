import numpy as np
import pytest
from pyspark.sql import functions as F

from pullgraph import graphs, ids, programs, sinks, sources, workloads
from pullgraph.costs import meters
from pullgraph.engine import replica, tilepath
from pullgraph.engine.program import StopRule
from pullgraph.graphs import Graph, of_rows
from pullgraph.partition import cuts, tiles
from tests.conftest import SF


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def test_tiny8_tiles_and_servers(spark):
    p = tiles.prepare(graphs.tiny8(spark), tile_edges=2)
    got = {r.tile_id: r for r in p.tiles.collect()}
    want = {
        0: (0, 1, [0, 2], [1, 2], [2, 5]),
        1: (1, 3, [0, 1, 3], [0, 1, 3], [1, 7, 4]),
        2: (3, 4, [0, 2], [0, 2], [3, 1]),
        3: (4, 6, [0, 0, 1], [4], [6]),
    }
    assert {k: (r.v_lo, r.v_hi, r.row, r.col, r.val) for k, r in got.items()} == want
    assert rows(p.degrees, "id", "d_in", "d_out") == [(0, 2, 2), (1, 1, 2), (2, 2, 2), (3, 2, 1), (4, 0, 1), (5, 1, 0)]
    assert rows(tiles.assign_servers(p.tiles, 2), "server_id", "tile_id") == [(0, 0), (0, 2), (1, 1), (1, 3)]
    assert p.tiles.filter("val is null").count() == 0
    assert tiles.prepare(graphs.tiny8(spark), tile_edges=2, weighted=False).tiles.filter("val is not null").count() == 0


@pytest.mark.parametrize("name", ["trade", "skew", "link"])
def test_tiles_partition_the_edges(spark, name):
    g = graphs.build(spark, SF, name).stored()
    p = tiles.prepare(g, n_tiles=16)
    audit = tiles.audit(p.tiles).collect()
    assert all(r.rows_agree and r.next_follows for r in audit)
    assert min(r.v_lo for r in audit) == 0 and max(r.v_hi for r in audit) == g.n_vertices
    most = p.degrees.agg({"d_in": "max"}).first()[0]
    assert all(p.tile_edges <= r.n_edges < p.tile_edges + most for r in sorted(audit, key=lambda r: r.tile_id)[:-1])
    assert rows(tiles.unpack(p.tiles), "src", "dst", "w") == rows(g.edges, "src", "dst", "w")
    assert rows(tiles.assign(g.edges, p.splitter), "tile_id", "src", "dst") == rows(tiles.assign_by_range(g.edges, p.splitter), "tile_id", "src", "dst")


@pytest.mark.parametrize("block", [3, 7, 1 << 20])
def test_greedy_split_equals_a_walk_over_ids(spark, block):
    rng = np.random.default_rng(4)
    d = rng.integers(0, 9, 60)
    d[20] = 50
    deg = spark.createDataFrame([(i, int(x)) for i, x in enumerate(d)], "id long, d_in long")
    want, size, lo = [], 0, 0
    for i, x in enumerate(d):
        size += int(x)
        if size >= 12:
            want.append((len(want), lo, i + 1, size))
            size, lo = 0, i + 1
    if lo < len(d):
        want.append((len(want), lo, len(d), size))
    assert rows(tiles.split_greedy(deg, 12, block), "tile_id", "v_lo", "v_hi", "n_edges") == want
    quota = rows(tiles.split_quota(deg, 12, block), "tile_id", "v_lo", "v_hi", "n_edges")
    assert quota[0][1] == 0 and quota[-1][2] == 60 and all(a[2] == b[1] for a, b in zip(quota, quota[1:]))
    assert sum(q[3] for q in quota) == d.sum() and all(q[3] < 12 + 50 for q in quota)


def test_loops_duplicates_hubs_and_empty_rows_survive(spark):
    e = [(0, 0, 1), (0, 0, 2), (3, 0, 1)] + [(i, 4, 1) for i in range(6)]
    p = tiles.prepare(of_rows(spark, e, 8), tile_edges=2)
    assert rows(tiles.unpack(p.tiles), "src", "dst", "w") == sorted((a, b, float(c)) for a, b, c in e)
    assert max(r.n_edges for r in p.tiles.collect()) == 6


def test_empty_graph_and_more_tiles_than_vertices(spark):
    empty = tiles.prepare(of_rows(spark, [], 0), tile_edges=1)
    assert empty.n_tiles == 0 and empty.tiles.count() == 0
    lonely = tiles.prepare(of_rows(spark, [], 3), tile_edges=1)
    assert [(r.v_lo, r.v_hi, r.row, r.col) for r in lonely.tiles.collect()] == [(0, 3, [0, 0, 0, 0], [])]
    assert tiles.prepare(of_rows(spark, [(0, 1, 1)], 2), n_tiles=50).n_tiles <= 2


def test_save_and_load(spark, tmp_path):
    p = tiles.prepare(graphs.tiny8(spark), tile_edges=2)
    sinks.save_tiles(p, str(tmp_path / "t"), servers=2)
    back = sources.load_tiles(spark, str(tmp_path / "t"))
    assert (back.n_tiles, back.graph.n_vertices, back.weighted) == (4, 6, True)
    assert rows(tiles.unpack(back.tiles), "src", "dst", "w") == rows(tiles.unpack(p.tiles), "src", "dst", "w")


def test_edge_list_text(spark, tmp_path):
    f = tmp_path / "e.csv"
    f.write_text("# c\n0,1,2.5\n1,2,1\nbad,x,y\n")
    g = sources.graph_of(sources.read_edge_list(spark, str(f)))
    assert rows(g.edges, "src", "dst", "w") == [(0, 1, 2.5), (1, 2, 1.0)] and g.n_vertices == 3


def test_dense_ids_and_order(spark):
    keys = spark.createDataFrame([(k,) for k in ["b", "a", None, "c", "a", "Z", "é"]], "key string")
    assert rows(ids.densify(keys), "key", "id") == [("Z", 0), ("a", 1), ("b", 2), ("c", 3), ("é", 4)]
    ev = spark.createDataFrame([(i, (i * 7) % 5) for i in range(50)], "t long, u long")
    got = ids.follow(ev, "u", "t")
    assert sorted(tuple(r) for r in got.collect()) == sorted(((i * 7) % 5, ((i + 1) * 7) % 5) for i in range(49))
    assert ids.densify(keys.limit(0)).count() == 0


def test_cuts_keep_every_edge_and_one_master(spark):
    g = graphs.build(spark, SF, "skew").stored()
    n = g.n_edges
    for cut in cuts.CUTS.values():
        c = cut(g, 9).cache()
        assert c.count() == n and {r[0] for r in c.select("part").distinct().collect()} <= set(range(9))
        r = cuts.replicas(c)
        assert r.filter("is_master").count() == r.select("id").distinct().count()
    assert cuts.hash_edge_cut(g, 4).count() == cuts.streaming_partitions(g, 8, 4).count() == n


def test_symmetrize_and_subgraph(spark):
    g = of_rows(spark, [(0, 1, 5), (1, 0, 3), (1, 2, 1)], 3)
    assert rows(graphs.symmetrize(g).edges, "src", "dst", "w") == [(0, 1, 3.0), (1, 0, 3.0), (1, 2, 1.0), (2, 1, 1.0)]
    keep = spark.createDataFrame([(0,), (1,)], "id long")
    assert rows(graphs.subgraph(g, keep).edges, "src", "dst") == [(0, 1), (1, 0)]


def test_routing_table_holds_sources_and_targets(spark):
    p = tiles.prepare(graphs.tiny8(spark), tile_edges=2)
    assert rows(replica.vertices_of_tiles(p.tiles).filter("tile_id = 1"), "id") == [(0,), (1,), (2,), (3,)]
    assert isinstance(p.graph, Graph)


def test_large_tiles_are_kept_in_rows(spark, monkeypatch):
    g = graphs.build(spark, SF, "skew").stored()
    assert g.stored() is g
    one, few = tiles.prepare(g, n_tiles=4), tiles.prepare(g, n_tiles=4, row_edges=100)
    most = one.degrees.agg(F.max("d_in")).first()[0]
    rows = few.tiles.select("tile_id", "v_lo", "v_hi", "n_edges").orderBy("v_lo").collect()
    assert len(rows) > 2 * one.n_tiles and max(r["n_edges"] for r in rows) < 100 + most
    assert all(a["v_hi"] == b["v_lo"] for a, b in zip(rows, rows[1:])) and (rows[0]["v_lo"], rows[-1]["v_hi"]) == (0, g.n_vertices)
    assert few.largest_tile == one.largest_tile == one.largest_row > few.largest_row
    assert tilepath.policy(few, programs.pagerank(), tilepath.EngineConfig(memory_budget=24 * one.largest_tile)) == "all" != tilepath.policy(one, programs.pagerank(), tilepath.EngineConfig(memory_budget=24 * one.largest_tile))
    assert few.splitter.collect() == one.splitter.collect()
    assert tiles.unpack(few.tiles).exceptAll(tiles.unpack(one.tiles)).count() == tiles.unpack(one.tiles).exceptAll(tiles.unpack(few.tiles)).count() == 0
    for cfg in (tilepath.EngineConfig(cache_mode=1), tilepath.EngineConfig(skip="bloom"), tilepath.EngineConfig(replication="on_demand")):
        for p, stop in ((programs.pagerank(), StopRule(3)), (programs.sssp(0), StopRule())):
            a, b = (tilepath.run(x, p, stop, cfg) for x in (one, few))
            assert meters.agree(a.values, b.values).first()["max_diff"] < 1e-12
            assert [e.get("tiles_loaded") for e in a.log] == [e.get("tiles_loaded") for e in b.log] or cfg.skip == "bloom"
    made, keep = [], tilepath.run
    monkeypatch.setattr(tiles, "ROW_EDGES", 100)
    monkeypatch.setattr(tilepath, "run", lambda prep, *a: made.append((prep.n_tiles, prep.tiles.agg(F.max("n_edges")).first()[0])) or keep(prep, *a))
    got = workloads.tile_size_times(spark, g, (4, 16), 2).collect()
    assert [(r["asked"], r["n_tiles"]) for r in got] == [(4, made[0][0]), (16, made[1][0])] and all(m < 100 + most for _, m in made)
