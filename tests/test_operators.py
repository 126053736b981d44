import numpy as np
import pytest

from pullgraph import functions, graphs, operators, plans, programs
from pullgraph.engine import tilepath
from pullgraph.engine.program import StopRule
from pullgraph.engine import relational
from pullgraph.graphs import of_rows
from pullgraph.partition import tiles
from tests.conftest import SF


@pytest.fixture(scope="module")
def tiny(spark):
    return tiles.prepare(graphs.tiny8(spark), tile_edges=2)


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


def test_sql_packing_equals_the_packer(spark, tiny):
    sql = functions.pack_csr_sql(tiles.assign(tiny.graph.edges, tiny.splitter), tiny.splitter)
    assert rows(sql) == rows(tiny.tiles.select(sql.columns))


def test_sql_bloom_filters_find_all_active_tiles(spark):
    p = tiles.prepare(graphs.build(spark, SF, "skew"), n_tiles=8)
    src = tiles.sources(p.tiles)
    f = functions.bloom_filters(src, "tile_id", "src", 4096, 4)
    some = spark.createDataFrame([(3,), (7,)], "src long")
    exact = {r[0] for r in src.join(some, "src", "left_semi").select("tile_id").distinct().collect()}
    assert exact <= {r[0] for r in functions.bloom_active(f, "tile_id", some, "src", 4096, 4).collect()}


def test_views_and_table_function(spark, tiny):
    operators.register_views(tiny, prefix="t8_")
    assert rows(operators.neighbours(spark, 2, "t8_")) == [(1, 7.0), (3, 4.0)]
    spark.udtf.register("explode_tile", operators.ExplodeTile)
    got = spark.sql("SELECT src, dst, w FROM t8_tiles t, LATERAL explode_tile(t.v_lo, t.row, t.col, t.val)")
    assert rows(got) == rows(tiny.graph.edges.select("src", "dst", "w"))


def test_ranking_sets_and_parents(spark, tiny):
    d = tilepath.run(tiny, programs.sssp(0), StopRule()).values
    assert rows(operators.farthest(d, 1)) == [(2, 7.0)]
    assert rows(operators.parents(tiny.graph, d)) == [(1, 0), (2, 3), (3, 0)]
    e = tilepath.run(tiny, programs.sssp(4), StopRule()).values
    assert rows(operators.reached_sets(d, e)) == [("both", 0), ("first", 4), ("second", 2)]
    assert rows(operators.heaviest_tiles(tiny.splitter, 1)) == [(1, 1, 3, 3)]
    assert sum(r.n for r in operators.degree_ranks(tiny.graph, 2).collect()) == 6
    assert {(r.has_in, r.has_out): r.n for r in operators.degree_sets(tiny.graph).collect()}[(None, None)] == 6
    est = operators.distinct_sources_sketch(tiles.assign(tiny.graph.edges, tiny.splitter)).collect()
    assert {r.tile_id: r.estimate for r in est} == {0: 2, 1: 3, 2: 2, 3: 1}


def test_as_of_and_interval(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 1, 2), ("b", 9, 3)], "k string, t int, x int")
    right = spark.createDataFrame([("a", 2, 20), ("a", 5, 50), ("b", 10, 99)], "k string, t int, v int")
    assert rows(operators.as_of(left, right, "k", "t", "v")) == [("a", 1, 2, None), ("a", 5, 1, 50), ("b", 9, 3, None)]
    ev = spark.read.parquet(f"{SF}/events.parquet").limit(300)
    got = {(r.event_id, r.e2) for r in operators.within_interval(ev, 3600).collect()}
    p = ev.toPandas()
    want = set()
    for a in p.itertuples():
        for b in p.itertuples():
            gap = int(b.ts.timestamp()) - int(a.ts.timestamp())
            if a.event_type == b.event_type and a.event_id != b.event_id and a.user_id != b.user_id and 0 <= gap <= 3600:
                want.add((a.event_id, b.event_id))
    assert got == want


def test_plans_prune_and_push(spark):
    df = spark.read.parquet(f"{SF}/lineitem.parquet").filter("l_quantity > 40").select("l_partkey")
    assert any("GreaterThan(l_quantity" in f for f in plans.pushed_filters(df))
    assert plans.read_columns(df) == [{"l_partkey", "l_quantity"}]
    g = graphs.build(spark, SF, "trade")
    plans.forbid(g.edges, "CartesianProduct", "BroadcastNestedLoopJoin")
    with pytest.raises(ValueError):
        plans.forbid(g.edges, "HashAggregate", "Hash")


def test_dangling_mass_can_be_spread(spark):
    g = of_rows(spark, [(0, 1, 1), (1, 2, 1), (2, 0, 1), (2, 3, 1)], 5)
    p = tiles.prepare(g, tile_edges=2)
    v = tilepath.run(p, programs.pagerank(dangling="spread"), StopRule(40)).values.toPandas().value.to_numpy()
    assert np.isclose(v.sum(), 1)
    assert tilepath.run(p, programs.pagerank(), StopRule(40)).values.toPandas().value.sum() < 0.9
    with pytest.raises(ValueError):
        relational.run(g, programs.pagerank(dangling="spread"), StopRule(1))
