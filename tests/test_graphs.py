import numpy as np

from pullgraph import graphs
from tests.conftest import SF

#: Golden numbers of the derived graphs at sf0.001 (vertices, edges, largest in- and out-degree).
GOLDEN = {
    "trade": (360, 8731, 195, 147), "skew": (200, 4478, 198, 33), "basket": (200, 3817, 39, 37),
    "event": (15, 207, 14, 14), "word": (12566, 36129, 1405, 1388), "link": (305, 279, 6, 6),
}


def test_golden_statistics(spark):
    for name, want in GOLDEN.items():
        s = graphs.stats(graphs.build(spark, SF, name)).first()
        assert (s.n_vertices, s.n_edges, s.max_in, s.max_out) == want, name


def test_nearest_vectors(spark):
    g = graphs.knn(spark, SF, k=3, block=40)
    p = spark.read.parquet(f"{SF}/embeddings.parquet").toPandas().sort_values("vec_id")
    m = np.stack(p.embedding.to_list()).astype(float)
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    score = m @ m.T
    np.fill_diagonal(score, -np.inf)
    ids = p.vec_id.to_numpy()
    want = {(int(ids[i]), int(ids[j]), float(r + 1)) for i in range(len(ids)) for r, j in enumerate(np.lexsort((ids, -score[i]))[:3])}
    assert {tuple(r) for r in g.edges.collect()} == want


def test_small_builders(spark):
    geo = graphs.stats(graphs.build(spark, SF, "geo")).first()
    nations = spark.read.parquet(f"{SF}/nation.parquet").count()
    others = sum(spark.read.parquet(f"{SF}/{t}.parquet").count() for t in ("customer", "supplier"))
    assert geo.n_edges == 2 * nations + others
    assert graphs.build(spark, SF, "dialog").n_vertices <= 3
    assert graphs.build(spark, SF, "word_labelled").n_vertices < GOLDEN["word"][0]
    both = graphs.build(spark, SF, "link_both")
    assert both.edges.count() == both.edges.selectExpr("dst", "src").distinct().count()
