"""Directed graphs with dense ids, and those derived from the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .ids import densify, follow
from .session import materialize, ship

EDGE_SCHEMA = "src long, dst long, w double"


@dataclass
class Graph:
    """Vertices 0..n_vertices-1 and edges (src, dst, w); w is 1 for an unweighted graph.

    Self loops and parallel edges are allowed.  Edges are a plan, not data: `stored()` writes them once for programs that
    read them again and again.
    """

    edges: DataFrame
    n_vertices: int
    name: str = "graph"

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def vertices(self) -> DataFrame:
        return self.spark.range(self.n_vertices)

    @property
    def n_edges(self) -> int:
        if not hasattr(self, "_n_edges"):
            self._n_edges = self.edges.count()
        return self._n_edges

    def stored(self) -> Graph:
        """Itself, if that was done before."""
        if getattr(self.edges, "_scratch_path", None) and self.edges.dtypes == [("src", "bigint"), ("dst", "bigint"), ("w", "double")]:
            return self
        return Graph(materialize(self.edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("w").cast("double")), f"edges-{self.name}"), self.n_vertices, self.name)


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers, then parts, then suppliers: bought, sourced from, served; weight is the smallest quantity."""
    n_c, n_p, n_s = (_table(spark, sf_dir, t).count() for t in ("customer", "part", "supplier"))
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    c, p, s = F.col("o_custkey"), F.col("l_partkey") + n_c, F.col("l_suppkey") + n_c + n_p
    three = F.explode(F.array(*(F.struct(a.alias("src"), b.alias("dst")) for a, b in ((c, p), (p, s), (s, c)))))
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(three.alias("e"), "l_quantity")
    return Graph(pairs.groupBy("e.src", "e.dst").agg(F.min("l_quantity").alias("w")), n_c + n_p + n_s, "trade")


def skew(spark: SparkSession, sf_dir: str) -> Graph:
    """Part to part with a cubed target key, which gives low ids very many in-edges."""
    n = _table(spark, sf_dir, "part").count()
    k = F.pmod(F.col("l_suppkey") * 37 + F.col("l_partkey") * 11 + F.col("l_linenumber") * 101 + F.col("l_orderkey") * 7, F.lit(n)).cast("long" if n < 2_000_000 else "decimal(38,0)")
    rows = _table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("src"), k.alias("k"), "l_quantity")
    cube = F.expr(f"CAST((k * k * k) DIV ({n}L * {n}L) AS BIGINT)") if n < 2_000_000 else F.floor(F.col("k") * F.col("k") * F.col("k") / F.lit(n * n).cast("decimal(38,0)")).cast("long")
    rows = rows.select("src", cube.alias("dst"), "l_quantity").filter("src <> dst")
    return Graph(rows.groupBy("src", "dst").agg(F.min("l_quantity").alias("w")), n, "skew")


def word(spark: SparkSession, sf_dir: str, labelled: bool = False) -> Graph:
    """Word to next word in English documents; ids in byte order; weight counts.  A word that never has another next to
    it is no vertex.  labelled: only quality 1."""
    docs = _table(spark, sf_dir, "documents").filter("lang = 'en'").select("doc_id", "text")
    if labelled:
        docs = docs.join(_table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id"), "doc_id", "left_semi")
    words = docs.select(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), 0).alias("w")).filter(F.size("w") > 0)
    size = F.size("w")
    pairs = words.select(F.explode(F.zip_with(F.slice("w", F.lit(1), size - 1), F.slice("w", F.lit(2), size - 1), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("p")).select("p.a", "p.b")
    counted = materialize(pairs.filter("a <> b").groupBy("a", "b").agg(F.count("*").cast("double").alias("w")), "pairs")
    keys = materialize(densify(counted.select(F.explode(F.array("a", "b")).alias("key"))), "words")
    edges = counted.join(keys.select(F.col("key").alias("a"), F.col("id").alias("src")), "a").join(keys.select(F.col("key").alias("b"), F.col("id").alias("dst")), "b")
    return Graph(edges.select("src", "dst", "w"), keys.count(), "word_labelled" if labelled else "word")


def basket(spark: SparkSession, sf_dir: str) -> Graph:
    """Within an order, each distinct part to the next larger part; weight counts."""
    n = _table(spark, sf_dir, "part").count()
    parts = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    nxt = F.lead("l_partkey").over(Window.partitionBy("l_orderkey").orderBy("l_partkey"))
    pairs = parts.select(F.col("l_partkey").alias("src"), nxt.alias("dst")).filter("dst IS NOT NULL")
    return Graph(pairs.groupBy("src", "dst").agg(F.count("*").cast("double").alias("w")), n, "basket")


def event(spark: SparkSession, sf_dir: str) -> Graph:
    """User of an event to the user of the next event in time; weight counts."""
    rows = _table(spark, sf_dir, "events").select("ts", "event_id", "user_id")
    n = (rows.agg(F.max("user_id")).first()[0] or 0) + 1
    pairs = follow(rows, "user_id", "ts", "event_id").filter("this <> next")
    return Graph(pairs.groupBy(F.col("this").alias("src"), F.col("next").alias("dst")).agg(F.count("*").cast("double").alias("w")), n, "event")


def link(spark: SparkSession, sf_dir: str) -> Graph:
    """Page to link target; pages first, then targets in byte order; weight counts."""
    pages = _table(spark, sf_dir, "pages").select("page_id", "html")
    n = pages.count()
    out = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("key"))
    keys = materialize(densify(out), "targets")
    edges = out.groupBy("page_id", "key").agg(F.count("*").cast("double").alias("w")).join(keys, "key")
    return Graph(edges.select(F.col("page_id").alias("src"), (F.col("id") + n).alias("dst"), "w"), n + keys.count(), "link")


def geo(spark: SparkSession, sf_dir: str) -> Graph:
    """Regions, nations, customers, suppliers: nation and region both ways, customers and suppliers to their nation."""
    region, nation = _table(spark, sf_dir, "region"), _table(spark, sf_dir, "nation")
    customer, supplier = _table(spark, sf_dir, "customer"), _table(spark, sf_dir, "supplier")
    r, n, c, s = (t.count() for t in (region, nation, customer, supplier))
    up = nation.select((F.col("n_nationkey") + r).cast("long").alias("src"), F.col("n_regionkey").cast("long").alias("dst"))
    home = lambda t, key, at, base: t.select((F.col(key) + base).cast("long").alias("src"), (F.col(at) + r).cast("long").alias("dst"))
    edges = up.unionByName(up.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).unionByName(home(customer, "c_custkey", "c_nationkey", r + n)).unionByName(home(supplier, "s_suppkey", "s_nationkey", r + n + c))
    return Graph(edges.withColumn("w", F.lit(1.0)), r + n + c + s, "geo")


def dialog(spark: SparkSession, sf_dir: str) -> Graph:
    """Role of a turn to the role of the next turn of its conversation; self loops stay."""
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    nxt = F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))
    pairs = turns.select("role", nxt.alias("next")).filter("next IS NOT NULL").groupBy("role", "next").agg(F.count("*").cast("double").alias("w"))
    keys = materialize(densify(turns.select(F.col("role").alias("key"))), "roles")
    edges = pairs.join(keys.select(F.col("key").alias("role"), F.col("id").alias("src")), "role").join(keys.select(F.col("key").alias("next"), F.col("id").alias("dst")), "next")
    return Graph(edges.select("src", "dst", "w"), keys.count(), "dialog")


def knn(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 4096) -> Graph:
    """Extension: each vector to its k nearest by cosine (ties to the smaller id), weight = rank.

    All pairs of blocks of vectors are compared, one pair of blocks per task; no side is broadcast.
    """
    ship(spark)
    rows = _table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    n = rows.count()
    groups = max(1, -(-n // block))
    place = F.pmod(F.xxhash64("id"), F.lit(groups)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))
    left, right = rows.withColumn("a", place).withColumn("b", every), rows.withColumn("b", place).withColumn("a", every)

    def near(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(x) and len(y):
            y = y.sort_values("id")
            unit = lambda d: (lambda m: m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-30))(np.stack([np.asarray(v, float) for v in d["embedding"]]))
            score, ids, own = unit(x) @ unit(y).T, y["id"].to_numpy(), x["id"].to_numpy()
            score[own[:, None] == ids[None, :]] = -np.inf
            for i, v in enumerate(own):
                best = np.lexsort((ids, -score[i]))[:k]
                out += [(int(v), int(ids[j]), float(score[i, j])) for j in best if np.isfinite(score[i, j])]
        return pd.DataFrame(out, columns=["src", "dst", "score"])

    pairs = left.groupBy("a", "b").cogroup(right.groupBy("a", "b")).applyInPandas(near, "src long, dst long, score double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("score"), "dst"))
    return Graph(pairs.withColumn("w", rank.cast("double")).filter(F.col("w") <= k).select("src", "dst", "w"), n, "knn")


#: The hand-made eight-edge fixture.
TINY8 = ((1, 0, 2.0), (2, 0, 5.0), (0, 1, 1.0), (1, 2, 7.0), (3, 2, 4.0), (0, 3, 3.0), (2, 3, 1.0), (4, 5, 6.0))


def of_rows(spark: SparkSession, rows, n_vertices: int, name: str = "literal") -> Graph:
    return Graph(spark.createDataFrame([(int(a), int(b), float(c)) for a, b, c in rows], EDGE_SCHEMA), n_vertices, name)


def tiny8(spark: SparkSession, sf_dir: str = "") -> Graph:
    return of_rows(spark, TINY8, 6, "tiny8")


BUILDERS: dict[str, Callable[[SparkSession, str], Graph]] = {f.__name__: f for f in (trade, skew, word, basket, event, link, geo, dialog, knn, tiny8)}


def build(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    if name == "word_labelled":
        return word(spark, sf_dir, labelled=True)
    if name == "link_both":
        return symmetrize(link(spark, sf_dir))
    return BUILDERS[name](spark, sf_dir)


def symmetrize(g: Graph) -> Graph:
    """Both directions of every edge; of parallel edges the lightest stays."""
    back = g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return Graph(g.edges.select("src", "dst", "w").unionByName(back).groupBy("src", "dst").agg(F.min("w").alias("w")), g.n_vertices, f"{g.name}_both")


def subgraph(g: Graph, keep: DataFrame) -> Graph:
    """Edges with both ends among keep (id); ids stay as they are."""
    ids = keep.select("id").distinct()
    inside = g.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return Graph(inside.select("src", "dst", "w"), g.n_vertices, f"{g.name}_sub")


def degrees(g: Graph) -> DataFrame:
    """(id, d_in, d_out) of all vertices: one aggregation over both ends of each edge, combined before the shuffle."""
    ends = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("id"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("e"))
    counted = ends.groupBy("e.id").agg(F.sum("e.i").alias("d_in"), F.sum("e.o").alias("d_out"))
    return g.vertices.join(counted, "id", "left").select("id", F.coalesce("d_in", F.lit(0)).cast("long").alias("d_in"), F.coalesce("d_out", F.lit(0)).cast("long").alias("d_out"))


def stats(g: Graph) -> DataFrame:
    """One row of dataset statistics: vertices, edges, average degree, largest degrees, vertices without in- or out-edges."""
    d = degrees(g)
    return d.agg(
        F.count("*").alias("n_vertices"), F.sum("d_in").cast("long").alias("n_edges"), F.round(F.sum("d_in") / F.count("*"), 6).alias("avg_degree"),
        F.max("d_in").alias("max_in"), F.max("d_out").alias("max_out"),
        F.sum((F.col("d_in") == 0).cast("long")).alias("zero_in"), F.sum((F.col("d_out") == 0).cast("long")).alias("zero_out"),
    )
