"""Operators around the methods: SQL views, ranking, sketches, set operations, interval and as-of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..graphs import Graph, degrees
from ..partition.tiles import Prepared, assign_servers


def register_views(prep: Prepared, values: DataFrame | None = None, prefix: str = "") -> None:
    """edges, degrees, tiles, splitter (and states) as temporary views for spark.sql."""
    for name, df in (("edges", prep.graph.edges), ("degrees", prep.degrees), ("tiles", assign_servers(prep.tiles, 9)), ("splitter", prep.splitter), ("states", values)):
        if df is not None:
            df.createOrReplaceTempView(prefix + name)


def neighbours(spark: SparkSession, vertex: int, prefix: str = "") -> DataFrame:
    """In-neighbours of a vertex by parameterised SQL over the edges view."""
    return spark.sql(f"SELECT src, w FROM {prefix}edges WHERE dst = :v", args={"v": vertex})


@udtf(returnType="src: bigint, dst: bigint, w: double")
class ExplodeTile:
    """Table function: a tile (v_lo, row, col, val) as its edges."""

    def eval(self, v_lo: int, row: list, col: list, val: list):
        for i in range(len(row) - 1):
            for k in range(row[i], row[i + 1]):
                yield col[k], v_lo + i, 1.0 if val is None else val[k]


def top_vertices(values: DataFrame, k: int) -> DataFrame:
    """The k largest values, ties to the smaller id."""
    return values.orderBy(F.desc("value"), "id").limit(k)


def farthest(values: DataFrame, k: int) -> DataFrame:
    """The k farthest vertices that are reached."""
    return top_vertices(values.filter(F.abs("value") < F.lit(float("inf"))), k)


def heaviest_tiles(splitter: DataFrame, k: int) -> DataFrame:
    return splitter.orderBy(F.desc("n_edges"), "tile_id").limit(k)


def degree_ranks(g: Graph, buckets: int = 10) -> DataFrame:
    """(bucket, n, least, most): vertices by in-degree in equal-width shares of its distinct values.

    Ranks are over the distinct degrees, a small table, so no window holds the vertices.
    """
    by = degrees(g).groupBy("d_in").agg(F.count("*").alias("n"))
    w = Window.orderBy("d_in")
    ranked = by.withColumn("bucket", F.ntile(buckets).over(w)).withColumn("share", F.percent_rank().over(w))
    return ranked.groupBy("bucket").agg(F.sum("n").alias("n"), F.min("d_in").alias("least"), F.max("d_in").alias("most"))


def distinct_sources_sketch(edges_with_tile: DataFrame) -> DataFrame:
    """(tile_id, estimate): distinct sources per tile by a mergeable sketch."""
    return edges_with_tile.groupBy("tile_id").agg(F.hll_sketch_estimate(F.hll_sketch_agg("src")).alias("estimate"))


def reached_sets(a: DataFrame, b: DataFrame) -> DataFrame:
    """(kind, n): vertices reached in both results, in the first only, in the second only."""
    x, y = (v.filter(F.abs("value") < F.lit(float("inf"))).select("id") for v in (a, b))
    parts = (("both", x.intersect(y)), ("first", x.exceptAll(y)), ("second", y.exceptAll(x)))
    out = None
    for kind, df in parts:
        row = df.agg(F.count("*").alias("n")).select(F.lit(kind).alias("kind"), "n")
        out = row if out is None else out.unionByName(row)
    return out


def parents(g: Graph, distances: DataFrame) -> DataFrame:
    """(id, parent): the smallest in-neighbour on a shortest path, for reached vertices other than the source."""
    s = distances.select(F.col("id").alias("src"), F.col("value").alias("sv"))
    t = distances.select(F.col("id").alias("dst"), F.col("value").alias("tv"))
    tight = g.edges.join(s, "src").join(t, "dst").filter((F.abs("tv") < F.lit(float("inf"))) & (F.col("sv") + F.col("w") == F.col("tv")) & (F.col("src") != F.col("dst")))
    return tight.groupBy(F.col("dst").alias("id")).agg(F.min_by("src", F.struct("sv", "src")).alias("parent"))


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the last earlier or equal `value` of right per key, by one union and one window, without a range join."""
    cols = left.columns
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__side"))
    b = right.select(*[F.col(c) if c in (key, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.col(value).alias("__v"), F.lit(0).alias("__side"))
    w = Window.partitionBy(key).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn(f"{value}_as_of", F.last("__v", ignorenulls=True).over(w))
    return both.filter("__side = 1").drop("__v", "__side")


def within_interval(events: DataFrame, seconds: int, key: str = "event_type") -> DataFrame:
    """(src, dst): users of two events of one key at most `seconds` apart, by time buckets and an equi join.

    Each event goes to its bucket and the one before, so that every pair within the interval meets in one bucket.
    """
    t = F.col("ts").cast("timestamp").cast("long")
    rows = events.select(key, F.col("user_id"), "event_id", t.alias("t"), F.floor(t / seconds).alias("b"))
    later = rows.select(key, F.col("user_id").alias("dst"), F.col("event_id").alias("e2"), F.col("t").alias("t2"), F.explode(F.array(F.col("b"), F.col("b") - 1)).alias("b"))
    pairs = rows.join(later, [key, "b"]).filter((F.col("t2") >= F.col("t")) & (F.col("t2") - F.col("t") <= seconds) & (F.col("e2") != F.col("event_id")) & (F.col("user_id") != F.col("dst")))
    return pairs.select(F.col("user_id").alias("src"), "dst", "event_id", "e2")


def degree_sets(g: Graph) -> DataFrame:
    """Vertices by whether they have in-edges and out-edges, with grouping sets over both."""
    flags = degrees(g).select((F.col("d_in") > 0).alias("has_in"), (F.col("d_out") > 0).alias("has_out"))
    flags.createOrReplaceTempView("__degree_flags")
    return g.spark.sql("SELECT has_in, has_out, count(*) AS n FROM __degree_flags GROUP BY GROUPING SETS ((has_in, has_out), (has_in), (has_out), ())")
