"""Connected components of a table of links, by smallest labels with shortcuts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialize, release, scoped

MAX_ROUNDS = 200


@scoped
def components(edges: DataFrame) -> DataFrame:
    """(node, component) of every node of edges (a, b); component is the smallest node that can be reached.

    Each round takes the smallest label among neighbours and then the label of one's label.  Every shuffle is a hash
    aggregate with map-side combining or an equi join that adaptive execution can split, so a node with very many links
    is no bottleneck.  Rounds are cut by tables in the shared folder.  Nodes may be of any orderable type; an empty
    table gives an empty result.
    """
    both = materialize(edges.select("a", "b").union(edges.select("b", "a")).filter("a <> b").distinct(), "links")
    if not both.limit(1).count():
        return both.select(F.col("a").alias("node"), F.col("b").alias("component"))
    label = materialize(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("component")), "labels")
    for _ in range(MAX_ROUNDS):
        near = both.join(label.withColumnRenamed("node", "b"), "b").groupBy("a").agg(F.min("component").alias("near"))
        next_ = label.join(near, label.node == near.a).select("node", "component", F.least("component", "near").alias("new"))
        up = label.select(F.col("node").alias("new"), F.col("component").alias("above"))
        next_ = next_.join(up, "new", "left").select("node", F.col("component").alias("was"), F.least("new", F.coalesce("above", "new")).alias("component"))
        kept = materialize(next_, "labels")
        moved = kept.filter("was <> component").limit(1).count()
        release(label)
        label = kept
        if not moved:
            break
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    release(both)
    return label.select("node", "component")
