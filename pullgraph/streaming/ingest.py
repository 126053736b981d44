"""Extension: append-only edge streams.

Events arrive in files; a watermark bounds lateness, duplicates within it are dropped, windows count edges, a keyed state
remembers each key's last user, and each micro-batch merges its degrees into a table that tells which tiles are stale.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..ids import ordered_rows
from ..session import materialize, ship

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def daily_edges(events: DataFrame) -> DataFrame:
    """(day, n_edges, n_sources): edges from each event's user to the next event's, per day of the first event."""
    from pyspark.sql import Window

    rows = ordered_rows(events.select("ts", "event_id", "user_id"), "ts", "event_id")
    firsts = {r["part"]: r["v"] for r in rows.groupBy("part").agg(F.min_by("user_id", "at").alias("v")).collect()}
    parts = sorted(firsts)
    after = [F.lit(x) for p, q in zip(parts, parts[1:], strict=False) for x in (p, firsts[q])]
    border = F.try_element_at(F.create_map(*after), F.col("part")) if after else F.lit(None).cast("long")
    dst = F.coalesce(F.lead("user_id").over(Window.partitionBy("part").orderBy("at")), border)
    edges = rows.select(F.date_trunc("DAY", "ts").cast("timestamp_ntz").alias("day"), F.col("user_id").alias("src"), dst.alias("dst")).filter("dst IS NOT NULL AND src <> dst")
    return edges.groupBy(F.date_format("day", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n_edges"), F.countDistinct("src").alias("n_sources"))


def event_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A stream of events from parquet files, with ts as a timestamp that a watermark can use."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Events per window and type: tumbling, or sliding with `slide`; rows behind the watermark are dropped."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("value")).select("w.start", "w.end", "event_type", "n", "value")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    s = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy(s.alias("w"), "user_id").agg(F.count("*").alias("n")).select("w.start", "w.end", "user_id", "n")


def edges_by_key(events: DataFrame, key: str = "event_type") -> DataFrame:
    """(key, src, dst, ts): from the last user of a key to the next, across micro-batches; one long of state per key."""
    ship(events.sparkSession)

    def link(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for t in rows.itertuples(index=False):
            if last is not None and last != t.user_id:
                out.append((k[0], last, t.user_id, t.ts))
            last = int(t.user_id)
        if last is not None:
            state.update((last,))
        yield pd.DataFrame(out, columns=["key", "src", "dst", "ts"])

    return events.groupBy(key).applyInPandasWithState(link, "key string, src long, dst long, ts timestamp", "last long", "append", GroupStateTimeout.NoTimeout)


class DegreeTable:
    """Degrees and stale tiles kept up to date by foreachBatch.

    update() merges a micro-batch of edges (src, dst) into the degrees with one aggregation; stale(splitter) lists the
    tiles that got in-edges since the last call, which alone need packing again.
    """

    def __init__(self, spark: SparkSession) -> None:
        self.table = materialize(spark.createDataFrame([], "id long, d_in long, d_out long"), "degree-table")
        self.touched = materialize(spark.createDataFrame([], "dst long"), "touched")

    def update(self, batch: DataFrame, _: int = 0) -> None:
        ends = batch.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("id"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("e")).select("e.id", F.col("e.i").cast("long").alias("d_in"), F.col("e.o").cast("long").alias("d_out"))
        merged = self.table.unionByName(ends).groupBy("id").agg(F.sum("d_in").alias("d_in"), F.sum("d_out").alias("d_out"))
        self.table = materialize(merged, "degree-table")
        self.touched = materialize(self.touched.union(batch.select("dst")).distinct(), "touched")

    def stale(self, splitter: DataFrame) -> DataFrame:
        t = F.broadcast(splitter.select("tile_id", "v_lo", "v_hi"))  # one row per tile
        return self.touched.join(t, (F.col("dst") >= F.col("v_lo")) & (F.col("dst") < F.col("v_hi"))).select("tile_id").distinct()
