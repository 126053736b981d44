from pyspark.sql import functions as F

from pullgraph.streaming import ingest
from tests.conftest import SF


def run(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()


def test_stream_counts_edges_and_degrees(spark, tmp_path):
    src = spark.read.parquet(f"{SF}/events.parquet")
    src.repartition(3).write.parquet(str(tmp_path / "ev"))
    ev = ingest.event_stream(spark, str(tmp_path / "ev"))
    run(ingest.windowed_counts(ev, late="365 days"), "w", "complete")
    assert spark.table("w").agg(F.sum("n")).first()[0] == src.count()
    run(ingest.deduplicated(ev, "365 days"), "d")
    assert spark.table("d").count() == src.select("event_id").distinct().count()
    run(ingest.edges_by_key(ev), "e")
    assert 0 < spark.table("e").count() < src.count()
    table = ingest.DegreeTable(spark)
    q = ingest.edges_by_key(ev).select("src", "dst").writeStream.foreachBatch(table.update).start()
    q.processAllAvailable()
    q.stop()
    total = table.table.agg(F.sum("d_in"), F.sum("d_out")).first()
    assert total[0] == total[1] == spark.table("e").count()
    splitter = spark.createDataFrame([(0, 0, 5), (1, 5, 10**9)], "tile_id long, v_lo long, v_hi long")
    assert {r[0] for r in table.stale(splitter).collect()} <= {0, 1}
    run(ingest.sessions(ev, late="365 days"), "s", "append")
