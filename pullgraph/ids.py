"""Dense ids and global order without a single-partition window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import materialize


def ordered_rows(df: DataFrame, *order: str, partitions: int | None = None) -> DataFrame:
    """df with part and at: the number of its range partition in the order, and its place inside.

    The range bounds come from a sample and may differ from run to run, so the outcome is written once and read back;
    (part, at) is a total order that agrees with `order`.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(n, *order).sortWithinPartitions(*order)
    step = F.monotonically_increasing_id()
    return materialize(ranged.withColumn("part", F.shiftright(step, 33)).withColumn("at", step.bitwiseAND(F.lit((1 << 33) - 1))), "ordered")


def by_part(df: DataFrame, value: Column, default: Column) -> Column:
    """Column that maps part to a value aggregated per part; the map has one entry per partition, never per row."""
    found = {r["part"]: r["v"] for r in df.groupBy("part").agg(value.alias("v")).collect()}
    if not found:
        return default
    pairs = [F.lit(x) for kv in sorted(found.items()) for x in kv]
    return F.coalesce(F.try_element_at(F.create_map(*pairs), F.col("part")), default)


def densify(keys: DataFrame, key: str = "key") -> DataFrame:
    """(key, id): distinct keys numbered 0..n-1 in byte order; null keys are dropped."""
    rows = ordered_rows(keys.select(F.col(key).alias("key")).filter("key IS NOT NULL").distinct(), "key")
    counts = {r["part"]: r["count"] for r in rows.groupBy("part").count().collect()}
    before, total = {}, 0
    for p in sorted(counts):
        before[p], total = total, total + counts[p]
    if not before:
        return rows.select("key", F.col("at").alias("id"))
    offset = F.create_map(*[F.lit(x) for kv in before.items() for x in kv])
    return rows.select("key", (F.element_at(offset, F.col("part")) + F.col("at")).alias("id"))


def follow(df: DataFrame, value: str, *order: str) -> DataFrame:
    """(this, next): each row's value with that of the row after it in the whole order.

    Inside a range partition a window finds the next row; the last row of a partition takes the first value of the next
    partition that has rows.
    """
    rows = ordered_rows(df, *order)
    firsts = {r["part"]: r["v"] for r in rows.groupBy("part").agg(F.min_by(value, "at").alias("v")).collect()}
    parts = sorted(firsts)
    after = {p: firsts[q] for p, q in zip(parts, parts[1:], strict=False)}
    border = F.try_element_at(F.create_map(*[F.lit(x) for kv in after.items() for x in kv]), F.col("part")) if after else F.lit(None)
    nxt = F.lead(value).over(Window.partitionBy("part").orderBy("at"))
    return rows.select(F.col(value).alias("this"), F.coalesce(nxt, border).alias("next")).filter("next IS NOT NULL")
