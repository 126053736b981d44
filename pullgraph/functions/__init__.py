"""Column functions and SQL twins of the array kernels: everything here stays in the JVM."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def scaled(value: Column, digits: int = 9) -> Column:
    """A double as a whole number of 10**-digits, for comparisons that must not depend on summation order."""
    return F.round(value * F.lit(float(10**digits))).cast("long")


def reached(value: Column) -> Column:
    return F.abs(value) < F.lit(float("inf"))


def pack_csr_sql(edges_with_tile: DataFrame, splitter: DataFrame) -> DataFrame:
    """Tiles by grouping and sorting arrays; for graphs whose tiles are small, and as a check of the packer."""
    e = edges_with_tile.groupBy("tile_id").agg(F.sort_array(F.collect_list(F.struct("dst", "src", "w"))).alias("es"))
    t = splitter.join(e, "tile_id", "left").withColumn("es", F.coalesce("es", F.array().cast("array<struct<dst:bigint,src:bigint,w:double>>")))
    targets = F.sequence(F.col("v_lo"), F.col("v_hi"))
    row = F.transform(targets, lambda v: F.size(F.filter("es", lambda x: x["dst"] < v)).cast("long"))
    return t.select("tile_id", "v_lo", "v_hi", "n_edges", row.alias("row"), F.col("es.src").alias("col"), F.col("es.w").alias("val"))


def bloom_places(value: Column, m_bits: int, k_hash: int) -> Column:
    """Bit numbers of a value: k seeded hashes modulo the size."""
    return F.array(*[F.pmod(F.xxhash64(value, F.lit(i)), F.lit(m_bits)) for i in range(k_hash)])


def bloom_filters(df: DataFrame, key: str, value: str, m_bits: int, k_hash: int) -> DataFrame:
    """(key, bucket, bits): a Bloom filter per key as bitmaps of 32768 bits, built by one aggregation."""
    bit = df.select(key, F.explode(bloom_places(F.col(value), m_bits, k_hash)).alias("b"))
    return bit.groupBy(key, F.bitmap_bucket_number("b").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("bits"))


def bloom_active(filters: DataFrame, key: str, changed: DataFrame, value: str, m_bits: int, k_hash: int) -> DataFrame:
    """(key): keys whose filter holds all bits of some changed value.

    Every changed value is asked of every key, so the number of keys times changed values is the cost; meant for few of
    either.  Filters are joined by bucket, never collected.
    """
    asked = changed.select(value).distinct().select(value, F.explode(bloom_places(F.col(value), m_bits, k_hash)).alias("b")).distinct()
    asked = asked.select(value, F.bitmap_bucket_number("b").alias("bucket"), F.bitmap_bit_position("b").alias("pos"))
    want = asked.groupBy(value).agg(F.count("*").alias("need"))
    byte = F.conv(F.hex(F.substring("bits", (F.col("pos") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    found = filters.join(asked, "bucket").filter(F.getbit(byte, (F.col("pos") % 8).cast("int")) == 1).groupBy(key, value).agg(F.count("*").alias("have"))
    return found.join(want, value).filter("have = need").select(key).distinct()
