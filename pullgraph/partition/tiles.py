"""First-stage partitioning: tiles of in-edges, balanced by in-degree, in compressed sparse rows.

A tile owns an interval of target ids and every edge into it, so each target has one writer.  Boundaries come from prefix
sums of in-degrees that are computed block by block, edges find their tile by bisection in the boundaries, and one
shuffle brings each tile's edges together, sorted by target, then source.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..graphs import Graph, degrees
from ..pieces import deal, edges_of
from ..session import materialize, release, ship

#: Ids whose prefix sums one window partition holds.
BLOCK = 1 << 20
#: Blocks that one task walks at a time to find where tiles close.
STRIPE = 16
#: Edges of a row, where tiles are kept in several rows: 4 MB with weights, as readers hold pages of whole rows.
ROW_EDGES = 1 << 18
TILE = "tile_id long, v_lo long, v_hi long, n_edges long, `row` array<long>, col array<long>, val array<double>"


@dataclass
class Prepared:
    """A partitioned graph: its degrees, boundaries and tiles, for any number of programs.

    rows: boundaries of the rows that tiles are kept in, where these are not the tiles.
    kept: what engines derive from the tiles and use again in later runs, by name.
    """

    graph: Graph
    degrees: DataFrame
    splitter: DataFrame
    tiles: DataFrame
    n_tiles: int
    weighted: bool
    tile_edges: int
    rows: DataFrame | None = None
    kept: dict[str, object] = field(default_factory=dict)

    def drop(self) -> None:
        """Delete the tiles and what was derived from them; graph and degrees stay."""
        release(self.tiles)
        for x in self.kept.values():
            for y in x if isinstance(x, tuple) else (x,):
                if isinstance(y, DataFrame):
                    y.unpersist()
                    release(y)
                elif hasattr(y, "drop"):
                    y.drop()
        self.kept.clear()

    def once(self, name: str, make: Callable[[], object]):
        if name not in self.kept:
            self.kept[name] = make()
        return self.kept[name]

    @property
    def largest_tile(self) -> int:
        """Bytes of the largest tile as the engine holds it."""
        return self.once("largest_tile", lambda: self._largest(self.splitter))

    @property
    def largest_row(self) -> int:
        """Bytes of the largest tile, or row of one, that a worker has at a time."""
        return self.largest_tile if self.rows is None else self.once("largest_row", lambda: self._largest(self.rows))

    def _largest(self, bounds: DataFrame) -> int:
        return bounds.agg(F.max(8 * (F.col("v_hi") - F.col("v_lo") + 1 + (2 if self.weighted else 1) * F.col("n_edges")))).first()[0] or 0


def out_degrees(g: Graph) -> DataFrame:
    return degrees(g).select("id", "d_out")


def in_degrees(g: Graph) -> DataFrame:
    return degrees(g).select("id", "d_in")


def prefix_sums(deg: DataFrame, block: int = BLOCK) -> DataFrame:
    """(id, d_in, before, through, block): in-edges of smaller ids, and those up to this id.

    Each block of ids has a window of its own; the totals of the blocks before it are added, one number per block.
    """
    rows = deg.select("id", "d_in", F.floor(F.col("id") / block).cast("long").alias("block"))
    totals = rows.groupBy("block").agg(F.sum("d_in").alias("total"))
    # One row per block of BLOCK ids: at most 1e5 rows for 1e11 vertices, so ordering them in one task is bounded.
    start = totals.select("block", (F.sum("total").over(Window.orderBy("block")) - F.col("total")).alias("start"))
    inside = F.sum("d_in").over(Window.partitionBy("block").orderBy("id"))
    out = rows.withColumn("inside", inside).join(F.broadcast(start), "block")
    return out.select("id", "d_in", (F.col("start") + F.col("inside") - F.col("d_in")).cast("long").alias("before"), (F.col("start") + F.col("inside")).cast("long").alias("through"), "block")


def split_greedy(deg: DataFrame, tile_edges: int, block: int = BLOCK, stripe: int = STRIPE) -> DataFrame:
    """(tile_id, v_lo, v_hi, n_edges): a tile closes after the first id that brings it to tile_edges or more.

    Exact and sequential over tiles, not over ids.  Prefix sums are written by stripes of `stripe` blocks; where a tile
    closes in a stripe, one task walks the stripe from where the open tile starts, and the ids that close tiles are all
    the driver sees.  split_quota() needs no walk.
    """
    if tile_edges < 1:
        raise ValueError("a tile needs room for one edge at least")
    spark = deg.sparkSession
    ship(spark)
    sums = prefix_sums(deg, block).select("id", "through", F.floor(F.col("block") / stripe).cast("long").alias("stripe"))
    sums = materialize(sums.repartition("stripe"), "prefix", by=("stripe",))
    stripes = sums.groupBy("stripe").agg(F.max("id").alias("hi"), F.max("through").alias("through")).orderBy("stripe").collect()
    rows, v_lo, start = [], 0, 0
    for x in stripes:
        if x["through"] - start < tile_edges:
            continue
        part = sums.filter(F.col("stripe") == x["stripe"]).select("id", "through").repartition(1).sortWithinPartitions("id")
        for r in part.mapInArrow(_closings(start, tile_edges), "id long, through long").collect():
            rows.append((len(rows), v_lo, r["id"] + 1, r["through"] - start))
            v_lo, start = r["id"] + 1, r["through"]
    if stripes and v_lo <= stripes[-1]["hi"]:
        rows.append((len(rows), v_lo, stripes[-1]["hi"] + 1, stripes[-1]["through"] - start))
    release(sums)
    return spark.createDataFrame(rows, "tile_id long, v_lo long, v_hi long, n_edges long")


def _closings(start: int, tile_edges: int) -> Callable:
    """Walk over (id, through) in order of id; start: edges before the tile that is open."""

    def run(it):
        at = start
        for b in it:
            through, closed = b.column(1).to_numpy(zero_copy_only=False), []
            while (k := int(np.searchsorted(through, at + tile_edges))) < len(through):
                closed.append(k)
                at = int(through[k])
            yield b.take(pa.array(closed, pa.int64()))

    return run


def split_quota(deg: DataFrame, tile_edges: int, block: int = BLOCK) -> DataFrame:
    """Extension for very many tiles: an id belongs to tile floor(in-edges of smaller ids / tile_edges).

    No step depends on another; tiles are within tile_edges plus the largest in-degree.  Numbers that a hub skips are
    closed up.
    """
    q = prefix_sums(deg, block).withColumn("q", F.floor(F.col("before") / tile_edges))
    tiles = q.groupBy("q").agg(F.min("id").alias("v_lo"), (F.max("id") + 1).alias("v_hi"), F.sum("d_in").cast("long").alias("n_edges"))
    # One row per tile.
    return tiles.select((F.row_number().over(Window.orderBy("q")) - 1).cast("long").alias("tile_id"), "v_lo", "v_hi", "n_edges")


def split_rows(deg: DataFrame, splitter: DataFrame, row_edges: int) -> tuple[DataFrame, dict[int, int]]:
    """(tile_id, v_lo, v_hi, n_edges) of rows instead of tiles, numbered through, and the tile of each row.

    A tile with more than row_edges edges is cut where the edges before a target pass a multiple of row_edges, so a row
    has fewer than row_edges plus the largest in-degree; smaller tiles are one row.
    """
    whole = splitter.orderBy("tile_id").collect()
    start, at = {}, 0  # first target of a row: edges of smaller targets, tile
    for t in whole:
        start[t["v_lo"]] = (at, t["tile_id"])
        at += t["n_edges"]
    if any(t["n_edges"] > row_edges for t in whole):
        lows, at = [t["v_lo"] for t in whole], 0
        for q in split_quota(deg, row_edges).orderBy("tile_id").collect():
            t = whole[bisect_right(lows, q["v_lo"]) - 1]
            if t["n_edges"] > row_edges:
                start[q["v_lo"]] = (at, t["tile_id"])
            at += q["n_edges"]
    lows = sorted(start)
    ends = [*((lo, start[lo][0]) for lo in lows[1:]), *((t["v_hi"], at) for t in whole[-1:])]
    rows = [(k, lo, hi, through - start[lo][0]) for k, (lo, (hi, through)) in enumerate(zip(lows, ends, strict=True))]
    return deg.sparkSession.createDataFrame(rows, "tile_id long, v_lo long, v_hi long, n_edges long"), {k: start[lo][1] for k, lo in enumerate(lows)}


def assign(edges: DataFrame, splitter: DataFrame) -> DataFrame:
    """edges with tile_id, by bisection of dst in the boundaries: 16 bytes per tile travel with each task."""
    ship(edges.sparkSession)
    bounds = splitter.orderBy("tile_id").select("tile_id", "v_lo").toPandas()
    lows, tile_ids = bounds["v_lo"].to_numpy(np.int64), bounds["tile_id"].to_numpy(np.int64)

    def run(it):
        for b in it:
            at = np.searchsorted(lows, b.column(1).to_numpy(zero_copy_only=False), side="right") - 1
            yield pa.RecordBatch.from_arrays([pa.array(tile_ids[at] if len(at) else at, pa.int64()), *b.columns[:3]], ["tile_id", "src", "dst", "w"])

    return edges.select("src", "dst", "w").mapInArrow(run, "tile_id long, src long, dst long, w double")


def assign_by_range(edges: DataFrame, splitter: DataFrame) -> DataFrame:
    """The same by a range join with the splitter (one row per tile) broadcast."""
    s = F.broadcast(splitter.select("tile_id", "v_lo", "v_hi"))
    return edges.join(s, (edges["dst"] >= s["v_lo"]) & (edges["dst"] < s["v_hi"])).select("tile_id", "src", "dst", "w")


def assign_servers(tiles: DataFrame, servers: int) -> DataFrame:
    """Second stage: tiles go round the servers."""
    return tiles.withColumn("server_id", F.pmod("tile_id", F.lit(servers)).cast("int"))


def pack_csr(edges_with_tile: DataFrame, splitter: DataFrame, weighted: bool = True, partitions: int | None = None, owner: dict[int, int] | None = None) -> DataFrame:
    """Tiles (row, col, val); one shuffle of the edges, as arrays, and one tile in memory at a time, where it is sorted.

    owner: where the numbers are those of split_rows(), the tile that each row belongs to.

    row has one offset per target and the total; targets without in-edges keep an empty row.  Unweighted tiles have a
    null val.  Tiles without edges are made from the splitter.
    """
    ship(edges_with_tile.sparkSession)
    bounds = splitter.orderBy("tile_id").select("tile_id", "v_lo", "v_hi").toPandas()
    span = {int(t): (int(a), int(b)) for t, a, b in bounds.itertuples(index=False)}
    n = partitions or max(1, min(len(span), 4 * int(edges_with_tile.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    names = ["tile_id", "v_lo", "v_hi", "n_edges", "row", "col", "val"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.float64())]

    def run(it):
        for tile_id, src, dst, w in edges_of(it):
            lo, hi = span[tile_id]
            order = np.lexsort((w, src, dst))
            row = np.concatenate([[0], np.cumsum(np.bincount(dst - lo, minlength=hi - lo))])
            values = [[owner[tile_id] if owner else tile_id], [lo], [hi], [len(src)], [row], [src[order]], [w[order] if weighted else None]]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names)

    # The tile's number is the partition's: hashing few tiles would leave some tasks empty and others with several.
    dealt = deal(edges_with_tile.select("tile_id", "src", "dst", "w"), len(span), n)
    packed = (dealt.sortWithinPartitions("key") if n < len(span) else dealt).mapInArrow(run, TILE)
    own = F.element_at(F.create_map(*[F.lit(x) for kv in owner.items() for x in kv]), F.col("tile_id")) if owner else F.col("tile_id")
    empty = splitter.filter("n_edges = 0").select(
        own.cast("long").alias("tile_id"), "v_lo", "v_hi", "n_edges", F.array_repeat(F.lit(0).cast("long"), (F.col("v_hi") - F.col("v_lo") + 1).cast("int")).alias("row"),
        F.array().cast("array<long>").alias("col"), (F.array().cast("array<double>") if weighted else F.lit(None).cast("array<double>")).alias("val"),
    )
    return packed.unionByName(empty)


def prepare(g: Graph, tile_edges: int | None = None, n_tiles: int | None = None, weighted: bool = True, split: str = "greedy", row_edges: int | None = None, deg: DataFrame | None = None) -> Prepared:
    """Degrees, boundaries and tiles, written once to the shared folder.

    The size is given as edges per tile, or as a number of tiles (size = edges / tiles, rounded up).  row_edges: larger
    tiles are kept in several rows of about so many edges, which the tile kernel works on one at a time; else a tile is one row.
    deg: the degrees, if they are there already.
    """
    g = g.stored()
    if tile_edges is None:
        tile_edges = max(1, -(-g.n_edges // (n_tiles or 32)))
    deg = deg if deg is not None else materialize(degrees(g), "degrees")
    splitter = (split_greedy if split == "greedy" else split_quota)(deg, tile_edges)
    if split != "greedy":
        splitter = materialize(splitter, "splitter")
    rows, owner = split_rows(deg, splitter, row_edges) if row_edges else (splitter, None)
    tiles = materialize(pack_csr(assign(g.edges, rows), rows, weighted, owner=owner), "tiles", codec="zstd" if owner else None)
    return Prepared(g, deg, splitter, tiles, splitter.count(), weighted, tile_edges, rows if row_edges else None)


def unpack(tiles: DataFrame) -> DataFrame:
    """(tile_id, src, dst, w): the edges back from the rows, with SQL functions alone."""
    targets = F.flatten(F.transform(F.sequence(F.lit(0), F.size("row") - 2), lambda i: F.array_repeat(F.col("v_lo") + i, (F.col("row")[i + 1] - F.col("row")[i]).cast("int"))))
    weights = F.coalesce("val", F.transform("col", lambda _: F.lit(1.0)))
    return tiles.filter("n_edges > 0").select("tile_id", F.explode(F.arrays_zip(F.col("col").alias("src"), targets.alias("dst"), weights.alias("w"))).alias("e")).select("tile_id", "e.src", "e.dst", "e.w")


def sources(tiles: DataFrame) -> DataFrame:
    """(tile_id, src): the distinct sources of each tile."""
    return tiles.select("tile_id", F.explode(F.array_distinct("col")).alias("src"))


def audit(tiles: DataFrame) -> DataFrame:
    """Per tile: size, targets, whether rows agree with edges, and whether the next tile starts where it ends."""
    nxt = F.lead("v_lo").over(Window.orderBy("tile_id"))  # one row per tile
    return tiles.select(
        "tile_id", "v_lo", "v_hi", "n_edges", (F.col("v_hi") - F.col("v_lo")).alias("n_targets"),
        ((F.size("row") == F.col("v_hi") - F.col("v_lo") + 1) & (F.element_at("row", -1) == F.col("n_edges")) & (F.size("col") == F.col("n_edges"))).alias("rows_agree"),
        F.coalesce(nxt == F.col("v_hi"), F.lit(True)).alias("next_follows"),
    )
