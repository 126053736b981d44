"""Gather, apply, broadcast over tiles with full replication.

The driver plays the barrier: it broadcasts the dense state, the tiles whose sources changed run the kernel (one tile per
Arrow batch), each sends one encoded message with its changed values, and after the job all messages are committed at
once, so no value is seen in the superstep that made it.  Messages come as job results while all of them, were they dense,
take no more than half of what the driver may receive at once; beyond that they are files, read back a part at a time.

State is 8 bytes a vertex and component on the driver and on each executor.  With replication="auto" a state and tiles
that exceed `memory_budget` go to the on-demand engine, which holds no array of all vertices; "all" refuses them, and
"cheapest" takes the policy that the memory model finds smaller.
"""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..costs.model import m_aa, m_od
from ..partition.tiles import Prepared, sources
from ..session import materialize, release, ship
from .cache import MODES, choose_mode, decode_payload, encode_tiles, plan_cache
from .exchange import compress, decode, decompress, dense_bytes, encode, sparse_bytes
from .program import StopRule, VertexProgram, np_changed
from .relational import Result
from .replica import Replicas, gather_tile, run_on_demand
from .skip import active_by_bloom, active_exact, tile_filters


@dataclass(frozen=True)
class EngineConfig:
    """servers, workers: the logical cluster of the counted costs; each worker of a server holds one tile at a time.
    skip: none, exact or bloom.  probe_below: above this share of changed vertices all tiles are loaded without asking (1:
    always ask).  audit: with bloom, also count the tiles that were loaded in vain.  cache_mode: None (no cache), 1..4 or
    0 for the automatic choice; cache_capacity: bytes per server.  message_mode: dense, sparse, hybrid.  replication:
    auto, all, on_demand or cheapest."""

    servers: int = 9
    workers: int = 24
    skip: str = "none"
    bloom_fpp: float = 0.01
    probe_below: float = 1.0
    audit: bool = False
    cache_mode: int | None = None
    cache_capacity: int = 1 << 60
    message_mode: str = "hybrid"
    threshold: float | str = 0.8
    codec: str = "snappy"
    replication: str = "auto"
    memory_budget: int = 8 << 30


MESSAGE = "tile_id long, v_lo long, n long, n_edges long, mode string, codec string, n_changed long, raw_bytes long, payload binary"
#: Vertices whose degrees the driver fetches at a time.
FETCH = 1 << 24


def memory_needed(prep: Prepared, program: VertexProgram, cfg: EngineConfig) -> tuple[int, int]:
    """Bytes a server needs with full replication and on demand: states, messages and one tile, or row of one, per worker.

    A state here is the value, its message and the components, 8 bytes each; on demand also the id.
    """
    n, state = prep.graph.n_vertices, 16 + 8 * len(program.components)
    if n == 0:
        return 0, 0
    tile, d_avg = prep.largest_row, prep.graph.n_edges / n
    return round(m_aa(n, tile, cfg.workers, state)), round(m_od(n, d_avg, cfg.servers, tile, cfg.workers, state + 8, capped=True))


def policy(prep: Prepared, program: VertexProgram, cfg: EngineConfig) -> str:
    """all or on_demand."""
    if cfg.replication in ("all", "on_demand"):
        return cfg.replication
    everywhere, on_demand = memory_needed(prep, program, cfg)
    if program.spread:
        return "all"
    if cfg.replication == "cheapest":
        return "all" if everywhere <= on_demand else "on_demand"
    return "all" if everywhere <= cfg.memory_budget else "on_demand"


def _kernel(program: VertexProgram, n: int, value: Replicas, d_out: Replicas | None, tol: float, cfg: EngineConfig, shared: float):
    def run(it):
        for b in it:
            cols = {name: b.column(i) for i, name in enumerate(b.schema.names)}
            for k in range(b.num_rows):
                lo, hi, n_edges = (cols[c][k].as_py() for c in ("v_lo", "v_hi", "n_edges"))
                if "payload" in cols:
                    row, col, val = decode_payload(cols["payload"][k].as_py(), cols["codec"][k].as_py(), hi - lo, n_edges)
                else:
                    row, col = (cols[c][k].values.to_numpy(zero_copy_only=False) for c in ("row", "col"))
                    val = cols["val"][k].values
                    val = None if val is None else val.to_numpy(zero_copy_only=False)
                old = value.at(np.arange(lo, hi))
                new = gather_tile(program, n, lo, row, col, val, old, value.at, d_out.at if d_out else None, shared)
                flags = np_changed(new, old, tol)
                changed = int(flags.sum())
                if cfg.message_mode == "hybrid" and changed == 0:
                    mode, raw = "sparse", b""
                else:
                    mode, raw = encode(new, flags, cfg.message_mode, cfg.threshold)
                out = [[cols["tile_id"][k].as_py()], [lo], [hi - lo], [n_edges], [mode], [cfg.codec], [changed], [len(raw)], [compress(raw, cfg.codec)]]
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, kinds, strict=True)], ["tile_id", "v_lo", "n", "n_edges", "mode", "codec", "n_changed", "raw_bytes", "payload"])

    return run


def _result_limit(spark: SparkSession) -> int:
    """Bytes the driver may receive at once."""
    size = spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get("spark.driver.maxResultSize", "1g"))
    return size if size > 0 else 1 << 62


def _messages(found: DataFrame, by_file: bool) -> Iterator:
    """All messages of a superstep: a job result, or a table that is read part by part and then deleted."""
    if not by_file:
        yield from found.collect()
        return
    kept = materialize(found, "messages")
    yield from kept.toLocalIterator()
    release(kept)


def _degrees(prep: Prepared, n: int) -> np.ndarray:
    out = np.empty(n)
    for lo in range(0, n, FETCH):
        got = prep.degrees.filter((F.col("id") >= lo) & (F.col("id") < lo + FETCH)).select("id", "d_out").toPandas()
        out[got["id"].to_numpy()] = got["d_out"].to_numpy()
    return out


def degrees_everywhere(prep: Prepared) -> tuple[np.ndarray, Replicas]:
    """Out-degrees as an array on the driver and on every worker, fetched once."""
    degree = prep.once("d_out", lambda: _degrees(prep, prep.graph.n_vertices))
    return degree, prep.once("d_out_everywhere", lambda: Replicas(prep.graph.spark, degree))


def run(prep: Prepared, program: VertexProgram, stop: StopRule = StopRule(), cfg: EngineConfig = EngineConfig()) -> Result:
    """Supersteps with counted costs in the log; see EngineConfig for the variants."""
    spark, n = prep.tiles.sparkSession, prep.graph.n_vertices
    ship(spark)
    need = memory_needed(prep, program, cfg)[0]
    if policy(prep, program, cfg) == "on_demand":
        return run_on_demand(prep, program, stop)
    if need > cfg.memory_budget and cfg.replication == "all":
        raise MemoryError(f"full replication needs {need} bytes a server, more than {cfg.memory_budget}; use replication='on_demand' or 'auto'")
    if n == 0:
        return Result(spark.createDataFrame([], "id long, value double"), 0)
    by_file = dense_bytes(n) > _result_limit(spark) // 2
    values = program.np_init(n)
    d_out = None
    if "d_out" in program.components:
        degree, d_out = degrees_everywhere(prep)
    filters = prep.once(f"filters-{cfg.bloom_fpp}", lambda: materialize(tile_filters(prep.tiles, cfg.bloom_fpp), "filters")) if cfg.skip == "bloom" else None
    tile_src = prep.once("sources", lambda: materialize(sources(prep.tiles), "tile-sources")) if cfg.skip == "exact" or cfg.audit else None
    cached, plain, bytes_of = _cache(prep, cfg)
    log, done, held = [], 0, set()
    moved = np.arange(n) if program.start is None else np.array([program.start])
    while stop.max_supersteps is None or done < stop.max_supersteps:
        began = time.time()
        active, exact = _active(spark, prep, program, cfg, filters, tile_src, moved, done, n)
        share = Replicas(spark, values)
        lost = float(values[degree == 0].sum()) / n if program.spread else 0.0
        run_one = _kernel(program, n, share, d_out, stop.tol, cfg, lost)
        parts = [_only(d, active).mapInArrow(run_one, MESSAGE) for d in (cached, plain) if d is not None]
        new, ids, seen = values.copy(), [], []
        for m in _messages(reduce(DataFrame.unionAll, parts), by_file):  # the barrier is behind us: commit
            payload = bytes(m["payload"])
            at, v = decode(decompress(payload, m["codec"]), m["mode"], m["n"])
            new[m["v_lo"] + at] = v
            ids.append(m["v_lo"] + at)
            seen.append((m["tile_id"], m["n"], m["n_edges"], m["n_changed"], m["raw_bytes"], len(payload)))
        share.drop()
        values, moved, done = new, np.concatenate(ids) if ids else np.zeros(0, np.int64), done + 1
        loaded = list(dict.fromkeys(x[0] for x in seen))  # a tile kept in several rows sends a message for each
        # The first time a tile is loaded it comes from disk, whether it is then kept or not.
        read = [t for t in loaded if t not in held]
        held.update(t for t in loaded if bytes_of.get(t, (0, False))[1])
        per_server = Counter(t % cfg.servers for t in loaded)
        log.append(
            {
                "superstep": done, "wall_s": time.time() - began, "changed": len(moved), "update_ratio": len(moved) / n,
                "tiles_total": prep.n_tiles, "tiles_loaded": len(loaded), "tiles_skipped": prep.n_tiles - len(loaded), "tiles_fp": len(loaded) - exact if exact is not None else None,
                "cache_hits": len(loaded) - len(read), "cache_misses": len(read), "disk_read_b": sum(bytes_of.get(t, (0, False))[0] for t in read), "disk_write_b": 0,
                "msg_count": sum(1 for x in seen if x[3]), "msg_dense_b": sum(dense_bytes(x[1]) for x in seen), "msg_sparse_b": sum(sparse_bytes(x[3]) for x in seen),
                "msg_hybrid_b": sum(x[4] for x in seen), "msg_compressed_b": sum(x[5] for x in seen),
                "op_gather": sum(x[2] for x in seen), "op_apply": sum(x[1] for x in seen), "op_broadcast": len(moved),
                "rounds": max((-(-k // cfg.workers) for k in per_server.values()), default=0), "memory_b": need,
            }
        )
        if not len(moved):
            break
    return Result(values_frame(spark, values), done, log)


def _cache(prep: Prepared, cfg: EngineConfig) -> tuple[DataFrame | None, DataFrame | None, dict[int, tuple[int, bool]]]:
    """(tiles held in memory, tiles read each time, size on disk and place of each tile).

    Held tiles are blocks of the executors, made from files when they are first loaded and again if an executor is lost.
    """
    if cfg.cache_mode is None:
        return None, prep.tiles, {}
    mode = cfg.cache_mode
    if mode == 0:
        mode = choose_mode(prep.once("raw_bytes", lambda: raw_bytes(prep)), cfg.cache_capacity * cfg.servers)

    def make():
        encoded = prep.once(f"encoded-{mode}", lambda: materialize(encode_tiles(prep.tiles, MODES[mode]), "encoded", **({"codec": "zstd", "file_rows": 2} if prep.rows is not None else {})))
        # One row per tile.
        sizes = encoded.groupBy("tile_id").agg(F.sum(F.length("payload")).alias("bytes"), F.sum("raw_bytes").alias("raw_bytes"))
        rows = plan_cache(sizes, cfg.cache_capacity, cfg.servers).select("tile_id", "cached", "raw_bytes").collect()
        keep, rest = ([r["tile_id"] for r in rows if r["cached"] == x] for x in (True, False))
        return _only(encoded, keep).persist() if keep else None, _only(prep.tiles, rest) if rest else None, {r["tile_id"]: (r["raw_bytes"], r["cached"]) for r in rows}

    return prep.once(f"cache-{mode}-{cfg.cache_capacity}-{cfg.servers}", make)


def give_up_cache(prep: Prepared) -> None:
    """Free the executors' memory that held tiles take; a later run holds them again, from the encoded files."""
    for name in [k for k in prep.kept if k.startswith("cache-")]:
        held = prep.kept.pop(name)[0]
        if held is not None:
            held.unpersist()


def raw_bytes(prep: Prepared) -> int:
    """Bytes of all tiles as the engine holds them."""
    return prep.tiles.agg(F.sum(8 * (F.size("row") + F.size("col") + F.coalesce(F.size("val"), F.lit(0))))).first()[0] or 0


#: Up to so many tile numbers are written into the plan, where they prune files; more are joined.
LISTED = 1000


def _only(tiles: DataFrame, active: list[int] | None) -> DataFrame:
    """The tiles to load; the list has a number per tile, so broadcasting it is bounded by the number of tiles."""
    if active is None:
        return tiles
    if len(active) <= LISTED:
        return tiles.filter(F.col("tile_id").isin(active))
    return tiles.join(F.broadcast(ids_frame(tiles.sparkSession, np.array(active)).withColumnRenamed("id", "tile_id")), "tile_id", "left_semi")


def _active(spark: SparkSession, prep: Prepared, program: VertexProgram, cfg: EngineConfig, filters, tile_src, moved: np.ndarray, done: int, n: int) -> tuple[list[int] | None, int | None]:
    """(tiles to load, None for all; how many have a changed source, where that is known)."""
    if cfg.skip == "none" or program.spread or done == 0 and program.apply_without_input or len(moved) > cfg.probe_below * n:
        return None, None
    exact = [r[0] for r in active_exact(tile_src, ids_frame(spark, moved)).collect()] if tile_src is not None else None
    if cfg.skip == "exact":
        return exact, len(exact)
    return [r[0] for r in active_by_bloom(filters, moved).collect()], None if exact is None else len(exact)


def ids_frame(spark: SparkSession, ids: np.ndarray) -> DataFrame:
    import pandas as pd

    return spark.createDataFrame(pd.DataFrame({"id": ids.astype(np.int64)}), "id long")


def values_frame(spark: SparkSession, values: np.ndarray) -> DataFrame:
    """(id, value) from a dense array that is broadcast in chunks; rows are made on the executors."""
    shared = Replicas(spark, values)

    def run(it):
        for b in it:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(shared.at(ids))], ["id", "value"])

    return spark.range(len(values)).mapInArrow(run, "id long, value double")
