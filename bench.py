"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Each query is built and fully evaluated; graphs and tiles are prepared once per graph and that time is reported apart, as
the published figures leave loading out too.
"""

from __future__ import annotations

import json
import os
import time

from pullgraph import programs
from pullgraph import queries as q
from pullgraph.baselines.engines import ENGINES
from pullgraph.costs import meters
from pullgraph.engine import tilepath
from pullgraph.engine.program import StopRule
from pullgraph.session import local_session

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", str(os.cpu_count() or 8))
#: Supersteps of the step-time comparison: the first is dropped.
STEPS = 6


def main() -> None:
    spark = local_session("bench", CPUS, int(CPUS) if CPUS.isdigit() else 8)
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    rates: dict[str, float] = {}

    def timed(name: str, run) -> object:
        began = time.time()
        out = run()
        times[name] = round(time.time() - began, 3)
        return out

    for g in ("trade", "skew", "word", "basket"):
        prep = timed(f"prepare_{g}", lambda g=g: q.prepared(spark, SF_DIR, g))
        r = timed(f"pagerank_pull_{g}", lambda: tilepath.run(prep, programs.pagerank(), StopRule(21), tilepath.EngineConfig(cache_mode=0)))
        rates[f"pagerank_step_s_{g}"] = round(meters.mean_step_time(r.log), 4)
        r = timed(f"sssp_pull_{g}", lambda: tilepath.run(prep, programs.sssp(0), StopRule(), tilepath.EngineConfig(cache_mode=0)))
        rates[f"sssp_step_s_{g}"] = round(meters.mean_step_time(r.log), 4)
        rates[f"edges_per_s_{g}"] = round(prep.graph.n_edges / rates[f"pagerank_step_s_{g}"])
    g = q.graph(spark, SF_DIR, "trade")
    for name, engine in ENGINES.items():
        r = timed(f"pagerank_{name}_trade", lambda engine=engine: engine(g, programs.pagerank(), StopRule(STEPS)))
        rates[f"speedup_over_{name}_trade"] = round(meters.mean_step_time(r.log) / rates["pagerank_step_s_trade"], 2)
    for name in ("graph_stats_trade", "tile_splitter_quota_trade", "sssp_frontier_trade", "topk_rank_word", "components_link", "replication_factor_random_trade"):
        timed(name, lambda name=name: q.queries()[name](spark, SF_DIR).write.format("noop").mode("overwrite").save())
    total = round(sum(times.values()), 3)
    print(json.dumps({"metric": "total_seconds", "value": total, "unit": "sec", "queries": times, "rates": rates, "sf": SF_DIR.rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
