"""DuckDB SQL of the graph queries, put together from one part per graph and one per measure."""

from __future__ import annotations

from .queries import COMPARED, GRAPHS, STEPS, TILES, TIMED_STEPS, WORKERS
from .workloads import COMPARED as ENGINES
from .workloads import SIZES

#: Common table expressions that end in e(src, dst, w), nv(n) and ne(m) for each graph.
EDGES = {
    "trade": """
  c AS (SELECT (SELECT count(*) FROM customer) AS nc, (SELECT count(*) FROM part) AS np, (SELECT count(*) FROM supplier) AS ns),
  l AS (SELECT o_custkey AS cu, l_partkey + nc AS pa, l_suppkey + nc + np AS su, l_quantity AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey, c),
  e AS (SELECT src, dst, min(q) AS w FROM (SELECT cu AS src, pa AS dst, q FROM l UNION ALL SELECT pa, su, q FROM l UNION ALL SELECT su, cu, q FROM l) GROUP BY src, dst),
  nv AS (SELECT nc + np + ns AS n FROM c)""",
    "skew": """
  nv AS (SELECT count(*) AS n FROM part),
  k AS (SELECT l_partkey AS src, (l_suppkey * 37 + l_partkey * 11 + l_linenumber * 101 + l_orderkey * 7) % n AS k, n, l_quantity AS q FROM lineitem, nv),
  e AS (SELECT src, dst, min(q) AS w FROM (SELECT src, (k * k * k) // (n * n) AS dst, q FROM k) WHERE src <> dst GROUP BY src, dst)""",
    "word": """
  t AS (SELECT regexp_extract_all(lower(text), '[a-z]+') AS ws FROM documents WHERE lang = 'en'),
  p AS (SELECT ws[i] AS a, ws[i + 1] AS b FROM (SELECT ws, unnest(range(1, len(ws))) AS i FROM t)),
  v AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM (SELECT a AS key FROM p WHERE a <> b UNION SELECT b FROM p WHERE a <> b)),
  nv AS (SELECT count(*) AS n FROM v),
  e AS (SELECT x.id AS src, y.id AS dst, w FROM (SELECT a, b, CAST(count(*) AS DOUBLE) AS w FROM p WHERE a <> b GROUP BY a, b) JOIN v x ON x.key = a JOIN v y ON y.key = b)""",
    "basket": """
  nv AS (SELECT count(*) AS n FROM part),
  p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS src FROM lineitem),
  q AS (SELECT src, lead(src) OVER (PARTITION BY o ORDER BY src) AS dst FROM p),
  e AS (SELECT src, dst, CAST(count(*) AS DOUBLE) AS w FROM q WHERE dst IS NOT NULL GROUP BY src, dst)""",
    "event": """
  nv AS (SELECT max(user_id) + 1 AS n FROM events),
  q AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events),
  e AS (SELECT src, dst, CAST(count(*) AS DOUBLE) AS w FROM q WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst)""",
    "link": """
  h AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS key FROM pages),
  np AS (SELECT count(*) AS np FROM pages),
  v AS (SELECT key, row_number() OVER (ORDER BY key) - 1 + (SELECT np FROM np) AS id FROM (SELECT DISTINCT key FROM h)),
  nv AS (SELECT np + (SELECT count(*) FROM v) AS n FROM np),
  e AS (SELECT page_id AS src, id AS dst, CAST(count(*) AS DOUBLE) AS w FROM h JOIN v USING (key) GROUP BY page_id, id)""",
}
EDGES["geo"] = """
  c AS (SELECT (SELECT count(*) FROM region) AS r, (SELECT count(*) FROM nation) AS n, (SELECT count(*) FROM customer) AS cu, (SELECT count(*) FROM supplier) AS su),
  nv AS (SELECT r + n + cu + su AS n FROM c),
  e AS (SELECT n_nationkey + r AS src, n_regionkey AS dst, 1.0::DOUBLE AS w FROM nation, c UNION ALL SELECT n_regionkey, n_nationkey + r, 1.0 FROM nation, c
    UNION ALL SELECT c_custkey + r + n, c_nationkey + r, 1.0 FROM customer, c UNION ALL SELECT s_suppkey + r + n + cu, s_nationkey + r, 1.0 FROM supplier, c)"""
EDGES["dialog"] = """
  q AS (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations),
  v AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM (SELECT DISTINCT role AS key FROM conversations WHERE role IS NOT NULL)),
  nv AS (SELECT count(*) AS n FROM v),
  e AS (SELECT x.id AS src, y.id AS dst, w FROM (SELECT role, nxt, CAST(count(*) AS DOUBLE) AS w FROM q WHERE nxt IS NOT NULL GROUP BY role, nxt) JOIN v x ON x.key = role JOIN v y ON y.key = nxt)"""
EDGES["word_labelled"] = EDGES["word"].replace("WHERE lang = 'en'", "WHERE lang = 'en' AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")

MORE = """,
  ids AS (SELECT unnest(range(0, (SELECT n FROM nv))) AS id),
  o AS (SELECT src, count(*) AS d_out FROM e GROUP BY src), i AS (SELECT dst, count(*) AS d_in FROM e GROUP BY dst),
  dg AS (SELECT id, coalesce(d_in, 0) AS d_in, coalesce(d_out, 0) AS d_out FROM ids LEFT JOIN i ON i.dst = id LEFT JOIN o ON o.src = id)"""
#: sz(s, n): tile size and number of vertices; pre(id, through); sp(tile_id, v_lo, v_hi, n_edges): greedy boundaries.
SPLIT_INTO = """,
  sz AS (SELECT greatest(1, (count(*) + {tiles} - 1) // {tiles}) AS s, (SELECT n FROM nv) AS n, count(*) AS m FROM e),
  pre AS (SELECT id, d_in, CAST(sum(d_in) OVER (ORDER BY id) AS BIGINT) AS through FROM dg),
  sg(tile_id, v_lo, v_hi, a, b) AS (
    SELECT 0, 0, coalesce((SELECT min(id) + 1 FROM pre WHERE through >= s), n), 0, coalesce((SELECT min(through) FROM pre WHERE through >= s), m) FROM sz
    UNION ALL
    SELECT tile_id + 1, v_hi, coalesce((SELECT min(id) + 1 FROM pre WHERE through >= b + s), n), b, coalesce((SELECT min(through) FROM pre WHERE through >= b + s), m)
    FROM sg, sz WHERE v_hi < n),
  sp AS (SELECT CAST(tile_id AS BIGINT) AS tile_id, CAST(v_lo AS BIGINT) AS v_lo, CAST(v_hi AS BIGINT) AS v_hi, CAST(b - a AS BIGINT) AS n_edges FROM sg)"""
SPLIT = SPLIT_INTO.format(tiles=TILES)
BALANCE = "count(*) AS n_tiles, min(n_edges) AS min_edges, max(n_edges) AS max_edges, round(avg(n_edges), 6) AS avg_edges, round(stddev_pop(n_edges), 6) AS std_edges, round(max(n_edges) / any_value(s), 6) AS max_ratio, round(min(n_edges) / any_value(s), 6) AS min_ratio"
#: aug: edges with out-degrees and one row per vertex for itself.
AUG = """,
  aug AS (SELECT e.src, e.dst, e.w, o.d_out, false AS own FROM e JOIN o ON o.src = e.src UNION ALL SELECT id, id, 0, 1, true FROM ids)"""
PR = """,
  pr(step, id, v) AS (SELECT 0, id, 1.0::DOUBLE / (SELECT n FROM nv) FROM ids
    UNION ALL SELECT step + 1, dst, 0.15::DOUBLE / (SELECT n FROM nv) + 0.85::DOUBLE * sum(CASE WHEN own THEN 0.0::DOUBLE ELSE v / d_out END)
    FROM pr JOIN aug ON pr.id = aug.src WHERE step < {steps} GROUP BY step, dst)"""
SSSP = """,
  ds(step, id, v) AS (SELECT 0, id, CASE WHEN id = 0 THEN 0.0::DOUBLE ELSE 'inf'::DOUBLE END FROM ids
    UNION ALL SELECT step + 1, dst, min(CASE WHEN own THEN v ELSE v + {w} END) FROM ds JOIN aug ON ds.id = aug.src WHERE step < {steps} GROUP BY step, dst),
  ch AS (SELECT x.step AS superstep, x.id FROM ds x JOIN ds y ON x.id = y.id AND x.step = y.step + 1 WHERE x.v <> y.v)"""
RANKS = "SELECT CAST(id AS BIGINT) AS id, CAST(round(v * 1e9) AS BIGINT) AS rank_e9 FROM pr WHERE step = {steps}"
DISTANCES = "SELECT CAST(id AS BIGINT) AS id, CAST(v AS BIGINT) AS distance FROM ds WHERE step = {steps} AND isfinite(v)"
FAR = 25


def _with(g: str, *parts: str) -> str:
    return "WITH RECURSIVE " + EDGES[g] + "".join(parts) + "\n"


def _per_graph(g: str) -> dict[str, str]:
    base = _with(g, MORE)
    split = _with(g, MORE, SPLIT)
    tile = "e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi"
    return {
        f"graph_stats_{g}": base + "SELECT count(*) AS n_vertices, CAST(sum(d_in) AS BIGINT) AS n_edges, round(sum(d_in) / count(*), 6) AS avg_degree, max(d_in) AS max_in, max(d_out) AS max_out, CAST(sum(CAST(d_in = 0 AS BIGINT)) AS BIGINT) AS zero_in, CAST(sum(CAST(d_out = 0 AS BIGINT)) AS BIGINT) AS zero_out FROM dg",
        f"out_degrees_{g}": base + "SELECT id, d_out FROM dg",
        f"in_degrees_{g}": base + "SELECT id, d_in FROM dg",
        f"tile_splitter_greedy_{g}": split + "SELECT tile_id, v_lo, v_hi, n_edges FROM sp",
        f"tile_splitter_quota_{g}": split + "SELECT CAST(row_number() OVER (ORDER BY q) - 1 AS BIGINT) AS tile_id, v_lo, v_hi, n_edges FROM (SELECT (through - d_in) // s AS q, min(id) AS v_lo, max(id) + 1 AS v_hi, CAST(sum(d_in) AS BIGINT) AS n_edges FROM pre, sz GROUP BY q)",
        f"tile_balance_{g}": split + f"SELECT {BALANCE} FROM sp, sz",
        f"tile_servers_{g}": split + "SELECT CAST(tile_id % 9 AS INTEGER) AS server_id, count(*) AS n_tiles, CAST(sum(n_edges) AS BIGINT) AS n_edges FROM sp GROUP BY 1",
        f"tile_roundtrip_{g}": split + f"SELECT tile_id, CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(w AS DOUBLE) AS w FROM {tile}",
        f"tile_sources_{g}": split + f"SELECT tile_id, count(DISTINCT src) AS n_sources FROM {tile} GROUP BY tile_id",
        f"pagerank_pull_{g}": _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS),
        f"pagerank_tilekernel_{g}": _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS),
        f"sssp_pull_{g}": _with(g, MORE, AUG, SSSP.format(w="w", steps=FAR)) + DISTANCES.format(steps=FAR),
        f"sssp_tilekernel_{g}": _with(g, MORE, AUG, SSSP.format(w="w", steps=FAR)) + DISTANCES.format(steps=FAR),
        f"sssp_unit_{g}": _with(g, MORE, AUG, SSSP.format(w="1", steps=FAR)) + DISTANCES.format(steps=FAR),
        f"sssp_unreached_{g}": _with(g, MORE, AUG, SSSP.format(w="w", steps=FAR)) + f"SELECT CAST(id AS BIGINT) AS id FROM ds WHERE step = {FAR} AND NOT isfinite(v)",
        f"combine_eta_{g}": _with(g) + "SELECT CAST(sum(n) AS BIGINT) AS raw, count(*) AS combined, round(count(*) / sum(n), 6) AS eta FROM (SELECT count(*) AS n FROM e GROUP BY src % 36, dst)",
    }


#: Part of an edge in the vertex-cuts of {n} servers.
PARTS = {"random": "(src * 31 + dst * 17) % {n}", "hybrid": "CASE WHEN d_in <= 100 THEN dst ELSE src END % {n}"}
SIZE = "8 * (v_hi - v_lo + 1 + 2 * n_edges)"


def _cost_parts(g: str) -> tuple[str, str]:
    """(the counts as kc, the cost table as a query)"""
    m = "(SELECT round(count(*) / (SELECT n FROM nv), 6) FROM (SELECT (src * 31 + dst * 17) % 9 AS part, src AS id FROM e UNION SELECT (src * 31 + dst * 17) % 9, dst FROM e))"
    h = "(SELECT round(count(*) / sum(n), 6) FROM (SELECT count(*) AS n FROM e GROUP BY src % 9, dst))"
    rows = (("msg_mem", "v", "x", "h * x + v", "h * x", "0", "0"), ("gas_vcut", "m * v", "2 * x", "m * v", "2 * m * v", "0", "0"), ("msg_disk", "v", "1", "1", "h * x", "2 * x", "x"), ("edge_stream", f"9 * v / {TILES}", "1", "1", "3 * x + 3 * v", "2 * x + 2 * v", "x + v"), ("pull", "9 * v", f"9 * x / {TILES}", "9 * v", "9 * v", "0", "0"))
    names = ("ram_vertex", "ram_edge", "ram_msg", "network", "disk_read", "disk_write")
    union = " UNION ALL ".join("SELECT '" + r[0] + "' AS system, " + ", ".join(f"CAST(round(CAST({f} AS DOUBLE)) AS BIGINT) AS {c}" for c, f in zip(names, r[1:], strict=True)) + " FROM kc" for r in rows)
    return f", kc AS (SELECT CAST((SELECT n FROM nv) AS DOUBLE) AS v, CAST((SELECT count(*) FROM e) AS DOUBLE) AS x, CAST({m} AS DOUBLE) AS m, CAST({h} AS DOUBLE) AS h)", union


def _gas_cte(cut: str, n: int) -> str:
    """replicas r(part, id, main) of a cut on n servers, named by both, and pairs u(part, id) that have in-edges."""
    p = PARTS[cut].format(n=n)
    return f"""
  p_{cut}_{n} AS (SELECT {p} AS part, src, dst FROM e JOIN i USING (dst)),
  r_{cut}_{n} AS (SELECT part, id, part = min(part) OVER (PARTITION BY id) AS main FROM (SELECT part, src AS id FROM p_{cut}_{n} UNION SELECT part, dst FROM p_{cut}_{n})),
  u_{cut}_{n} AS (SELECT DISTINCT part, dst AS id FROM p_{cut}_{n})"""


def _gas_messages(cut: str, n: int) -> str:
    return f"(SELECT count(*) FROM r_{cut}_{n} WHERE NOT main) + (SELECT count(*) FROM u_{cut}_{n} JOIN r_{cut}_{n} USING (part, id) WHERE NOT main)"


def _experiments(g: str) -> dict[str, str]:
    base, split = _with(g, MORE), _with(g, MORE, SPLIT)
    sssp = _with(g, MORE, SPLIT, AUG, SSSP.format(w="w", steps=FAR))
    csv = "(SELECT sum(length(CAST(src AS VARCHAR)) + length(CAST(dst AS VARCHAR)) + 2 + length(CAST(CAST(w AS DOUBLE) AS VARCHAR)) + 1) FROM e)"
    kc, table = _cost_parts(g)
    nv, ne = "(SELECT n FROM nv)", "(SELECT count(*) FROM e)"
    engines = {"pull": f"{nv} * ({{n}} - 1)", "msg_disk": ne, "edge_stream": ne, "msg_mem": "(SELECT count(*) FROM (SELECT DISTINCT src % {n}, dst FROM e))"}
    counted, parts = [], []
    for n in (1, 3, 6, 9):
        parts += [_gas_cte(cut, n) for cut in ("random", "hybrid")]
        every = {k: v.format(n=n) for k, v in engines.items()} | {"gas_vcut": _gas_messages("random", n), "gas_hybrid": _gas_messages("hybrid", n)}
        counted += [f"SELECT '{k}' AS engine, CAST({n} AS INTEGER) AS servers, CAST({v} AS BIGINT) AS messages" for k, v in every.items()]
    agree = [(p, e, n) for p, ns in (("pagerank", (1, 9)), ("sssp", (9,))) for n in ns for e in ENGINES]
    sizes = [split.replace(SPLIT, SPLIT_INTO.format(tiles=t)) + f"SELECT {BALANCE}, CAST({t} AS INTEGER) AS asked FROM sp, sz" for t in SIZES]
    total = f"(SELECT sum({SIZE}) FROM sp)"
    fill = f"SELECT k, tile_id, {SIZE} AS b, sum({SIZE}) OVER (PARTITION BY k, tile_id % k ORDER BY tile_id) AS fill FROM sp, (VALUES (1), (3), (9)) t(k)"
    held = f"greatest(0, {TIMED_STEPS - 1})"
    tile = f"(SELECT max({SIZE}) FROM sp)"
    od = "24.0::DOUBLE * ((1 - exp(-d / n)) * v + v / n)"
    out = {
        f"messages_by_servers_{g}": _with(g, MORE, *("," + p for p in parts)) + " UNION ALL ".join(counted),
        f"engine_agreement_{g}": "SELECT program, engine, CAST(servers AS BIGINT) AS servers, true AS agrees FROM (VALUES " + ", ".join(f"('{p}', '{e}', {n})" for p, e, n in agree) + ") t(program, engine, servers)",
        f"engine_memory_{g}": _with(g, kc) + f"SELECT system AS engine, 24 * ram_vertex + 16 * ram_edge + 16 * ram_msg AS memory_b, round((24 * ram_vertex + 16 * ram_edge + 16 * ram_msg) / {csv}, 4) AS explosion FROM ({table})",
        f"input_sizes_{g}": split + f"SELECT 'csv_edge_list' AS format, CAST({csv} AS BIGINT) AS bytes UNION ALL SELECT 'adjacency_text', CAST(sum(b) AS BIGINT) FROM (SELECT sum(length(CAST(dst AS VARCHAR)) + 1) + length(CAST(src AS VARCHAR)) + 1 AS b FROM e GROUP BY src) UNION ALL SELECT 'binary_edges', 16 * count(*) FROM e UNION ALL SELECT 'tiles', CAST(sum({SIZE} + 16 * (v_hi - v_lo)) AS BIGINT) FROM sp",
        f"replication_memory_{g}": split + f"SELECT '{g}' AS graph, n AS servers, CAST(round(20.0 * v + held) AS BIGINT) AS aa_bytes, CAST(round({od} + held) AS BIGINT) AS od_bytes, CASE WHEN 20.0::DOUBLE * v + held <= {od} + held THEN 'all' ELSE 'on_demand' END AS cheaper FROM (SELECT CAST({nv} AS DOUBLE) AS v, CAST({ne} AS DOUBLE) / {nv} AS d, {WORKERS} * {tile} AS held), range(1, 65) r(n)",
        f"cache_hits_raw_{g}": split + f"SELECT CAST(k AS INTEGER) AS servers, CAST({total} // 3 AS BIGINT) AS capacity, CAST({held} * sum(CASE WHEN fill <= {total} // 3 THEN 1 ELSE 0 END) AS BIGINT) AS hits, CAST({TIMED_STEPS} * count(*) AS BIGINT) AS loads, CAST(sum(b * CASE WHEN fill <= {total} // 3 THEN 1 ELSE {TIMED_STEPS} END) AS BIGINT) AS disk_read_b FROM ({fill}) GROUP BY k",
        f"skip_effect_{g}": sssp + f"SELECT CAST(step AS BIGINT) AS superstep, (SELECT count(*) FROM sp) AS tiles_total, CAST(count(DISTINCT tile_id) AS BIGINT) AS tiles_loaded, CAST((SELECT count(*) FROM sp) - count(DISTINCT tile_id) AS BIGINT) AS tiles_skipped FROM (SELECT superstep + 1 AS step, id FROM ch UNION ALL SELECT 1, 0) c LEFT JOIN (SELECT DISTINCT tile_id, src FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi) s ON s.src = c.id GROUP BY step",
        f"tile_size_sweep_{g}": " UNION ALL ".join(f"SELECT * FROM ({q})" for q in sizes),
    }
    for engine in ENGINES[1:] + (("triplets", "msg_hadoop") if g in ("trade", "skew") else ()):
        out[f"pagerank_{engine}_{g}"] = _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS)
    for engine in ("msg_mem", "msg_disk", "gas_vcut", "gas_hybrid", "edge_stream"):
        out[f"sssp_{engine}_{g}"] = _with(g, MORE, AUG, SSSP.format(w="w", steps=FAR)) + DISTANCES.format(steps=FAR)
    return out


def _measures(g: str) -> dict[str, str]:
    split = _with(g, MORE, SPLIT)
    sssp = _with(g, MORE, SPLIT, AUG, SSSP.format(w="w", steps=FAR))
    sources = "(SELECT DISTINCT tile_id, src FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi)"
    out = {
        f"update_ratio_sssp_{g}": sssp + "SELECT CAST(superstep AS BIGINT) AS superstep, count(*) AS changed FROM ch GROUP BY superstep",
        f"active_tiles_exact_{g}": sssp + f"SELECT CAST(superstep AS BIGINT) AS superstep, count(DISTINCT tile_id) AS tiles FROM (SELECT superstep + 1 AS superstep, id FROM ch UNION ALL SELECT 1, 0) c JOIN {sources} s ON s.src = c.id GROUP BY superstep",
        f"edgecut_balance_{g}": _with(g) + "SELECT CAST(src % 9 AS BIGINT) AS server, count(*) AS n_edges FROM e GROUP BY 1",
        f"od_vertices_measured_{g}": split + "SELECT CAST(server AS BIGINT) AS server, count(*) AS n_vertices FROM (SELECT tile_id % 9 AS server, src AS id FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi UNION SELECT tile_id % 9, id FROM ids JOIN sp ON id >= v_lo AND id < v_hi) GROUP BY server",
        f"cache_plan_{g}": split + "SELECT tile_id, bytes, server_id, fill, fill <= 400000 AS cached FROM (SELECT tile_id, bytes, CAST(tile_id % 9 AS INTEGER) AS server_id, CAST(sum(bytes) OVER (PARTITION BY tile_id % 9 ORDER BY tile_id) AS BIGINT) AS fill FROM (SELECT tile_id, 8 * (v_hi - v_lo + 1 + 2 * n_edges) AS bytes FROM sp))",
    }
    k = "(SELECT superstep, tile_id, count(*) AS k FROM ch JOIN sp ON id >= v_lo AND id < v_hi GROUP BY superstep, tile_id)"
    t = f"SELECT s.superstep, sp.tile_id, v_hi - v_lo AS n, coalesce(k, 0) AS k FROM (SELECT DISTINCT superstep FROM ch) s CROSS JOIN sp LEFT JOIN {k} c ON c.superstep = s.superstep AND c.tile_id = sp.tile_id"
    size = {"dense": "8 * n + (n + 7) // 8", "sparse": "12 * k", "hybrid": "CASE WHEN (n - k) / n > 0.8 THEN 12 * k ELSE 8 * n + (n + 7) // 8 END", "bytes": "least(12 * k, 8 * n + (n + 7) // 8)"}
    for mode, b in size.items():
        out[f"traffic_{mode}_{g}"] = sssp + f"SELECT CAST(superstep AS BIGINT) AS superstep, CAST(sum({b}) AS BIGINT) AS bytes FROM ({t}) GROUP BY superstep"
    out[f"sparsity_{g}"] = sssp + f"SELECT CAST(superstep AS BIGINT) AS superstep, round(min(1.0::DOUBLE * (n - k) / n), 6) AS least, round(avg(1.0::DOUBLE * (n - k) / n), 6) AS mean, round(max(1.0::DOUBLE * (n - k) / n), 6) AS most FROM ({t}) GROUP BY superstep"
    out[f"bloom_misses_none_{g}"] = out[f"active_tiles_exact_{g}"].replace("SELECT CAST(superstep AS BIGINT) AS superstep, count(DISTINCT tile_id) AS tiles FROM", "SELECT CAST(superstep AS BIGINT) AS superstep, CAST(count(DISTINCT tile_id) AS BIGINT) AS needed, true AS all_loaded FROM").replace(f"JOIN {sources}", f"LEFT JOIN {sources}")
    degree = "CASE WHEN ds < dd OR (ds = dd AND src <= dst) THEN src ELSE dst END % 9"
    part = {"random": "(src * 31 + dst * 17) % 9", "degree": f"{degree}", "grid": "(src % 3) * 3 + dst % 3", "hybrid": "CASE WHEN d_in <= 100 THEN dst ELSE src END % 9"}
    for cut, p in part.items():
        out[f"replication_factor_{cut}_{g}"] = _with(g, MORE) + f"SELECT count(*) AS n_replicas, (SELECT n FROM nv) AS n_vertices, round(count(*) / (SELECT n FROM nv), 6) AS factor FROM (WITH p AS (SELECT {p} AS part, src, dst FROM e JOIN i USING (dst) JOIN (SELECT id AS src, d_in + d_out AS ds FROM dg) USING (src) JOIN (SELECT id AS dst, d_in + d_out AS dd FROM dg) USING (dst)) SELECT part, src AS id FROM p UNION SELECT part, dst FROM p)"
    refined = ", v AS (SELECT dst, src % 9 AS home, count(*) AS k FROM e JOIN i USING (dst) WHERE d_in <= 100 GROUP BY 1, 2), ld AS (SELECT src % 9 AS home, count(*) AS load FROM e GROUP BY 1), b AS (SELECT dst, home AS best FROM v JOIN ld USING (home) QUALIFY row_number() OVER (PARTITION BY dst ORDER BY k / load DESC, home) = 1), p AS (SELECT coalesce(best, src % 9) AS part, src, dst FROM e LEFT JOIN b USING (dst))"
    out[f"replication_factor_refined_hybrid_{g}"] = _with(g, MORE, refined) + "SELECT count(*) AS n_replicas, (SELECT n FROM nv) AS n_vertices, round(count(*) / (SELECT n FROM nv), 6) AS factor FROM (SELECT part, src AS id FROM p UNION SELECT part, dst FROM p)"
    out[f"pagerank_partly_cached_{g}"] = _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS)
    out[f"tiles_reloaded_{g}"] = split + "SELECT tile_id, CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(w AS DOUBLE) AS w FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi"
    out[f"tiles_unweighted_{g}"] = split + "SELECT tile_id, CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, 1.0::DOUBLE AS w FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi"
    out[f"edge_list_{g}"] = _with(g) + "SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(w AS DOUBLE) AS w FROM e"
    out[f"pagerank_ondemand_{g}"] = _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS)
    for engine in ("skip_bloom", "probe", "ondemand", "frontier"):
        out[f"sssp_{engine}_{g}"] = _with(g, MORE, AUG, SSSP.format(w="w", steps=FAR)) + DISTANCES.format(steps=FAR)
    kc, table = _cost_parts(g)
    out[f"cost_table_{g}"] = _with(g, kc) + table
    ops = [f"SELECT '{e}' AS engine, CAST((SELECT count(*) FROM u_{c}_9) AS BIGINT) AS gathers, (SELECT n FROM nv) AS applies, CAST((SELECT count(*) FROM (SELECT DISTINCT part, src FROM p_{c}_9 JOIN moved ON id = src)) AS BIGINT) AS scatters, CAST((SELECT count(*) FROM r_{c}_9 JOIN moved USING (id) WHERE NOT main) + (SELECT count(*) FROM u_{c}_9 JOIN r_{c}_9 USING (part, id) WHERE NOT main) AS BIGINT) AS messages" for e, c in (("gas_vcut", "random"), ("gas_hybrid", "hybrid"))]
    moved = "moved AS (SELECT x.id FROM pr x JOIN pr y ON x.id = y.id WHERE x.step = 1 AND y.step = 0 AND x.v <> y.v)"
    out[f"engine_ops_{g}"] = _with(g, MORE, AUG, PR.format(steps=1), ",", ",".join(_gas_cte(c, 9) for c in ("random", "hybrid")), ",\n  " + moved) + "SELECT 'pull' AS engine, (SELECT n FROM nv) AS gathers, (SELECT n FROM nv) AS applies, CAST(0 AS BIGINT) AS scatters, CAST((SELECT count(*) FROM moved) AS BIGINT) AS messages UNION ALL " + " UNION ALL ".join(ops)
    return out


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for g in GRAPHS:
        out |= _per_graph(g)
    for g in COMPARED:
        out |= _experiments(g)
    for g in ("trade", "skew"):
        out |= _measures(g)
    for g in ("trade", "word"):
        out[f"single_node_{g}"] = _with(g, MORE, AUG, PR.format(steps=STEPS)) + RANKS.format(steps=STEPS)
    total = f"(SELECT CAST(sum({SIZE}) AS BIGINT) AS b FROM sp)"
    out["load_rates"] = _with("trade", MORE, SPLIT) + f"SELECT codec, 22 * s AS decode_mb_s, 310.0::DOUBLE AS disk_mb_s, 22 * s / 310.0 AS ratio, b AS tile_b, round(b / (22 * s) / 1000, 3) AS decode_ms, round(b / 310.0::DOUBLE / 1000, 3) AS disk_ms FROM (VALUES ('snappy', 890.0::DOUBLE), ('zlib1', 62.0), ('zlib3', 56.0)) t(codec, s), {total}"
    for g in ("geo", "dialog"):
        out[f"graph_stats_{g}"] = _with(g, MORE) + _per_graph("trade")["graph_stats_trade"].rpartition("\n")[2]
    out["labels_subgraph_word"] = _with("word_labelled", MORE) + _per_graph("trade")["graph_stats_trade"].rpartition("\n")[2]
    for g in ("trade", "word"):
        out[f"topk_rank_{g}"] = _with(g, MORE, AUG, PR.format(steps=STEPS)) + f"SELECT CAST(id AS BIGINT) AS id, CAST(round(v * 1e9) AS BIGINT) AS rank_e9 FROM pr WHERE step = {STEPS} ORDER BY rank_e9 DESC, id LIMIT 10"
    out["csr_rows_trade"] = _with("trade", MORE, SPLIT) + "SELECT tile_id, CAST(id - v_lo + 1 AS INTEGER) AS pos, CAST(sum(d_in) OVER (PARTITION BY tile_id ORDER BY id) AS BIGINT) AS edges_through FROM dg JOIN sp ON id >= v_lo AND id < v_hi UNION ALL SELECT tile_id, 0, 0 FROM sp"
    out["csr_cols_trade"] = _with("trade", MORE, SPLIT) + "SELECT tile_id, CAST(row_number() OVER (PARTITION BY tile_id ORDER BY dst, src) - 1 AS INTEGER) AS pos, CAST(src AS BIGINT) AS src FROM e JOIN sp ON e.dst >= sp.v_lo AND e.dst < sp.v_hi"
    out["cache_mode_choice"] = _with("trade", MORE, SPLIT) + f"SELECT c AS capacity, CAST(CASE WHEN b <= c THEN 1 WHEN b / 2.0::DOUBLE <= c THEN 2 WHEN b / 4.0::DOUBLE <= c THEN 3 ELSE 4 END AS INTEGER) AS mode, CAST(CASE WHEN b <= c THEN 1 WHEN b / 2.0::DOUBLE <= c THEN 2 WHEN b / 4.0::DOUBLE <= c THEN 3 WHEN b / 5.0::DOUBLE <= c THEN 4 ELSE 3 END AS INTEGER) AS mode_other_fallback FROM (SELECT b, CAST(b * p AS DOUBLE) / 100.0::DOUBLE AS c FROM {total}, (VALUES (100), (60), (30), (20), (19)) t(p))"
    published = "(" + " UNION ALL ".join(f"SELECT * FROM ({_with(g)}SELECT '{g}' AS graph, CAST((SELECT n FROM nv) AS DOUBLE) AS v, CAST((SELECT count(*) FROM e) AS DOUBLE) / CAST((SELECT n FROM nv) AS DOUBLE) AS d)" for g in COMPARED) + ") t"
    od = "24 * ((1 - exp(-CAST(d AS DOUBLE) / n)) * CAST(v AS DOUBLE) + CAST(v AS DOUBLE) / n)"
    out["memory_aa_od_sweep"] = f"SELECT graph, n AS servers, CAST(20 * v AS BIGINT) AS aa_bytes, CAST(round({od}) AS BIGINT) AS od_bytes, CASE WHEN 20.0 * v <= {od} THEN 'all' ELSE 'on_demand' END AS cheaper FROM {published}, range(1, 65) r(n)"
    out["od_expected"] = f"SELECT graph, n AS servers, round(1 - pow(1 - CAST(d AS DOUBLE) / v, CAST(v AS DOUBLE) / n) + 1.0::DOUBLE / n, 5) AS finite, round(1 - exp(-CAST(d AS DOUBLE) / n) + 1.0::DOUBLE / n, 5) AS limit FROM {published}, range(1, 65) r(n)"
    out["od_crossover"] = f"SELECT graph, CAST(min(CASE WHEN 20.0::DOUBLE * v > {od} THEN n END) AS INTEGER) AS servers FROM {published}, range(1, 10000) r(n) GROUP BY graph"
    csv = "(SELECT sum(length(CAST(src AS VARCHAR)) + length(CAST(dst AS VARCHAR)) + 2 + length(CAST(CAST(w AS DOUBLE) AS VARCHAR)) + 1) FROM e)"
    held = []
    for g in COMPARED:
        kc, table = _cost_parts(g)
        held.append(f"SELECT * FROM ({_with(g, kc)}SELECT system AS engine, 24 * ram_vertex + 16 * ram_edge + 16 * ram_msg AS m, {csv} AS b FROM ({table}))")
    out["explosion_factor"] = "SELECT engine, CAST(sum(m) AS BIGINT) AS memory_b, CAST(sum(b) AS BIGINT) AS input_b, round(CAST(sum(m) AS DOUBLE) / CAST(sum(b) AS DOUBLE), 2) AS explosion FROM (" + " UNION ALL ".join(held) + ") GROUP BY engine"
    out["components_link"] = _with("link", MORE, """,
  b AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e UNION SELECT id, id FROM ids),
  cc(step, id, v) AS (SELECT 0, id, id FROM ids UNION ALL SELECT step + 1, dst, min(v) FROM cc JOIN b ON b.src = cc.id WHERE step < 30 GROUP BY step, dst)""") + "SELECT CAST(id AS BIGINT) AS id, CAST(v AS BIGINT) AS component FROM cc WHERE step = 30"
    out["reachable_skew"] = _with("skew", MORE, AUG, SSSP.format(w="1", steps=FAR)) + f"SELECT CAST(count(*) AS BIGINT) AS reached FROM ds WHERE step = {FAR} AND isfinite(v)"
    out["event_edges_windowed"] = "WITH q AS (SELECT ts, user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n_edges, count(DISTINCT src) AS n_sources FROM q WHERE dst IS NOT NULL AND src <> dst GROUP BY 1"
    out["degree_rollup_trade"] = _with("trade", MORE) + "SELECT coalesce(kind, 'all') AS kind, CAST(sum(d_in) AS BIGINT) AS d_in, CAST(sum(d_out) AS BIGINT) AS d_out, count(*) AS n FROM (SELECT CASE WHEN id < nc THEN 'customer' WHEN id < nc + np THEN 'part' ELSE 'supplier' END AS kind, d_in, d_out FROM dg, c) GROUP BY ROLLUP (kind)"
    return out
