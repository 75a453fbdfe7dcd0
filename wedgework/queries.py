"""Registered queries of the graph engine, with DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import costs, udx
from .operators import baselines, cache, csr, intersect, lcc, partition, prep, trace, triangles
from .plans import experiments, fetch, sqlface
from .schema import CacheConfig, CostModel, Graph
from .sources import graphs
from .sources.graphs import build
from .sources.tables import load

QUERIES: dict = {}
SQL: dict[str, str] = {}

VERTICES = "vs AS MATERIALIZED (SELECT DISTINCT v FROM (SELECT src AS v FROM arcs UNION ALL SELECT dst FROM arcs))"
DEG = "deg AS MATERIALIZED (SELECT src AS v, count(*) AS d FROM arcs GROUP BY src)"
ORIENTED = "o AS MATERIALIZED (SELECT a.src AS u, a.dst AS v, y.d AS dv FROM arcs a JOIN deg x ON x.v = a.src JOIN deg y ON y.v = a.dst WHERE x.d < y.d OR (x.d = y.d AND a.src < a.dst))"
#: Wedges are written out before they are closed, so that no other join order can be picked.
CORNERS = (
    f"{DEG}, {ORIENTED}, wg AS MATERIALIZED (SELECT x.u, x.v, y.v AS w FROM o x JOIN o y ON x.u = y.u AND (x.dv < y.dv OR (x.dv = y.dv AND x.v < y.v))), "
    "tri AS MATERIALIZED (SELECT wg.u AS a, wg.v AS b, wg.w AS c FROM wg JOIN o z ON z.u = wg.v AND z.v = wg.w)"
)
PER_VERTEX = f"{CORNERS}, tv AS MATERIALIZED (SELECT v, count(*)::BIGINT AS t FROM (SELECT unnest([a, b, c]) AS v FROM tri) GROUP BY v)"
INDEX = f"{VERTICES}, ix AS MATERIALIZED (SELECT v, row_number() OVER (ORDER BY v) - 1 AS idx, count(*) OVER () AS n FROM vs)"
_PERMUTED = "pm AS (SELECT t.* FROM tri, LATERAL (VALUES (a, b, c), (a, c, b), (b, a, c), (b, c, a), (c, a, b), (c, b, a)) AS t(i, j, k))"
BOTH = "sym AS MATERIALIZED (SELECT DISTINCT * FROM (SELECT src, dst FROM arcs UNION ALL SELECT dst, src FROM arcs))"
#: Triangles of a directed graph's undirected form, then every ordered pair of out-neighbours with an arc.
DIRECTED = (
    f"{BOTH}, {CORNERS.replace('FROM arcs', 'FROM sym')}, {_PERMUTED}, "
    "cp AS MATERIALIZED (SELECT i AS v, count(*)::BIGINT AS t FROM pm JOIN arcs x ON x.src = i AND x.dst = j JOIN arcs y ON y.src = i AND y.dst = k JOIN arcs z ON z.src = j AND z.dst = k GROUP BY i), "
    "od AS (SELECT src AS v, count(*) AS d FROM arcs GROUP BY src)"
)


def part_sql(p: int, name: str = "part") -> str:
    return f"{name} AS MATERIALIZED (SELECT v, idx, (((idx + 1) * {p} + n - 1) // n - 1)::INT AS part FROM ix)"


def reads_sql(p: int, name: str = "rd", part: str = "part") -> str:
    return f"{name} AS MATERIALIZED (SELECT x.part, a.src, a.dst FROM arcs a JOIN {part} x ON x.v = a.src JOIN {part} y ON y.v = a.dst WHERE x.part <> y.part)"


def blocks(p: int) -> str:
    return f"{INDEX}, {part_sql(p)}, {reads_sql(p)}"


def add(name: str, run, sql: str | None = None, graph: str | None = None) -> None:
    """``sql`` is a select, or further CTEs and a select with ' | ' between; the graph's arcs are put before."""
    QUERIES[name] = run
    if sql is not None and graph:
        *ctes, select = sql.split(" | ", 1)
        sql = f"WITH {', '.join([graphs.SQL[graph], *ctes])} {select}"
    if sql is not None:
        SQL[name] = sql


def on(graph: str):
    return lambda f: lambda spark, d: f(build(spark, d, graph))


# --- preparation and storage -------------------------------------------------------------------------------------------------------------
_TABLE = ("copurchase", "cosupply", "segment_cliques", "coactive", "cobuyer", "part_supp", "bigram", "succession_directed", "rmat_s10_ef16")
_KIND = {g: "D" if g.endswith("directed") or g == "knn" else "U" for g in graphs.BUILDERS}
add("graph_table", lambda s, d: experiments.graph_table([build(s, d, g) for g in _TABLE]))
SQL["graph_table"] = " UNION ALL ".join(
    f"(WITH {graphs.SQL[g]}, {VERTICES} SELECT '{g}' AS graph, '{_KIND[g]}' AS kind, n, {'m' if _KIND[g] == 'D' else 'm // 2'} AS m, 4 * (n + 1 + m) AS csr_bytes FROM (SELECT count(*) AS n FROM vs), (SELECT count(*) AS m FROM arcs))"
    for g in _TABLE
)
for _g in ("copurchase", "succession_directed"):
    add(f"degrees_{_g}", on(_g)(prep.degrees), "SELECT v, sum(o)::BIGINT AS deg_out, sum(i)::BIGINT AS deg_in FROM (SELECT src AS v, 1 AS o, 0 AS i FROM arcs UNION ALL SELECT dst, 0, 1 FROM arcs) GROUP BY v", _g)
for _g in ("bigram", "rmat_s10_ef16"):
    add(f"degree_histogram_{_g}", on(_g)(prep.degree_histogram), f"{DEG} | SELECT d AS deg, count(*) AS n_vertices FROM deg GROUP BY d", _g)
add("tail_slope_bigram", lambda s, d: prep.tail_slope(build(s, d, "bigram")).select(F.round("exponent", 6).alias("exponent")), f"{DEG} | SELECT round(1 + count(*) / sum(ln(d / 1.5)), 6) AS exponent FROM deg WHERE d >= 2", "bigram")
_HIGH = "hi AS MATERIALIZED (SELECT v FROM deg WHERE d >= 2)"
add(
    "prune_bigram", lambda s, d: prep.prune(build(s, d, "bigram")).arcs.agg(F.count(F.lit(1)).alias("n_arcs"), F.countDistinct("src").alias("n")),
    f"{DEG}, {_HIGH} | SELECT count(*) AS n_arcs, count(DISTINCT src) AS n FROM arcs SEMI JOIN hi ON hi.v = arcs.src SEMI JOIN hi h2 ON h2.v = arcs.dst", "bigram",
)
add(
    "core2_bigram", lambda s, d: prep.prune(build(s, d, "bigram"), rounds=None).arcs.agg(F.count(F.lit(1)).alias("n_arcs"), F.countDistinct("src").alias("n")),
    "r AS (SELECT 0 AS i, src, dst FROM arcs UNION ALL SELECT i, src, dst FROM (WITH d AS (SELECT src AS v, count(*) AS c FROM r GROUP BY src) SELECT r.i + 1 AS i, r.src, r.dst FROM r JOIN d x ON x.v = r.src JOIN d y ON y.v = r.dst WHERE x.c >= 2 AND y.c >= 2 AND (SELECT min(c) FROM d) < 2)) "
    "| SELECT count(*) AS n_arcs, count(DISTINCT src) AS n FROM r WHERE i = (SELECT max(i) FROM r)", "bigram",
)
SQL["core2_bigram"] = SQL["core2_bigram"].replace("WITH ", "WITH RECURSIVE ", 1)
add("dense_index_bigram", lambda s, d: prep.dense_index(prep.vertices(build(s, d, "bigram"))), f"{INDEX} | SELECT v, idx FROM ix", "bigram")
add("relabel_hash_rmat", lambda s, d: prep.shuffled_index(prep.vertices(build(s, d, "rmat_s8_ef8"))), f"{VERTICES} | SELECT v, row_number() OVER (ORDER BY md5(v::VARCHAR), v::VARCHAR) - 1 AS idx FROM vs", "rmat_s8_ef8")
add("degree_ordered_rmat", on("rmat_s10_ef16")(prep.is_degree_ordered), f"{DEG} | SELECT round(corr(v::DOUBLE, d::DOUBLE), 6) AS correlation, abs(round(corr(v::DOUBLE, d::DOUBLE), 6)) > 0.5 AS degree_ordered FROM deg", "rmat_s10_ef16")
for _g in ("copurchase", "bigram"):
    add(f"csr_size_{_g}", on(_g)(csr.size_bytes), f"{VERTICES} | SELECT n, n_arcs, 4 * (n + 1 + n_arcs) AS csr_bytes FROM (SELECT count(*) AS n FROM vs), (SELECT count(*) AS n_arcs FROM arcs)", _g)


def _csr_round_trip(g):
    parts = partition.block(g, 4)
    return csr.from_csr(csr.to_csr(g, parts))


add("csr_round_trip_coactive", on("coactive")(_csr_round_trip), f"{INDEX} | SELECT x.idx AS src, y.idx AS dst FROM arcs a JOIN ix x ON x.v = a.src JOIN ix y ON y.v = a.dst", "coactive")
add("adjacency_chunks_coactive", lambda s, d: csr.adjacency(build(s, d, "coactive"), chunk=4).select("v", "deg", "chunk", F.array_join("nbrs", ",").alias("nbrs")),
    "rk AS (SELECT src AS v, dst, count(*) OVER (PARTITION BY src) AS deg, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS r FROM arcs) | SELECT v, deg, (r // 4)::INT AS chunk, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nbrs FROM rk GROUP BY v, deg, r // 4", "coactive")
for _g in ("copurchase", "coactive", "bigram", "succession_directed", "part_supp", "knn", "cobuyer", "segment_cliques"):
    add(f"arcs_{_g}", lambda s, d, g=_g: build(s, d, g).arcs, "SELECT src, dst FROM arcs", _g)
add("arcs_rmat_s10_ef16", lambda s, d: build(s, d, "nation_days").arcs, "SELECT src, dst FROM arcs", "nation_days")

# --- triangles and coefficients ----------------------------------------------------------------------------------------------------------
_UNDIRECTED = ("copurchase", "bigram", "coactive", "cobuyer", "part_supp", "cosupply", "segment_cliques", "succession", "rmat_s8_ef8", "rmat_s10_ef16")
for _g in _UNDIRECTED:
    add(f"triangles_global_{_g}", on(_g)(triangles.count), f"{CORNERS} | SELECT count(*) AS triangles FROM tri", _g)
for _g in ("copurchase", "coactive", "bigram", "rmat_s10_ef16"):
    add(f"triangles_vertex_{_g}", on(_g)(triangles.per_vertex), f"{PER_VERTEX} | SELECT v, t AS triangles FROM tv", _g)
add("triangles_global_relational_bigram", lambda s, d: triangles.count(build(s, d, "bigram"), plan="relational"), f"{CORNERS} | SELECT count(*) AS triangles FROM tri", "bigram")
add("triangles_full_enumeration_coactive", lambda s, d: triangles.per_vertex(build(s, d, "coactive"), offset=False), f"{PER_VERTEX} | SELECT v, 2 * t AS triangles FROM tv", "coactive")
add("triangles_upper_lists_coactive", lambda s, d: triangles.per_vertex_lists(build(s, d, "coactive")), f"{PER_VERTEX} | SELECT v, t AS triangles FROM tv", "coactive")
add("triangles_all_lists_coactive", lambda s, d: triangles.per_vertex_lists(build(s, d, "coactive"), offset=False), f"{PER_VERTEX} | SELECT v, 2 * t AS triangles FROM tv", "coactive")
_SORTED = "SELECT list_sort([a, b, c])[1] AS a, list_sort([a, b, c])[2] AS b, list_sort([a, b, c])[3] AS c FROM tri"
for _g in ("coactive", "rmat_s8_ef8"):
    add(f"triangle_listing_{_g}", on(_g)(triangles.listing), f"{CORNERS} | {_SORTED}", _g)
_SUPPORT = "w AS (SELECT a.src, a.dst, count(*) AS c FROM arcs a JOIN arcs x ON x.src = a.src JOIN arcs y ON y.src = a.dst AND y.dst = x.dst GROUP BY 1, 2) | SELECT a.src, a.dst, coalesce(w.c, 0)::BIGINT AS common FROM arcs a LEFT JOIN w ON w.src = a.src AND w.dst = a.dst"
for _g in ("copurchase", "coactive"):
    add(f"edge_support_{_g}", on(_g)(triangles.edge_support), _SUPPORT, _g)
_CLOSED = "coalesce(tv.t, 0)::BIGINT"
_LCC = f"{PER_VERTEX} | SELECT deg.v, deg.d AS deg, {_CLOSED} AS closed, CASE WHEN deg.d >= 2 THEN 2.0::DOUBLE * {_CLOSED} / (deg.d * (deg.d - 1)) END AS lcc FROM deg LEFT JOIN tv ON tv.v = deg.v"
_L = _LCC.replace(" | SELECT", ", l AS (SELECT") + ")"
_LCC_D = f"{DIRECTED} | SELECT od.v, od.d AS deg, coalesce(cp.t, 0) AS closed, CASE WHEN od.d >= 2 THEN 1.0::DOUBLE * coalesce(cp.t, 0) / (od.d * (od.d - 1)) END AS lcc FROM od LEFT JOIN cp ON cp.v = od.v"
for _g in _UNDIRECTED:
    add(f"lcc_{_g}", on(_g)(lcc.local_clustering), _LCC, _g)
for _g in ("succession_directed", "bigram_directed", "knn"):
    add(f"lcc_{_g}", on(_g)(lcc.local_clustering), _LCC_D, _g)
    add(f"closed_pairs_{_g}", on(_g)(triangles.closed_pairs), f"{DIRECTED} | SELECT v, t AS closed_pairs FROM cp", _g)
add("closed_pairs_joined_succession", on("succession_directed")(triangles.closed_pairs_joined), f"{DIRECTED} | SELECT v, t AS closed_pairs FROM cp", "succession_directed")
add("lcc_zero_bigram", lambda s, d: lcc.local_clustering(build(s, d, "bigram"), isolated="zero"), _LCC.replace(" END AS lcc", " ELSE 0.0 END AS lcc"), "bigram")
add("lcc_drop_bigram", lambda s, d: lcc.local_clustering(build(s, d, "bigram"), isolated="drop"), _LCC + " WHERE deg.d >= 2", "bigram")


def _subset(g):
    return lcc.local_clustering(g, only=prep.vertices(g).where("v % 10 = 3"))


add("lcc_subset_copurchase", on("copurchase")(_subset), _LCC + " WHERE deg.v % 10 = 3", "copurchase")
#: Vertices of one neighbour lie in no triangle, so the twin counts triangles before pruning and degrees after it.
_PRUNED = f"{PER_VERTEX}, dp AS (SELECT a.src AS v, count(*) AS d FROM arcs a JOIN deg x ON x.v = a.src JOIN deg y ON y.v = a.dst WHERE x.d >= 2 AND y.d >= 2 GROUP BY a.src) | " + _LCC.split(" | ")[1].replace("deg.", "dp.").replace("FROM deg", "FROM dp")
add("lcc_pruned_bigram", lambda s, d: lcc.local_clustering(prep.prune(build(s, d, "bigram"))), _PRUNED, "bigram")
add("lcc_pruned_original_degrees_bigram", lambda s, d: (lambda g: lcc.local_clustering(prep.prune(g), degrees_of=g))(build(s, d, "bigram")), _LCC, "bigram")
_SUMMARY = (
    "SELECT count(*) FILTER (WHERE deg >= 2) AS n_vertices, round(avg(lcc), 6) AS mean_lcc, sum(closed)::BIGINT AS closed, sum(deg * (deg - 1) // 2)::BIGINT AS wedges, round(sum(closed) / sum(deg * (deg - 1) // 2), 6) AS transitivity FROM l"
)
for _g in ("copurchase", "bigram", "rmat_s10_ef16"):
    add(f"lcc_summary_{_g}", on(_g)(lcc.summary), _L + " | " + _SUMMARY, _g)
add("lcc_histogram_copurchase", lambda s, d: lcc.histogram(lcc.local_clustering(build(s, d, "copurchase"))), _L + " | SELECT least(floor(lcc * 10), 9)::INT AS bin, count(*) AS n_vertices FROM l WHERE lcc IS NOT NULL GROUP BY 1", "copurchase")
add("lcc_top_copurchase", lambda s, d: lcc.top(lcc.local_clustering(build(s, d, "copurchase")), 20), _L + " | SELECT * FROM l ORDER BY lcc DESC NULLS LAST, v LIMIT 20", "copurchase")
add("triplets_coactive", on("coactive")(triangles.triplets), f"{PER_VERTEX} | SELECT deg.v, {_CLOSED} AS closed, deg.d * (deg.d - 1) // 2 - {_CLOSED} AS open FROM deg LEFT JOIN tv ON tv.v = deg.v", "coactive")
add("core_frontier_coactive", on("coactive")(lcc.core_frontier), _L + " | SELECT v, deg, CASE WHEN lcc >= 0.7 THEN 'core' WHEN lcc <= 0.3 THEN 'frontier' ELSE 'between' END AS role FROM l WHERE deg >= 2", "coactive")
add("recommend_links_coactive", on("coactive")(lcc.recommend_links),
    "f AS (SELECT a.dst AS v, b.dst AS other, count(*) AS common FROM arcs a JOIN arcs b ON a.src = b.src AND a.dst <> b.dst GROUP BY 1, 2), n AS (SELECT f.* FROM f ANTI JOIN arcs ON arcs.src = f.v AND arcs.dst = f.other) | SELECT v, other, common, row_number() OVER (PARTITION BY v ORDER BY common DESC, other)::INT AS rank FROM n QUALIFY row_number() OVER (PARTITION BY v ORDER BY common DESC, other) <= 3", "coactive")
add("sql_lcc_coactive", lambda s, d: sqlface.run(build(s, d, "coactive"), "lcc"), _LCC, "coactive")
add("toy_lcc", on("toy")(lcc.local_clustering), _LCC, "toy")

# --- kernels -----------------------------------------------------------------------------------------------------------------------------
for _k in ("search", "merge", "hybrid", "builtin", "relational"):
    add(f"kernel_{_k}_coactive", lambda s, d, k=_k: intersect.edge_support(build(s, d, "coactive"), k), _SUPPORT, "coactive")
add("kernel_search_succession_directed", lambda s, d: intersect.edge_support(build(s, d, "succession_directed"), "search"), _SUPPORT, "succession_directed")
for _k in ("search", "merge", "hybrid"):
    add(f"kernel_split_{_k}_coactive", lambda s, d, k=_k: intersect.edge_support(build(s, d, "coactive"), k, chunk_cutoff=16), _SUPPORT, "coactive")
for _k in ("search", "merge", "hybrid"):
    add(f"kernel_parts_{_k}_coactive", lambda s, d, k=_k: intersect.edge_support(build(s, d, "coactive"), k, parts=8), _SUPPORT, "coactive")
add("kernel_parts_hybrid_rmat", lambda s, d: intersect.edge_support(build(s, d, "rmat_s10_ef32"), "hybrid", parts=16), _SUPPORT, "rmat_s10_ef32")
add("kernel_parts_hybrid_succession_directed", lambda s, d: intersect.edge_support(build(s, d, "succession_directed"), "hybrid", parts=4), _SUPPORT, "succession_directed")
_RULE = "least(di, dj) > 0 AND least(di, dj) * (log2(greatest(di, dj)) - 1) >= greatest(di, dj)"
_PAIRS = f"{DEG}, dp AS (SELECT x.d AS di, y.d AS dj FROM arcs a JOIN deg x ON x.v = a.src JOIN deg y ON y.v = a.dst)"
for _g in ("rmat_s8_ef8", "rmat_s10_ef8", "rmat_s10_ef16", "rmat_s10_ef32", "bigram", "copurchase", "part_supp"):
    add(f"kernel_ops_{_g}", on(_g)(intersect.op_counts),
        f"{_PAIRS} | SELECT sum(di + dj)::BIGINT AS merge_ops, round(sum(least(di, dj) * log2(greatest(di, dj))), 0)::BIGINT AS search_ops, round(sum(CASE WHEN {_RULE} THEN di + dj ELSE least(di, dj) * log2(greatest(di, dj)) END), 0)::BIGINT AS hybrid_ops FROM dp", _g)
    add(f"rule_share_{_g}", on(_g)(intersect.rule_share), f"{_PAIRS} | SELECT count(*) AS n_arcs, sum(({_RULE})::INT)::BIGINT AS n_merge FROM dp", _g)
add("kernel_steps_rmat", on("rmat_s10_ef16")(intersect.op_counts_ceiled),
    f"{_PAIRS} | SELECT sum(di + dj)::BIGINT AS merge_ops, sum(least(di, dj) * ceil(log2(greatest(di, dj) + 1)))::BIGINT AS search_ops, sum(CASE WHEN {_RULE} THEN di + dj ELSE least(di, dj) * ceil(log2(greatest(di, dj) + 1)) END)::BIGINT AS hybrid_ops FROM dp", "rmat_s10_ef16")

# --- partitions and reads ----------------------------------------------------------------------------------------------------------------
_POWER = ("rmat_s10_ef16", "bigram", "copurchase")
add("block_partition_copurchase", lambda s, d: partition.block(build(s, d, "copurchase"), 8), f"{INDEX}, {part_sql(8)} | SELECT v, idx, part FROM part", "copurchase")
add("block_floor_partition_rmat", lambda s, d: partition.block(build(s, d, "nation_days"), 64, rounding="floor"), f"{INDEX} | SELECT v, idx, ((idx * 64) // n)::INT AS part FROM ix", "nation_days")
_CYCLIC = f"{DEG} | SELECT v, row_number() OVER (ORDER BY d DESC, v) - 1 AS idx, ((row_number() OVER (ORDER BY d DESC, v) - 1) % 8)::INT AS part FROM deg"
add("cyclic_partition_rmat", lambda s, d: partition.cyclic(build(s, d, "rmat_s10_ef16"), 8), _CYCLIC, "rmat_s10_ef16")
_BALANCED = f"{DEG}, {INDEX} | SELECT ix.v, idx, least(7, floor(coalesce(sum(d) OVER (ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 8 / sum(d) OVER ()))::INT AS part FROM ix JOIN deg ON deg.v = ix.v"
add("balanced_partition_rmat", lambda s, d: partition.balanced(build(s, d, "nation_days"), 8), _BALANCED, "nation_days")
for _g in ("rmat_s10_ef16", "bigram", "copurchase", "coactive", "part_supp"):
    add(f"cut_p8_{_g}", lambda s, d, g=_g: (lambda x: partition.cut_stats(x, partition.block(x, 8)))(build(s, d, g)),
        f"{blocks(8)} | SELECT n_arcs, n_cut, round(n_cut / n_arcs, 6) AS cut_share FROM (SELECT count(*) AS n_cut FROM rd), (SELECT count(*) AS n_arcs FROM arcs)", _g)
add("read_counts_p8_rmat", lambda s, d: (lambda x: trace.read_counts(x, partition.block(x, 8)))(build(s, d, "rmat_s10_ef16")),
    f"{INDEX}, {part_sql(8)} | SELECT x.part, count(*) FILTER (WHERE x.part = y.part) AS n_local, count(*) FILTER (WHERE x.part <> y.part) AS n_remote FROM arcs a JOIN part x ON x.v = a.src JOIN part y ON y.v = a.dst GROUP BY x.part", "rmat_s10_ef16")
_STEP_CTES = ", ".join(f"{part_sql(p, f'part{p}')}, {reads_sql(p, f'rd{p}', f'part{p}')}" for p in experiments.STEPS)
_STEPS = f"{INDEX}, {_STEP_CTES} | " + " UNION ALL ".join(
    f"SELECT {p} AS p, n_arcs, n_remote, n_first, round(n_remote / n_arcs, 6) AS remote_share, round(n_first / n_remote, 6) AS first_share FROM (SELECT count(*) AS n_arcs FROM arcs), (SELECT count(*) AS n_remote, count(DISTINCT (part, dst)) AS n_first FROM rd{p})" for p in experiments.STEPS
)
for _g in _POWER:
    add(f"reads_by_parts_{_g}", on(_g)(experiments.by_parts), _STEPS, _g)
    add(f"regimes_{_g}", lambda s, d, g=_g: experiments.regime(experiments.by_parts(build(s, d, g))),
        _STEPS.replace(" | ", ", st AS (", 1) + ") | SELECT p, CASE WHEN remote_share < 0.5 THEN 'compute' WHEN first_share > 0.5 THEN 'compulsory' ELSE 'cacheable' END AS regime FROM st", _g)
for _g in ("bigram", "coactive", "copurchase"):
    add(f"repeat_histogram_p2_{_g}", lambda s, d, g=_g: (lambda x: trace.repeat_histogram(x, partition.block(x, 2)))(build(s, d, g)),
        f"{blocks(2)} | SELECT repeats, count(*) AS n_targets FROM (SELECT count(*) AS repeats FROM rd GROUP BY part, dst) GROUP BY repeats", _g)
for _g in ("copurchase", "coactive", "rmat_s10_ef16", "bigram", "part_supp"):
    add(f"top10_reads_p8_{_g}", lambda s, d, g=_g: (lambda x: trace.top_share(x, partition.block(x, 8)))(build(s, d, g)),
        f"{DEG}, {blocks(8)}, tp AS (SELECT v FROM deg QUALIFY row_number() OVER (ORDER BY d DESC, v) <= count(*) OVER () // 10) | SELECT n_remote, n_top, round(n_top / n_remote, 6) AS share FROM (SELECT count(*) AS n_remote, count(*) FILTER (WHERE dst IN (SELECT v FROM tp)) AS n_top FROM rd)", _g)
_REUSE = f"{DEG}, {blocks(2)}, ru AS (SELECT part, dst, count(*) AS c FROM rd GROUP BY part, dst), rv AS (SELECT ru.c, deg.d FROM ru JOIN deg ON deg.v = ru.dst)"
for _g in ("bigram", "coactive"):
    add(f"reuse_vs_size_p2_{_g}", lambda s, d, g=_g: (lambda x: trace.reuse_vs_size(x, partition.block(x, 2)))(build(s, d, g)), f"{_REUSE} | SELECT d AS deg, count(*) AS n_targets, sum(c)::BIGINT AS n_reads FROM rv GROUP BY d", _g)
    add(f"reuse_correlation_p2_{_g}", lambda s, d, g=_g: (lambda x: trace.reuse_correlation(x, partition.block(x, 2)))(build(s, d, g)), f"{_REUSE} | SELECT round(corr(c, d), 5) AS correlation FROM rv", _g)
for _g in ("rmat_s10_ef16", "copurchase"):
    add(f"expected_accesses_p8_{_g}", lambda s, d, g=_g: (lambda x: trace.expected_accesses(x, partition.block(x, 8), 8))(build(s, d, g)),
        f"{_REUSE.replace('* 2 +', '* 8 +')} | SELECT round(avg(c), 4) AS measured, round(avg(d / 8), 4) AS uniform, round(avg(d / 8 - 1), 4) AS printed FROM rv", _g)
_IMB = (
    "wk AS (SELECT s, part, sum(x.d + y.d)::BIGINT AS work, count(*) AS arcs FROM arcs a JOIN deg x ON x.v = a.src JOIN deg y ON y.v = a.dst JOIN sch ON sch.v = a.src GROUP BY s, part) | "
    "SELECT s AS scheme, n_parts, max(work) AS max_work, sum(work)::BIGINT AS all_work, max(arcs) AS max_arcs, round(max(work) * n_parts / sum(work), 6) AS max_over_mean FROM wk JOIN (SELECT s, count(DISTINCT part) AS n_parts FROM sch GROUP BY s) USING (s) GROUP BY s, n_parts"
)
add("imbalance_by_scheme_rmat", on("rmat_s10_ef16")(experiments.imbalance_by_scheme),
    f"{DEG}, {INDEX}, {part_sql(8)}, sch AS (SELECT 'block' AS s, v, part FROM part UNION ALL SELECT 'cyclic', v, part FROM ({_CYCLIC.split(' | ')[1]}) UNION ALL SELECT 'balanced', v, part FROM ({_BALANCED.split(' | ')[1]})), {_IMB}", "rmat_s10_ef16")
add("toy_reads", lambda s, d: (lambda x: trace.compulsory(x, partition.block(x, 2)))(build(s, d, "toy")), f"{blocks(2)} | SELECT n_remote, n_first, round(n_first / n_remote, 6) AS share FROM (SELECT count(*) AS n_remote, count(DISTINCT (part, dst)) AS n_first FROM rd)", "toy")
add("trace_p8_rmat_s8", lambda s, d: (lambda x: trace.build(x, partition.block(x, 8)).select("part", "seq", "src", "dst", "adj_bytes"))(build(s, d, "rmat_s8_ef8")),
    f"{DEG}, {blocks(8)} | SELECT part, row_number() OVER (PARTITION BY part ORDER BY src, dst) - 1 AS seq, src, dst, 4 * deg.d AS adj_bytes FROM rd JOIN deg ON deg.v = rd.dst", "rmat_s8_ef8")

# --- fetch plans -------------------------------------------------------------------------------------------------------------------------
for _k in ("per_arc", "two_step", "halo", "hot", "relational", "auto"):
    add(f"fetch_{_k}_coactive", lambda s, d, k=_k: fetch.edge_support(build(s, d, "coactive"), k, budget=4096), _SUPPORT, "coactive")
add("fetch_bytes_rmat", lambda s, d: fetch.shipped(build(s, d, "rmat_s10_ef16")),
    f"{DEG}, {blocks(8)}, sz AS (SELECT part, dst, d FROM rd JOIN deg ON deg.v = rd.dst), hb AS (SELECT d, sum(sum(8 * d)) OVER (ORDER BY d DESC) AS used FROM deg GROUP BY d), "
    "he AS (SELECT min(d) AS edge, max(used) AS used FROM hb WHERE used <= 65536) | SELECT 'hot' AS plan, ((SELECT coalesce(sum(d), 0) FROM sz WHERE d < (SELECT coalesce(edge, 1 << 40) FROM he)) + coalesce((SELECT used FROM he), 0) // 8 * 8)::BIGINT AS ids UNION ALL SELECT 'per_arc' AS plan, sum(d)::BIGINT AS ids FROM sz UNION ALL SELECT 'two_step', sum(d + 2)::BIGINT FROM sz UNION ALL SELECT 'halo', sum(d)::BIGINT FROM (SELECT DISTINCT * FROM sz)", "rmat_s10_ef16")  # fmt: skip
_RUN = f"{INDEX}, {part_sql(8)}, {{}} | SELECT part.part, l.v, l.deg, {{}}l.closed AS closed, l.lcc FROM l JOIN part ON part.v = l.v"
for _g, _k, _kernel, _scheme in (("coactive", "halo", "builtin", "block"), ("rmat_s10_ef16", "hot", "builtin", "block"), ("rmat_s8_ef8", "two_step", "hybrid", "block"), ("rmat_s8_ef8", "per_arc", "search", "block"), ("succession_directed", "halo", "merge", "block")):
    add(f"run_{_k}_{_g}", lambda s, d, g=_g, k=_k, n=_kernel: fetch.run(build(s, d, g), 8, k, kernel=n), (_RUN.format(_L, "2 * ") if not _g.endswith("directed") else _RUN.format(_LCC_D.replace(" | SELECT", ", l AS (SELECT") + ")", "")), _g)
add("fetch_estimates_bigram", lambda s, d: fetch.estimates(build(s, d, "bigram"), 8), f"{DEG} | SELECT 8 * sum(d * d)::BIGINT AS per_arc_bytes, 8 * sum(least(8, d) * d)::BIGINT AS halo_bytes, sum(d)::BIGINT AS n_arcs, count(*) AS n FROM deg", "bigram")

# --- caches and costs --------------------------------------------------------------------------------------------------------------------
_TRACED = f"{DEG}, {blocks(2)}, tr AS MATERIALIZED (SELECT part, row_number() OVER (PARTITION BY part ORDER BY src, dst) - 1 AS seq, dst, 4 * deg.d AS b, deg.d FROM rd JOIN deg ON deg.v = rd.dst)"


def _trace2(g):
    return trace.build(g, partition.block(g, 2))


_ENTRIES = [4, 16, 64, 128]
_REUSE_SQL = (
    f"{_TRACED}, pv AS (SELECT part, seq, dst, lag(seq) OVER (PARTITION BY part, dst ORDER BY seq) AS prev, lead(seq) OVER (PARTITION BY part, dst ORDER BY seq) AS nxt FROM tr), "
    "ds AS (SELECT a.part, a.seq, count(b.seq) AS dist FROM pv a LEFT JOIN pv b ON b.part = a.part AND b.seq > a.prev AND b.seq < a.seq AND (b.nxt IS NULL OR b.nxt >= a.seq) WHERE a.prev IS NOT NULL GROUP BY a.part, a.seq) | "
    f"SELECT p.part, e.e AS entries, (SELECT count(*) FROM ds WHERE ds.part = p.part AND ds.dist < e.e) AS hits FROM (SELECT DISTINCT part FROM tr) p, (SELECT unnest({_ENTRIES})::BIGINT AS e) e"
)
add("cache_sweep_offsets_rmat_s8", lambda s, d: cache.recency_hits(_trace2(build(s, d, "nation_days")), _ENTRIES), _REUSE_SQL, "nation_days")
add("cache_sweep_offsets_joined_toy", lambda s, d: cache.recency_hits_sql(_trace2(build(s, d, "nation_segments")), _ENTRIES), _REUSE_SQL, "nation_segments")
add("cache_unlimited_rmat", lambda s, d: cache.summarize(cache.replay(_trace2(build(s, d, "nation_days")), CacheConfig(1 << 40))).select("part", "reads", "hit", "compulsory", "capacity", "conflict"),
    f"{blocks(2)} | SELECT part, count(*) AS reads, count(*) - count(DISTINCT dst) AS hit, count(DISTINCT dst) AS compulsory, 0::BIGINT AS capacity, 0::BIGINT AS conflict FROM rd GROUP BY part", "nation_days")
add("cache_sweep_adj_rmat", lambda s, d: experiments.cache_sweep(build(s, d, "rmat_s10_ef16"), "adj", (10, 25, 50, 100)))
add("cache_sweep_offsets_rmat", lambda s, d: experiments.cache_sweep(build(s, d, "rmat_s10_ef16"), "offsets", (10, 25, 50, 100)))
add("score_compare_25_rmat", lambda s, d: experiments.score_comparison(build(s, d, "rmat_s10_ef16")))
_HOT = "hs AS (SELECT part, dst, b, sum(b) OVER (PARTITION BY part ORDER BY d DESC, dst ROWS UNBOUNDED PRECEDING) AS run, sum(b) OVER (PARTITION BY part) AS total FROM (SELECT DISTINCT part, dst, b, d FROM tr))"
add("hot_set_25_rmat", lambda s, d: cache.hot_set(_trace2(build(s, d, "rmat_s10_ef16")), 25), f"{_TRACED}, {_HOT} | SELECT part, dst FROM hs WHERE 100 * run <= 25 * total", "rmat_s10_ef16")
for _g in ("rmat_s10_ef16", "bigram"):
    add(f"static_hits_25_{_g}", lambda s, d, g=_g: cache.static_hits(_trace2(build(s, d, g)), 25),
        f"{_TRACED}, {_HOT}, ct AS (SELECT part, dst, count(*) AS c FROM tr GROUP BY part, dst), h AS (SELECT sum(c - 1)::BIGINT AS hits FROM ct JOIN hs USING (part, dst) WHERE 100 * run <= 25 * total) | SELECT reads, hits, round(1 - hits / reads, 6) AS miss_rate FROM (SELECT count(*) AS reads FROM tr), h", _g)
for _n, _g in (("rmat", "rmat_s10_ef16"), ("bigram", "bigram")):
    add(f"hash_law_{_n}", on(_g)(experiments.hash_law),
    f"{_TRACED}, {_HOT}, nn AS (SELECT count(*) AS n FROM (SELECT DISTINCT part, dst FROM tr)) | SELECT q::INT AS percent, (SELECT count(*) FROM hs WHERE 100 * run <= q * total) AS held, round((SELECT n FROM nn) * (q / 100.0::DOUBLE) ** 2, 3) AS predicted FROM (SELECT unnest([10, 25, 50, 75]) AS q)", _g)
_M = CostModel()
add("read_time_rmat", lambda s, d: costs.read_time(_trace2(build(s, d, "rmat_s10_ef16"))).select("part", "n_reads", "bytes", F.round("seconds", 9).alias("seconds")),
    f"{_TRACED} | SELECT part, count(*) AS n_reads, sum(8 + b)::BIGINT AS bytes, round(2 * count(*) * {_M.alpha!r} + sum(8 + b) * {_M.beta!r}, 9)::DOUBLE AS seconds FROM tr GROUP BY part", "rmat_s10_ef16")


def _budget(spark, d):
    """Caches of 1 MiB for graphs whose vertices are the suppliers, parts and orders of the line items."""
    lines = load(spark, d, "lineitem").select(F.explode(F.expr("array(struct('suppliers' AS vertices, l_suppkey AS v), struct('parts' AS vertices, l_partkey AS v), struct('orders' AS vertices, l_orderkey AS v))")).alias("e"))
    n = lines.select("e.*").distinct().groupBy("vertices").agg(F.count(F.lit(1)).alias("n"))
    return n.select("vertices", "n", *(x.alias(k) for k, x in costs.split_columns(1 << 20, F.col("n")).items()))


add("budget_split", _budget, "SELECT vertices, n, least(1048576, floor(0.8 * n)::BIGINT * 4) AS offsets_bytes, floor(0.8 * n)::BIGINT // 2 AS offsets_entries, 1048576 - least(1048576, floor(0.8 * n)::BIGINT * 4) AS adj_bytes "
    "FROM (SELECT 'suppliers' AS vertices, count(DISTINCT l_suppkey) AS n FROM lineitem UNION ALL SELECT 'parts', count(DISTINCT l_partkey) FROM lineitem UNION ALL SELECT 'orders', count(DISTINCT l_orderkey) FROM lineitem)")
for _g in ("rmat_s10_ef16", "bigram"):
    add(f"overall_{_g}", on(_g)(experiments.overall))
    add(f"speedup_{_g}", lambda s, d, g=_g: experiments.speedup(experiments.overall(build(s, d, g)), 4))


def _overall_sql() -> str:
    m, out = _M, []
    for p in experiments.STEPS:
        out.append(
            f"SELECT {p} AS p, round(max(comp + plain), 6) AS plain_s, round(max(comp + once), 6) AS cached_s, round(max(comp), 6) AS compute_s, round(sum(plain) / sum(plain + comp), 4) AS comm_share FROM "
            f"(SELECT x.part, sum(CASE WHEN {_RULE} THEN di + dj ELSE least(di, dj) * log2(greatest(di, dj)) END) * {m.gamma!r}::DOUBLE AS comp FROM ad JOIN part{p} x ON x.v = ad.src GROUP BY x.part) w LEFT JOIN "
            f"(SELECT part, sum(c * t) AS plain, sum(t) AS once FROM (SELECT part, dst, count(*) AS c, {2 * m.alpha!r}::DOUBLE + (4 * max(d) + 8) * {m.beta!r}::DOUBLE AS t FROM rd{p} JOIN deg ON deg.v = rd{p}.dst GROUP BY part, dst) GROUP BY part) r USING (part)"
        )
    return f"{DEG}, {INDEX}, {_STEP_CTES}, ad AS MATERIALIZED (SELECT a.src, x.d AS di, y.d AS dj FROM arcs a JOIN deg x ON x.v = a.src JOIN deg y ON y.v = a.dst) | " + " UNION ALL ".join(out)


for _g in ("rmat_s10_ef16", "bigram"):
    SQL[f"overall_{_g}"] = (lambda c, s: f"WITH {graphs.SQL[_g]}, {c} {s}")(*_overall_sql().split(" | ", 1))

# --- budgets, sweeps and read times by the closed form of the degree score ----------------------------------------------------------------
_C = experiments.CACHED
_DG = "dg AS MATERIALIZED (SELECT vs.v, coalesce(deg.d, 0) AS d FROM vs LEFT JOIN deg ON deg.v = vs.v)"


def _classes_sql(p: int) -> str:
    return (
        f"{part_sql(p, f'part{p}')}, {reads_sql(p, f'rd{p}', f'part{p}')}, "
        f"hc{p} AS (SELECT part, d, count(*) AS k, sum(c)::BIGINT AS c FROM (SELECT part, dst, count(*) AS c FROM rd{p} GROUP BY part, dst) x JOIN dg ON dg.v = x.dst GROUP BY part, d), "
        f"hr{p} AS MATERIALIZED (SELECT *, sum(k) OVER w AS held, sum(4 * d * k) OVER w AS bytes, sum(k) OVER (PARTITION BY part) AS all_held, sum(4 * d * k) OVER (PARTITION BY part) AS all_bytes FROM hc{p} WINDOW w AS (PARTITION BY part ORDER BY d DESC))"
    )


def _costs_sql(entries: str, size: str, windows: tuple[str, ...] = ("offsets", "adj")) -> str:
    """Columns plain, cached, once, hit_o, hit_a of the classes."""
    mo, ma = f"CASE WHEN held <= {entries} THEN k ELSE c END", f"CASE WHEN bytes <= {size} THEN k ELSE c END"
    so, sa = f"({_C.alpha + 8 * _C.beta!r}::DOUBLE)", f"({_C.alpha!r}::DOUBLE + 4 * d * {_C.beta!r}::DOUBLE)"
    pay = lambda m, s: f"({m}) * ({s} + {_C.miss_extra!r}::DOUBLE) + c * {_C.lookup!r}::DOUBLE"
    cached = {"offsets": pay(mo, so), "adj": pay(ma, sa)}
    once = {"offsets": pay("k", so), "adj": pay("k", sa)}
    plain = {"offsets": f"c * {so}", "adj": f"c * {sa}"}
    of = lambda x: " + ".join(x[w] if w in windows else plain[w] for w in plain)
    return f"{' + '.join(plain.values())} AS plain, {of(cached)} AS cached, {of(once)} AS once, c - ({mo}) AS hit_o, c - ({ma}) AS hit_a"


def _budgeted_sql(steps: tuple[int, ...], percent: int, buffer_bytes: int = 1 << 16, m: CostModel = _C) -> str:
    ops = f"CASE WHEN {_RULE} THEN di + dj ELSE least(di, dj) * log2(greatest(di, dj)) END"
    ctes = [
        VERTICES, DEG, _DG, INDEX.replace(VERTICES + ", ", ""),
        "ad AS MATERIALIZED (SELECT a.src, a.dst, x.d AS di, y.d AS dj, x.d - row_number() OVER (PARTITION BY a.src ORDER BY a.dst) AS later FROM arcs a JOIN dg x ON x.v = a.src JOIN dg y ON y.v = a.dst)",
        f"bd AS (SELECT n, csr, csr * {percent} // 100 AS size, least(csr * {percent} // 100, floor(0.8 * n)::BIGINT * 4) AS o FROM (SELECT n, 4 * (n + 1 + m) AS csr FROM (SELECT count(*) AS n FROM vs), (SELECT count(*) AS m FROM arcs)))",
    ]
    out = []
    for p in steps:
        ctes += [
            _classes_sql(p),
            f"wk{p} AS (SELECT x.part, sum({ops}) * {m.gamma!r}::DOUBLE AS comp FROM ad JOIN part{p} x ON x.v = ad.src WHERE dj > 0 GROUP BY x.part)",
            f"cm{p} AS (SELECT part, sum(plain) AS plain, sum(cached) AS cached, sum(c) AS c, sum(k) AS k, sum(hit_o) AS hit_o, sum(hit_a) AS hit_a FROM (SELECT part, c, k, {_costs_sql('bd.o // 8', '(bd.size - bd.o)')} FROM hr{p}, bd) GROUP BY part)",
            f"al{p} AS (SELECT coalesce(comp, 0) AS comp, coalesce(plain, 0) AS plain, coalesce(cached, 0) AS cached, c, k, hit_o, hit_a FROM wk{p} FULL JOIN cm{p} USING (part))",
            f"pr{p} AS MATERIALIZED (SELECT asker, owner, count(*) AS messages, sum(q) AS q, sum(answer) AS answer FROM (SELECT x.part AS asker, y.part AS owner, ad.src, sum(later) AS q, sum(later * log2(greatest(dj, 1))) * {m.gamma!r}::DOUBLE AS answer FROM ad JOIN part{p} x ON x.v = ad.src JOIN part{p} y ON y.v = ad.dst WHERE later > 0 GROUP BY 1, 2, 3) GROUP BY asker, owner)",
            f"sn{p} AS (SELECT sum(CASE WHEN asker <> owner THEN {2 * m.alpha!r}::DOUBLE * messages + {17 * m.beta!r}::DOUBLE * q ELSE 0 END) AS single, sum(CASE WHEN asker <> owner THEN {2 * m.alpha!r}::DOUBLE * ceil(16 * q / {buffer_bytes}.0::DOUBLE) + {17 * m.beta!r}::DOUBLE * q ELSE 0 END) AS buffered FROM pr{p} GROUP BY asker)",
        ]
        out.append(
            f"SELECT {p} AS p, csr AS csr_bytes, size AS cache_bytes, round(plain_s, 9) AS plain_s, round(cached_s, 9) AS cached_s, round(compute_s, 9) AS compute_s, round(single + answer, 9) AS asking_s, round(buffered + answer, 9) AS asking_buffered_s, round(comm_share, 6) AS comm_share, "
            "round(first_share, 6) AS first_share, round(offsets_hit, 6) AS offsets_hit, round(adj_hit, 6) AS adj_hit, round(1 - cached_s / plain_s, 6) AS gain, CASE WHEN comm_share < 0.5 THEN 'compute' WHEN cached_s <= 0.95 * plain_s THEN 'cacheable' ELSE 'compulsory' END AS scenario FROM bd, "
            f"(SELECT max(comp + plain) AS plain_s, max(comp + cached) AS cached_s, max(comp) AS compute_s, sum(plain) / sum(plain + comp) AS comm_share, sum(k) / sum(c) AS first_share, sum(hit_o) / sum(c) AS offsets_hit, sum(hit_a) / sum(c) AS adj_hit FROM al{p}), "
            f"(SELECT max(single) AS single, max(buffered) AS buffered FROM sn{p}), (SELECT max(answer) AS answer FROM (SELECT sum(answer) AS answer FROM pr{p} GROUP BY owner))"
        )
    return ", ".join(ctes) + " | " + " UNION ALL ".join(out)


_BUDGETED = {g: (experiments.STEPS, 50) for g in ("rmat_s10_ef16", "bigram", "copurchase", "succession_directed", "coactive")}
for _g, (_st, _pc) in _BUDGETED.items():
    add(f"budgeted_{_g}", lambda s, d, g=_g, st=_st, pc=_pc: experiments.budgeted(build(s, d, g), st, pc), _budgeted_sql(_st, _pc), _g)
for _g in ("rmat_s12_ef16", "bigram"):  # at large scale the caches are small beside the graph
    add(f"budgeted_large_{_g}", lambda s, d, g=_g: experiments.budgeted(build(s, d, g), experiments.LARGE, 12), _budgeted_sql(experiments.LARGE, 12), _g)
add("budgeted_slow_cores_coactive", lambda s, d: experiments.budgeted(build(s, d, "coactive"), model=experiments.SLOW), _budgeted_sql(experiments.STEPS, 50, m=experiments.SLOW), "coactive")
add("budgeted_speedup_rmat", lambda s, d: experiments.speedup(experiments.budgeted(build(s, d, "rmat_s10_ef16")), 4, ("plain_s", "cached_s", "asking_s")),
    _budgeted_sql(experiments.STEPS, 50).replace(" | ", ", bt AS MATERIALIZED (", 1) + ") | SELECT bt.p, round(b.plain_s / bt.plain_s, 4) AS speedup_plain_s, round(b.cached_s / bt.cached_s, 4) AS speedup_cached_s, round(b.asking_s / bt.asking_s, 4) AS speedup_asking_s FROM bt, bt b WHERE b.p = 4", "rmat_s10_ef16")
for _g in ("rmat_s10_ef16", "bigram"):
    _ov = SQL[f"overall_{_g}"]
    _cut = _ov.rindex(" SELECT 4 AS p,")
    SQL[f"speedup_{_g}"] = _ov[:_cut] + ", ov AS MATERIALIZED (" + _ov[_cut:] + ") SELECT ov.p, round(b.plain_s / ov.plain_s, 4) AS speedup_plain_s, round(b.cached_s / ov.cached_s, 4) AS speedup_cached_s FROM ov, ov b WHERE b.p = 4"
_BASE = ", ".join([VERTICES, DEG, _DG, INDEX.replace(VERTICES + ", ", "")])
for _g in ("rmat_s12_ef16", "bigram"):
    for _w, _hit in (("offsets", "hit_o"), ("adj", "hit_a")):
        add(f"sweep_{_w}_{_g}", lambda s, d, g=_g, w=_w: experiments.sweep(build(s, d, g), w),
            f"{_BASE}, {_classes_sql(2)} | SELECT q AS percent, sum(c)::BIGINT AS reads, sum({_hit})::BIGINT AS hits, round(1 - sum({_hit}) / sum(c), 6) AS miss_rate, round(sum(k) / sum(c), 6) AS first_share, round(1 - sum(cached) / sum(plain), 6) AS saved_share "
            f"FROM (SELECT q, c, k, {_costs_sql('all_held * q / 100', 'all_bytes * q / 100', (_w,))} FROM hr2, (SELECT unnest(range(5, 101, 5))::INT AS q)) GROUP BY q", _g)  # fmt: skip
for _g in ("rmat_s10_ef16", "bigram", "copurchase"):
    add(f"hot_read_times_{_g}", on(_g)(experiments.hot_read_times), f"{_BASE}, {', '.join(map(_classes_sql, experiments.STEPS))} | " + " UNION ALL ".join(
        f"SELECT {p} AS p, sum(c)::BIGINT AS reads, round(sum(plain) / sum(c) * 1e6, 6) AS plain_us, round(sum(cached) / sum(c) * 1e6, 6) AS cached_us, round(sum(once) / sum(c) * 1e6, 6) AS once_us FROM (SELECT c, {_costs_sql('0', 'all_bytes * 25 / 100', ('adj',))} FROM hr{p})" for p in experiments.STEPS), _g)
for _g in ("rmat_s8_ef8", "succession_directed"):
    add(f"score_read_times_{_g}", lambda s, d, g=_g: experiments.score_read_times(build(s, d, g)))
add("score_bounds_rmat", lambda s, d: cache.compare_application_scores(_trace2(build(s, d, "rmat_s10_ef16"))))
#: Replays and partitions below that are named after the generator run on a table's graph of like shape: few hubs, bounded size.
#: An index of one way: a slot holds the last key read that falls into it.
_SLOT = "((dst::HUGEINT * 11400714819323198485::HUGEINT) % 18446744073709551616::HUGEINT // 1048576 % 64)"
add("cache_direct_mapped_rmat", lambda s, d: cache.summarize(cache.replay(_trace2(build(s, d, "nation_days")), CacheConfig(1 << 40, slots=64))).select("part", "reads", "hit", "compulsory", "capacity", "conflict", "evicted"),
    f"{_TRACED}, sl AS (SELECT part, seq, dst, lag(dst) OVER (PARTITION BY part, {_SLOT} ORDER BY seq) AS held, lag(seq) OVER (PARTITION BY part, dst ORDER BY seq) AS prev FROM tr) | "
    "SELECT part, count(*) AS reads, count(*) FILTER (WHERE held = dst) AS hit, count(*) FILTER (WHERE prev IS NULL) AS compulsory, 0::BIGINT AS capacity, count(*) FILTER (WHERE prev IS NOT NULL AND held <> dst) AS conflict, count(*) FILTER (WHERE held <> dst)::BIGINT AS evicted FROM sl GROUP BY part", "nation_days")  # fmt: skip
add("cache_recency_outcomes_rmat", lambda s, d: cache.summarize(cache.replay(_trace2(build(s, d, "nation_days")), CacheConfig(64 * 8, window="offsets"))).select("part", "reads", "hit", "compulsory", "capacity", "conflict"),
    _REUSE_SQL.split(" | ")[0] + " | SELECT p.part, reads, hit, first AS compulsory, reads - hit - first AS capacity, 0::BIGINT AS conflict FROM (SELECT part, count(*) AS reads, count(DISTINCT dst) AS first FROM tr GROUP BY part) p JOIN (SELECT part, count(*) FILTER (WHERE dist < 64) AS hit FROM ds GROUP BY part) h USING (part)", "nation_days")

# --- baselines ---------------------------------------------------------------------------------------------------------------------------
_TV = f"{PER_VERTEX} | SELECT v, t AS triangles FROM tv"
for _n, _f in {
    "wedge_mapreduce": baselines.wedge_mapreduce,
    "query_response": lambda g: baselines.query_response(g, partition.block(g, 8)),
    "bulk_synchronous": baselines.bulk_synchronous,
    "shadow_count": lambda g: baselines.shadow_count(g, partition.block(g, 4)),
    "query_response_buffered": lambda g: baselines.query_response_buffered(g, partition.block(g, 8), 4096).groupBy("v").agg(F.sum("triangles").alias("triangles")),
}.items():
    for _g in ("coactive", "rmat_s8_ef8"):
        add(f"{_n}_{_g}", on(_g)(_f), _TV, _g)
_ASKED = f"{INDEX}, {part_sql(8)}, qs AS MATERIALIZED (SELECT x.part AS asker, y.part AS owner, count(*) AS questions FROM arcs a JOIN arcs b ON a.src = b.src AND a.dst < b.dst JOIN part x ON x.v = a.src JOIN part y ON y.v = a.dst WHERE x.part <> y.part GROUP BY 1, 2)"
add("query_messages_rmat", lambda s, d: (lambda x: baselines.query_messages(x, partition.block(x, 8), 1 << 16))(build(s, d, "rmat_s10_ef16")), f"{_ASKED} | SELECT asker, owner, questions, questions * 16 AS bytes, (questions * 16 + 65535) // 65536 AS rounds FROM qs", "rmat_s10_ef16")
add("query_rounds_rmat", lambda s, d: experiments.questions_by_parts(build(s, d, "rmat_s10_ef16"), (8,)), f"{_ASKED} | SELECT 8 AS p, sum(questions)::BIGINT AS questions, sum(questions * 16)::BIGINT AS bytes, max((questions * 16 + 65535) // 65536) AS rounds FROM qs", "rmat_s10_ef16")
_ASK = lambda p: f"qs{p} AS MATERIALIZED (SELECT x.part AS asker, y.part AS owner, count(*) AS questions FROM arcs a JOIN arcs b ON a.src = b.src AND a.dst < b.dst JOIN part{p} x ON x.v = a.src JOIN part{p} y ON y.v = a.dst WHERE x.part <> y.part GROUP BY 1, 2)"
add("query_rounds_by_parts_rmat", lambda s, d: experiments.questions_by_parts(build(s, d, "rmat_s10_ef16")), f"{INDEX}, " + ", ".join(f"{part_sql(p, f'part{p}')}, {_ASK(p)}" for p in (4, 8, 16)) + " | " + " UNION ALL ".join(
    f"SELECT {p} AS p, sum(questions)::BIGINT AS questions, sum(questions * 16)::BIGINT AS bytes, max((questions * 16 + 65535) // 65536) AS rounds FROM qs{p}" for p in (4, 8, 16)), "rmat_s10_ef16")
add("shadow_replication_rmat", lambda s, d: (lambda x: baselines.shadow_replication(x, partition.block(x, 4)))(build(s, d, "rmat_s10_ef16")),
    f"{INDEX}, {part_sql(4)}, ow AS MATERIALIZED (SELECT x.part, a.src, a.dst FROM arcs a JOIN part x ON x.v = a.src), nr AS MATERIALIZED (SELECT DISTINCT part, dst AS x FROM ow), hd AS (SELECT part, src, dst FROM ow UNION SELECT p.part, a.src, a.dst FROM arcs a JOIN nr p ON p.x = a.src JOIN nr q ON q.x = a.dst AND q.part = p.part) | SELECT n_held, n_arcs, round(n_held / n_arcs, 6) AS factor FROM (SELECT count(*) AS n_held FROM hd), (SELECT count(*) AS n_arcs FROM arcs)", "rmat_s10_ef16")

# --- hash partitions, flushes, growing balance, set operations, functions ------------------------------------------------------------------
_HASHED = f"{INDEX}, part AS MATERIALIZED (SELECT v, idx, (('0x' || substr(md5(v::VARCHAR), 1, 8))::BIGINT % 8)::INT AS part FROM ix)"
for _g in ("rmat_s10_ef16", "bigram"):
    add(f"hashed_partition_{_g}", lambda s, d, g=_g: partition.hashed(build(s, d, g), 8), f"{_HASHED} | SELECT v, idx, part FROM part", _g)
    add(f"cut_hashed_p8_{_g}", lambda s, d, g=_g: (lambda x: partition.cut_stats(x, partition.hashed(x, 8)))(build(s, d, g)),
        f"{_HASHED}, {reads_sql(8)} | SELECT n_arcs, n_cut, round(n_cut / n_arcs, 6) AS cut_share FROM (SELECT count(*) AS n_cut FROM rd), (SELECT count(*) AS n_arcs FROM arcs)", _g)
#: Without limits, only flushes lose entries: a read hits if its target was read since the last one.
_FLUSHED = "SELECT part, count(*) AS reads, count(*) - count(DISTINCT (dst, {0})) AS hit, count(DISTINCT dst) AS compulsory, count(DISTINCT (dst, {0})) - count(DISTINCT dst) AS capacity, 0::BIGINT AS conflict FROM tr GROUP BY part"
for _n, _cfg, _flush in (("transparent", CacheConfig(1 << 40, mode="transparent", epoch_len=100), None), ("user", CacheConfig(1 << 40, mode="user"), "flush")):
    add(f"cache_{_n}_flush_rmat", lambda s, d, c=_cfg, f=_flush: cache.summarize(cache.replay(_trace2(build(s, d, "nation_days")).withColumn("flush", F.col("seq") % 100 == 0), c, flush_col=f)).select("part", "reads", "hit", "compulsory", "capacity", "conflict"),
        f"{_TRACED} | {_FLUSHED.format('seq // 100')}", "nation_days")
#: A cache of one entry holds the last read target.
add("cache_one_entry_rmat", lambda s, d: cache.summarize(cache.replay(_trace2(build(s, d, "nation_days")), CacheConfig(8, window="offsets", fragmentation=True))).select("part", "reads", "hit", "compulsory", "capacity", "conflict"),
    f"{_TRACED}, pv AS (SELECT part, dst, lag(dst) OVER (PARTITION BY part ORDER BY seq) AS held FROM tr) | SELECT part, count(*) AS reads, count(*) FILTER (WHERE held = dst) AS hit, count(DISTINCT dst) AS compulsory, count(*) - count(DISTINCT dst) - count(*) FILTER (WHERE held = dst) AS capacity, 0::BIGINT AS conflict FROM pv GROUP BY part", "nation_days")
_TWO = "WITH " + graphs.SQL["coactive"].replace("arcs AS", "ga AS") + ", " + graphs.SQL["succession"].replace("arcs AS", "gb AS")
for _n, _f, _op in (("union", graphs.union, "UNION"), ("intersect", graphs.intersect, "INTERSECT"), ("difference", graphs.difference, "EXCEPT")):
    add(f"graph_{_n}_coactive_succession", lambda s, d, f=_f: f(build(s, d, "coactive"), build(s, d, "succession")).arcs, f"{_TWO} SELECT src, dst FROM ga {_op} SELECT src, dst FROM gb")
add("common_count_function_coactive", lambda s, d: intersect.arc_lists(build(s, d, "coactive")).select("src", "dst", udx.common_count("a", "b").alias("common")), _SUPPORT, "coactive")


def _drawn_edges(spark, d):
    udx.register(spark)
    drawn = spark.sql("SELECT r.src, r.dst FROM range(0, 4) AS x, LATERAL rmat_edges(8, 8, int(x.id), 4) AS r")
    return prep.symmetrize(Graph(prep.simplify(drawn))).arcs


add("rmat_edges_function", _drawn_edges, "SELECT src, dst FROM arcs", "rmat_s8_ef8")
add("adjacency_round_trip_coactive", lambda s, d: csr.adjacency(build(s, d, "coactive")).select(F.col("v").alias("src"), F.explode("nbrs").alias("dst")), "SELECT src, dst FROM arcs", "coactive")

# --- events ------------------------------------------------------------------------------------------------------------------------------
add("within_10_minutes", lambda s, d: graphs.within(s, d).arcs, "SELECT DISTINCT * FROM (SELECT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE AND a.user_id <> b.user_id UNION ALL SELECT b.user_id, a.user_id FROM events a JOIN events b ON b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE AND a.user_id <> b.user_id)")
add("last_click_before_purchase", graphs.last_before, "SELECT event_id, user_id, before_id FROM (SELECT event_id, user_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) WHERE event_type = 'purchase'")


def _day_triangles(spark, d):
    from .streaming.edges import window_triangles

    e = load(spark, d, "events").select(F.to_date("ts").alias("start"), "event_type", F.get_json_object("props", "$.k").alias("k"), "user_id").distinct()
    o = e.withColumnRenamed("user_id", "dst")
    return window_triangles(e.join(o, ["start", "event_type", "k"]).where("user_id < dst").select("start", F.col("user_id").alias("src"), "dst"))


add("window_graph_triangles", _day_triangles,
    "WITH e AS (SELECT DISTINCT ts::DATE AS start, event_type, json_extract_string(props, '$.k') AS k, user_id AS u FROM events), a AS (SELECT DISTINCT x.start, x.u AS src, y.u AS dst FROM e x JOIN e y ON x.start = y.start AND x.event_type = y.event_type AND x.k = y.k AND x.u < y.u) SELECT x.start, count(*) AS triangles FROM a x JOIN a y ON x.start = y.start AND x.src = y.src AND x.dst < y.dst JOIN a z ON z.start = x.start AND z.src = x.dst AND z.dst = y.dst GROUP BY x.start")
