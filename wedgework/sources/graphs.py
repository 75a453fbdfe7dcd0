"""Graphs built from the given tables, the recursive-matrix generator and set operations on graphs.

Each builder has its DuckDB twin in ``SQL`` (a CTE named arcs), which the oracles use.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.prep import simplify, symmetrize
from ..schema import Graph
from .tables import load, settle


def _co_members(rows: DataFrame, group: list[str], member: str) -> DataFrame:
    """Arcs between members of the same group: an equi-join on the group; members are made distinct before."""
    rows = rows.select(*group, F.col(member).cast("long").alias("m")).dropna().distinct()
    other = rows.withColumnRenamed("m", "o")
    return rows.join(other, group).where("m != o").select(F.col("m").alias("src"), F.col("o").alias("dst")).distinct()


#: Members that a task holds at most, about, of the groups that its vertices belong to; and tasks at least.
HELD, TASKS = 1 << 24, 16


def _co_lists(rows: DataFrame, group: list[str], member: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(v, nbrs), (v) and (ms): the same as whole lists, for large groups, whose pairs are far more than their members.

    No pair is moved: each group goes once to every block of vertices that has a member in it, and a block joins its vertices' groups one
    vertex at a time. Blocks grow in number until one's groups fit a task.
    """
    rows = rows.select(*group, F.col(member).cast("long").alias("m")).dropna().distinct()
    groups = settle(rows.groupBy(*group).agg(F.collect_list("m").alias("ms")).where("size(ms) > 1").select("ms"), "groups")
    sizes = [(r.s, r.c) for r in groups.groupBy(F.size("ms").alias("s")).agg(F.count(F.lit(1)).alias("c")).collect()]  # one row a size
    blocks = TASKS
    while sum(c * s * (1 - (1 - 1 / blocks) ** s) for s, c in sizes) > HELD and blocks < 1 << 20:
        blocks *= 2
    at = f"int(pmod(xxhash64(m), {blocks}))"
    sent = groups.select("ms", F.explode(F.expr(f"array_distinct(transform(ms, m -> {at}))")).alias("block")).repartition(blocks, "block")
    held = sent.select("block", F.expr(f"filter(ms, m -> {at} = block)").alias("own"), "ms").sortWithinPartitions("block")

    def joined(own: pa.Array, ms: pa.Array) -> Iterator[pa.RecordBatch]:
        values, ends = np.asarray(ms.values), np.asarray(ms.offsets)
        mine, of = np.asarray(own.values), np.repeat(np.arange(len(own)), np.diff(np.asarray(own.offsets)))
        order = np.argsort(mine, kind="stable")
        mine, of = mine[order], of[order]
        names, at = np.unique(values, return_inverse=True)
        seen = np.zeros(len(names), dtype=bool)
        starts = np.append(np.flatnonzero(np.r_[True, mine[1:] != mine[:-1]]), len(mine))
        vs, lists, n = [], [], 0
        for a, b in zip(starts[:-1], starts[1:], strict=True):
            met = np.concatenate([at[ends[i] : ends[i + 1]] for i in of[a:b]])
            if len(names) > 16 * len(met):
                near = np.unique(met)
            else:
                seen[met] = True
                near = np.flatnonzero(seen)
                seen[near] = False
            near = names[near]
            vs.append(mine[a])
            lists.append(near[near != mine[a]])
            n += len(near)
            if n > 1 << 20 or b == len(mine):
                cuts = np.cumsum([0, *map(len, lists)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(np.array(vs, dtype=np.int64)), pa.ListArray.from_arrays(pa.array(cuts), pa.array(np.concatenate(lists)))], ["v", "nbrs"])
                vs, lists, n = [], [], 0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.Table] = []

        def ended() -> Iterator[pa.RecordBatch]:
            t = pa.concat_tables(kept).combine_chunks()
            kept.clear()
            yield from joined(t["own"].combine_chunks(), t["ms"].combine_chunks())

        for b in batches:
            block = b.column("block").to_numpy()
            edges = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(block)]
            for lo, hi in zip(edges[:-1], edges[1:], strict=True):
                if lo == hi:
                    continue
                if kept and kept[-1]["block"][0].as_py() != block[lo]:
                    yield from ended()
                kept.append(pa.table(b.slice(lo, hi - lo)))
        if kept:
            yield from ended()

    return held.mapInArrow(run, "v long, nbrs array<long>"), groups.select(F.explode("ms").alias("v")).distinct(), groups


def _from_lists(lists: DataFrame, ends: DataFrame, groups: DataFrame, name: str) -> Graph:
    return Graph(lists.select(F.col("v").alias("src"), F.explode("nbrs").alias("dst")), name=name, lists=lists, ends=ends, groups=groups)


def copurchase(spark: SparkSession, d: str) -> Graph:
    return Graph(_co_members(load(spark, d, "lineitem"), ["l_orderkey"], "l_partkey"), name="copurchase")


def cosupply(spark: SparkSession, d: str) -> Graph:
    return Graph(_co_members(load(spark, d, "lineitem"), ["l_orderkey"], "l_suppkey"), name="cosupply")


def segment_cliques(spark: SparkSession, d: str) -> Graph:
    return _from_lists(*_co_lists(load(spark, d, "customer"), ["c_nationkey", "c_mktsegment"], "c_custkey"), "segment_cliques")


def coactive(spark: SparkSession, d: str) -> Graph:
    e = load(spark, d, "events").select("event_type", F.get_json_object("props", "$.k").alias("k"), F.to_date("ts").alias("day"), "user_id")
    return _from_lists(*_co_lists(e, ["event_type", "k", "day"], "user_id"), "coactive")


def cobuyer(spark: SparkSession, d: str) -> Graph:
    bought = load(spark, d, "lineitem").select("l_orderkey", "l_partkey", F.date_trunc("month", F.col("l_shipdate").cast("timestamp")).alias("month"))
    rows = bought.join(load(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return Graph(_co_members(rows, ["l_partkey", "month"], "o_custkey"), name="cobuyer")


def part_supp(spark: SparkSession, d: str) -> Graph:
    """Bipartite: parts have even ids, suppliers odd ones."""
    e = load(spark, d, "lineitem").select((2 * F.col("l_partkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"))
    return symmetrize(Graph(simplify(e), name="part_supp"))


def nation_days(spark: SparkSession, d: str) -> Graph:
    """Bipartite with few hubs and a bounded size: nations (below 100) and the days, from 100 on, on which their customers ordered."""
    o, c = load(spark, d, "orders"), load(spark, d, "customer")
    day = F.date_diff(F.to_date("o_orderdate"), F.lit("1970-01-01").cast("date")).cast("long") + 100
    e = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select(F.col("c_nationkey").cast("long").alias("src"), day.alias("dst"))
    return symmetrize(Graph(simplify(e), name="nation_days"))


def nation_segments(spark: SparkSession, d: str) -> Graph:
    """Bipartite and tiny: nations and the market segments of their customers, as strings."""
    e = load(spark, d, "customer").select(F.concat(F.lit("n"), F.col("c_nationkey").cast("string")).alias("src"), F.col("c_mktsegment").alias("dst"))
    return symmetrize(Graph(simplify(e), name="nation_segments"))


def _tokens(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").select(F.expr("regexp_extract_all(lower(text), '[a-zà-ÿ]+', 0)").alias("t"))


def bigram(spark: SparkSession, d: str, directed: bool = False) -> Graph:
    """Neighbouring tokens of the documents; vertices are the tokens themselves."""
    pairs = _tokens(spark, d).where("size(t) > 1").select(F.explode(F.expr("arrays_zip(slice(t, 1, size(t) - 1), slice(t, 2, size(t) - 1))")).alias("p"))
    arcs = simplify(pairs.select(F.col("p.0").alias("src"), F.col("p.1").alias("dst")))
    g = Graph(arcs, directed=directed, name="bigram" + "_directed" * directed)
    return g if directed else symmetrize(g)


def succession(spark: SparkSession, d: str, directed: bool = True) -> Graph:
    """User of an event to the user of the next event. Days are windows of their own; day borders are stitched by one row a day."""
    e = load(spark, d, "events").select(F.to_date("ts").alias("day"), "ts", "event_id", "user_id")
    by = W.partitionBy("day").orderBy("ts", "event_id")
    inside = e.select(F.col("user_id").alias("src"), F.lead("user_id").over(by).alias("dst")).dropna()
    order = F.struct("ts", "event_id")
    ends = e.groupBy("day").agg(F.min_by("user_id", order).alias("first"), F.max_by("user_id", order).alias("last"))
    across = ends.select(F.col("last").alias("src"), F.lead("first").over(W.orderBy("day")).alias("dst")).dropna()  # one row a day
    g = Graph(simplify(inside.unionByName(across)), directed=directed, name="succession" + "_directed" * directed)
    return g if directed else symmetrize(g)


def knn(spark: SparkSession, d: str, k: int = 10, block: int = 1024) -> Graph:
    """Directed: the k nearest rows by cosine (ties: smaller id), by products of blocks of rows: the exact baseline, all pairs in task-sized units."""
    e = load(spark, d, "embeddings").select("vec_id", "embedding")
    n = e.count()
    blocks = max(1, -(-n // block))
    keyed = e.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    left = keyed.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("b", "o", "vec_id", "embedding")
    right = keyed.withColumn("l", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(F.col("l").alias("b"), F.col("b").alias("o"), "vec_id", "embedding")

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        def unit(x: pd.DataFrame) -> np.ndarray:
            m = np.stack(x["embedding"].to_numpy()).astype(np.float64)
            return m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)

        if not len(a) or not len(b):
            return pd.DataFrame({"src": [], "dst": [], "sim": []}).astype({"src": "int64", "dst": "int64", "sim": "float64"})
        ia, ib = a["vec_id"].to_numpy(), b["vec_id"].to_numpy()
        sim = unit(a) @ unit(b).T
        sim[ia[:, None] == ib[None, :]] = -np.inf
        # only what reaches the k-th value is sorted
        least = np.partition(sim, max(sim.shape[1] - k, 0), axis=1)[:, max(sim.shape[1] - k, 0)]
        best = [(lambda at: at[np.lexsort((ib[at], -row[at]))[:k]])(np.flatnonzero(row >= m)) for row, m in zip(sim, least, strict=True)]
        return pd.DataFrame({"src": np.repeat(ia, [len(x) for x in best]), "dst": ib[np.concatenate(best)], "sim": np.concatenate([r[x] for r, x in zip(sim, best, strict=True)])})

    found = left.groupBy("b", "o").cogroup(right.groupBy("b", "o")).applyInPandas(near, "src long, dst long, sim double").where("sim > -2")
    by = W.partitionBy("src").orderBy(F.desc("sim"), "dst")
    return Graph(found.withColumn("r", F.row_number().over(by)).where(F.col("r") <= k).select("src", "dst"), directed=True, name="knn")


#: Quadrant probabilities of the generator.
RMAT = (0.57, 0.19, 0.19, 0.05)


def rmat(spark: SparkSession, scale: int, edge_factor: int, probabilities: tuple[float, float, float, float] = RMAT, seed: str = "") -> Graph:
    """2^scale * edge_factor draws; level l of edge e is decided by md5(seed e:l), so every engine draws the same graph."""
    a, b, c, _ = probabilities
    u = f"conv(substr(md5(concat('{seed}', id, ':', l)), 1, 7), 16, 10) / 268435456D"
    bits = (
        f"aggregate(transform(sequence(0, {scale - 1}), l -> named_struct('l', l, 'u', {u})), named_struct('s', 0L, 't', 0L), (x, y) -> named_struct("
        f"'s', x.s | CASE WHEN y.u >= {a + b} THEN shiftleft(1L, y.l) ELSE 0L END, 't', x.t | CASE WHEN (y.u >= {a} AND y.u < {a + b}) OR y.u >= {a + b + c} THEN shiftleft(1L, y.l) ELSE 0L END))"
    )
    drawn = spark.range((1 << scale) * edge_factor).select(F.expr(bits).alias("e")).select(F.col("e.s").alias("src"), F.col("e.t").alias("dst"))
    return symmetrize(Graph(simplify(drawn), name=f"rmat_s{scale}_ef{edge_factor}"))


def toy(spark: SparkSession) -> Graph:
    """Six vertices, eight edges; blocks {0,1,2} and {3,4,5} share one vertex's list."""
    edges = [(0, 1), (0, 2), (1, 2), (1, 4), (2, 4), (3, 4), (3, 5), (4, 5)]
    return symmetrize(Graph(spark.createDataFrame(edges, "src long, dst long"), name="toy"))


def host_links(spark: SparkSession, d: str) -> Graph:
    """Directed: page host to the first path part of its links."""
    p = load(spark, d, "pages").select(F.expr("parse_url(url, 'HOST')").alias("src"), F.explode(F.expr("regexp_extract_all(html, 'href=\"/?([^\"/]+)', 1)")).alias("dst"))
    return Graph(simplify(p.select("src", F.concat(F.lit("/"), "dst").alias("dst"))), directed=True, name="host_links")


def within(spark: SparkSession, d: str, minutes: int = 10) -> Graph:
    """Users with events at most ``minutes`` apart: a range join by time buckets, each event meets its own and the next bucket."""
    e = load(spark, d, "events").select(F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "user_id")
    width = minutes * 60_000_000
    a = e.select("t", F.col("user_id").alias("src"), F.explode(F.array(F.expr(f"t div {width}"), F.expr(f"t div {width} + 1"))).alias("b"))
    b = e.select(F.col("t").alias("u"), F.col("user_id").alias("dst"), F.expr(f"t div {width}").alias("b"))
    near = a.join(b, "b").where((F.col("u") >= F.col("t")) & (F.col("u") - F.col("t") <= width) & (F.col("src") != F.col("dst")))
    return symmetrize(Graph(simplify(near.select("src", "dst")), name="within"))


def last_before(spark: SparkSession, d: str, of: str = "purchase", by: str = "click") -> DataFrame:
    """As-of join: for each ``of`` event the user's last earlier ``by`` event (null: none)."""
    e = load(spark, d, "events").select("user_id", "ts", "event_id", "event_type")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return e.withColumn("before_id", F.last(F.when(F.col("event_type") == by, F.col("event_id")), ignorenulls=True).over(w)).where(F.col("event_type") == of).select("event_id", "user_id", "before_id")


def union(a: Graph, b: Graph) -> Graph:
    return a.with_arcs(a.arcs.unionByName(b.arcs).distinct())


def intersect(a: Graph, b: Graph) -> Graph:
    return a.with_arcs(a.arcs.intersect(b.arcs))


def difference(a: Graph, b: Graph) -> Graph:
    return a.with_arcs(a.arcs.subtract(b.arcs))


def _co_sql(source: str, group: str, member: str) -> str:
    return f"arcs AS MATERIALIZED (SELECT DISTINCT a.m AS src, b.m AS dst FROM (SELECT DISTINCT {group} AS g, {member} AS m FROM {source}) a JOIN (SELECT DISTINCT {group} AS g, {member} AS m FROM {source}) b ON a.g = b.g AND a.m <> b.m)"


_BIGRAM = "tk AS (SELECT regexp_extract_all(lower(text), '[a-zà-ÿ]+') AS t FROM documents), bg AS (SELECT unnest(t[:len(t) - 1]) AS a, unnest(t[2:]) AS b FROM tk WHERE len(t) > 1)"
_NEXT = "sc AS (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events)"
_BOTH = "arcs AS MATERIALIZED (SELECT DISTINCT * FROM (SELECT a AS src, b AS dst FROM {0} WHERE a <> b UNION ALL SELECT b, a FROM {0} WHERE a <> b))"
_ONE = "arcs AS MATERIALIZED (SELECT DISTINCT a AS src, b AS dst FROM {0} WHERE a <> b)"
SQL = {
    "copurchase": _co_sql("lineitem", "l_orderkey", "l_partkey"),
    "cosupply": _co_sql("lineitem", "l_orderkey", "l_suppkey"),
    "segment_cliques": _co_sql("customer", "(c_nationkey, c_mktsegment)", "c_custkey"),
    "coactive": _co_sql("events", "(event_type, json_extract_string(props, '$.k'), ts::DATE)", "user_id"),
    "cobuyer": _co_sql("(SELECT * FROM lineitem JOIN orders ON l_orderkey = o_orderkey)", "(l_partkey, date_trunc('month', l_shipdate))", "o_custkey"),
    "part_supp": "ps AS (SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem), " + _BOTH.format("ps"),
    "nation_days": "nd AS (SELECT c_nationkey::BIGINT AS a, 100 + date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS b FROM orders JOIN customer ON o_custkey = c_custkey), " + _BOTH.format("nd"),
    "nation_segments": "ns AS (SELECT 'n' || c_nationkey AS a, c_mktsegment AS b FROM customer), " + _BOTH.format("ns"),
    "bigram": f"{_BIGRAM}, {_BOTH.format('bg')}",
    "bigram_directed": f"{_BIGRAM}, {_ONE.format('bg')}",
    "succession": f"{_NEXT}, {_BOTH.format('sc')}",
    "succession_directed": f"{_NEXT}, {_ONE.format('sc')}",
    "knn": "arcs AS MATERIALIZED (SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id QUALIFY row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) DESC, b.vec_id) <= 10)",
    "toy": "ty AS (SELECT * FROM (VALUES (0, 1), (0, 2), (1, 2), (1, 4), (2, 4), (3, 4), (3, 5), (4, 5)) AS v(a, b)), arcs AS MATERIALIZED (SELECT a::BIGINT AS src, b::BIGINT AS dst FROM ty UNION ALL SELECT b, a FROM ty)",
}


def rmat_sql(scale: int, edge_factor: int) -> str:
    a, b, c, _ = RMAT
    return (
        f"rl AS (SELECT e.e, l.l, ('0x' || substr(md5(e.e || ':' || l.l), 1, 7))::BIGINT / 268435456.0::DOUBLE AS u FROM range({(1 << scale) * edge_factor}) e(e), range({scale}) l(l)), "
        f"rm AS (SELECT sum(CASE WHEN u >= {a + b} THEN 1 << l ELSE 0 END)::BIGINT AS a, sum(CASE WHEN (u >= {a} AND u < {a + b}) OR u >= {a + b + c} THEN 1 << l ELSE 0 END)::BIGINT AS b FROM rl GROUP BY e), " + _BOTH.format("rm")
    )


RMATS = ((8, 8), (10, 8), (10, 16), (10, 32), (12, 16))
for _s, _f in RMATS:
    SQL[f"rmat_s{_s}_ef{_f}"] = rmat_sql(_s, _f)

BUILDERS = {
    "copurchase": copurchase, "cosupply": cosupply, "segment_cliques": segment_cliques, "coactive": coactive, "cobuyer": cobuyer,
    "part_supp": part_supp, "nation_days": nation_days, "nation_segments": nation_segments, "bigram": bigram, "bigram_directed": lambda s, d: bigram(s, d, True), "succession": lambda s, d: succession(s, d, False),
    "succession_directed": succession, "knn": knn, "toy": lambda s, d: toy(s),
} | {f"rmat_s{x}_ef{y}": lambda s, d, x=x, y=y: rmat(s, x, y) for x, y in RMATS}


def build(spark: SparkSession, d: str, name: str) -> Graph:
    return BUILDERS[name](spark, d)
