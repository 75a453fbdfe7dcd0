"""Worked example, closed forms and invariants of the graph engine."""

from itertools import combinations

import pytest
from pyspark.sql import functions as F

from wedgework.operators import baselines, csr, intersect, lcc, partition, prep, trace, triangles
from wedgework.plans import fetch, sqlface
from wedgework.schema import Graph
from wedgework.sources import graphs

TOY_T = {0: 1, 1: 2, 2: 2, 3: 1, 4: 2, 5: 1}
TOY_LCC = {0: 1.0, 1: 2 / 3, 2: 2 / 3, 3: 1.0, 4: 1 / 3, 5: 1.0}


def undirected(spark, edges):
    return prep.symmetrize(Graph(prep.simplify(spark.createDataFrame(edges or [(0, 0)], "src long, dst long"))))


def directed(spark, arcs):
    return Graph(spark.createDataFrame(arcs, "src long, dst long"), directed=True)


def rows(df, key, value):
    return {r[key]: r[value] for r in df.collect()}


@pytest.fixture(scope="module")
def toy(spark):
    return graphs.toy(spark)


@pytest.fixture(scope="module")
def small(spark, data):
    g = graphs.coactive(spark, data)
    return g.with_arcs(g.arcs.cache())


@pytest.fixture(scope="module")
def rmat(spark):
    g = graphs.rmat(spark, 7, 6)
    return g.with_arcs(g.arcs.cache())


def brute(g):
    near = {}
    for r in g.arcs.collect():
        near.setdefault(r.src, set()).add(r.dst)
    return {v: sum(1 for a, b in combinations(ns, 2) if b in near.get(a, ())) for v, ns in near.items()}


def test_toy_by_hand(toy):
    assert rows(triangles.per_vertex(toy), "v", "triangles") == TOY_T
    assert triangles.count(toy).first()[0] == 3
    assert {(r.a, r.b, r.c) for r in triangles.listing(toy).collect()} == {(0, 1, 2), (1, 2, 4), (3, 4, 5)}
    assert rows(lcc.local_clustering(toy), "v", "lcc") == pytest.approx(TOY_LCC)
    support = {(r.src, r.dst): r.common for r in triangles.edge_support(toy).collect() if r.src < r.dst}
    assert support == {(0, 1): 1, (0, 2): 1, (1, 2): 2, (1, 4): 1, (2, 4): 1, (3, 4): 1, (3, 5): 1, (4, 5): 1}


def test_toy_reads(toy):
    parts = partition.block(toy, 2)
    assert rows(parts, "v", "part") == {0: 0, 1: 0, 2: 0, 3: 1, 4: 1, 5: 1}
    c = trace.compulsory(toy, parts).first()
    assert (c.n_remote, c.n_first, c.share) == (4, 3, 0.75)
    assert partition.cut_stats(toy, parts).first().cut_share == 0.25
    t = trace.build(toy, parts).orderBy("part", "seq").collect()
    assert [(r.part, r.src, r.dst) for r in t] == [(0, 1, 4), (0, 2, 4), (1, 4, 1), (1, 4, 2)]


@pytest.mark.parametrize(
    "edges,total,mean",
    [
        ([(a, b) for a, b in combinations(range(6), 2)], 20, 1.0),  # clique
        ([(0, i) for i in range(1, 9)], 0, 0.0),  # star
        ([(i, i + 1) for i in range(6)], 0, 0.0),  # path
        ([(0, 1), (1, 2), (2, 3), (3, 0)], 0, 0.0),  # cycle
        ([(0, i) for i in range(1, 6)] + [(1, 2), (2, 3), (3, 4), (4, 5), (5, 1)], 5, None),  # wheel
        ([(0, 1)], 0, None),
        ([(0, 0), (0, 1), (1, 0), (0, 1), (1, 2), (2, 0)], 1, 1.0),  # loops and repeats
    ],
)
def test_closed_forms(spark, edges, total, mean):
    g = undirected(spark, edges)
    assert triangles.count(g).first()[0] == total
    if mean is not None:
        assert lcc.summary(g).first().mean_lcc == mean


def test_empty_graph(spark):
    g = undirected(spark, [])
    assert triangles.count(g).first()[0] == 0
    assert lcc.local_clustering(g).count() == 0
    assert partition.block(g, 4).count() == 0
    assert prep.prune(g, rounds=None).arcs.count() == 0


def test_degree_under_two(spark):
    g = undirected(spark, [(0, 1), (1, 2), (0, 2), (2, 3)])
    assert rows(lcc.local_clustering(g), "v", "lcc")[3] is None
    assert rows(lcc.local_clustering(g, isolated="zero"), "v", "lcc")[3] == 0.0
    assert 3 not in rows(lcc.local_clustering(g, isolated="drop"), "v", "lcc")


def test_directed_forms(spark):
    ring = directed(spark, [(0, 1), (1, 2), (2, 0)])
    assert triangles.closed_pairs(ring).count() == 0
    transitive = directed(spark, [(0, 1), (0, 2), (1, 2)])
    assert rows(lcc.local_clustering(transitive), "v", "lcc")[0] == 0.5
    both = directed(spark, [(a, b) for a in range(3) for b in range(3) if a != b])
    assert set(rows(lcc.local_clustering(both), "v", "lcc").values()) == {1.0}


def test_masks_equal_direct_join(spark, data):
    g = graphs.succession(spark, data)
    a, b = rows(triangles.closed_pairs(g), "v", "closed_pairs"), rows(triangles.closed_pairs_joined(g), "v", "closed_pairs")
    assert a == b and sum(a.values()) == 2615


def test_directed_formula_on_symmetric_arcs(rmat):
    a = rows(lcc.local_clustering(rmat), "v", "lcc")
    b = rows(lcc.local_clustering(Graph(rmat.arcs, directed=True)), "v", "lcc")
    assert a == pytest.approx(b, nan_ok=True) if None not in a.values() else {k: v for k, v in a.items() if v is not None} == pytest.approx({k: v for k, v in b.items() if v is not None})


def test_all_plans_agree_with_brute_force(rmat):
    want = {v: t for v, t in brute(rmat).items() if t}
    parts = partition.block(rmat, 4)
    found = {
        "relational": triangles.per_vertex(rmat, plan="relational"), "lists": triangles.per_vertex(rmat), "upper": triangles.per_vertex_lists(rmat), "wedges": baselines.wedge_mapreduce(rmat),
        "questions": baselines.query_response(rmat, parts), "bulk": baselines.bulk_synchronous(rmat), "shadow": baselines.shadow_count(rmat, parts),
    }
    for name, df in found.items():
        assert rows(df, "v", "triangles") == want, name
    assert rows(triangles.per_vertex(rmat, offset=False), "v", "triangles") == {v: 2 * t for v, t in want.items()}
    buffered = baselines.query_response_buffered(rmat, parts, 1024)
    assert buffered.agg(F.max("round")).first()[0] > 0
    assert rows(buffered.groupBy("v").agg(F.sum("triangles").alias("triangles")), "v", "triangles") == want
    assert triangles.count(rmat).first()[0] * 3 == sum(want.values())


@pytest.mark.parametrize("kernel", ["search", "merge", "hybrid", "builtin", "relational"])
def test_kernels(rmat, kernel):
    want = {(r.src, r.dst): r.common for r in triangles.edge_support(rmat).collect()}
    assert {(r.src, r.dst): r.common for r in intersect.edge_support(rmat, kernel).collect()} == want
    if kernel in ("search", "merge", "hybrid"):
        assert {(r.src, r.dst): r.common for r in intersect.edge_support(rmat, kernel, chunk_cutoff=4).collect()} == want


@pytest.mark.parametrize("plan", ["per_arc", "two_step", "halo", "hot", "relational", "auto"])
def test_fetch_plans(rmat, plan):
    want = {(r.src, r.dst): r.common for r in triangles.edge_support(rmat).collect()}
    assert {(r.src, r.dst): r.common for r in fetch.edge_support(rmat, plan, budget=2048).collect()} == want


def test_rule_boundaries():
    import numpy as np

    from wedgework.functions.kernels import use_merge

    #     empty, one key, exact boundary (4 lists of 8: 4 * (3 - 1) = 8), beyond
    assert use_merge(np.array([0, 1, 4, 3]), np.array([5, 8, 8, 8])).tolist() == [False, False, True, False]


def test_hybrid_takes_the_smaller_count(rmat):
    o = intersect.op_counts(rmat).first()
    assert o.hybrid_ops <= min(o.merge_ops, o.search_ops)
    pairs = intersect._degree_pairs(rmat).where("least(di, dj) > 0")
    worse = pairs.where(f"CASE WHEN {intersect.RULE} THEN di + dj > least(di, dj) * log2(greatest(di, dj)) + 1e-9 ELSE di + dj < least(di, dj) * log2(greatest(di, dj)) - 1e-9 END")
    assert worse.count() == 0


def test_prune_keeps_triangles(spark, rmat):
    tail = undirected(spark, [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (4, 5)])
    assert prep.vertices(prep.prune(tail)).count() == 5
    assert prep.vertices(prep.prune(tail, rounds=None)).count() == 3
    want = triangles.count(rmat).first()[0]
    assert triangles.count(prep.prune(rmat)).first()[0] == want == triangles.count(prep.prune(rmat, rounds=None)).first()[0]


@pytest.mark.parametrize("scheme", ["block", "cyclic", "balanced", "hashed"])
@pytest.mark.parametrize("p", [1, 3, 8])
def test_partitions(rmat, scheme, p):
    parts = partition.SCHEMES[scheme](rmat, p)
    got = parts.collect()
    n = len(got)
    assert sorted(r.idx for r in got) == list(range(n)) and {r.part for r in got} <= set(range(p))
    if scheme in ("block", "cyclic"):
        sizes = [sum(r.part == k for r in got) for k in range(p)]
        assert max(sizes) - min(sizes) <= 1
    c = trace.read_counts(rmat, parts).agg(F.sum("n_local"), F.sum("n_remote")).first()
    assert sum(c) == rmat.arcs.count()


def test_dense_and_shuffled_index(spark):
    vs = spark.range(0, 1000, 7).select((F.col("id") * 3).alias("v"))
    got = sorted((r.v, r.idx) for r in prep.dense_index(vs).collect())
    assert [i for _, i in got] == list(range(len(got)))
    assert sorted(r.idx for r in prep.shuffled_index(vs, "s").collect()) == list(range(len(got)))


def test_relabelling_keeps_counts(rmat):
    assert triangles.count(prep.relabel(rmat, "x")).first()[0] == triangles.count(rmat).first()[0]


def test_csr_round_trip(rmat):
    parts = partition.block(rmat, 3)
    index = {r.v: r.idx for r in parts.collect()}
    back = {(r.src, r.dst) for r in csr.from_csr(csr.to_csr(rmat, parts)).collect()}
    assert back == {(index[r.src], index[r.dst]) for r in rmat.arcs.collect()}
    small = csr.to_csr(rmat, parts, group=10)
    assert small.count() > 3 and {(r.src, r.dst) for r in csr.from_csr(small).collect()} == back
    chunks = csr.adjacency(rmat, chunk=4)
    assert chunks.where(F.size("nbrs") > 4).count() == 0
    assert chunks.agg(F.sum(F.size("nbrs"))).first()[0] == rmat.arcs.count()


def test_subset(rmat):
    only = prep.vertices(rmat).where("v % 7 = 0")
    whole = {r.v: r for r in lcc.local_clustering(rmat).collect()}
    for r in lcc.local_clustering(rmat, only=only).collect():
        assert r == whole[r.v]


def test_sql_face(spark, toy):
    assert sqlface.run(toy, "triangles").first()[0] == 3
    assert rows(sqlface.run(toy, "lcc"), "v", "lcc") == pytest.approx(TOY_LCC)
    assert sqlface.run(toy, "degree_at_least", {"least": 4}).first().v == 4
    sqlface.register(spark, toy, "toy_")
    assert spark.sql("SELECT max(deg) FROM toy_adj").first()[0] == 4


def test_plans_without_cross_products(rmat):
    for df in (triangles.count(rmat), lcc.local_clustering(rmat), fetch.edge_support(rmat, "hot", budget=2048)):
        text = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    assert "BroadcastHashJoin" in fetch.attach(rmat, "hot", budget=2048)._jdf.queryExecution().executedPlan().toString()


def test_graph_set_operations(spark):
    a, b = undirected(spark, [(0, 1), (1, 2)]), undirected(spark, [(1, 2), (2, 3)])
    assert graphs.union(a, b).arcs.count() == 6
    assert graphs.intersect(a, b).arcs.count() == 2
    assert graphs.difference(a, b).arcs.count() == 2


def test_recommendations_are_new(small):
    known = {(r.src, r.dst) for r in small.arcs.collect()}
    got = lcc.recommend_links(small).collect()
    assert all((r.v, r.other) not in known and r.v != r.other for r in got)


def test_edge_list_sources(spark, tmp_path):
    from wedgework.sources import tables

    (tmp_path / "e.txt").write_text("# comment\n0\t1\n1 \t2\n")
    assert tables.read_edges(spark, str(tmp_path / "e.txt"), "text").count() == 2
    (tmp_path / "e.csv").write_text("# comment\n0,1\n1,2\n")
    assert tables.read_edges(spark, str(tmp_path / "e.csv"), "csv", sep=",").count() == 2
    g = undirected(spark, [(0, 1), (1, 2), (0, 2)])
    tables.write_adjacency(csr.adjacency(g), str(tmp_path / "adj"))
    assert tables.read_adjacency(spark, str(tmp_path / "adj")).count() == 3
    tables.write_scores(lcc.local_clustering(g), str(tmp_path / "s"), "json")
    assert spark.read.json(str(tmp_path / "s")).count() == 3


@pytest.mark.parametrize("kernel", ["search", "merge", "hybrid", "tuned"])
def test_part_kernels(rmat, spark, kernel):
    want = {(r.src, r.dst): r.common for r in triangles.edge_support(rmat).collect()}
    assert {(r.src, r.dst): r.common for r in intersect.edge_support(rmat, kernel, parts=3).collect()} == want
    assert {(r.src, r.dst): r.common for r in intersect.edge_support(rmat, kernel, chunk_cutoff=5).collect()} == want
    d = Graph(spark.createDataFrame([(-3, 5), (5, 9), (-3, 9), (9, -3)], "src long, dst long"), directed=True)
    assert {(r.src, r.dst): r.common for r in intersect.edge_support(d, kernel, parts=2).collect()} == {(-3, 5): 1, (5, 9): 0, (-3, 9): 0, (9, -3): 0}


@pytest.mark.parametrize("plan", ["per_arc", "two_step", "halo", "hot", "relational"])
def test_part_runs(rmat, plan):
    want = {r.v: (r.deg, 2 * r.closed) for r in lcc.local_clustering(rmat).collect()}
    got = fetch.run(rmat, 4, plan)
    assert {r.v: (r.deg, r.closed) for r in got.collect()} == want and got.select("part").distinct().count() == 4


def test_names_get_dense_ids_and_come_back(spark):
    arcs = spark.createDataFrame([("a", "b"), ("b", "c"), ("a", "c"), ("c", "d")], "src string, dst string")
    g = prep.symmetrize(Graph(arcs))
    assert triangles.count(g).first()[0] == triangles.count(g, "relational").first()[0] == 1
    assert {(r.v, r.triangles) for r in triangles.per_vertex(g).collect()} == {("a", 1), ("b", 1), ("c", 1)}
