"""Graphs of large groups: lists instead of pairs, and what reads them without moving pairs or lists beside arcs."""

from itertools import combinations

import pytest

from wedgework.operators import csr
from wedgework.sources import graphs


@pytest.fixture(scope="module")
def dense(spark):
    """Three groups that share members, some repeated, one alone, and rows without a group."""
    groups = {0: range(40), 1: range(30, 55), 2: [3, 3, 41, 60], 3: [77]}
    rows = [(g, m) for g, ms in groups.items() for m in ms] + [(None, 1), (0, None)]
    made = graphs._co_lists(spark.createDataFrame(rows, "g int, m long"), ["g"], "m")
    want = {p for ms in groups.values() for a, b in combinations(set(ms), 2) for p in ((a, b), (b, a))}
    return graphs._from_lists(*made, "dense"), want


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_groups_become_lists_without_moving_pairs(dense, spark, data):
    g, want = dense
    got = [(r.src, r.dst) for r in g.arcs.collect()]
    assert len(got) == len(want) and set(got) == want
    assert all(r.nbrs == sorted(set(r.nbrs)) for r in g.lists.collect())
    for name in ("coactive", "segment_cliques"):  # one shuffle of groups, none of pairs, no join
        p = plan(graphs.build(spark, data, name).arcs)
        assert "Join" not in p and "HashAggregate" not in p


def test_small_blocks_make_the_same_lists(dense, spark, monkeypatch):
    monkeypatch.setattr(graphs, "HELD", 8)
    rows = spark.createDataFrame([(g, m) for g in range(3) for m in range(g, 30, g + 1)], "g int, m long")
    want = {(r.src, r.dst) for r in graphs._co_members(rows, ["g"], "m").collect()}
    assert {(r.v, x) for r in graphs._co_lists(rows, ["g"], "m")[0].collect() for x in r.nbrs} == want


@pytest.mark.parametrize("name", ["nation_days", "nation_segments"])
def test_graphs_that_replace_made_up_ones_read_tables(spark, data, name):
    arcs = graphs.build(spark, data, name).arcs
    assert arcs.inputFiles()
    assert {(r.src, r.dst) for r in arcs.collect()} == {(r.dst, r.src) for r in arcs.collect()}


def test_queries_read_given_tables(spark, data):
    from wedgework.queries import QUERIES

    assert all(QUERIES[q](spark, data).inputFiles() for q in ("arcs_rmat_s10_ef16", "budget_split"))
    assert {r.vertices: r.adj_bytes for r in QUERIES["budget_split"](spark, data).collect()}.keys() == {"suppliers", "parts", "orders"}


def test_dense_lists_meet_as_arcs_do(dense, spark):
    """Each against the same graph without lists."""
    from wedgework.operators import baselines, intersect, lcc, partition, trace, triangles
    from wedgework.plans import experiments, fetch

    g, _ = dense
    plain = g.with_arcs(spark.createDataFrame(g.arcs.collect(), "src long, dst long"))
    assert plain.lists is None
    parts = partition.block(g, 4)
    for f in (
        triangles.count, triangles.listing, triangles.per_vertex, triangles.per_vertex_lists, triangles.edge_support, lcc.core_frontier, lambda x: intersect.edge_support(x, "builtin"), lambda x: intersect.edge_support(x, "search"),
        lambda x: baselines.query_response(x, parts), lambda x: baselines.shadow_count(x, parts), baselines.bulk_synchronous, lambda x: fetch.edge_support(x, "auto"), lambda x: csr.adjacency(x, chunk=4), csr.adjacency,
        lambda x: partition.cut_stats(x, parts), lambda x: trace.top_share(x, parts), lambda x: trace.repeat_histogram(x, parts), lambda x: trace.reuse_vs_size(x, parts), lambda x: experiments.budgeted(x, (2, 3, 5)),
    ):
        a, b = f(g), f(plain)
        assert sorted(map(str, a.select(*b.columns).collect())) == sorted(map(str, b.collect()))


def test_no_row_with_a_list_is_moved_for_each_arc(dense):
    from wedgework.operators import intersect

    g, _ = dense
    p = plan(intersect.arc_lists(g))
    join = p.index("ShuffledHashJoin")
    assert "SortMergeJoin" not in p and p.index("Generate", join) < p.index("Exchange", join)  # arcs are made after the last exchange


def test_cells_move_groups_alone(dense, spark, monkeypatch):
    """Twins, several blocks, ids below zero and far apart; a plan without joins, in which no list and no arc is moved."""
    from wedgework.operators import cells, triangles

    monkeypatch.setattr(cells, "LEAST", 7)
    groups = {0: range(-20, 20), 1: [*range(10, 30), 1 << 40], 2: [3, 1 << 40, -7], 3: range(100, 110)}
    made = graphs._co_lists(spark.createDataFrame([(g, m) for g, ms in groups.items() for m in ms], "g int, m long"), ["g"], "m")
    g = graphs._from_lists(*made, "far")
    arcs = {p for ms in groups.values() for a, b in combinations(ms, 2) for p in ((a, b), (b, a))}
    near = {v: {b for a, b in arcs if a == v} for v in {a for a, _ in arcs}}
    want = {(a, b): len(near[a] & near[b]) for a, b in arcs}
    assert {(r.src, r.dst): r.common for r in triangles.edge_support(g).collect()} == want
    assert {r.v: r.triangles for r in triangles.per_vertex(g).collect()} == {v: sum(want[v, x] for x in near[v]) // 2 for v in near if any(want[v, x] for x in near[v])}
    assert triangles.count(g).first().triangles == sum(want.values()) // 6
    for f in (triangles.edge_support, triangles.per_vertex, triangles.count):
        assert "Join" not in plan(f(g)) and "nbrs" not in plan(f(g))


def test_a_long_list_meets_its_partners_together():
    import numpy as np

    from wedgework.functions import kernels

    rng = np.random.default_rng(3)
    lists = [np.flatnonzero(rng.random(400) < share) - 7 for share in (0.5, 0.3, 0.2, 0.0, 0.9, 0.02)]
    values, offsets = np.concatenate(lists), np.cumsum([0, *map(len, lists)])
    a, b = (x.ravel() for x in np.meshgrid(range(6), range(6)))
    want = [len(set(lists[i]) & set(lists[j])) for i, j in zip(a, b, strict=True)]
    for kernel in ("search", "merge", "hybrid", "tuned"):
        for cutoff in (None, 1, 16, 1000):
            assert kernels.common_rows(values, offsets, a, b, kernel, cutoff).tolist() == want


def test_pieces_and_rounds_in_cells(dense, spark):
    """No question and no piece is a row; numbers of rounds as by ordering the questions."""
    from wedgework.operators import baselines, intersect, partition

    g, _ = dense
    plain = g.with_arcs(spark.createDataFrame(g.arcs.collect(), "src long, dst long"))
    parts = partition.block(g, 4)
    for f in (lambda x: intersect.edge_support(x, "merge", chunk_cutoff=16), lambda x: baselines.query_response_buffered(x, parts, 1024)):
        a, b = f(g), f(plain)
        assert "Join" not in plan(a) and "Window" not in plan(a)
        assert sorted(map(tuple, a.select(*b.columns).collect())) == sorted(map(tuple, b.collect()))


@pytest.fixture(scope="module")
def twinned(spark):
    """A random graph of groups, each vertex four times over, and what its edges share."""
    import random

    rng = random.Random(5)
    held = {(rng.randrange(25), rng.randrange(40)) for _ in range(140)}
    rows = [(g, m + 1000 * k) for g, m in held for k in range(4)]
    g = graphs._from_lists(*graphs._co_lists(spark.createDataFrame(rows, "g int, m long"), ["g"], "m"), "twinned")
    groups = {}
    for k, m in rows:
        groups.setdefault(k, set()).add(m)
    near = {m: set().union(*(ms for ms in groups.values() if m in ms)) - {m} for _, m in rows}
    return g, {(a, b): len(near[a] & near[b]) for a in near for b in near[a]}, len(held)


def sent(monkeypatch):
    """Members of the groups that go to cells, of each call."""
    from pyspark.sql import functions as F

    from wedgework.operators import cells

    over, seen = cells.over, []

    def counted(groups, *args, **kwargs):
        seen.append(groups.agg(F.sum(F.size("ms"))).first()[0])
        return over(groups, *args, **kwargs)

    monkeypatch.setattr(cells, "over", counted)
    return seen


@pytest.mark.parametrize("lists", [True, False])
def test_triangles_of_twins_count_once(twinned, monkeypatch, lists):
    from wedgework.operators import triangles

    g, want, members = twinned
    seen = sent(monkeypatch)
    got = (triangles.per_vertex_lists if lists else triangles.per_vertex)(g)
    each = {}
    for (a, _), n in want.items():
        each[a] = each.get(a, 0) + n
    assert {r.v: r.triangles for r in got.collect()} == {v: n // 2 for v, n in each.items() if n}
    assert seen[0] <= members and "Join" not in plan(got) and "nbrs" not in plan(got)


def test_array_intersect_runs_once_for_twins(twinned, monkeypatch):
    from wedgework.operators import cells, intersect

    g, want, members = twinned
    monkeypatch.setattr(cells, "TILE", 3)
    seen = sent(monkeypatch)
    got = intersect.edge_support(g, "builtin")
    rows = got.collect()
    assert len(rows) == len(want) and {(r.src, r.dst): r.common for r in rows} == want
    assert seen[0] <= members and "Join" not in plan(got) and "nbrs" not in plan(got) and "array_intersect" in plan(got)


def test_reads_of_twins_count_once(twinned, spark, monkeypatch):
    """Against the same graph without groups; no list is made."""
    from wedgework.operators import partition, trace

    g, _, members = twinned
    plain = g.with_arcs(spark.createDataFrame(g.arcs.collect(), "src long, dst long"))
    for p in (2, 5):
        parts = partition.block(g, p)
        seen = sent(monkeypatch)
        assert trace.reuse_correlation(g, parts).first() == trace.reuse_correlation(plain, parts).first()
        assert seen[0] <= members
        a, b = (sorted(map(tuple, trace._met(x, parts).select("part", "dst", "deg", "c").collect())) for x in (g, plain))
        assert a == b
        assert "Join" not in plan(trace.reuse_correlation(g, parts)) and "nbrs" not in plan(trace.reuse_correlation(g, parts))


def test_lists_are_exchanged_as_rows_of_bits(twinned, spark, monkeypatch):
    """Several blocks and parts; against the same graph without lists. No list and no array_intersect is beside an arc."""
    from wedgework.operators import baselines, bitrows, partition

    g, _, _ = twinned
    plain = g.with_arcs(spark.createDataFrame(g.arcs.collect(), "src long, dst long"))
    want = sorted(map(tuple, baselines.wedge_mapreduce(plain).collect()))
    parts = partition.block(g, 3)
    monkeypatch.setattr(bitrows, "LEAST", 7)
    monkeypatch.setattr(bitrows, "WORDS", 5)
    for f in (baselines.bulk_synchronous, lambda x: baselines.query_response(x, parts), lambda x: baselines.shadow_count(x, parts)):
        got = f(g)
        assert sorted(map(tuple, got.collect())) == want
        p = plan(got)
        assert "array_intersect" not in p and "ShuffledHashJoin" not in p and "nbrs" not in p and "bits" in p


def test_triangles_of_groups_are_listed_in_cells(twinned, spark, monkeypatch):
    """Several cells, small batches, ids in another order than blocks; no list is moved or beside an arc."""
    from wedgework.operators import cells, triangles

    g, want, _ = twinned
    monkeypatch.setattr(cells, "CORNERS", 50)
    monkeypatch.setattr(cells, "SPREAD", 1 << 10)
    near = {}
    for a, b in want:
        near.setdefault(a, set()).add(b)
    got = triangles.listing(g)
    rows = [tuple(r) for r in got.collect()]
    assert len(rows) == len(set(rows)) and set(rows) == {(a, b, c) for a, b in want if a < b for c in near[a] & near[b] if c > b}
    assert got.columns == ["a", "b", "c"] and "Join" not in plan(got) and "array_intersect" not in plan(got) and "nbrs" not in plan(got)


@pytest.mark.parametrize("strip", [1, 3])
def test_triangles_are_counted_in_strips(twinned, spark, monkeypatch, strip):
    """Rows of several words, with and without twins; no count reads more than a strip of a row."""
    import numpy as np

    from wedgework.operators import cells, triangles

    groups = [(k, m) for k in range(60) for m in range(k * 7 % 50, 300, 11 + k % 5)]
    alone = graphs._from_lists(*graphs._co_lists(spark.createDataFrame(groups, "g int, m long"), ["g"], "m"), "alone")
    monkeypatch.setattr(cells, "STRIP", strip)
    monkeypatch.setattr(cells, "PIECE", 8)
    for g in (alone, twinned[0]):
        near = {r.v: set(r.nbrs) for r in g.lists.collect()}
        want = {v: n for v, ns in near.items() if (n := sum(len(ns & near[x]) for x in ns) // 2)}
        for f in (triangles.per_vertex, triangles.per_vertex_lists):
            assert {r.v: r.triangles for r in f(g).collect()} == want
    c = cells.cell(np.array(sorted({m for _, m in groups})), np.array([0, len({m for _, m in groups})]), 0, 0, 1)
    count = cells.counter(c, np.ones(len(c.names), dtype=np.int64), 0, strip)
    assert count(np.ascontiguousarray(c.bits[:, :strip]), np.array([1]), c.bits[0][:strip]).tolist() == [64 * strip - 2]


@pytest.mark.parametrize("kernel,cutoff", [("search", None), ("merge", 16), ("hybrid", 1), ("tuned", None)])
def test_kernels_make_one_list_at_a_time(kernel, cutoff, monkeypatch):
    """A dense cell, alone and with another block: each edge once, by its longer list, without all lists of the cell."""
    import numpy as np

    from wedgework.operators import cells

    rng = np.random.default_rng(4)
    groups = [np.flatnonzero(rng.random(150) < 0.2) * 3 for _ in range(9)] + [np.array([1, 4])]
    values, ends = np.concatenate(groups), np.cumsum([0, *map(len, groups)])
    near = {}
    for ms in groups:
        for m in ms.tolist():
            near.setdefault(m, set()).update({*ms.tolist()} - {m})
    monkeypatch.setattr(cells, "PIECE", 7)
    for i, j, blocks in ((0, 0, 1), (0, 1, 2), (1, 1, 2)):
        c = cells.cell(values, ends, i, j, blocks)
        assert cells.dense(c) and not cells.dense(cells.cell(np.array([1, 2, 3, 5]), np.array([0, 2, 4]), 0, 0, 1))
        monkeypatch.setattr(cells.Cell, "csr", None)
        got = [r for b in cells.together(cells.by_longer(c, kernel, cutoff), c) for r in zip(*b.to_pydict().values(), strict=True)]
        side = lambda v, k: v % cells.PRIME % blocks == k  # noqa: B023, E731
        want = {(a, b, len(near[a] & near[b])) for a in near for b in near[a] if side(a, i) and side(b, j) or side(a, j) and side(b, i)}
        assert len(got) == len(want) and set(got) == want
