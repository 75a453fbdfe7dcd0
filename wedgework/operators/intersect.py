"""Edge support by neighbour-list intersection: kernels, argument order, splitting of large pairs, operation counts."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle
from . import cells
from .csr import adjacency

#: Merge where the longer list is at most (log2 of its length, less 1) times the shorter one; no kernel for empty lists.
RULE = "least(di, dj) > 0 AND least(di, dj) * (log2(greatest(di, dj)) - 1) >= greatest(di, dj)"


#: Bytes of lists that a task of ``met_lists`` keeps, about.
KEPT_BYTES = 1 << 26


def beside(rows: DataFrame) -> None:
    """Lets a join on (cell, vertex) use sides that are dealt by the cell alone; else Spark would deal them anew, rows with lists included. Read when the plan runs, so it stays set."""
    rows.sparkSession.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")


def met_lists(lists: DataFrame) -> DataFrame:
    """src, dst, a, b for every entry dst of the list (v, nbrs) of src; b is empty where dst has no list. ``lists`` is read twice: settle it before.

    Vertices are dealt into blocks. A list travels once to each block with one of its entries, and once to the tasks that keep its own
    block; a row with two lists is made there and goes nowhere, so what moves grows with the lists and not with arcs times lists.
    """
    total = 8 * (lists.agg(F.sum(F.size("nbrs").cast("long"))).first()[0] or 0)
    far = max(4, -(-total // KEPT_BYTES))
    near = 2 if far < 8 else 1
    block = lambda x, n: f"int(pmod(xxhash64({x}), {n}))"
    tasks = 4 * near * far + 1  # a few cells share a task
    asking = lists.select("v", "nbrs", F.explode(F.expr(f"array_distinct(transform(nbrs, x -> {block('x', far)}))")).alias("at"))
    asking = asking.select(F.expr(f"{block('v', near)} * {far} + at").alias("cell"), "at", F.col("v").alias("src"), F.col("nbrs").alias("a")).repartition(tasks, "cell")
    asking = asking.select("cell", "src", "a", F.explode(F.expr(f"filter(a, x -> {block('x', far)} = at)")).alias("dst"))
    own = lists.select(F.col("v").alias("dst"), F.col("nbrs").alias("b"), F.explode(F.sequence(F.lit(0), F.lit(near - 1))).alias("i"))
    own = own.select(F.expr(f"i * {far} + {block('dst', far)}").alias("cell"), "dst", "b").repartition(tasks, "cell")
    none = F.array().cast(lists.schema["nbrs"].dataType)
    beside(lists)
    return asking.join(own.hint("shuffle_hash"), ["cell", "dst"], "left").select("src", "dst", "a", F.coalesce("b", none).alias("b"))


def arc_lists(g: Graph) -> DataFrame:
    """src, dst, a, b: each arc with both ends' lists."""
    return met_lists(settle(adjacency(g).select("v", "nbrs"), "lists"))


def arrow_common(rows: DataFrame, kernel: str, keys: tuple[str, ...] = ("src", "dst")) -> DataFrame:
    """keys and common for rows with two ascending list columns a and b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from ..functions.kernels import common

        for b in batches:
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(common(b.column("a"), b.column("b"), kernel))], [*keys, "common"])

    kinds = dict(rows.dtypes)
    return rows.select(*keys, "a", "b").mapInArrow(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", common long")


def split_lists(g: Graph, cutoff: int, kernel: str = "hybrid") -> DataFrame:
    """src, dst, a, b of pairs and of pieces of pairs: those whose longer list exceeds the cut-off meet in chunks, the others are one unit.

    For searching, the shorter list (the keys) is cut; for merging, the longer one, each chunk against the whole other list. Lists
    are cut before they are joined to arcs, so a hub's list is never beside each of its arcs as a whole when it is merged; arcs are
    sorted into the ways by degrees alone. The pieces' counts are summed by the caller.
    """
    merged = F.expr({"merge": "least(di, dj) > 0", "search": "false"}.get(kernel, RULE))
    arcs = _degree_pairs(g).select("src", "dst", "di", "dj", merged.alias("m"), F.greatest("di", "dj").alias("most"))
    whole = adjacency(g).select("v", "nbrs")
    pieces = adjacency(g, chunk=cutoff).select("v", "nbrs")
    at = lambda lists, v, name: lists.select(F.col("v").alias(v), F.col("nbrs").alias(name))
    none = F.array().cast(whole.schema["nbrs"].dataType)
    small = arcs.where(F.col("most") <= cutoff).join(at(whole, "src", "a"), "src", "left").join(at(whole, "dst", "b"), "dst", "left")
    small = small.select("src", "dst", F.coalesce("a", none).alias("a"), F.coalesce("b", none).alias("b"))
    ends = arcs.where(F.col("most") > cutoff).select("src", "dst", "m", F.expr("CASE WHEN di <= dj THEN src ELSE dst END").alias("s"), F.expr("CASE WHEN di <= dj THEN dst ELSE src END").alias("l"))
    keys_cut = ends.where("NOT m").join(at(pieces, "s", "a"), "s").join(at(whole, "l", "b"), "l")
    long_cut = ends.where("m").join(at(whole, "s", "a"), "s").join(at(pieces, "l", "b"), "l")
    long_cut = long_cut.where("b[0] <= element_at(a, -1) AND element_at(b, -1) >= a[0]")  # a chunk beside the other list's range has nothing in common with it
    return small.unionByName(keys_cut.select("src", "dst", "a", "b")).unionByName(long_cut.select("src", "dst", "a", "b"))


def edge_support(g: Graph, kernel: str = "hybrid", chunk_cutoff: int | None = None, parts: int | None = None) -> DataFrame:
    """src, dst, common by the named kernel: 'search', 'merge', 'hybrid', 'tuned' (Arrow), 'builtin' (array_intersect) or 'relational' (joins only).

    ``parts`` hands whole parts to the kernels, each list once to a part, instead of both lists to each arc; ids must be numbers.
    """
    if parts:
        return part_common(*part_frames(g, parts), kernel)
    if kernel == "relational":
        other = g.arcs.select(F.col("src").alias("dst"), F.col("dst").alias("w"))
        mine = g.arcs.select("src", F.col("dst").alias("w"))
        met = g.arcs.join(other, "dst").join(mine, ["src", "w"]).groupBy("src", "dst").agg(F.count(F.lit(1)).alias("common"))
        return g.arcs.join(met, ["src", "dst"], "left").select("src", "dst", F.coalesce("common", F.lit(0)).alias("common"))
    if chunk_cutoff and cells.usable(g):
        return cells.edge_support(g, kernel, chunk_cutoff)
    if chunk_cutoff:
        met = arrow_common(split_lists(g, chunk_cutoff, kernel), kernel).groupBy("src", "dst").agg(F.sum("common").alias("common"))
        return g.arcs.join(met, ["src", "dst"], "left").select("src", "dst", F.coalesce("common", F.lit(0)).alias("common"))
    if cells.usable(g):
        return cells.builtin_support(g) if kernel == "builtin" else cells.edge_support(g, kernel)
    rows = arc_lists(g)
    if kernel == "builtin":
        return rows.select("src", "dst", F.size(F.array_intersect("a", "b")).cast("long").alias("common"))
    return arrow_common(rows, kernel)


def part_frames(g: Graph, p: int) -> tuple[DataFrame, DataFrame]:
    """(part, src, dst) and (of, v, nbrs): the arcs of each part, and each list that they need, once."""
    arcs = g.arcs.select(F.pmod(F.xxhash64("src"), F.lit(p)).cast("int").alias("part"), "src", "dst")
    needed = arcs.select(F.col("part").alias("of"), F.explode(F.array("src", "dst")).alias("v")).distinct()
    return arcs, needed.join(adjacency(g).select("v", "nbrs"), "v").select("of", "v", "nbrs")


def part_common(arcs: DataFrame, lists: DataFrame, kernel: str = "hybrid") -> DataFrame:
    """src, dst, common: a part's lists become compressed sparse rows, on which the kernels work without copying a list for each arc."""

    def run(own: pa.Table, known: pa.Table) -> pa.Table:
        import numpy as np

        from ..functions.kernels import _flat, common_rows

        if not len(own):
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "common": pa.array([], pa.int64())})
        src, dst = own["src"].to_numpy(), own["dst"].to_numpy()
        v = known["v"].to_numpy()
        order = np.argsort(v)
        values, offsets = _flat(known["nbrs"])
        at = lambda x: (lambda i: np.where(v[order[i]] == x, order[i], len(v)))(np.minimum(np.searchsorted(v, x, sorter=order), len(v) - 1))
        offsets = np.append(offsets, offsets[-1])  # the last row is empty, for vertices without a list
        return pa.table({"src": own["src"], "dst": own["dst"], "common": common_rows(values, offsets, at(src), at(dst), kernel)})

    return arcs.groupBy("part").cogroup(lists.groupBy("of")).applyInArrow(run, "src long, dst long, common long")


def _degree_pairs(g: Graph) -> DataFrame:
    deg = g.arcs.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("d"))
    return g.arcs.join(deg.select(F.col("v").alias("src"), F.col("d").alias("di")), "src").join(deg.select(F.col("v").alias("dst"), F.col("d").alias("dj")), "dst", "left").withColumn("dj", F.coalesce("dj", F.lit(0)))


def op_counts(g: Graph) -> DataFrame:
    """One row: comparisons of merging, searching (keys times log2 of the longer list) and the hybrid, from degrees alone.

    Arcs with the same two degrees are counted first, so that a sum has few terms: one over all arcs loses some tenths in another order.
    """
    pairs = _degree_pairs(g).where("least(di, dj) > 0").groupBy("di", "dj").agg(F.count(F.lit(1)).alias("k"))
    merged = F.expr("k * (di + dj)")
    searched = F.expr("k * (least(di, dj) * log2(greatest(di, dj)))")
    return pairs.agg(F.sum(merged).alias("merge_ops"), F.round(F.sum(searched), 0).cast("long").alias("search_ops"), F.round(F.sum(F.when(F.expr(RULE), merged).otherwise(searched)), 0).cast("long").alias("hybrid_ops"))


def op_counts_ceiled(g: Graph) -> DataFrame:
    """The same with whole steps of a binary search over the longer list."""
    searched = F.expr("least(di, dj) * ceil(log2(greatest(di, dj) + 1))")
    merged = F.col("di") + F.col("dj")
    pairs = _degree_pairs(g).where("least(di, dj) > 0")
    return pairs.agg(F.sum(merged).alias("merge_ops"), F.sum(searched).alias("search_ops"), F.sum(F.when(F.expr(RULE), merged).otherwise(searched)).alias("hybrid_ops"))


def rule_share(g: Graph) -> DataFrame:
    """One row: arcs, and arcs that the rule gives to merging."""
    return _degree_pairs(g).agg(F.count(F.lit(1)).alias("n_arcs"), F.sum(F.expr(RULE).cast("long")).alias("n_merge"))
