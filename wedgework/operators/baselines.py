"""The approaches the engine is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle
from . import bitrows, cells
from .csr import adjacency
from .intersect import arc_lists, beside
from .partition import arcs_with_parts


def _wedges(g: Graph) -> DataFrame:
    a = g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("j"))
    return a.join(g.arcs.select(F.col("src").alias("v"), F.col("dst").alias("k")), "v").where("j < k")


def wedge_mapreduce(g: Graph) -> DataFrame:
    """v, triangles: one job forms all neighbour pairs, a second closes them."""
    closed = _wedges(g).join(g.arcs.select(F.col("src").alias("j"), F.col("dst").alias("k")), ["j", "k"], "left_semi")
    return closed.groupBy("v").agg(F.count(F.lit(1)).alias("triangles"))


def questions(g: Graph, parts: DataFrame) -> DataFrame:
    """v, j, k, asker, owner: each neighbour pair of a vertex is a question to the owner of its first end."""
    a = parts.select("v", F.col("part").alias("asker"))
    b = parts.select(F.col("v").alias("j"), F.col("part").alias("owner"))
    return _wedges(g).join(a, "v").join(b, "j")


def query_response(g: Graph, parts: DataFrame) -> DataFrame:
    """v, triangles by questions and answers."""
    if cells.usable(g):  # v's questions about its neighbour j are its later neighbours: the list travels once for many j, and is answered by j's list
        return bitrows.closed(g, beyond=True).where("n > 0").select("v", F.col("n").alias("triangles"))
    if g.lists is not None:
        answered = arc_lists(g).select(F.col("src").alias("v"), F.size(F.filter(F.array_intersect("a", "b"), lambda k: k > F.col("dst"))).cast("long").alias("yes"))
        return answered.groupBy("v").agg(F.sum("yes").alias("triangles")).where("triangles > 0")
    asked = questions(g, parts)
    yes = asked.join(g.arcs.select(F.col("src").alias("j"), F.col("dst").alias("k")), ["j", "k"], "left_semi")
    return yes.groupBy("v").agg(F.count(F.lit(1)).alias("triangles"))


def query_messages(g: Graph, parts: DataFrame, buffer_bytes: int = 16 << 20, question_bytes: int = 16) -> DataFrame:
    """asker, owner, questions, bytes, rounds: what the pair exchanges, and how many buffers of that size it fills."""
    sent = questions(g, parts).where("asker != owner").groupBy("asker", "owner").agg(F.count(F.lit(1)).alias("questions"))
    return sent.withColumn("bytes", F.col("questions") * question_bytes).withColumn("rounds", F.expr(f"(bytes + {buffer_bytes - 1}) div {buffer_bytes}"))


def query_response_buffered(g: Graph, parts: DataFrame, buffer_bytes: int = 16 << 20, question_bytes: int = 16) -> DataFrame:
    """v, round, triangles: the questions of a pair of parts are numbered, so a round is their number over the buffer's capacity; one plan for all rounds."""
    share = max(1, buffer_bytes // question_bytes // 16)
    if g.groups is not None and not g.directed and (found := cells.rounds(g, parts, share, 16)) is not None:
        return found
    w = W.partitionBy("asker", "owner", F.pmod(F.col("v"), F.lit(16))).orderBy("v", "j", "k")
    asked = questions(g, parts).withColumn("round", ((F.row_number().over(w) - 1) / share).cast("int"))
    yes = asked.join(g.arcs.select(F.col("src").alias("j"), F.col("dst").alias("k")), ["j", "k"], "left_semi")
    return yes.groupBy("v", "round").agg(F.count(F.lit(1)).alias("triangles"))


def bulk_synchronous(g: Graph) -> DataFrame:
    """v, triangles: all lists are written out and exchanged, each once to a block of vertices, then everybody counts."""
    if cells.usable(g):
        return bitrows.closed(g, beyond=False).where("n > 0").select("v", F.expr("n div 2").alias("triangles"))
    return arc_lists(g).groupBy(F.col("src").alias("v")).agg((F.sum(F.size(F.array_intersect("a", "b"))).cast("long") / 2).cast("long").alias("triangles")).where("triangles > 0")


def shadow_edges(g: Graph, parts: DataFrame) -> DataFrame:
    """part, src, dst, own: the arcs that each part needs to count alone: those of its vertices, and those between their neighbours."""
    own = arcs_with_parts(g, parts).select(F.col("ps").alias("part"), "src", "dst")
    near = own.select("part", F.col("dst").alias("x")).distinct()
    at_src = near.select("part", F.col("x").alias("src"))
    at_dst = near.select("part", F.col("x").alias("dst"))
    between = at_src.join(g.arcs, "src").join(at_dst, ["part", "dst"], "left_semi").select("part", "src", "dst")
    return own.withColumn("own", F.lit(1)).unionByName(between.withColumn("own", F.lit(0))).groupBy("part", "src", "dst").agg(F.max("own").alias("own"))


def shadow_count(g: Graph, parts: DataFrame) -> DataFrame:
    """v, triangles: each part counts on its own copy, no list is fetched. Where lists come from the source, the copy is the lists of a part's vertices and of their neighbours."""
    if cells.usable(g):
        return bitrows.copies(g, parts).where("n > 0").select("v", F.col("n").alias("triangles"))
    if g.lists is not None:
        lists = settle(adjacency(g).select("v", "nbrs"), "lists")
        own = lists.join(parts.select("v", "part"), "v")
        beside(lists)
        near = own.select("part", F.explode("nbrs").alias("v")).distinct()
        tasks = 4 * (parts.agg(F.max("part")).first()[0] or 0) + 5
        copy = near.join(lists, "v").select("part", F.col("v").alias("j"), F.col("nbrs").alias("b")).repartition(tasks, "part")
        mine = own.repartition(tasks, "part").select("part", "v", F.col("nbrs").alias("a"), F.explode("nbrs").alias("j"))
        closed = mine.join(copy.hint("shuffle_hash"), ["part", "j"]).select("v", F.size(F.filter(F.array_intersect("a", "b"), lambda k: k > F.col("j"))).cast("long").alias("n"))
        return closed.groupBy("v").agg(F.sum("n").alias("triangles")).where("triangles > 0")
    held = settle(shadow_edges(g, parts), "shadow")
    mine = held.where("own = 1")
    a = mine.select("part", F.col("src").alias("v"), F.col("dst").alias("j"))
    b = mine.select("part", F.col("src").alias("v"), F.col("dst").alias("k"))
    closing = held.select("part", F.col("src").alias("j"), F.col("dst").alias("k"))
    return a.join(b, ["part", "v"]).where("j < k").join(closing, ["part", "j", "k"], "left_semi").groupBy("v").agg(F.count(F.lit(1)).alias("triangles"))


def shadow_replication(g: Graph, parts: DataFrame) -> DataFrame:
    """One row: arcs, arcs held by all parts, replication factor."""
    held = shadow_edges(g, parts).agg(F.count(F.lit(1)).alias("n_held"))
    return held.join(g.arcs.agg(F.count(F.lit(1)).alias("n_arcs")), how="cross").withColumn("factor", F.round(F.col("n_held") / F.col("n_arcs"), 6))
