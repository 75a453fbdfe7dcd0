"""Replay of read traces through caches, closed forms for special cases, and summaries."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.replay import ReadCache, reuse_hits
from ..schema import CacheConfig


def replay(trace: DataFrame, cfg: CacheConfig, score_col: str = "deg", flush_col: str | None = None) -> DataFrame:
    """part, seq, window, outcome, bytes, evicted for every read. ``cfg.window``: 'adj', 'offsets' or 'both' (two independent caches).

    A part is replayed in one task, in order, with only the cache in memory: a sequential state machine has no other order. Few parts make
    few tasks; the closed forms (``experiments.hot_costs``, ``static_hits``) have no such limit and are the way at scale.
    """
    windows = ("offsets", "adj") if cfg.window == "both" else (cfg.window,)
    size = {"offsets": "off_bytes", "adj": "adj_bytes"}
    rows = trace.select("part", "seq", "dst", "off_bytes", "adj_bytes", F.col(score_col).cast("double").alias("score"), (F.col(flush_col) if flush_col else F.lit(False)).alias("flush"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, caches = None, {}
        for b in batches:
            out = []
            for r in b.itertuples(index=False):
                if r.part != part:
                    part, caches = r.part, {w: ReadCache(cfg) for w in windows}
                for w in windows:
                    n = getattr(r, size[w])
                    out.append((r.part, r.seq, w, *caches[w].read(r.dst, n, r.score, r.flush), n))
            yield pd.DataFrame(out, columns=["part", "seq", "window", "outcome", "evicted", "bytes"])

    return rows.repartition("part").sortWithinPartitions("part", "seq").mapInPandas(run, "part int, seq long, window string, outcome string, evicted int, bytes long")


def summarize(replayed: DataFrame) -> DataFrame:
    """part, window: reads, hits and misses by kind, bytes read."""
    kind = lambda k: F.sum((F.col("outcome") == k).cast("long")).alias(k)
    return replayed.groupBy("part", "window").agg(
        F.count(F.lit(1)).alias("reads"), kind("hit"), kind("compulsory"), kind("capacity"), kind("conflict"), F.sum("evicted").alias("evicted"),
        F.sum(F.when(F.col("outcome") != "hit", F.col("bytes")).otherwise(0)).alias("bytes_read"),
    )


def recency_hits(trace: DataFrame, entries: list[int]) -> DataFrame:
    """part, entries, hits of recency caches of so many equal entries (offsets): reuse distances, all capacities in one pass over a part."""

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        hits = reuse_hits(rows.sort_values("seq")["dst"].tolist(), entries)
        return pd.DataFrame({"part": key[0], "entries": entries, "hits": hits})

    return trace.select("part", "seq", "dst").groupBy("part").applyInPandas(run, "part int, entries long, hits long")


def recency_hits_sql(trace: DataFrame, entries: list[int]) -> DataFrame:
    """The same by joins: a read hits if fewer than ``entries`` distinct targets lie between it and the target's last read. For short traces."""
    t = trace.select("part", "seq", "dst", F.lag("seq").over(W.partitionBy("part", "dst").orderBy("seq")).alias("prev"))
    # a target lies between if its last read before ``seq`` is after ``prev``: those are reads whose next read isn't before seq
    nxt = t.select("part", F.col("prev").alias("seq2"), F.col("seq").alias("next2")).where("seq2 IS NOT NULL")
    seen = trace.select("part", F.col("seq").alias("seq2")).join(nxt, ["part", "seq2"], "left")
    between = t.where("prev IS NOT NULL").join(seen, "part").where((F.col("seq2") > F.col("prev")) & (F.col("seq2") < F.col("seq")) & (F.col("next2").isNull() | (F.col("next2") >= F.col("seq"))))
    dist = t.where("prev IS NOT NULL").select("part", "seq").join(between.groupBy("part", "seq").agg(F.count(F.lit(1)).alias("d")), ["part", "seq"], "left").select("part", F.coalesce("d", F.lit(0)).alias("d"))
    caps = dist.sparkSession.createDataFrame([(e,) for e in entries], "entries long")
    parts = trace.select("part").distinct().join(F.broadcast(caps), how="cross")
    met = dist.join(F.broadcast(caps), F.col("d") < F.col("entries")).groupBy("part", "entries").agg(F.count(F.lit(1)).alias("hits"))
    return parts.join(met, ["part", "entries"], "left").select("part", "entries", F.coalesce("hits", F.lit(0)).alias("hits"))


def hot_set(trace: DataFrame, percent: int) -> DataFrame:
    """part, dst of each part's largest lists that fit ``percent`` of the bytes it reads from others (each list once): the static form of the degree score."""
    lists = trace.select("part", "dst", "adj_bytes", "deg").distinct()
    w = W.partitionBy("part").orderBy(F.desc("deg"), "dst")
    run = F.sum("adj_bytes").over(w.rowsBetween(W.unboundedPreceding, 0))
    total = F.sum("adj_bytes").over(W.partitionBy("part"))
    return lists.withColumn("run", run).withColumn("total", total).where(100 * F.col("run") <= percent * F.col("total")).select("part", "dst")


def static_hits(trace: DataFrame, percent: int) -> DataFrame:
    """One row: reads, reads of hot lists after their first, and the miss rate."""
    hot = hot_set(trace, percent).withColumn("hot", F.lit(1))
    met = trace.groupBy("part", "dst").agg(F.count(F.lit(1)).alias("c")).join(hot, ["part", "dst"], "left")
    one = met.agg(F.sum("c").alias("reads"), F.coalesce(F.sum(F.when(F.col("hot") == 1, F.col("c") - 1)), F.lit(0)).alias("hits"))
    return one.withColumn("miss_rate", F.round(1 - F.col("hits") / F.col("reads"), 6))


def capacity_for(trace: DataFrame, percent: int) -> int:
    """Bytes of ``percent`` of the mean non-local list bytes of a part."""
    one = trace.select("part", "dst", "adj_bytes").distinct().groupBy("part").agg(F.sum("adj_bytes").alias("b")).agg(F.avg("b")).first()[0]
    return int((one or 0) * percent / 100)


def with_scores(trace: DataFrame) -> DataFrame:
    """The trace with further application scores: degree per byte, and minus the place of the target's next read (the bound that knows the future)."""
    after = F.lead("seq").over(W.partitionBy("part", "dst").orderBy("seq"))
    return trace.select("*", (F.col("deg") / F.greatest("adj_bytes", F.lit(1))).alias("deg_per_byte"), (-F.coalesce(after, F.lit(1 << 53))).cast("double").alias("next_use"))


def compare_application_scores(trace: DataFrame, percent: int = 25, window: str = "adj", scores: tuple[str, ...] = ("deg", "deg_in", "deg_per_byte", "next_use")) -> DataFrame:
    """score, reads, hits, miss_rate, bytes_read of caches that evict by each of these columns, and of recency, under the same capacity."""
    size = "adj_bytes" if window == "adj" else "off_bytes"
    known = with_scores(trace)
    cap = int(known.select("part", "dst", size).distinct().groupBy("part").agg(F.sum(size).alias("b")).agg(F.avg("b")).first()[0] or 0) * percent // 100
    out = None
    for score in ("recency", *scores):
        cfg = CacheConfig(cap, window=window, score="lru" if score == "recency" else "app")
        s = summarize(replay(known, cfg, score_col="deg" if score == "recency" else score))
        one = s.agg(F.sum("reads").alias("reads"), F.sum("hit").alias("hits"), F.sum("bytes_read").alias("bytes_read")).select(F.lit(score).alias("score"), "*", F.round(1 - F.col("hits") / F.col("reads"), 6).alias("miss_rate"))
        out = one if out is None else out.unionByName(one)
    return out


def compare_scores(trace: DataFrame, percent: int = 25, cfg: CacheConfig | None = None) -> DataFrame:
    """policy, reads, hits, miss_rate, bytes_read of recency, positional recency and the degree score under the same capacity."""
    cap = capacity_for(trace, percent)
    base = replace(cfg or CacheConfig(cap), capacity_bytes=cap, window="adj")
    out = None
    for policy in ("lru", "lru_positional", "app"):
        s = summarize(replay(trace, replace(base, score=policy, fragmentation=policy == "lru_positional" or base.fragmentation)))
        one = s.agg(F.sum("reads").alias("reads"), F.sum("hit").alias("hits"), F.sum("bytes_read").alias("bytes_read")).select(F.lit(policy).alias("policy"), "*", F.round(1 - F.col("hits") / F.col("reads"), 6).alias("miss_rate"))
        out = one if out is None else out.unionByName(one)
    return out
