"""The read-time model and the sizing rules of the caches."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import CostModel


def read_time(trace: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """part, n_reads, bytes, seconds without a cache: each remote read is two transfers, the offset pair and the list."""
    one = trace.groupBy("part").agg(F.count(F.lit(1)).alias("n_reads"), F.sum(F.col("off_bytes") + F.col("adj_bytes")).alias("bytes"))
    return one.withColumn("seconds", 2 * F.col("n_reads") * model.alpha + F.col("bytes") * model.beta)


def replay_time(replayed: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """part, window, seconds with a cache: misses pay the transfer, every read the look-up, every miss the cache's own work."""
    miss = F.col("outcome") != "hit"
    paid = F.when(miss, F.lit(model.alpha) + F.col("bytes") * model.beta + F.lit(model.miss_extra)).otherwise(0.0) + F.lit(model.lookup)
    return replayed.groupBy("part", "window").agg(F.count(F.lit(1)).alias("n_reads"), F.sum(paid).alias("seconds"))


def window_time(trace: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """part, window, seconds without a cache."""
    rows = trace.select("part", F.explode(F.array(F.struct(F.lit("offsets").alias("window"), F.col("off_bytes").cast("long").alias("b")), F.struct(F.lit("adj").alias("window"), F.col("adj_bytes").alias("b")))).alias("e"))
    return rows.groupBy("part", "e.window").agg(F.sum(F.lit(model.alpha) + F.col("e.b") * model.beta).alias("seconds"))


def saving(trace: DataFrame, replayed: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """One row: communication seconds without and with the cache (windows that aren't cached pay in full), and the share saved."""
    full = window_time(trace, model).withColumnRenamed("seconds", "s0")
    cached = replay_time(replayed, model).select("part", "window", F.col("seconds").alias("s1"))
    both = full.join(cached, ["part", "window"], "left").withColumn("s1", F.coalesce("s1", "s0"))
    return both.agg(F.sum("s0").alias("plain_s"), F.sum("s1").alias("cached_s")).withColumn("saved_share", F.round(1 - F.col("cached_s") / F.col("plain_s"), 6))


def per_read(replayed: DataFrame, model: CostModel = CostModel()) -> DataFrame:
    """One row: mean seconds of reading one remote vertex."""
    return replay_time(replayed, model).agg((F.sum("seconds") / F.max("n_reads")).alias("seconds_a_read"))


def overlap_bound(comm: float, comp: float) -> dict[str, float]:
    """Total without overlap, and with the next read hidden behind the current intersection."""
    return {"sum": comm + comp, "overlapped": max(comm, comp)}


def hash_slots(n: int, fraction: float, window: str = "adj", alpha: float = 2.0) -> int:
    """Slots to start with when a cache holds ``fraction`` of the bytes: entries of equal size, or a power law of lists."""
    return max(1, round(n * fraction if window == "offsets" else n * fraction**alpha))


def split_budget(total_bytes: int, n: int, id_bytes: int = 4, share: float = 0.8) -> dict[str, int]:
    """Memory of both caches: ``share * n`` positions for offsets (two a vertex), the rest for lists."""
    offsets = min(total_bytes, int(share * n) * id_bytes)
    return {"offsets_bytes": offsets, "offsets_entries": int(share * n) // 2, "adj_bytes": total_bytes - offsets}


def split_columns(total_bytes: int, n: Column, id_bytes: int = 4, share: float = 0.8) -> dict[str, Column]:
    """``split_budget`` for a column of vertex counts."""
    places = F.floor(F.lit(share) * n)
    offsets = F.least(F.lit(total_bytes).cast("long"), places * id_bytes)
    return {"offsets_bytes": offsets, "offsets_entries": F.floor(places / 2), "adj_bytes": F.lit(total_bytes).cast("long") - offsets}
