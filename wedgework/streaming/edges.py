"""Edge streams from the events table: windowed graphs, incremental triangle counts, a live read cache."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.replay import ReadCache
from ..operators.triangles import listing
from ..schema import CacheConfig, Graph


def events(spark: SparkSession, path: str, schema, watermark: str = "1 hour", files_a_batch: int = 1) -> DataFrame:
    """The event stream; times are cast to timestamps, which watermarks need."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def edges_within(left: DataFrame, delta: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """src, dst, ts: users with events at most ``delta`` apart (stream-stream interval join); repeats within the watermark are dropped."""
    a = left.select(F.col("user_id").alias("src"), "ts", F.col("event_type").alias("ka"))
    b = left.select(F.col("user_id").alias("dst"), F.col("ts").alias("ts2"), F.col("event_type").alias("kb"))
    near = a.join(b, F.expr(f"ka = kb AND ts2 >= ts AND ts2 <= ts + interval {delta} AND src < dst"))
    return near.select("src", "dst", "ts").dropDuplicatesWithinWatermark(["src", "dst"])


def windowed(edges: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """start, src, dst, n: the edges of each tumbling or sliding window."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(w.alias("w"), F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "src", "dst", "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    """start, user_id, n: activity sessions."""
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def window_triangles(rows: DataFrame) -> DataFrame:
    """start, triangles of a batch of windowed edges: the window is part of every join key."""
    e = rows.select("start", "src", "dst").distinct()
    a = e.select("start", F.col("src").alias("x"), F.col("dst").alias("y"))
    b = e.select("start", F.col("src").alias("x"), F.col("dst").alias("z"))
    c = e.select("start", F.col("src").alias("y"), F.col("dst").alias("z"))
    return a.join(b, ["start", "x"]).where("y < z").join(c, ["start", "y", "z"]).groupBy("start").agg(F.count(F.lit(1)).alias("triangles"))


def new_triangles(old: DataFrame, new: DataFrame) -> DataFrame:
    """Triangles of old and new edges (src < dst) with one new side at least, each once."""
    fresh = new.select("src", "dst").distinct().join(old.select("src", "dst"), ["src", "dst"], "left_anti").withColumn("fresh", F.lit(1))
    whole = old.select("src", "dst").distinct().withColumn("fresh", F.lit(0)).unionByName(fresh)
    # only what stands beside a new edge can close with it
    ends = fresh.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    near = whole.join(ends, F.col("src") == F.col("v"), "left_semi").select(F.col("dst").alias("v")).union(whole.join(ends, F.col("dst") == F.col("v"), "left_semi").select(F.col("src").alias("v"))).union(ends).distinct()
    part = whole.join(near, F.col("src") == F.col("v"), "left_semi").join(near, F.col("dst") == F.col("v"), "left_semi")
    both = part.select("src", "dst").unionByName(part.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    t = listing(Graph(both))
    side = fresh.select("src", "dst", "fresh")
    for x, y in (("a", "b"), ("a", "c"), ("b", "c")):
        t = t.join(side.select(F.col("src").alias(x), F.col("dst").alias(y), F.col("fresh").alias(f"{x}{y}")), [x, y], "left")
    return t.where("coalesce(ab, ac, bc) = 1").select("a", "b", "c")


def incremental(edges: DataFrame, state_path: str):
    """A foreachBatch query that keeps edges and found triangles under ``state_path``; a repeated batch id writes the same folders again."""
    spark = edges.sparkSession

    def step(batch: DataFrame, batch_id: int) -> None:
        new = batch.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src != dst").distinct()
        schema = new.schema
        old = spark.createDataFrame([], schema)
        if batch_id:
            try:
                old = _before(spark, state_path, batch_id, schema)
            except Exception as e:
                if "PATH_NOT_FOUND" not in str(e):
                    raise
        fresh = new.join(old, ["src", "dst"], "left_anti").persist()
        new_triangles(old, fresh).write.mode("overwrite").parquet(f"{state_path}/triangles/batch={batch_id}")
        fresh.write.mode("overwrite").parquet(f"{state_path}/edges/batch={batch_id}")
        fresh.unpersist()

    return edges.writeStream.foreachBatch(step)


def _before(spark: SparkSession, state_path: str, batch_id: int, schema) -> DataFrame:
    """Edges of earlier batches only, so that a repeated batch meets the same state."""
    return spark.read.parquet(f"{state_path}/edges").where(F.col("batch") < batch_id).select([f.name for f in schema])


def live_cache(reads: DataFrame, cfg: CacheConfig) -> DataFrame:
    """part, reads, hits after each micro-batch: one cache for each part in the stream's state (flushed each batch in 'transparent' mode)."""
    import pickle

    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        cache, total, hits = pickle.loads(state.get[0]) if state.exists else (ReadCache(cfg), 0, 0)
        if cfg.mode == "transparent":
            cache.flush()
        for b in batches:
            for r in b.sort_values("seq").itertuples(index=False):
                total += 1
                hits += cache.read(r.dst, r.adj_bytes, float(r.deg))[0] == "hit"
        state.update((pickle.dumps((cache, total, hits)),))
        yield pd.DataFrame({"part": [key[0]], "reads": [total], "hits": [hits]})

    return reads.groupBy("part").applyInPandasWithState(step, "part int, reads long, hits long", "cache binary", "update", GroupStateTimeout.NoTimeout)
