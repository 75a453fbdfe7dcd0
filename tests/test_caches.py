"""Replays against plain references, closed forms, costs, measures, functions and streams."""

import random
from collections import OrderedDict

import pytest
from pyspark.sql import functions as F

from wedgework.functions import costs, udx
from wedgework.functions.replay import Buffer, ReadCache, reuse_hits
from wedgework.operators import cache, partition, prep, trace
from wedgework.plans import experiments
from wedgework.schema import CacheConfig, CostModel, Graph
from wedgework.sources import graphs


@pytest.fixture(scope="module")
def traced(spark):
    g = graphs.rmat(spark, 7, 6)
    return trace.build(g, partition.block(g, 2)).cache()


def plain_lru(reads, capacity):
    held, used, hits = OrderedDict(), 0, 0
    for key, size in reads:
        if key in held:
            held.move_to_end(key)
            hits += 1
            continue
        if size > capacity:
            continue
        while used + size > capacity:
            used -= held.popitem(last=False)[1]
        held[key] = size
        used += size
    return hits


def replay_hits(cfg, reads, **extra):
    c = ReadCache(cfg)
    return sum(c.read(k, n, **{x: f(k, n) for x, f in extra.items()})[0] == "hit" for k, n in reads)


@pytest.fixture(scope="module")
def reads():
    rng = random.Random(5)
    sizes = {k: rng.choice([4, 8, 40, 200]) for k in range(80)}
    return [(k, sizes[k]) for k in (min(int(rng.expovariate(0.05)), 79) for _ in range(3000))]


@pytest.mark.parametrize("capacity", [0, 50, 500, 2000, 10**6])
def test_recency_against_reference(reads, capacity):
    assert replay_hits(CacheConfig(capacity), reads) == plain_lru(reads, capacity)


def test_more_memory_never_hurts_equal_entries(reads):
    same = [(k, 8) for k, _ in reads]
    hits = [replay_hits(CacheConfig(8 * e), same) for e in (1, 2, 4, 8, 16, 32, 64, 128)]
    assert hits == sorted(hits) == reuse_hits([k for k, _ in same], [1, 2, 4, 8, 16, 32, 64, 128])


def test_outcomes(reads):
    c = ReadCache(CacheConfig(10**9))
    got = [c.read(k, n)[0] for k, n in reads]
    assert got.count("compulsory") == len({k for k, _ in reads}) and got.count("hit") == len(reads) - got.count("compulsory")
    c = ReadCache(CacheConfig(10**9, slots=4))
    assert "conflict" in [c.read(k, n)[0] for k, n in reads]
    c = ReadCache(CacheConfig(200))
    assert "capacity" in [c.read(k, n)[0] for k, n in reads]


def test_modes(reads):
    always = replay_hits(CacheConfig(10**9), reads)
    epochs = replay_hits(CacheConfig(10**9, mode="transparent", epoch_len=100), reads)
    never = replay_hits(CacheConfig(10**9, mode="user"), reads, flush_before=lambda k, n: True)
    assert always > epochs > never == 0


def test_degree_score_keeps_large(reads):
    c = ReadCache(CacheConfig(200, score="app"))
    c.read(1, 100, 5.0), c.read(2, 100, 4.0)
    assert c.read(3, 100, 3.0) == ("compulsory", 0) and set(c.held) == {1, 2}  # no room for a smaller score
    assert c.read(4, 100, 6.0) == ("compulsory", 1) and set(c.held) == {1, 4}


def test_positional_and_fragmented(reads):
    whole = replay_hits(CacheConfig(600), reads)
    for fit in ("first", "best"):
        assert 0 < replay_hits(CacheConfig(600, fragmentation=True, fit=fit), reads) <= whole * 1.1
    assert replay_hits(CacheConfig(600, score="lru_positional", fragmentation=True), reads) > 0


def test_buffer_regions():
    b = Buffer(100, "first")
    x, y, z = b.place(30), b.place(30), b.place(40)
    assert (x, y, z) == (0, 30, 60) and b.place(1) is None
    b.free(y, 30)
    assert b.beside(x, 30) == 30 and b.place(31) is None
    b.free(x, 30)
    assert b.place(60) == 0


def test_adaptive_grows(reads):
    c = ReadCache(CacheConfig(100, slots=2, adaptive=True, adapt_every=200, conflict_threshold=0.05, capacity_threshold=0.05))
    for k, n in reads:
        c.read(k, n)
    assert c.slots > 2 and c.capacity > 100


def test_batch_replay_equals_machine(spark, traced):
    cfg = CacheConfig(800, score="app")
    got = {(r.part, r.seq): r.outcome for r in cache.replay(traced, cfg).collect()}
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        again = {(r.part, r.seq): r.outcome for r in cache.replay(traced, cfg).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    want, caches = {}, {}
    for r in traced.orderBy("part", "seq").collect():
        want[r.part, r.seq] = caches.setdefault(r.part, ReadCache(cfg)).read(r.dst, r.adj_bytes, float(r.deg))[0]
    assert got == again == want


def test_summaries_and_costs(spark, traced):
    free = cache.replay(traced, CacheConfig(1 << 40, window="both"))
    s = cache.summarize(free).collect()
    assert all(r.hit + r.compulsory == r.reads and r.capacity == r.conflict == 0 for r in s)
    saved = costs.saving(traced, free).first()
    assert 0 < saved.saved_share < 1
    lists_only = costs.saving(traced, cache.replay(traced, CacheConfig(1 << 40))).first()
    assert lists_only.saved_share < saved.saved_share
    slow = costs.saving(traced, cache.replay(traced, CacheConfig(0)), CostModel(lookup=1e-6, miss_extra=1e-6)).first()
    assert slow.saved_share < 0  # a cache that never hits costs more than none
    assert costs.per_read(free).first()[0] > 0
    assert costs.overlap_bound(2.0, 1.0) == {"sum": 3.0, "overlapped": 2.0}
    assert costs.hash_slots(1000, 0.5) == 250 and costs.hash_slots(1000, 0.5, "offsets") == 500
    assert costs.split_budget(10_000, 1000) == {"offsets_bytes": 3200, "offsets_entries": 400, "adj_bytes": 6800}


def test_static_hot_set_is_close_to_the_degree_score(spark):
    g = graphs.rmat(spark, 9, 8)
    t = trace.build(g, partition.block(g, 2)).cache()
    by = {r.policy: r.miss_rate for r in cache.compare_scores(t, 25).collect()}
    assert by["app"] < by["lru"]
    assert abs(cache.static_hits(t, 25).first().miss_rate - by["app"]) < 0.08


def test_recency_by_joins(traced):
    a = {(r.part, r.entries): r.hits for r in cache.recency_hits(traced, [2, 8, 32]).collect()}
    assert a == {(r.part, r.entries): r.hits for r in cache.recency_hits_sql(traced, [2, 8, 32]).collect()}


def test_more_parts_mean_more_remote_and_first_reads(spark):
    got = {r.p: r for r in experiments.by_parts(graphs.rmat(spark, 8, 8), (2, 8, 32)).collect()}
    assert got[2].remote_share < got[8].remote_share < got[32].remote_share
    assert got[2].first_share < got[8].first_share < got[32].first_share
    assert {r.regime for r in experiments.regime(experiments.by_parts(graphs.rmat(spark, 8, 8), (2, 32))).collect()} <= {"compute", "compulsory", "cacheable"}


def test_timed_and_throughput(spark):
    t = experiments.timed(lambda: sum(range(1000)), 3, 5)
    assert t["low_s"] <= t["median_s"] <= t["high_s"]
    assert {x["kernel"] for x in experiments.throughput(graphs.rmat(spark, 6, 4), repeats=1)} == {"hybrid", "merge", "search", "tuned"}


def test_functions(spark, traced):
    udx.register(spark)
    df = spark.createDataFrame([([1, 2, 3], [2, 3, 4])], "a array<long>, b array<long>")
    assert df.select(udx.common_count("a", "b")).first()[0] == 2
    m = spark.createDataFrame([(float(x),) for x in range(9)], "x double").agg(udx.median_ci("x").alias("m")).first().m
    assert m[1] <= m[0] == 4.0 <= m[2]
    drawn = spark.sql("SELECT * FROM rmat_edges(6, 4, 0, 1)")
    edges = prep.symmetrize(Graph(prep.simplify(drawn)))
    assert {tuple(r) for r in edges.arcs.collect()} == {tuple(r) for r in graphs.rmat(spark, 6, 4).arcs.collect()}
    traced.createOrReplaceTempView("trace")
    got = {(r.part, r.seq): r.outcome for r in spark.sql("SELECT * FROM cache_replay(TABLE(trace), 800, 'lru')").collect()}
    assert got == {(r.part, r.seq): r.outcome for r in cache.replay(traced, CacheConfig(800)).collect()}


def test_streams(spark, data, tmp_path):
    from wedgework.operators.triangles import count
    from wedgework.streaming import edges as streams

    e = spark.read.parquet(f"{data}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    e.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = streams.events(spark, str(tmp_path / "in"), e.schema, watermark="400 days")
    pairs = stream.select(F.col("user_id").alias("src"), (F.col("event_id") % 15).alias("dst")).where("src != dst")
    q = streams.incremental(pairs, str(tmp_path / "state")).option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination()
    whole = prep.symmetrize(Graph(prep.simplify(e.select(F.col("user_id").alias("src"), (F.col("event_id") % 15).alias("dst")))))
    assert spark.read.parquet(str(tmp_path / "state/triangles")).count() == count(whole).first()[0]

    w = streams.windowed(stream.select(F.col("user_id").alias("src"), (F.col("event_id") % 15).alias("dst"), "ts").where("src != dst"), "1 day")
    w.writeStream.format("memory").queryName("win").outputMode("complete").option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start().awaitTermination()
    batch = e.select(F.date_trunc("day", "ts").alias("start"), F.col("user_id").alias("src"), (F.col("event_id") % 15).alias("dst")).where("src != dst").select("start", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    win = spark.createDataFrame(spark.table("win").collect(), spark.table("win").schema)
    assert {tuple(r) for r in streams.window_triangles(win).collect()} == {tuple(r) for r in streams.window_triangles(batch).collect()}
    s = streams.sessions(stream, "1 hour")
    s.writeStream.format("memory").queryName("ses").outputMode("append").option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start().awaitTermination()


def test_live_cache(spark, traced, tmp_path):
    from wedgework.streaming.edges import live_cache

    flat = traced.select("part", "seq", "dst", "adj_bytes", "deg")
    flat.coalesce(1).write.parquet(str(tmp_path / "in"))
    reads = spark.readStream.schema(flat.schema).parquet(str(tmp_path / "in"))
    live_cache(reads, CacheConfig(800)).writeStream.format("memory").queryName("live").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    want = {r.part: (r.reads, r.hit) for r in cache.summarize(cache.replay(traced, CacheConfig(800))).collect()}
    assert {r.part: (r.reads, r.hits) for r in spark.table("live").collect()} == want


def test_budgets_show_the_three_scenarios(spark):
    g = graphs.rmat(spark, 8, 8)
    rows = experiments.budgeted(g, (4, 16, 64)).collect()
    assert [r.first_share for r in rows] == sorted(r.first_share for r in rows) and [r.gain for r in rows] == sorted((r.gain for r in rows), reverse=True)
    assert rows[0].scenario == "cacheable" and rows[0].cached_s < rows[0].plain_s
    assert {r.scenario for r in experiments.budgeted(g, (200,), 12).collect()} == {"compulsory"}
    assert {r.scenario for r in experiments.budgeted(g, (4,), model=experiments.SLOW).collect()} == {"compute"}


def test_sweep_against_the_replayed_degree_score(spark):
    """Whole degrees held or not come within a few points of the replay, and larger caches never miss more."""
    g = graphs.rmat(spark, 8, 8)
    rows = experiments.sweep(g, "adj", (10, 25, 50, 100)).collect()
    assert [r.miss_rate for r in rows] == sorted((r.miss_rate for r in rows), reverse=True) and rows[-1].miss_rate == rows[-1].first_share
    t = trace.build(g, partition.block(g, 2))
    cap = cache.capacity_for(t, 25)
    replayed = cache.summarize(cache.replay(t, CacheConfig(cap, score="app"))).agg(F.sum("hit") / F.sum("reads")).first()[0]
    assert abs((1 - rows[1].miss_rate) - replayed) < 0.06


def test_knowing_the_future_beats_every_score(traced):
    by = {r.score: r.hits for r in cache.compare_application_scores(traced, 25, window="offsets").collect()}
    assert set(by) == {"recency", "deg", "deg_in", "deg_per_byte", "next_use"} and by["next_use"] == max(by.values()) > by["recency"]


def test_read_times(spark):
    g = graphs.rmat(spark, 7, 6)
    for r in experiments.hot_read_times(g, (2, 8), 100).collect():
        assert r.cached_us == r.once_us
    rows = experiments.score_read_times(g, (2,)).collect()
    assert {r.policy for r in rows} == {"lru", "lru_positional", "app"} and all(r.mean_us > 0 for r in rows)
