"""The experiment workloads: tables, sweeps, modelled run times, measured run times."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import costs
from ..operators import baselines, cache, csr, intersect, partition, prep, trace
from ..schema import CacheConfig, CostModel, Graph
from ..sources.tables import settle

STEPS = (4, 8, 16, 32, 64)
LARGE = (128, 256, 512)
#: A comparison costs what makes 79 % of the time communication on the generator graph with four parts, a look-up some reads of local
#: memory, and a miss in a cache the cache's own work on top of the transfer. SLOW has 25 times slower cores.
CACHED = CostModel(gamma=4e-9, lookup=2e-7, miss_extra=1e-6)
SLOW = CostModel(gamma=1e-7, lookup=2e-7, miss_extra=1e-6)


def stack(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def kept(g: Graph) -> Graph:
    """The graph with its arcs written once, for workloads that read them several times."""
    return g.with_arcs(settle(g.arcs, "arcs"))


def graph_table(graphs: list[Graph]) -> DataFrame:
    """graph, kind, n, m, csr_bytes; m counts an undirected edge once."""
    rows = []
    for g in graphs:
        s = csr.size_bytes(g)
        m = F.col("n_arcs") if g.directed else F.expr("n_arcs div 2")
        rows.append(s.select(F.lit(g.name).alias("graph"), F.lit("D" if g.directed else "U").alias("kind"), "n", m.alias("m"), "csr_bytes"))
    return stack(rows)


def by_parts(g: Graph, steps: tuple[int, ...] = STEPS) -> DataFrame:
    """p, n_arcs, n_remote, n_first, remote_share, first_share as the number of parts grows."""
    g, index = kept(g), settle(prep.dense_index(prep.vertices(g)), "index")
    rows = []
    for p in steps:
        parts = partition.block(g, p, index)
        c = partition.cut_stats(g, parts)
        f = trace.compulsory(g, parts)
        rows.append(c.join(f, how="cross").select(F.lit(p).alias("p"), "n_arcs", "n_remote", "n_first", F.col("cut_share").alias("remote_share"), F.col("share").alias("first_share")))
    return stack(rows)


def overall(g: Graph, steps: tuple[int, ...] = STEPS, model: CostModel = CostModel()) -> DataFrame:
    """p, plain_s, cached_s, compute_s: modelled seconds of the slowest part without a cache and with an unlimited one.

    Communication is two transfers a read; computation the hybrid's comparisons; a part's total is their sum.
    """
    g, index = kept(g), settle(prep.dense_index(prep.vertices(g)), "index")
    deg = prep.degrees(g).select("v", "deg_out")
    rows = []
    for p in steps:
        parts = partition.block(g, p, index)
        arcs = partition.arcs_with_parts(g, parts).join(deg.select(F.col("v").alias("src"), F.col("deg_out").alias("di")), "src").join(deg.select(F.col("v").alias("dst"), F.col("deg_out").alias("dj")), "dst")
        arcs = arcs.withColumn("ops", F.expr(f"CASE WHEN {intersect.RULE} THEN di + dj ELSE least(di, dj) * log2(greatest(di, dj)) END"))
        work = arcs.groupBy(F.col("ps").alias("part")).agg((F.sum("ops") * model.gamma).alias("comp"))
        far = arcs.where("ps != pd").groupBy(F.col("ps").alias("part"), "dst").agg(F.count(F.lit(1)).alias("c"), F.max("dj").alias("d"))
        cost = F.lit(2 * model.alpha) + (F.col("d") * 4 + 8) * model.beta
        comm = far.groupBy("part").agg(F.sum(F.col("c") * cost).alias("plain"), F.sum(cost).alias("once"), F.sum("c").alias("reads"))
        both = work.join(comm, "part", "left").na.fill(0.0)
        lookups = F.col("reads") * 2 * model.lookup
        rows.append(
            both.agg(F.max(F.col("comp") + F.col("plain")).alias("plain_s"), F.max(F.col("comp") + F.col("once") + lookups).alias("cached_s"), F.max("comp").alias("compute_s"), (F.sum("plain") / F.sum(F.col("plain") + F.col("comp"))).alias("comm")).select(
                F.lit(p).alias("p"), F.round("plain_s", 6).alias("plain_s"), F.round("cached_s", 6).alias("cached_s"), F.round("compute_s", 6).alias("compute_s"), F.round("comm", 4).alias("comm_share")
            )
        )
    return stack(rows)


def placed(g: Graph) -> tuple[DataFrame, int, int]:
    """src, dst, di, dj (out-degrees), si, ti (dense indices), later (the source's neighbours after dst) of every arc, written once; n and the arcs' number.

    The part of an index is an expression of p, so a table for many p needs no further join.
    """
    g = kept(g)
    index = settle(prep.dense_index(prep.vertices(g)), "index")
    deg = prep.degrees(g).select("v", "deg_out")
    at = lambda rows, v, name, new: rows.select(F.col("v").alias(v), F.col(name).alias(new))
    arcs = g.arcs
    for v, i, d in (("src", "si", "di"), ("dst", "ti", "dj")):
        arcs = arcs.join(at(index, v, "idx", i), v).join(at(deg, v, "deg_out", d), v)
    later = F.col("di") - F.row_number().over(W.partitionBy("src").orderBy("dst"))
    known = settle(arcs.withColumn("later", later), "placed")
    return known, partition._n(index), known.count()


#: An arc's comparisons by the hybrid.
OPS = f"CASE WHEN {intersect.RULE} THEN di + dj ELSE least(di, dj) * log2(greatest(di, dj)) END"


def folded(g: Graph, steps: tuple[int, ...]) -> tuple[DataFrame, int, int]:
    """The same as sums, for undirected graphs that come as lists: src, ds (its degree), si, ti, k (arcs), ops, later, answer (later times log2 dj).

    The arcs of a vertex into vertices that share their part at every step make one row, ti being one of their indices: no arc is moved or written.
    """
    index = settle(prep.dense_index(prep.vertices(g)), "index")
    n = partition._n(index)
    known = settle(index.join(prep.degrees(g).select("v", F.col("deg_out").alias("d")), "v"), "known")
    far = known.select(F.col("v").alias("dst"), F.col("idx").alias("ti"), F.col("d").alias("dj"), sum((part_of("idx", p, n) for p in steps), F.lit(0)).alias("cell"))  # no two cells share all parts
    arcs = g.lists.select(F.col("v").alias("src"), F.size("nbrs").cast("long").alias("di"), F.posexplode("nbrs").alias("pos", "dst")).join(prep.sent(far, n), "dst")
    later = F.col("di") - F.col("pos") - 1
    sums = arcs.groupBy("src", "cell").agg(F.min("ti").alias("ti"), F.count(F.lit(1)).alias("k"), F.sum(F.expr(OPS)).alias("ops"), F.sum(later).alias("later"), F.sum(later * F.log2("dj")).alias("answer"))
    at = known.select(F.col("v").alias("src"), F.col("idx").alias("si"), F.col("d").alias("ds"))
    rows = settle(sums.join(prep.sent(at, n), "src"), "folded")
    return rows, n, known.agg(F.sum("d")).first()[0] or 0


def part_of(index: str, p: int, n: int):
    return F.expr(f"int((({index} + 1) * {p} + {n} - 1) div {max(n, 1)} - 1)")


def read_classes(known: DataFrame, p: int, n: int) -> DataFrame:
    """part, d, k, c and running sums of k (vertices) and b (list bytes) from the largest degree on: far targets of each degree, and reads of them."""
    if "di" not in known.columns:  # folded: a vertex is read as often as it has neighbours
        far = known.select(part_of("ti", p, n).alias("part"), part_of("si", p, n).alias("at"), F.col("src").alias("dst"), F.col("ds").alias("d"), F.col("k").alias("c")).where("part != at")
    else:
        far = known.select(part_of("si", p, n).alias("part"), part_of("ti", p, n).alias("at"), "dst", F.col("dj").alias("d"), F.lit(1).alias("c")).where("part != at")
    classes = far.groupBy("part", "dst", "d").agg(F.sum("c").alias("c")).groupBy("part", "d").agg(F.count(F.lit(1)).alias("k"), F.sum("c").alias("c"))
    w = W.partitionBy("part").orderBy(F.desc("d"))  # a row for each degree
    return classes.select("*", F.sum("k").over(w).alias("held"), F.sum(F.expr("4 * d * k")).over(w).alias("bytes"))


def hot_costs(classes: DataFrame, offsets_entries, adj_bytes, model: CostModel, windows: tuple[str, ...] = ("offsets", "adj")) -> DataFrame:
    """The classes with the seconds of their reads: plain, cached (the largest degrees that fit are held after their first read) and once (no limits); and hits of each window.

    This is the degree score in closed form: whole degrees are held or not, so it needs a histogram and no replay.
    """
    o, a = F.col("held") <= offsets_entries, F.col("bytes") <= adj_bytes
    miss_o, miss_a = F.when(o, F.col("k")).otherwise(F.col("c")), F.when(a, F.col("k")).otherwise(F.col("c"))
    step_o, step_a = F.lit(model.alpha + 8 * model.beta), F.lit(model.alpha) + F.expr("4 * d") * F.lit(model.beta)
    extra, look = F.lit(model.miss_extra), F.lit(model.lookup)
    window = {
        "offsets": (miss_o * (step_o + extra) + F.col("c") * look, F.col("k") * (step_o + extra) + F.col("c") * look, F.col("c") * step_o),
        "adj": (miss_a * (step_a + extra) + F.col("c") * look, F.col("k") * (step_a + extra) + F.col("c") * look, F.col("c") * step_a),
    }
    pick = lambda j: sum((window[w][j if w in windows else 2] for w in ("offsets", "adj")), F.lit(0.0))
    return classes.select("*", pick(2).alias("plain"), pick(0).alias("cached"), pick(1).alias("once"), (F.col("c") - miss_o).alias("hit_o"), (F.col("c") - miss_a).alias("hit_a"))


def budgeted(g: Graph, steps: tuple[int, ...] = STEPS, percent: int = 50, model: CostModel = CACHED, buffer_bytes: int = 1 << 16) -> DataFrame:
    """One row for each p: modelled seconds of the slowest part without a cache, with both caches under a budget, and of the query-response baseline.

    A part's caches have ``percent`` of the bytes of the graph's compressed rows: 0.8 n positions for offsets, the rest for lists, which
    the degree score holds (``hot_costs``). Every read pays two look-ups, every miss the cache's own work. The baseline asks the owner of a
    vertex's neighbour for each later neighbour: a message pair for each vertex and owner, or for each full buffer of a pair of parts;
    everyone waits for the slowest to ask and for the slowest to answer. scenario: 'compute' (less than half of the time is
    communication), 'cacheable' (caching saves 5 % at least) or 'compulsory'.
    """
    fold = g.lists is not None and not g.directed
    known, n, m = folded(g, steps) if fold else placed(g)
    csr_bytes = 4 * (n + 1 + m)
    cache_bytes = csr_bytes * percent // 100
    split = costs.split_budget(cache_bytes, n)
    r9 = lambda c: F.round(c, 9)
    rows = []
    for p in steps:
        part, at = part_of("si", p, n), part_of("ti", p, n)
        ops = F.col("ops") if fold else F.expr(OPS)
        work = (known if fold else known.where("dj > 0")).groupBy(part.alias("part")).agg((F.sum(ops) * model.gamma).alias("comp"))
        comm = hot_costs(read_classes(known, p, n), split["offsets_bytes"] // 8, split["adj_bytes"], model).groupBy("part").agg(*(F.sum(x).alias(x) for x in ("plain", "cached", "c", "k", "hit_o", "hit_a")))
        both = work.join(comm, "part", "full").na.fill(0)
        one = both.agg(
            F.max(F.col("comp") + F.col("plain")).alias("plain_s"), F.max(F.col("comp") + F.col("cached")).alias("cached_s"), F.max("comp").alias("compute_s"), (F.sum("plain") / F.sum(F.col("plain") + F.col("comp"))).alias("comm_share"),
            (F.sum("k") / F.sum("c")).alias("first_share"), (F.sum("hit_o") / F.sum("c")).alias("offsets_hit"), (F.sum("hit_a") / F.sum("c")).alias("adj_hit"),
        )
        answer = F.col("answer") if fold else F.col("later") * F.log2(F.greatest(F.col("dj"), F.lit(1)))
        asked = known.where("later > 0").groupBy(part.alias("asker"), at.alias("owner"), "src").agg(F.sum("later").alias("q"), (F.sum(answer) * model.gamma).alias("answer"))
        pairs = asked.groupBy("asker", "owner").agg(F.count(F.lit(1)).alias("messages"), F.sum("q").alias("q"), F.sum("answer").alias("answer"))
        away = F.col("asker") != F.col("owner")
        sends = pairs.groupBy("asker").agg(
            F.sum(F.when(away, 2 * model.alpha * F.col("messages") + 17 * model.beta * F.col("q")).otherwise(0.0)).alias("single"),
            F.sum(F.when(away, 2 * model.alpha * F.ceil(16 * F.col("q") / F.lit(buffer_bytes)) + 17 * model.beta * F.col("q")).otherwise(0.0)).alias("buffered"),
        )
        sent = sends.agg(F.max("single").alias("single"), F.max("buffered").alias("buffered"))
        answered = pairs.groupBy("owner").agg(F.sum("answer").alias("answer")).agg(F.max("answer").alias("answer"))
        rows.append(one.join(sent, how="cross").join(answered, how="cross").select(
            F.lit(p).alias("p"), F.lit(csr_bytes).cast("long").alias("csr_bytes"), F.lit(cache_bytes).cast("long").alias("cache_bytes"), r9("plain_s").alias("plain_s"), r9("cached_s").alias("cached_s"), r9("compute_s").alias("compute_s"),
            r9(F.col("single") + F.col("answer")).alias("asking_s"), r9(F.col("buffered") + F.col("answer")).alias("asking_buffered_s"), *(F.round(x, 6).alias(x) for x in ("comm_share", "first_share", "offsets_hit", "adj_hit")),
            F.round(1 - F.col("cached_s") / F.col("plain_s"), 6).alias("gain"), F.when(F.col("comm_share") < 0.5, "compute").when(F.col("cached_s") <= 0.95 * F.col("plain_s"), "cacheable").otherwise("compulsory").alias("scenario"),
        ))
    return stack(rows)


def sweep(g: Graph, window: str, percents: tuple[int, ...] = tuple(range(5, 101, 5)), p: int = 2, model: CostModel = CACHED) -> DataFrame:
    """percent, reads, hits, miss_rate, first_share, saved_share when one window is cached by the degree score, in closed form; sizes in percent of what the parts read of it."""
    known, n, _ = placed(g)
    classes = settle(read_classes(known, p, n), "classes")
    full = classes.groupBy("part").agg(F.max("held").alias("all_held"), F.max("bytes").alias("all_bytes"))
    both = classes.join(full, "part")
    hit = "hit_o" if window == "offsets" else "hit_a"
    rows = []
    for q in percents:
        one = hot_costs(both, F.expr(f"all_held * {q} / 100"), F.expr(f"all_bytes * {q} / 100"), model, (window,)).agg(F.sum("c").alias("reads"), F.sum(hit).alias("hits"), F.sum("k").alias("k"), F.sum("plain").alias("plain"), F.sum("cached").alias("cached"))
        rows.append(one.select(F.lit(q).alias("percent"), "reads", "hits", F.round(1 - F.col("hits") / F.col("reads"), 6).alias("miss_rate"), F.round(F.col("k") / F.col("reads"), 6).alias("first_share"), F.round(1 - F.col("cached") / F.col("plain"), 6).alias("saved_share")))
    return stack(rows)


def hot_read_times(g: Graph, steps: tuple[int, ...] = STEPS, percent: int = 25, model: CostModel = CACHED) -> DataFrame:
    """p, reads, plain_us, cached_us, once_us: mean microseconds of reading a remote vertex without a cache, with lists cached by the degree score under ``percent`` of what a part reads, and with first reads only."""
    known, n, _ = placed(g)
    rows = []
    for p in steps:
        classes = read_classes(known, p, n)
        both = classes.join(classes.groupBy("part").agg(F.max("bytes").alias("all_bytes")), "part")
        one = hot_costs(both, F.lit(0), F.expr(f"all_bytes * {percent} / 100"), model, ("adj",)).agg(F.sum("c").alias("reads"), *(F.sum(x).alias(x) for x in ("plain", "cached", "once")))
        rows.append(one.select(F.lit(p).alias("p"), "reads", *(F.round(F.col(x) / F.col("reads") * 1e6, 6).alias(f"{x}_us") for x in ("plain", "cached", "once"))))
    return stack(rows)


def score_read_times(g: Graph, steps: tuple[int, ...] = (4, 16, 64), percent: int = 25, model: CostModel = CACHED) -> DataFrame:
    """p, policy, reads, hits, mean_us: replayed reads of recency, positional recency and the degree score, lists cached under the same capacity."""
    g = kept(g)
    rows = []
    for p in steps:
        t = settle(trace.build(g, partition.block(g, p)), "trace")
        cap = cache.capacity_for(t, percent)
        for policy in ("lru", "lru_positional", "app"):
            r = cache.replay(t, CacheConfig(cap, score=policy, fragmentation=policy == "lru_positional", window="adj"))
            one = costs.replay_time(r, model).agg(F.sum("seconds").alias("s"), F.sum("n_reads").alias("reads")).join(r.agg(F.count_if(F.col("outcome") == "hit").alias("hits")), how="cross")
            offsets = model.alpha + 8 * model.beta
            rows.append(one.select(F.lit(p).alias("p"), F.lit(policy).alias("policy"), "reads", "hits", F.round((F.col("s") / F.col("reads") + offsets) * 1e6, 6).alias("mean_us")))
    return stack(rows)


def speedup(table: DataFrame, base: int, columns: tuple[str, ...] = ("plain_s", "cached_s")) -> DataFrame:
    """The table with each time's ratio to that of the smallest configuration."""
    ref = table.where(F.col("p") == base).select(*(F.col(c).alias(f"base_{c}") for c in columns))
    return table.join(ref, how="cross").select("p", *(F.round(F.col(f"base_{c}") / F.col(c), 4).alias(f"speedup_{c}") for c in columns))


def regime(by: DataFrame, first_limit: float = 0.5, remote_limit: float = 0.5) -> DataFrame:
    """p, regime: 'compute' (few remote reads), 'compulsory' (most of them first touches) or 'cacheable'."""
    return by.select("p", F.when(F.col("remote_share") < remote_limit, "compute").when(F.col("first_share") > first_limit, "compulsory").otherwise("cacheable").alias("regime"))


def imbalance_by_scheme(g: Graph, p: int = 8, schemes: tuple[str, ...] = ("block", "cyclic", "balanced")) -> DataFrame:
    g = kept(g)
    return stack([partition.imbalance(g, partition.SCHEMES[s](g, p)).select(F.lit(s).alias("scheme"), "*") for s in schemes])


def cache_sweep(g: Graph, window: str, percents: tuple[int, ...] = (5, 10, 25, 50, 75, 100), p: int = 2, score: str = "lru", model: CostModel = CostModel()) -> DataFrame:
    """percent, capacity_bytes, reads, hits, miss_rate, saved_share when one window is cached: sizes in percent of what a part can read of it."""
    t = settle(trace.build(g, partition.block(g, p)), "trace")
    size = "off_bytes" if window == "offsets" else "adj_bytes"
    full = t.select("part", "dst", size).distinct().groupBy("part").agg(F.sum(size).alias("b")).agg(F.max("b")).first()[0] or 0
    rows = []
    for q in percents:
        cap = full * q // 100
        r = cache.replay(t, CacheConfig(cap, window=window, score=score))
        one = cache.summarize(r).agg(F.sum("reads").alias("reads"), F.sum("hit").alias("hits"))
        saved = costs.saving(t, r, model).select("saved_share")
        rows.append(one.join(saved, how="cross").select(F.lit(q).alias("percent"), F.lit(cap).cast("long").alias("capacity_bytes"), "reads", "hits", F.round(1 - F.col("hits") / F.col("reads"), 6).alias("miss_rate"), "saved_share"))
    return stack(rows)


def score_comparison(g: Graph, percent: int = 25, p: int = 2) -> DataFrame:
    return cache.compare_scores(settle(trace.build(g, partition.block(g, p)), "trace"), percent)


def hash_law(g: Graph, percents: tuple[int, ...] = (10, 25, 50, 75), p: int = 2, alpha: float = 2.0) -> DataFrame:
    """percent, held (entries of the hot set, all parts), predicted (entries with lists times fraction^alpha)."""
    t = settle(trace.build(g, partition.block(g, p)), "trace")
    n = t.select("part", "dst").distinct().agg(F.count(F.lit(1)).alias("n"))
    rows = []
    for q in percents:
        held = cache.hot_set(t, q).agg(F.count(F.lit(1)).alias("held"))
        rows.append(held.join(n, how="cross").select(F.lit(q).alias("percent"), "held", F.round(F.col("n") * F.pow(F.lit(q / 100), F.lit(alpha)), 3).alias("predicted")))
    return stack(rows)


def timed(run: Callable[[], object], least: int = 3, most: int = 10, within: float = 0.05) -> dict[str, float]:
    """Median seconds and the 95 % interval of the median; repeats until the interval lies within 5 % of it, or ``most`` times."""
    seconds: list[float] = []
    while True:
        began = time.perf_counter()
        run()
        seconds.append(time.perf_counter() - began)
        if len(seconds) >= least:
            mid = float(np.median(seconds))
            rng = np.random.default_rng(0)
            lo, hi = np.percentile([np.median(rng.choice(seconds, len(seconds))) for _ in range(500)], [2.5, 97.5])
            if max(hi - mid, mid - lo) <= within * mid or len(seconds) >= most:
                return {"median_s": mid, "low_s": float(lo), "high_s": float(hi), "runs": len(seconds)}


def throughput(g: Graph, kernels: tuple[str, ...] = ("hybrid", "merge", "search", "tuned"), repeats: int = 3, tasks: int = 8) -> list[dict[str, float | str]]:
    """Arcs per microsecond of each kernel on so many parallel tasks, each with its part's arcs and lists beside it."""
    arcs, lists = intersect.part_frames(prep.compact(g)[0], 4 * tasks)
    arcs, lists = arcs.repartition(tasks, "part").persist(), lists.repartition(tasks, "of").persist()
    n = arcs.count()
    lists.count()
    out = []
    for k in kernels:
        t = timed(lambda k=k: intersect.part_common(arcs, lists, k).agg(F.sum("common")).collect(), repeats, repeats)
        out.append({"graph": g.name, "kernel": k, "tasks": tasks, "edges_per_us": n / t["median_s"] / 1e6, **t})
    for x in (arcs, lists):
        x.unpersist()
    return out


def scaling(g: Graph, kernel: str = "hybrid", tasks: tuple[int, ...] = (1, 2, 4, 8), repeats: int = 3) -> list[dict[str, float | str]]:
    """Throughput of one kernel as the parallel tasks grow."""
    return [throughput(g, (kernel,), repeats, t)[0] for t in tasks]


def cube(report: DataFrame, dims: list[str], value: str) -> DataFrame:
    return report.cube(*dims).agg(F.count(F.lit(1)).alias("n"), F.sum(value).alias(f"sum_{value}"), F.max(value).alias(f"max_{value}"))


def questions_by_parts(g: Graph, steps: tuple[int, ...] = (4, 8, 16), buffer_bytes: int = 1 << 16) -> DataFrame:
    """p, questions, bytes, rounds of the query-response baseline with bounded buffers."""
    g, index = kept(g), settle(prep.dense_index(prep.vertices(g)), "index")
    rows = []
    for p in steps:
        m = baselines.query_messages(g, partition.block(g, p, index), buffer_bytes)
        rows.append(m.agg(F.sum("questions").alias("questions"), F.sum("bytes").alias("bytes"), F.max("rounds").alias("rounds")).select(F.lit(p).alias("p"), "*"))
    return stack(rows)
