"""Interpolated Kneser-Ney character models, one for each class, over shared sorted hash arrays.

Words are the unit: a gram is a run of characters of ``<word>`` with its two boundary marks. Highest-order (and word-initial) grams have
their counts, all others the number of distinct characters before them. Counts, continuation counts, discounts and context sums are plain
aggregates over all grams, without a bound; probabilities come from them by the recursion, lowest order first.

Two ways of scoring give the same results. For a model of at most ``MODEL_BYTES`` one task works out the log probability of each gram and
the back-off weight of each context; these are sent to the workers in sorted hash arrays, one pair for each order, and each worker scores its
texts by binary search, longest gram first. A larger model stays distributed: texts are cut into words once and kept as codes,
batches of the distinct words ask for the rows of their own grams, and chunks of texts ask for the scores of their own words.

With ``shared=True`` only word-initial grams are counted for each class (up to ``order`` characters, so they hold whole stems); grams
inside words, up to ``free`` characters, are estimated from all classes together. An expression that a class hardly knows then backs off
to the same probability under each, and only what a class really prefers tells them apart.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise, release

BEGIN, FINISH = "\x02", "\x03"
#: Longest word, in characters, that is taken as one unit; longer ones are cut into units of this size.
UNIT = 64
#: Bytes of a model that is put into one place at most: 24 for the hashes of a gram and 12 for each class.
MODEL_BYTES = 192 << 20
#: Pieces of text whose scores a worker remembers at most; beyond it, it starts anew.
REMEMBERED = 500_000
#: Characters of texts that share one list of words, characters that are cut up at a time, and distinct words that are scored at a time.
CHUNK = 16_000_000
SLICE = 4_000_000
BATCH = 20_000
_RNG = np.random.default_rng(20240229)
_FACTORS = (_RNG.integers(1 << 62, size=16, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)


def units(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Code points of the marked words, the index of each one's word, and its position within the unit."""
    marked, owner = [], []
    for i, w in enumerate(words):
        for at in range(0, max(len(w), 1), UNIT):
            marked.append(BEGIN + w[at : at + UNIT] + FINISH)
            owner.append(i)
    sizes = np.fromiter(map(len, marked), dtype=np.int64, count=len(marked))
    points = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    starts = np.cumsum(sizes) - sizes
    return points, np.repeat(np.array(owner, dtype=np.int64), sizes), np.arange(len(points)) - np.repeat(starts, sizes)


def gram_hashes(points: np.ndarray, order: int) -> list[np.ndarray]:
    """For n = 1..order: the hash of the n characters that end at each place (meaningless where fewer stand before)."""
    out, total = [], np.zeros(len(points), dtype=np.uint64)
    for n in range(order):
        shifted = np.zeros_like(points)
        shifted[n:] = points[: max(len(points) - n, 0)]
        total = total + (shifted + np.uint64(1)) * _FACTORS[n]
        mixed = total ^ (total >> np.uint64(29))
        out.append(mixed * np.uint64(0x9E3779B97F4A7C15) + np.uint64(n))
    return out


def gram_rows(counts: dict[int, Counter], order: int, free: int) -> Iterator[pd.DataFrame]:
    """(n, gram, suffix, context, first, k, c): gram counts of each class from its word counts. Above ``free``, only word-initial grams."""
    for k, words in counts.items():
        names = list(words)
        if not names:
            continue
        weight = np.fromiter(words.values(), dtype=np.int64, count=len(names))
        points, owner, place = units(names)
        hashes = gram_hashes(points, order)
        for n in range(1, order + 1):
            at = np.flatnonzero(place >= max(n - 1, 1) if n <= free else place == n - 1)  # the opening mark is never predicted
            g, where, back = np.unique(hashes[n - 1][at], return_index=True, return_inverse=True)
            c = np.bincount(back, weights=weight[owner[at]], minlength=len(g)).astype(np.int64)
            one = at[where]
            yield pd.DataFrame({
                "n": np.int32(n), "gram": g.view(np.int64),
                "suffix": hashes[min(n - 1, free) - 1][one].view(np.int64) if n > 1 else np.int64(0),
                "context": hashes[n - 2][one - 1].view(np.int64) if n > 1 else np.int64(0),
                "first": place[one] == n - 1, "k": np.int32(k), "c": c,
            })


def count_grams(rows: DataFrame, order: int, free: int, split: Callable[[str], list[str]], labels=None, most_words: int = 80_000) -> DataFrame:
    """Gram counts of the texts of each class: the column k (null: none) or, with ``labels``, a broadcast pair of sorted doc_ids and their classes.

    Words are counted within the partition first, so that each distinct one is cut up once.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        raw: dict[int, Counter] = {}
        for b in batches:
            of = b["k"].to_numpy(np.int64) if labels is None else classes_of(b["doc_id"], labels.value)
            for k, t in zip(of.tolist(), b["text"], strict=True):
                if k < 0:
                    continue
                known = raw.setdefault(k, Counter())
                known.update(t.split())
                if len(known) > most_words:
                    yield from gram_rows(_cleaned({k: raw.pop(k)}, split), order, free)
        yield from gram_rows(_cleaned(raw, split), order, free)
        release()

    schema = "n int, gram long, suffix long, context long, first boolean, k int, c long"
    key = "k" if labels is None else "doc_id"
    return rows.select("text", key).where(f"text IS NOT NULL AND {key} IS NOT NULL").mapInPandas(run, schema).groupBy("n", "gram", "suffix", "context", "first", "k").agg(F.sum("c").alias("c"))


def classes_of(doc_id: pd.Series, labels: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The class of each id, -1 where it has none."""
    ids, classes = labels
    if not len(ids):
        return np.full(len(doc_id), -1)
    own = doc_id.fillna(ids[0] - 1).to_numpy(np.int64)
    i = np.minimum(np.searchsorted(ids, own), len(ids) - 1)
    return np.where(ids[i] == own, classes[i], -1)


def _cleaned(raw: dict[int, Counter], split: Callable[[str], list[str]]) -> dict[int, Counter]:
    out: dict[int, Counter] = {}
    for k, words in raw.items():
        own = out[k] = Counter()
        while words:
            w, c = words.popitem()
            for x in split(w):
                own[x] += c
    return out


def _look(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(table):
        return np.zeros(len(keys), dtype=bool), np.zeros(len(keys), dtype=np.int64)
    i = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return table[i] == keys, i


def _wide(counted: DataFrame, classes: int) -> DataFrame:
    return counted.groupBy("n", "gram", "suffix", "context", "first").agg(*(F.sum(F.when(F.col("k") == k, F.col("c")).otherwise(0)).alias(f"c{k}") for k in range(classes)))


def gram_table(counted: DataFrame, order: int, free: int, classes: int, shared: bool) -> tuple[DataFrame, list[tuple]]:
    """Rows (gram, n, suffix, context, c0.., t0.., m0..) of all grams, and (letters, discounts, sum, number) of each order.

    c is what counts for the gram, t and m are the sum and the number of the counts that follow it as a context; n is null for the opening mark.
    """
    cs, ks = [f"c{k}" for k in range(classes)], range(classes)
    grams = materialise(_wide(counted, classes), "grams")
    # each gram and, below the highest free order, the grams that it ends: how many are known to each class
    own = grams.select("n", "gram", "suffix", "context", "first", *cs, *(F.lit(0).cast("long").alias(f"b{k}") for k in ks))
    ends = grams.where((F.col("n") > 1) & (F.col("n") <= free)).select((F.col("n") - 1).alias("n"), F.col("suffix").alias("gram"), F.lit(None).cast("long").alias("suffix"), F.lit(None).cast("long").alias("context"), F.lit(False).alias("first"), *(F.lit(0).cast("long").alias(c) for c in cs), *((F.col(c) > 0).cast("long").alias(f"b{k}") for k, c in enumerate(cs)))
    both = own.unionByName(ends).groupBy("n", "gram").agg(F.max("suffix").alias("suffix"), F.max("context").alias("context"), F.max("first").alias("first"), *(F.sum(x).alias(x) for k in ks for x in (f"c{k}", f"b{k}")))
    counting = {k: F.when((F.col("n") >= free) | F.col("first"), F.col(f"c{k}")).otherwise(F.col(f"b{k}")) for k in ks}
    if shared:
        every = sum((counting[k] for k in range(1, classes)), counting[0])
        counting = {k: F.when(F.col("first"), counting[k]).otherwise(every) for k in ks}
    counts = materialise(both.select("n", "gram", "suffix", "context", *(counting[k].alias(f"c{k}") for k in ks)), "counted")
    discard(grams)
    sums = counts.groupBy("n").agg(F.count(F.lit(1)).alias("rows"), *(f(c).alias(f"{x}{k}") for k, c in enumerate(cs) for x, f in (("one", lambda c: F.count_if(F.col(c) == 1)), ("two", lambda c: F.count_if(F.col(c) == 2)), ("sum", F.sum), ("kinds", lambda c: F.count_if(F.col(c) > 0)))))
    by = {r.n: r for r in sums.collect()}  # one row for each order
    orders = []
    for n in range(1, order + 1):
        one, two, total, kinds = (np.array([by[n][f"{x}{k}"] if n in by else 0 for k in ks], dtype=float) for x in ("one", "two", "sum", "kinds"))
        d = np.clip(np.where(one > 0, one / np.maximum(one + 2 * two, 1), 0.5), 0.1, 0.95)
        orders.append(((by[n].rows if n in by else 0) + 1, d, total, kinds))
    zeros = [F.lit(0).cast("long").alias(f"{x}{k}") for x in "tm" for k in ks]
    none = (F.lit(None).cast("int").alias("n"), F.lit(None).cast("long").alias("suffix"), F.lit(None).cast("long").alias("context"))
    follow = counts.where("n > 1").select(F.col("context").alias("gram"), *none, *(F.lit(0).cast("long").alias(c) for c in cs), *(F.col(c).alias(f"t{k}") for k, c in enumerate(cs)), *((F.col(c) > 0).cast("long").alias(f"m{k}") for k, c in enumerate(cs)))
    table = materialise(counts.select("gram", "n", "suffix", "context", *cs, *zeros).unionByName(follow).groupBy("gram").agg(*(F.max(x).alias(x) for x in ("n", "suffix", "context")), *(F.sum(f"{x}{k}").alias(f"{x}{k}") for x in "ctm" for k in ks)), "model")
    discard(counts)
    return table, orders


def _places(place: np.ndarray, n: int, free: int) -> np.ndarray:
    return np.flatnonzero(place >= max(n - 1, 1) if n <= free else place == n - 1)


def log_probabilities(points: np.ndarray, place: np.ndarray, table: np.ndarray, rows: np.ndarray, orders: list[tuple], free: int) -> np.ndarray:
    """Log probability of each character under each class (0 for opening marks), from rows (c, t, m) of sorted gram hashes."""
    order, classes = len(orders), len(orders[0][1])
    hashes = gram_hashes(points, order)
    p = np.full((len(points), classes), 1.0 / max(orders[0][0], 2))
    found, i = _look(table, hashes[0])
    known = np.where(found, i, -1)  # the row of the gram of the order below that ends at each place
    for n in range(1, order + 1):
        at = _places(place, n, free)
        d, total, kinds = orders[n - 1][1:]
        if n > 1:
            at = at[known[at - 1] >= 0]  # without its context, a gram is unknown and the order below holds
            before = rows[known[at - 1], classes:]
            total, kinds = before[:, :classes], before[:, classes:]
            found, i = _look(table, hashes[n - 1][at])
            known = np.full(len(points), -1)
            known[at] = np.where(found, i, -1)
        c = np.where(known[at, None] >= 0, rows[known[at], :classes], 0)
        some = np.maximum(total, 1)
        p[at] = np.where(total > 0, np.maximum(c - d, 0) / some + d * kinds / some * p[at], p[at])
    return np.where(place[:, None] >= 1, np.log(np.maximum(p, 1e-300)), 0.0)


def word_sums(words: list[str], table: np.ndarray, rows: np.ndarray, orders: list[tuple], free: int) -> np.ndarray:
    """Summed log probabilities of each word under each class and, last, its predicted characters."""
    points, owner, place = units(words)
    p = log_probabilities(points, place, table, rows, orders, free)
    return np.stack([*(np.bincount(owner, weights=p[:, k], minlength=len(words)) for k in range(p.shape[1])), np.bincount(owner, weights=place >= 1, minlength=len(words))], axis=1)


@dataclass
class Model:
    free: int
    grams: list[np.ndarray]  # for each order: sorted hashes
    logp: list[np.ndarray]  # for each order: rows of log probabilities
    contexts: list[np.ndarray]  # for each order: sorted hashes of its contexts
    backoff: list[np.ndarray]  # and their log back-off weights
    unknown: np.ndarray  # log probability of a character that no class has seen

    def positions(self, points: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Log probability of each character under each class (0 for opening marks)."""
        order = len(self.grams)
        hashes = gram_hashes(points, order)
        out = np.zeros((len(points), len(self.unknown)))
        open_ = np.flatnonzero(place >= 1)
        for n in range(order, 0, -1):
            fit = place[open_] >= n - 1 if n <= self.free else place[open_] == n - 1
            at = open_[fit]
            found, i = _look(self.grams[n - 1], hashes[n - 1][at])
            out[at[found]] += self.logp[n - 1][i[found]]
            missed = at[~found]
            if n > 1:
                known, j = _look(self.contexts[n - 1], hashes[n - 2][missed - 1])
                out[missed[known]] += self.backoff[n - 1][j[known]]
            else:
                out[missed] += self.unknown
            open_ = np.concatenate([open_[~fit], missed])
        return out

    def words(self, words: list[str]) -> np.ndarray:
        """Summed log probabilities of each word under each class and, last, its predicted characters."""
        points, owner, place = units(words)
        p = self.positions(points, place)
        return np.stack([*(np.bincount(owner, weights=p[:, k], minlength=len(words)) for k in range(p.shape[1])), np.bincount(owner, weights=place >= 1, minlength=len(words))], axis=1)


def fit(table: DataFrame, orders: list[tuple], free: int) -> Model:
    """The model of a table of bounded size: one task works it out, the driver gets its arrays (a row for each order)."""
    order, classes = len(orders), len(orders[0][1])
    kinds = {x: np.float32 for x in (f"{x}{k}" for x in "ctm" for k in range(classes))}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(b.column("gram").to_numpy(), b.column("n").fill_null(0).to_numpy(), b.column("suffix").fill_null(0).to_numpy(), b.column("context").fill_null(0).to_numpy(), np.stack([b.column(x).to_numpy().astype(t) for x, t in kinds.items()], axis=1)) for b in batches]
        gram, n_of, suffix, context, rows = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (*[np.zeros(0, dtype=np.int64)] * 4, np.zeros((0, 3 * classes)))
        gram, suffix, context = (x.view(np.uint64) for x in (gram, suffix, context))
        sort = np.argsort(gram)
        gram, n_of, suffix, context, rows = (x[sort] for x in (gram, n_of, suffix, context, rows))
        p = np.zeros((len(gram), classes))
        for n in range(1, order + 1):
            at = np.flatnonzero(n_of == n)
            letters, d, total, many = orders[n - 1]
            below = 1.0 / max(orders[0][0], 2)
            heads, weights = np.zeros(0, dtype=np.uint64), np.zeros((0, classes), dtype=np.float32)
            if n > 1:
                before = rows[np.searchsorted(gram, context[at]), classes:].astype(float)
                total, many = before[:, :classes], before[:, classes:]
                below = p[np.searchsorted(gram, suffix[at])]
                heads, first = np.unique(context[at], return_index=True)
                with np.errstate(divide="ignore"):
                    weights = np.log(np.where(total[first] > 0, d * many[first] / np.maximum(total[first], 1), 1.0)).astype(np.float32)
            p[at] = np.where(total > 0, np.maximum(rows[at, :classes] - d, 0) / np.maximum(total, 1) + d * many / np.maximum(total, 1) * below, below)
            yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int32()), "grams": [gram[at].tobytes()], "logp": [np.log(np.maximum(p[at], 1e-300)).astype(np.float32).tobytes()], "contexts": [heads.tobytes()], "backoff": [weights.tobytes()]})

    found = sorted(table.coalesce(1).mapInArrow(run, "n int, grams binary, logp binary, contexts binary, backoff binary").collect())
    letters, d, total, many = orders[0]
    unknown = np.log(np.where(total > 0, d * many / np.maximum(total, 1), 1.0) / max(letters, 2))
    hashes, values = (lambda x: np.frombuffer(x, dtype=np.uint64)), (lambda x: np.frombuffer(x, dtype=np.float32).reshape(-1, classes))
    return Model(free, [hashes(r.grams) for r in found], [values(r.logp) for r in found], [hashes(r.contexts) for r in found], [values(r.backoff) for r in found], unknown)


class Remembered:
    """Rows of the white-space pieces that a worker has met: a log probability for each class, and predicted characters."""

    def __init__(self, model: Model, split: Callable[[str], list[str]]):
        self.model, self.split = model, split
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.rows = np.zeros((1024, len(self.model.unknown) + 1), dtype=np.float32)
        self.used = 0

    def learn(self, pieces: list[str]) -> None:
        """A piece of one word shares its row, other pieces get the sum of their words."""
        index = self.index
        parts = [self.split(p) for p in pieces]
        words = list({w for ws in parts for w in ws}.difference(index))
        if words:
            self._add(words, self.model.words(words))
        others = [(p, ws) for p, ws in zip(pieces, parts, strict=True) if len(ws) != 1]
        index.update((p, index[ws[0]]) for p, ws in zip(pieces, parts, strict=True) if len(ws) == 1)
        if others:
            flat = np.fromiter((index[w] for _, ws in others for w in ws), dtype=np.int64)
            back = np.repeat(np.arange(len(others)), np.fromiter((len(ws) for _, ws in others), dtype=np.int64, count=len(others)))
            self._add([p for p, _ in others], np.stack([np.bincount(back, weights=self.rows[flat, j], minlength=len(others)) for j in range(self.rows.shape[1])], axis=1))

    def _add(self, names: list[str], own: np.ndarray) -> None:
        first = self.used
        while first + len(names) > len(self.rows):
            self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
        self.rows[first : first + len(names)] = own
        self.used = first + len(names)
        self.index.update(zip(names, range(first, self.used), strict=True))

    def texts(self, texts: list[str]) -> Iterator[np.ndarray]:
        """For each text, the rows of its pieces in order."""
        at = 0
        while at < len(texts):
            group, size = [], 0
            while at < len(texts) and size < SLICE:
                group.append(texts[at].split())
                size, at = size + len(texts[at]), at + 1
            fresh = set().union(*group).difference(self.index)
            if len(self.index) + len(fresh) > REMEMBERED:
                self.clear()
                fresh = set().union(*group)
            fresh = list(fresh)
            for i in range(0, len(fresh), BATCH):
                self.learn(fresh[i : i + BATCH])
            for g in group:
                yield self.rows[np.fromiter(map(self.index.__getitem__, g), dtype=np.int64, count=len(g))]


def encode(rows: DataFrame, carried: list[str], split: Callable[[str], list[str]]) -> DataFrame:
    """Texts as codes of words, in chunks: rows (chunk, carried columns, codes) and, for each distinct word of the chunk, rows (chunk, key, code).

    A white-space piece counts as the words that ``split`` finds in it, joined by blanks.
    """
    names = ["chunk", *carried, "codes", "key", "code"]
    schema = ", ".join(["chunk long", *(f"{c} {rows.schema[c].dataType.simpleString()}" for c in carried), "codes binary", "key string", "code int"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk, size = TaskContext.get().partitionId() << 24, 0
        index: dict[str, int] = {}  # piece to code
        keys: dict[str, int] = {}

        def batch(m: int, own: dict, like: pa.RecordBatch) -> pa.RecordBatch:
            kinds = [pa.int64(), *(like.schema.field(c).type for c in carried), pa.binary(), pa.string(), pa.int32()]
            own["chunk"] = pa.array(np.full(m, chunk))
            return pa.RecordBatch.from_arrays([own[x] if x in own else pa.nulls(m, t) for x, t in zip(names, kinds, strict=True)], names=names)

        def ended(like: pa.RecordBatch) -> pa.RecordBatch:
            return batch(len(keys), {"key": pa.array(list(keys), pa.string()), "code": pa.array(np.arange(len(keys), dtype=np.int32))}, like)

        b = None
        for b in batches:
            texts = b.column("text")
            at = 0
            while at < len(b):
                first, chars, pieces = at, 0, []
                while at < len(b) and chars < SLICE:
                    t = texts[at].as_py() or ""
                    pieces.append(t.split())
                    chars, at = chars + len(t), at + 1
                for p in set().union(*pieces).difference(index):
                    index[p] = keys.setdefault(" ".join(split(p)), len(keys))
                codes = [np.fromiter(map(index.__getitem__, g), dtype=np.int32, count=len(g)) for g in pieces]
                yield batch(at - first, {c: b.column(c).slice(first, at - first) for c in carried} | {"codes": pa.array([c.tobytes() for c in codes], pa.binary())}, b)
                size += chars
                if size > CHUNK:
                    yield ended(b)
                    index, keys = {}, {}
                    chunk, size = chunk + 1, 0
        if b is not None and keys:
            yield ended(b)
        release()

    return materialise(rows.select(*carried, "text").mapInArrow(run, schema), "codes")


def word_batches(coded: DataFrame) -> DataFrame:
    """key, batch of every distinct key of the corpus; a batch holds neighbours in alphabetical order, which share their first grams."""
    words = materialise(coded.where("key IS NOT NULL").select("key").distinct(), "words")
    n = max(1, -(-words.count() // BATCH))
    batches = materialise(words.repartitionByRange(n, "key").withColumn("batch", F.spark_partition_id()), "batches")
    discard(words)
    return batches


def asked(words: DataFrame, order: int, free: int) -> DataFrame:
    """(batch, gram): the grams that a batch of words needs, once each."""

    def needed(i: int, keys: list[str]) -> pd.DataFrame:
        points, _, place = units([w for key in keys for w in key.split(" ")])
        hashes = gram_hashes(points, order)
        # contexts are grams of the place before; only the opening mark isn't among them
        need = np.unique(np.concatenate([hashes[0][place == 0], *(hashes[n - 1][_places(place, n, free)] for n in range(1, order + 1))]))
        return pd.DataFrame({"batch": np.int32(i), "gram": need.view(np.int64)})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: tuple[int, list[str]] | None = None
        for b in batches:
            for i, own in b.groupby("batch"):
                if held and held[0] != i:
                    yield needed(*held)
                    held = None
                held = held or (i, [])
                held[1].extend(own["key"])
        if held:
            yield needed(*held)
        release()

    return words.select("batch", "key").sortWithinPartitions("batch").mapInPandas(run, "batch int, gram long")


def word_scores(words: DataFrame, table: DataFrame, orders: list[tuple], free: int) -> DataFrame:
    """key, s0.. (summed log probabilities under each class), chars (predicted characters)."""
    order, classes = len(orders), len(orders[0][1])
    answers = asked(words, order, free).join(table.drop("n", "suffix", "context"), "gram").withColumnRenamed("batch", "of")  # cogroup takes no name twice

    def run(own: pa.Table, known: pa.Table) -> pa.Table:
        keys = own["key"].to_pylist()
        parts = [key.split(" ") if key else [] for key in keys]
        sums = np.zeros((len(keys), classes + 1))
        flat = [w for ws in parts for w in ws]
        if flat:
            grams = known["gram"].to_numpy().view(np.uint64)
            sort = np.argsort(grams)
            rows = np.stack([known[f"{x}{k}"].to_numpy() for x in "ctm" for k in range(classes)], axis=1)[sort].astype(float)
            back = np.repeat(np.arange(len(keys)), list(map(len, parts)))
            each = word_sums(flat, grams[sort], rows, orders, free)
            sums = np.stack([np.bincount(back, weights=each[:, j], minlength=len(keys)) for j in range(classes + 1)], axis=1)
        return pa.table({"key": pa.array(keys, pa.string())} | {f"s{k}": sums[:, k] for k in range(classes)} | {"chars": pa.array(sums[:, -1].astype(np.int64), pa.int64())})

    schema = ", ".join(["key string", *(f"s{k} double" for k in range(classes)), "chars long"])
    return words.select("batch", "key").groupBy("batch").cogroup(answers.groupBy("of")).applyInArrow(run, schema)


def scored(rows: DataFrame, carried: list[str], order: int, free: int, classes: int, shared: bool, split: Callable[[str], list[str]], measure: Callable[[Iterator[np.ndarray]], pa.Table], schema: str, labels=None) -> DataFrame:
    """The carried columns of (text, carried, k or doc_id) rows and what ``measure`` returns for their texts under the model of the labelled ones.

    ``measure`` gets, for each text, the rows of its pieces in order: a log probability for each class, then predicted characters.
    """
    table, orders = gram_table(count_grams(rows, order, free, split, labels), order, free, classes, shared)
    head = ", ".join(f"{c} {rows.schema[c].dataType.simpleString()}" for c in carried)
    schema = f"{head}, {schema}"
    with_carried = lambda docs, found: pa.table({c: docs[c] for c in carried} | {c: found[c] for c in found.column_names})
    if table.count() * (24 + 12 * classes) <= MODEL_BYTES:
        sent = rows.sparkSession.sparkContext.broadcast(fit(table, orders, free))
        discard(table)

        def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known = Remembered(sent.value, split)
            for b in batches:
                found = measure(known.texts([t or "" for t in b.column("text").to_pylist()]))
                yield from with_carried(pa.Table.from_batches([b]), found).combine_chunks().to_batches()
            release()

        return rows.select(*carried, "text").mapInArrow(whole, schema)
    coded = encode(rows, carried, split)
    words = word_batches(coded)
    scores = materialise(word_scores(words, table, orders, free), "scores")
    discard(words)
    names = [*(f"s{k}" for k in range(classes)), "chars"]
    own = coded.where("key IS NOT NULL").select("chunk", "key", "code").join(scores, "key").select(F.col("chunk").alias("of"), "code", *names)
    texts = coded.where("key IS NULL").select("chunk", *carried, "codes")

    def chunked(docs: pa.Table, known: pa.Table) -> pa.Table:
        table = np.zeros((len(known), classes + 1), dtype=np.float32)
        table[known["code"].to_numpy()] = np.stack([known[x].to_numpy() for x in names], axis=1)
        return with_carried(docs, measure(table[np.frombuffer(c.as_py(), dtype=np.int32)] for c in docs["codes"]))

    return texts.groupBy("chunk").cogroup(own.groupBy("of")).applyInArrow(chunked, schema)
