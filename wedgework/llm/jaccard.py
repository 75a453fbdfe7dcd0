"""N-gram Jaccard join by filters under several global orders, and the components of its links.

Sets are distinct 64-bit hashes of word shingles; documents with equal sets form a class, and classes are joined. Two sets of similarity t
or more share a token among their first ``n - ceil(t n) + 1`` tokens under any global order of all tokens, so:

1. Order 1 is rare tokens first: by the number of tokens, over all documents, in a token's hash bucket, then by hash. Prefix tokens are
   shuffled once and sorted; a token's rows are its list.
2. Lists of at most ``SMALL`` classes give their pairs, which are counted: the number of prefix tokens that a pair shares must do for the
   similarity. In longer lists each class first meets one pivot of its lists, twice, which connects most of a group of near copies at one
   comparison a member. Lists that still hold several components are cut into blocks of bounded size, ordered by component and set size,
   and blocks that can hold similar sets of different components meet in one group each. A group emits a spanning forest of the links
   that it finds instead of pairs, so a large group of near copies makes rows in proportion to its members, and no group grows with a list.
   Lists of hot tokens, and the meetings of long lists with their pivots, are dealt over many tasks, as are the blocks of very long lists.
3. The pairs of both ways must also share enough prefix tokens under orders 2 and 3 (hash ascending and descending), before whole sets
   meet. Then the intersection is counted exactly.
4. Components come from contraction rounds over the links.

Nothing is capped: every pair of a list is counted, connected before, or lies in exactly one pair of blocks of that list.

Defined results: a text without words (or null) has the empty set and is linked with nothing; texts of fewer words than a shingle are one
shingle; repeated rows are copies; a row without id gets the least id of its component (null, if none has one); other columns are ignored. The hashes are 64 bits wide.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, load, materialise, numbered, release, without

#: Buckets of the token counts that make order 1, and of one row of a partition's counts.
BUCKETS = 1 << 20
ROW = 1 << 12
#: Classes of a list that gives pairs, and classes and tokens of a block of a longer one (a set of more tokens is a block of its own).
SMALL = 48
BLOCK, BLOCK_TOKENS = 512, 1 << 18
#: Rounds in which each class meets one pivot of its long lists.
STARS = 2
#: A token whose bucket holds so many more tokens than four times the mean is dealt over ``SALTS`` tasks, as is a long list's meeting with its pivot.
HOT_ROWS, SALTS = 200_000, 64
#: Bits of the filter of candidate classes at most (64 MB): beyond it more sets are sent, none is missed.
FILTER_BITS = 29
_K = np.uint64(0x9E3779B97F4A7C15)


#: Base of the rolling sums over bytes (odd, so that it has an inverse modulo 2^64), and how many of its powers are kept.
_BASE = 0x5851F42D4C957F2D
_PIECE = 1 << 18


def _powers(base: int) -> np.ndarray:
    out = np.empty(_PIECE, dtype=np.uint64)
    out[0] = 1
    at = 1
    while at < _PIECE:  # doubling: the powers so far times base^at
        n = min(at, _PIECE - at)
        out[at : at + n] = out[:n] * np.uint64(pow(base, at, 1 << 64))
        at += n
    return out


_UP, _DOWN = _powers(_BASE), _powers(pow(_BASE, -1, 1 << 64))
_BYTES = np.random.default_rng(71).integers(1 << 63, size=256, dtype=np.uint64)
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[9, 10, 11, 12, 13, 32]] = True


def word_hashes(text: bytes) -> np.ndarray:
    """64-bit hashes of the words of a byte string: sums of byte values times powers, from one running sum."""
    out = []
    at = 0
    while at < len(text):
        end = min(at + _PIECE, len(text))
        if end < len(text):  # cut after the last space of the piece; a word longer than a piece is hashed whole
            cut = max(text.rfind(bytes([c]), at, end) for c in (9, 10, 11, 12, 13, 32))
            end = cut + 1 if cut >= at else next((i for i in range(end, len(text)) if _IS_SPACE[text[i]]), len(text))
        b = np.frombuffer(text, dtype=np.uint8, count=end - at, offset=at)
        at = end
        if len(b) > _PIECE:
            out.append(np.array([xxhash.xxh3_64_intdigest(b.tobytes())], dtype=np.uint64))
            continue
        word = np.zeros(len(b) + 2, dtype=bool)
        np.logical_not(_IS_SPACE[b], out=word[1:-1])
        edge = np.flatnonzero(word[1:] != word[:-1])
        first, last = edge[::2], edge[1::2]
        if not len(first):
            continue
        run = np.zeros(len(b) + 1, dtype=np.uint64)
        np.cumsum(_BYTES[b] * _UP[: len(b)], out=run[1:])
        h = (run[last] - run[first]) * _DOWN[first] + (last - first).astype(np.uint64)
        h ^= h >> np.uint64(31)
        h *= np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(30)
        out.append(h)
    return out[0] if len(out) == 1 else np.concatenate([np.zeros(0, dtype=np.uint64), *out])


def token_set(text: str | None, k: int) -> np.ndarray:
    """Sorted distinct shingle hashes."""
    h = word_hashes((text or "").encode("utf-8", "surrogatepass").lower())  # bytes: A-Z and ASCII white space only
    if not len(h):
        return h
    if len(h) < k:
        return np.array([xxhash.xxh3_64_intdigest(h.tobytes(), seed=len(h))], dtype=np.uint64)
    x = h[: len(h) - k + 1].copy()
    for j in range(1, k):
        x ^= x >> np.uint64(32)
        x *= _K
        x += h[j : len(h) - k + 1 + j]
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    x.sort()
    return x[np.concatenate([[True], x[1:] != x[:-1]])]


def class_of(tokens: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(tokens.tobytes(), seed=len(tokens)) - (1 << 63)


def prefix_size(n, percent: int):
    return n - -(-percent * n // 100) + 1


def least_size(percent: int) -> int:
    """Smallest set that can reach the similarity with a different one."""
    n = 1
    while 100 * n < percent * (n + 1):
        n += 1
    return n


def bucket_of(tokens: np.ndarray) -> np.ndarray:
    return ((tokens >> np.uint64(32)) & np.uint64(BUCKETS - 1)).astype(np.int64)


def sets_pass(docs: DataFrame, k: int, carried: list[str]) -> DataFrame:
    """The carried columns, n and cls of each document, and (where block isn't null) rows of the partition's token counts by bucket."""
    head = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in carried)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(BUCKETS, dtype="<u4")
        like = None
        for b in batches:
            n, cls, found, size = [], [], [], 0
            for t in b.column("text"):
                s = token_set(t.as_py(), k)
                n.append(len(s))
                cls.append(class_of(s) if len(s) else None)
                found.append(bucket_of(s).astype(np.int32))
                size += len(s)
                if size > 2_000_000:
                    counts += np.bincount(np.concatenate(found), minlength=BUCKETS).astype("<u4")
                    found, size = [], 0
            if found:
                counts += np.bincount(np.concatenate(found), minlength=BUCKETS).astype("<u4")
            like = [b.schema.field(c).type for c in carried]
            yield row(len(b), [b.column(c) for c in carried], {"n": pa.array(n, pa.int64()), "cls": pa.array(cls, pa.int64())}, like)
        used = [i for i in range(BUCKETS // ROW) if counts[i * ROW : (i + 1) * ROW].any()]
        if used:
            m, salt = len(used), TaskContext.get().partitionId() % 256
            yield row(m, [pa.nulls(m, t) for t in like], {"block": pa.array(used, pa.int32()), "salt": pa.array([salt] * m, pa.int32()), "counts": pa.array([counts[i * ROW : (i + 1) * ROW].tobytes() for i in used], pa.binary())}, like)
        release()

    rest = {"n": pa.int64(), "cls": pa.int64(), "block": pa.int32(), "salt": pa.int32(), "counts": pa.binary()}

    def row(m: int, first: list, own: dict, like: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*first, *(own.get(x, pa.nulls(m, t)) for x, t in rest.items())], names=[*carried, *rest])

    return docs.select(*carried, "text").mapInArrow(run, f"{head}, n long, cls long, block int, salt int, counts binary")


def bucket_counts(first: DataFrame) -> np.ndarray:
    """Tokens of each bucket over all documents: rows of counts are added up in two steps; the driver gets one row for each block."""

    def add(rows: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(ROW, dtype="<u8")
        for c in rows["counts"]:
            total += np.frombuffer(c, dtype="<u4")
        return pd.DataFrame({"block": rows["block"].iloc[:1], "counts": [np.minimum(total, 0xFFFFFFFF).astype("<u4").tobytes()]})

    rows = first.where("block IS NOT NULL").select("block", "salt", "counts")
    once = rows.groupBy("block", "salt").applyInPandas(add, "block int, counts binary")
    counts = np.zeros(BUCKETS, dtype=np.uint32)
    for r in once.groupBy("block").applyInPandas(add, "block int, counts binary").collect():  # BUCKETS / ROW rows
        counts[r.block * ROW : (r.block + 1) * ROW] = np.frombuffer(r.counts, dtype="<u4")
    return counts


def prefixes(docs: DataFrame, sent, k: int, percent: int) -> DataFrame:
    """(token, salt, n, cls) for the prefix of each set under order 1; a class is sent once for each partition. The salt is -1 but for hot tokens."""
    least = least_size(percent)
    hot = HOT_ROWS + 4 * float(sent.value.mean())

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: set[int] = set()
        for b in batches:
            tokens, often, cls, size = [], [], [], []
            for t in b["text"]:
                s = token_set(t, k)
                n = len(s)
                if n < least or (c := class_of(s)) in seen:
                    continue
                if len(seen) < 500_000:  # beyond it a class may be sent again, which changes nothing
                    seen.add(c)
                f = sent.value[bucket_of(s)]
                first = np.argsort(f, kind="stable")[: prefix_size(n, percent)]
                tokens.append(s[first])
                often.append(np.where(f[first] > hot, c % SALTS, -1).astype(np.int32))
                cls.append(c)
                size.append(n)
            many = list(map(len, tokens))
            yield pd.DataFrame({"salt": np.concatenate([np.zeros(0, dtype=np.int32), *often]), "token": np.concatenate(tokens or [np.zeros(0, dtype=np.uint64)]).view(np.int64), "n": np.repeat(np.array(size, dtype=np.int32), many), "cls": np.repeat(np.array(cls, dtype=np.int64), many)})
        release()

    return docs.select("text").mapInPandas(run, "salt int, token long, n int, cls long")


def possible(na, nb, shared, percent: int):
    """Can sets of these sizes be similar enough if their prefixes have at most ``shared`` tokens in common?

    Whichever prefix ends first under the order, its tokens in the other set all lie in the other prefix; so the overlap is at most the
    common prefix tokens and the rest of that set.
    """
    large, small = np.maximum(na, nb), np.minimum(na, nb)
    overlap = -(-percent * (na + nb) // (100 + percent))
    return (100 * small >= percent * large) & (shared >= overlap - -(-percent * large // 100) + 1)


def possible_sql(shared: str, percent: int) -> str:
    """``possible`` over columns na, nb; in integers, as a quotient of doubles could round up."""
    return f"100 * least(na, nb) >= {percent} * greatest(na, nb) AND {shared} >= ({percent} * (na + nb) + {99 + percent}) DIV {100 + percent} - ({percent} * greatest(na, nb) + 99) DIV 100 + 1"


def list_pass(entries: DataFrame, percent: int) -> DataFrame:
    """Rows of two kinds: pairs (a, b, na, nb) of the short lists, once for each list; rows (token, a, na) of the long ones.

    Lists come sorted, so at most ``SMALL`` rows of a list are held. The lists of hot tokens come in pieces and are long.
    """

    def pairs(n: np.ndarray, c: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> Iterator[pd.DataFrame]:
        for m in np.unique(sizes):
            if m < 2:
                continue
            x, y = np.triu_indices(m, 1)
            own = starts[sizes == m]
            step = max(1, 500_000 // len(x))
            for at in range(0, len(own), step):
                i, j = ((own[at : at + step, None] + z[None, :]).ravel() for z in (x, y))
                ok = 100 * n[i].astype(np.int64) >= percent * n[j].astype(np.int64)  # a list ascends by n
                i, j = i[ok], j[ok]
                yield pd.DataFrame({"token": pd.Series([None] * len(i), dtype="Int64"), "a": c[i], "b": c[j], "na": n[i], "nb": n[j]})

    def whole(t: np.ndarray, n: np.ndarray, c: np.ndarray) -> pd.DataFrame:
        none = pd.Series([None] * len(n), dtype="Int64")
        return pd.DataFrame({"token": t, "a": c, "b": none, "na": n, "nb": none.astype("Int32")})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, passing = None, None  # the rows of the last list, and the long list that is passing

        def lists(t: np.ndarray, h: np.ndarray, n: np.ndarray, c: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> Iterator[pd.DataFrame]:
            large = (sizes > SMALL) | (h[starts] >= 0) | (t[starts] == passing if passing is not None else False)
            yield from pairs(n, c, starts[~large], sizes[~large])
            rows = np.repeat(large, sizes)
            at = slice(starts[0], starts[-1] + sizes[-1]) if len(starts) else slice(0, 0)
            if rows.any():
                yield whole(t[at][rows], n[at][rows], c[at][rows])

        for b in batches:
            t, h, n, c = b["token"].to_numpy(np.int64), b["salt"].to_numpy(np.int32), b["n"].to_numpy(np.int32), b["cls"].to_numpy(np.int64)
            if held is not None:
                t, h, n, c = (np.concatenate([x, y]) for x, y in zip(held, (t, h, n, c), strict=True))
            if not len(t):
                continue
            new = np.concatenate([[True], (t[1:] != t[:-1]) | (c[1:] != c[:-1])])
            t, h, n, c = t[new], h[new], n[new], c[new]
            starts = np.flatnonzero(np.concatenate([[True], t[1:] != t[:-1]]))
            sizes = np.diff(np.append(starts, len(t)))
            last = starts[-1]
            yield from lists(t, h, n, c, starts[:-1], sizes[:-1])
            if sizes[-1] > SMALL + 1 or t[last] == passing:  # all but its last row pass; that one tells repeated rows
                yield whole(t[last:-1], n[last:-1], c[last:-1])
                passing, last = t[last], len(t) - 1
            held = (t[last:], h[last:], n[last:], c[last:])
        if held is not None and len(held[0]):
            yield from lists(*held, np.array([0]), np.array([len(held[0])]))

    return entries.repartition("token", "salt").sortWithinPartitions("token", "salt", "n", "cls").mapInPandas(run, "token long, a long, b long, na int, nb int")


def star_pairs(rows: DataFrame, r: int, percent: int) -> DataFrame:
    """One pair (a, b, na, nb) for each class b at most: with the pivot that most of its lists have. Pivots are the lists' first classes by a hash of the round."""
    pivot = rows.groupBy("token").agg(F.min_by(F.struct("cls", "n"), F.xxhash64("cls", F.lit(r))).alias("p")).select("token", F.col("p.cls").alias("a"), F.col("p.n").alias("na"))
    salted = pivot.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS // 4 - 1))))
    met = rows.withColumn("salt", F.pmod("cls", F.lit(SALTS // 4)).cast("int")).join(salted, ["token", "salt"]).where(f"cls != a AND 100 * least(n, na) >= {percent} * greatest(n, na)")
    best = met.groupBy("cls", "n", "a", "na").agg(F.count(F.lit(1)).alias("c")).groupBy(F.col("cls").alias("b"), F.col("n").alias("nb")).agg(F.max_by(F.struct("a", "na"), "c").alias("p"))
    return best.select(F.col("p.a").alias("a"), "b", F.col("p.na").alias("na"), "nb")


def blocks_of(rows: DataFrame) -> DataFrame:
    """Adds the block of each row (token, cls, n, label, and many: its list's rows) in its list: runs of bounded size in the order of label and n, so most blocks have one label.

    A list of more rows than ``SALTS`` blocks hold is dealt over several tasks.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        token, block, many, size = None, 0, 0, 0
        for b in batches:
            of = np.empty(len(b), dtype=np.int64)
            for i, (t, h, n) in enumerate(zip(b["token"].tolist(), b["salt"].tolist(), b["n"].tolist(), strict=True)):
                if (t, h) != token:
                    token, block, many, size = (t, h), h << 32, 0, 0
                elif many == BLOCK or size + n > BLOCK_TOKENS:
                    block, many, size = block + 1, 0, 0
                many, size, of[i] = many + 1, size + n, block
            yield b.drop(columns="salt").assign(block=of)

    dealt = rows.select("token", "cls", "n", "label", F.pmod("cls", F.expr(f"many div {BLOCK * SALTS} + 1")).alias("salt"))
    return dealt.repartition("token", "salt").sortWithinPartitions("token", "salt", "label", "n", "cls").mapInPandas(run, "token long, cls long, n int, label long, block long")


def candidate_filter(classes: DataFrame) -> np.ndarray:
    """A Bloom filter of the classes as 64-bit words; built in pieces, the driver gets one row for each."""
    bits = min(FILTER_BITS, max(18, (16 * classes.count()).bit_length()))
    words = np.zeros(1 << (bits - 6), dtype=np.uint64)

    def fill(rows: pd.DataFrame) -> pd.DataFrame:
        own = np.zeros(ROW, dtype=np.uint64)
        x = rows["x"].to_numpy(np.int64) & (ROW * 64 - 1)
        np.bitwise_or.at(own, x >> 6, np.uint64(1) << (x & 63).astype(np.uint64))
        return pd.DataFrame({"piece": rows["piece"].iloc[:1], "words": [own.tobytes()]})

    at = F.explode(F.array(F.col("cls").bitwiseAND(F.lit((1 << bits) - 1)), F.shiftrightunsigned("cls", 64 - bits)))
    placed = classes.select(at.alias("x")).select("x", F.shiftright("x", 18).alias("piece")).distinct()
    for r in placed.groupBy("piece").applyInPandas(fill, "piece long, words binary").collect():
        words[r.piece * ROW : (r.piece + 1) * ROW] = np.frombuffer(r.words, dtype=np.uint64)
    return words


def candidate_sets(docs: DataFrame, sent, k: int, percent: int) -> DataFrame:
    """cls, n, tokens (sorted) of the classes that pass the filter, one row each."""
    least, bits = least_size(percent), int(len(sent.value)).bit_length() - 1 + 6

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known, seen = sent.value, set()
        for b in batches:
            rows = []
            for t in b["text"]:
                s = token_set(t, k)
                if len(s) < least or (c := class_of(s)) in seen:
                    continue
                u = c & ((1 << 64) - 1)
                x, y = u & ((1 << bits) - 1), u >> (64 - bits)
                if not (int(known[x >> 6]) >> (x & 63) & 1 and int(known[y >> 6]) >> (y & 63) & 1):
                    continue
                if len(seen) < 500_000:
                    seen.add(c)
                rows.append((c, len(s), s.view(np.int64)))
            yield pd.DataFrame(rows, columns=["cls", "n", "tokens"])
        release()

    found = docs.select("text").mapInPandas(run, "cls long, n int, tokens array<long>")
    return found.groupBy("cls").agg(F.first("n").alias("n"), F.first("tokens").alias("tokens"))


def small_links(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b, na, nb) whose sets are similar enough: prefixes of orders 2 and 3 meet first, then whole sets."""
    size = f"int(n - ({percent} * n + 99) DIV 100 + 1)"
    short = sets.select("cls", F.expr(f"slice(tokens, 1, {size})").alias("p"), F.expr(f"slice(tokens, -{size}, {size})").alias("q"))
    a, b = (short.select(F.col("cls").alias(x), F.col("p").alias(f"p{x}"), F.col("q").alias(f"q{x}")) for x in "ab")
    share = possible_sql("least(size(array_intersect(pa, pb)), size(array_intersect(qa, qb)))", percent)
    near = pairs.join(a, "a").join(b, "b").where(share).select("a", "b", "na", "nb")
    a, b = (sets.select(F.col("cls").alias(x), F.col("tokens").alias(f"t{x}")) for x in "ab")
    whole = near.join(a, "a").join(b, "b").select("a", "b", "na", "nb", F.size(F.array_intersect("ta", "tb")).cast("long").alias("common"))
    return whole.where(f"100 * common >= {percent} * (na + nb - common)").select("a", "b")


def overlaps(a: list[np.ndarray], b: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Common elements of each array of a with each of b (distinct elements each), by products of 0/1 matrices of bounded width."""
    out = np.zeros((len(a), len(b)), dtype=np.float32)
    sides = [(np.concatenate([*x, np.zeros(0, dtype=np.int64)]), np.repeat(np.arange(len(x)), list(map(len, x)))) for x in (a, b)]
    keys = np.intersect1d(np.unique(sides[0][0]), np.unique(sides[1][0]), assume_unique=True)
    if not len(keys):
        return out.astype(np.int64)
    placed = []
    for v, row in sides:
        at = np.minimum(np.searchsorted(keys, v), len(keys) - 1)
        ok = keys[at] == v
        sort = np.argsort(at[ok], kind="stable")
        placed.append((at[ok][sort], row[ok][sort]))
    for first in range(0, len(keys), width):
        m = []
        for (at, row), x in zip(placed, (a, b), strict=True):
            lo, hi = np.searchsorted(at, (first, first + width))
            own = np.zeros((len(x), min(width, len(keys) - first)), dtype=np.float32)
            own[row[lo:hi], at[lo:hi] - first] = 1
            m.append(own)
        out += m[0] @ m[1].T
    return np.rint(out).astype(np.int64)


def forest(x: np.ndarray, y: np.ndarray, linked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a, b): stars over the components of the links between the classes x (rows) and y (columns)."""
    rows, cols = np.arange(len(x)), np.arange(len(y)) + len(x)
    far = len(x) + len(y)
    while True:
        up = np.minimum(rows, np.where(linked, cols[None, :], far).min(axis=1, initial=far))
        left = np.minimum(cols, np.where(linked, up[:, None], far).min(axis=0, initial=far))
        if (up == rows).all() and (left == cols).all():
            break
        rows, cols = up, left
    every = np.concatenate([x, y])
    root = every[np.concatenate([rows, cols])]
    out = root != every
    return root[out], every[out]


def block_links(a: list, b: list | None, token: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Links between two blocks of a list (b is None: within one); a block is (classes, sizes, labels, sets, long lists of each class).

    A pair that an earlier long list holds too is left to that one, and one of a component needs no link.
    """
    b = a if b is None else b
    (ca, na, ga, sa, la), (cb, nb, gb, sb, lb) = a, b
    na, nb = na[:, None], nb[None, :]
    pa_, pb_ = prefix_size(na, percent), prefix_size(nb, percent)
    rest = np.minimum(pa_ - np.array(list(map(len, la)))[:, None], pb_ - np.array(list(map(len, lb)))[None, :])
    todo = (ga[:, None] != gb[None, :]) & possible(na, nb, overlaps(la, lb) + rest, percent)
    todo &= overlaps([x[x < token] for x in la], [x[x < token] for x in lb]) == 0
    for part in (lambda s, p: s[:p], lambda s, p: s[len(s) - p :], None):  # orders 2 and 3, then whole sets
        i, j = np.flatnonzero(todo.any(axis=1)), np.flatnonzero(todo.any(axis=0))
        if not len(i):
            break
        n, m = na[i], nb[:, j]
        if part is None:
            shared = overlaps([sa[x] for x in i], [sb[x] for x in j])
            ok = 100 * shared >= percent * (n + m - shared)
        else:
            ok = possible(n, m, overlaps([part(sa[x], pa_[x, 0]) for x in i], [part(sb[x], pb_[0, x]) for x in j]), percent)
        todo[np.ix_(i, j)] &= ok
    return forest(ca, cb, todo)


def large_links(rows: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b): stars over what is linked in each pair of blocks of the long lists; rows has (token, block, cls, n, label)."""
    blocks = rows.groupBy("token", "block").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.min("label").alias("g"), F.max("label").alias("h"))
    other = blocks.select("token", F.col("block").alias("j"), *(F.col(c).alias(f"{c}2") for c in ("low", "high", "g", "h")))
    met = blocks.join(other, "token").where(f"block <= j AND 100 * high >= {percent} * low2 AND 100 * high2 >= {percent} * low AND NOT (g = h AND h = g2 AND g2 = h2)")
    met = met.select("token", F.col("block").alias("i"), "j")
    sides = met.select("token", "i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    of = rows.groupBy("cls").agg(F.sort_array(F.collect_list("token")).alias("long"))  # at most a class's prefix
    wide = sides.join(rows.select("token", "block", "cls", "label"), ["token", "block"]).join(of, "cls").join(sets, "cls")
    n = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(found: pa.Table) -> pa.Table:
        found = found.combine_chunks()
        token, i, j = (found[x][0].as_py() for x in ("token", "i", "j"))
        block, cls, size, label = (found[x].to_numpy() for x in ("block", "cls", "n", "label"))
        lists = []
        for x in ("tokens", "long"):
            c = found[x].chunk(0)
            ends = c.offsets.to_numpy()
            flat = c.values.to_numpy()
            lists.append([flat[s:e] for s, e in zip(ends[:-1], ends[1:], strict=True)])
        sides = []
        for k in dict.fromkeys((i, j)):
            at = np.flatnonzero(block == k)
            sides.append((cls[at], size[at].astype(np.int64), label[at], [lists[0][x] for x in at], [lists[1][x] for x in at]))
        a, b = block_links(sides[0], sides[1] if len(sides) > 1 else None, token, percent)
        return pa.table({"a": a, "b": b})

    # each group is much work for few bytes, so tasks are not joined by bytes
    return wide.repartition(n, "token", "i", "j").groupBy("token", "i", "j").applyInArrow(run, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """node, label (the smallest node reachable) for every node of the edges (a, b).

    In each round every node goes to its neighbour of least priority, if that is less than its own, and edges are contracted; priorities
    are hashes that change with the round, so any graph, a rising path too, loses a share of its nodes in each. The rounds end when no
    edge is left.
    """
    edges = materialise(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a != b").distinct(), "edges", light=True)
    labels, r = None, 0
    while not edges.isEmpty():
        ends = edges.select(F.explode(F.array(F.struct(F.col("a").alias("node"), F.col("b").alias("to")), F.struct(F.col("b").alias("node"), F.col("a").alias("to")))).alias("e")).select("e.*")
        first, own = (F.struct(F.xxhash64(c, F.lit(r)).alias("h"), F.col(c).alias("x")) for c in ("to", "node"))
        parent = materialise(ends.groupBy("node").agg(F.min(first).alias("m")).select("node", F.least("m", own)["x"].alias("up")), "parent", light=True)
        at = lambda c: parent.select(F.col("node").alias(c), F.col("up").alias(f"p{c}"))
        moved = edges.join(at("a"), "a").join(at("b"), "b").select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).where("a != b").distinct()
        edges, older = materialise(moved, "edges", light=True), edges
        discard(older)
        if labels is None:
            labels = parent.withColumnRenamed("up", "label")
        else:
            up = parent.withColumnRenamed("node", "label")
            labels, older = materialise(labels.join(up, "label", "left").select("node", F.coalesce("up", "label").alias("label")), "labels", light=True), labels
            discard(older)
            discard(parent)
        r += 1
    if labels is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("label"))
    least = labels.groupBy("label").agg(F.min("node").alias("low"))
    return labels.join(least, "label").select("node", F.col("low").alias("label"))


def links_of(docs: DataFrame, counts: np.ndarray, k: int, percent: int) -> DataFrame:
    """(a, b): links of classes that connect all that are similar enough."""
    context = docs.sparkSession.sparkContext
    sent = context.broadcast(counts)
    lists = materialise(list_pass(prefixes(docs, sent, k, percent), percent), "lists")
    sent.destroy()
    long = lists.where("token IS NOT NULL").select("token", F.col("a").alias("cls"), F.col("na").alias("n"))
    pairs = lists.where("token IS NULL").groupBy("a", "b").agg(F.first("na").alias("na"), F.first("nb").alias("nb"), F.count(F.lit(1)).alias("c"))
    many = long.groupBy("cls").agg(F.count(F.lit(1)).alias("m"))
    ma, mb = (many.select(F.col("cls").alias(x), F.col("m").alias(f"m{x}")) for x in "ab")
    near = pairs.join(ma, "a", "left").join(mb, "b", "left").where(possible_sql("c + least(coalesce(ma, 0), coalesce(mb, 0))", percent)).select("a", "b", "na", "nb")
    for r in range(STARS):
        near = near.unionByName(star_pairs(long, r, percent))
    near = materialise(near.distinct(), "pairs")
    classes = near.select(F.col("a").alias("cls")).union(near.select("b")).union(long.select("cls")).distinct()
    sent = context.broadcast(candidate_filter(classes))
    sets = materialise(candidate_sets(docs, sent, k, percent), "candidates")
    sent.destroy()
    found = materialise(small_links(near, sets, percent), "links")
    if not long.isEmpty():
        known = long.join(components(found).withColumnRenamed("node", "cls"), "cls", "left").withColumn("label", F.coalesce("label", "cls"))
        known = materialise(known, "known", light=True)
        still = known.groupBy("token").agg((F.min("label") != F.max("label")).alias("open"), F.count(F.lit(1)).alias("many")).where("open").select("token", "many")
        rows = materialise(blocks_of(known.join(still, "token")), "blocks")
        more = materialise(found.unionByName(large_links(rows, sets, percent)).distinct(), "links")
        for x in (known, rows, found):
            discard(x)
        found = more
    for x in (lists, near, sets):
        discard(x)
    return found


def linked(docs: DataFrame, k: int, percent: int, carried: list[str]) -> DataFrame:
    """The carried columns (doc_id among them), n and label of every document; documents of one label are one component, null is alone."""
    first = materialise(sets_pass(docs, k, carried), "sets")
    links = links_of(docs, bucket_counts(first), k, percent)
    labels = components(links)
    rows = first.where("block IS NULL").select(*carried, "n", "cls")
    return rows.join(labels.withColumnRenamed("node", "cls"), "cls", "left").select(*carried, "n", F.coalesce("label", "cls").alias("label"))


def link_components(docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    rows = materialise(linked(docs, k, percent, ["doc_id"]), "labelled")
    least = rows.where("label IS NOT NULL").groupBy("label").agg(F.min("doc_id").alias("low"))
    return rows.join(least, "label", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("low", "doc_id").alias("component_id"))


def copies(docs: DataFrame, key: str, k: int = 4, percent: int = 85) -> DataFrame:
    """The keys of the rows that another of their component stands for: the one of least doc_id (null last), then of least key."""
    rows = materialise(linked(docs, k, percent, [key, "doc_id"]), "labelled").where("label IS NOT NULL")
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col(key))
    least = rows.groupBy("label").agg(F.min(order)[key].alias("first"))
    return rows.join(least, "label").where(F.col(key) != F.col("first")).select(key)


def one_of_each(docs: DataFrame, k: int = 4, percent: int = 85) -> DataFrame:
    """The rows without those that another of their component stands for; decisions go by row, so repeated and null ids are no matter."""
    rows, key = numbered(docs)
    return without(rows, key, copies(rows, key, k, percent)).select(docs.columns)


def op7_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_components(load(spark, sf_dir, "documents"))


QUERIES = {"op7_ngram_jaccard_join": op7_ngram_jaccard_join}
SQL = {
    "op7_ngram_jaccard_join": r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS MATERIALIZED (SELECT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [list_aggregate(w, 'string_agg', ' ')]
  ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3])) END) AS s FROM w),
n AS MATERIALIZED (SELECT doc_id, count(*)::BIGINT AS n FROM g GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM g x JOIN g y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT a, b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
e AS MATERIALIZED (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r(doc_id, m) AS (SELECT a, a FROM e UNION SELECT e.b, r.m FROM r JOIN e ON e.a = r.doc_id WHERE r.m < e.b),
k AS (SELECT doc_id, min(m) AS m FROM r GROUP BY doc_id)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(k.m, d.doc_id)) AS component_id FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN k USING (doc_id)"""
}
