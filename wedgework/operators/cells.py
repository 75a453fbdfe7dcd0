"""Graphs of groups, worked on in cells: what the two ends of an edge have in common, without moving a list, an arc or a pair.

Vertices are dealt into blocks, and a cell is a pair of blocks. A group goes to the cells of the blocks that it has a member in, and a cell
makes its vertices' lists from their groups as rows of bits. What moves is groups times blocks, whatever the lists and arcs come to.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle

#: Bytes of bit rows of a cell, about; blocks at least, and at most (beyond it lists meet by joins).
CELL_BYTES, LEAST, MOST = 1 << 27, 5, 64
#: Blocks at least where an edge costs as much as its lists are long.
WORK = 9
#: Ids are dealt by their remainders of this prime.
PRIME = 1_000_003


@dataclass
class Cell:
    """Vertices (ascending names) of a cell's groups, and the neighbours of those in its two blocks as bits of one row each."""

    names: np.ndarray
    bits: np.ndarray  # uint64, row x word
    rows: np.ndarray  # the name's number of each row
    left: np.ndarray  # rows of the first block
    right: np.ndarray  # rows of the second block, None: the same

    def row(self, r: int) -> np.ndarray:
        """Numbers of the neighbours of a row's vertex, ascending."""
        return np.flatnonzero(np.unpackbits(self.bits[r].view(np.uint8), bitorder="little"))

    def edges(self) -> Iterator[tuple[int, np.ndarray]]:
        """(row, rows) for every edge of the cell, once."""
        to = self.left if self.right is None else self.right
        at = self.rows[to]
        word, bit = at >> 6, (at & 63).astype(np.uint64)
        for i, r in enumerate(self.left):
            hit = (self.bits[r][word] >> bit) & np.uint64(1) != 0
            if self.right is None:
                hit[: i + 1] = False
            met = to[hit]
            if len(met):
                yield r, met

    def csr(self) -> tuple[np.ndarray, np.ndarray]:
        lists = [self.row(r).astype(np.int32) for r in range(len(self.rows))]
        return np.concatenate([np.zeros(0, np.int32), *lists]), np.cumsum([0, *map(len, lists)])

    def beyond(self) -> np.ndarray:
        """The bits of each row that lie beyond its own vertex."""
        return past(self.bits, self.rows)


def past(bits: np.ndarray, own: np.ndarray) -> np.ndarray:
    """The bits of each row beyond the row's own number."""
    out = bits.copy()
    for r, at in enumerate(own):
        out[r, : at >> 6] = 0
        out[r, at >> 6] &= ~np.uint64(1) << np.uint64(at & 63)
    return out


def cell(values: np.ndarray, ends: np.ndarray, i: int, j: int, blocks: int) -> Cell:
    """From groups: their members one after the other, and where each group begins and ends."""
    names, at = np.unique(values, return_inverse=True)
    block = names % PRIME % blocks
    rows = np.flatnonzero((block == i) | (block == j))
    row_of = np.full(len(names), -1)
    row_of[rows] = np.arange(len(rows))
    bits = np.zeros((len(rows), -(-len(names) // 64) * 8), dtype=np.uint8)
    mine = row_of[at]
    own = np.flatnonzero(mine >= 0)
    own = own[np.argsort(mine[own], kind="stable")]
    of = np.repeat(np.arange(len(ends) - 1), np.diff(ends))[own]
    cuts = np.searchsorted(mine[own], np.arange(len(rows) + 1))
    seen = np.zeros(len(names), dtype=bool)
    for r in range(len(rows)):
        for g in of[cuts[r] : cuts[r + 1]]:
            seen[at[ends[g] : ends[g + 1]]] = True
        seen[rows[r]] = False
        packed = np.packbits(seen, bitorder="little")
        bits[r, : len(packed)] = packed
        seen[:] = False
    at_i, at_j = np.flatnonzero(block[rows] == i), np.flatnonzero(block[rows] == j)
    return Cell(names, bits.view(np.uint64), rows, at_i, None if i == j else at_j)


def blocks_of(n: int) -> int:
    return max(LEAST, -(-n * n // (4 * CELL_BYTES)))


def usable(g: Graph) -> bool:
    return g.groups is not None and not g.directed and blocks_of(g.ends.count()) <= MOST


def over(groups: DataFrame, n: int, run: Callable[[Cell], Iterator[pa.RecordBatch]], schema: str, least: int = 0, alone: bool = False) -> DataFrame:
    """What ``run`` makes of every cell; ``n``: vertices, ``least``: blocks at least, for long work. ``alone``: only the cells of a block with itself."""
    b = max(blocks_of(n), least)
    pairs = [(i, j) for i in range(b) for j in range(i, b) if i == j or not alone]
    number = {p: k for k, p in enumerate(pairs)}
    met = F.array(*(F.array(*(F.lit(number[p]) for j in range(b) if (p := (min(i, j), max(i, j))) in number)) for i in range(b)))  # the cells of each block
    blocks = F.expr(f"array_distinct(transform(ms, m -> int(pmod(pmod(m, {PRIME}), {b}))))")
    sent = groups.select("ms", blocks.alias("at"), met.alias("met")).select("ms", F.explode(F.expr("array_distinct(flatten(transform(at, i -> met[i])))")).alias("cell"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[pa.Array]] = {}
        for batch in batches:
            t = pa.table(batch)
            for k in np.unique(t["cell"].to_numpy()):
                held.setdefault(int(k), []).extend(t.filter(pa.compute.equal(t["cell"], int(k)))["ms"].chunks)
        for k in sorted(held):
            ms = pa.concat_arrays(held.pop(k))
            ends = ms.offsets.to_numpy().astype(np.int64)
            yield from run(cell(ms.values.to_numpy()[ends[0] : ends[-1]], ends - ends[0], *pairs[k], b))

    import pyarrow.compute  # noqa: F401  the workers' pa.compute

    return sent.repartitionById(len(pairs), F.col("cell")).mapInArrow(work, schema)


def shared(c: Cell, r: int, met: np.ndarray, other: np.ndarray | None = None) -> np.ndarray:
    """How many neighbours the row's vertex has in common with each of the rows ``met``."""
    return np.bitwise_count((c.bits if other is None else other)[met] & c.bits[r]).sum(axis=1, dtype=np.int64)


def batch(*columns: tuple[str, np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x) for _, x in columns], [k for k, _ in columns])


def both_ways(c: Cell, a: np.ndarray, b: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
    """src, dst, common of edges, each as two arcs, in batches."""
    names = c.names[c.rows]
    for lo in range(0, len(a), 1 << 19):
        s, t, k = names[a[lo : lo + (1 << 19)]], names[b[lo : lo + (1 << 19)]], n[lo : lo + (1 << 19)]
        yield batch(("src", np.concatenate([s, t])), ("dst", np.concatenate([t, s])), ("common", np.concatenate([k, k])))


def dense(c: Cell) -> bool:
    """Whether a longer list's partners hold, together, as many keys as there are names, at least: then it meets their distinct keys at once."""
    size = np.bitwise_count(c.bits).sum(axis=1, dtype=np.int64)
    return len(c.names) * len(c.rows) <= sum(int(np.minimum(size[r], size[met]).sum()) for r, met in c.edges())


def by_longer(c: Cell, kernel: str, cutoff: int | None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(row, rows, common) of every edge at its longer list: that list alone is made, and meets the distinct keys of its partners once, by search or
    merge; every partner then counts its own keys among those found, as bits."""
    from ..functions.kernels import _meet, _rule

    size = np.bitwise_count(c.bits).sum(axis=1, dtype=np.int64)
    right = c.left if c.right is None else c.right
    step = max(1, PIECE // c.bits.shape[1])
    sides = [(c.left, right, False), (right, c.left, True)]
    for mine, other, later in sides:
        at = c.rows[other]
        word, bit = at >> 6, (at & 63).astype(np.uint64)
        for r in mine:
            hit = (c.bits[r][word] >> bit) & np.uint64(1) != 0
            if c.right is None:
                hit &= (other < r) if later else (other > r)
            hit &= size[other] <= size[r] if later else size[other] < size[r]
            met = other[hit]
            if not len(met):
                continue
            whole, merged = c.row(r), _rule(kernel, size[met], np.full(len(met), size[r]))
            for by_merge in (True, False):
                some = met[merged == by_merge]
                if not len(some):
                    continue
                pieces = [some[lo : lo + step] for lo in range(0, len(some), step)]
                keys = np.bitwise_or.reduce([np.bitwise_or.reduce(c.bits[p], axis=0) for p in pieces])
                seen = np.zeros(c.bits.shape[1] * 64, dtype=bool)
                seen[_meet(np.flatnonzero(np.unpackbits(keys.view(np.uint8), bitorder="little")), whole, by_merge, cutoff)] = True
                found = np.packbits(seen, bitorder="little").view(np.uint64)
                yield r, some, np.concatenate([np.bitwise_count(c.bits[p] & found).sum(axis=1, dtype=np.int64) for p in pieces])


def together(found: Iterator[tuple[int, np.ndarray, np.ndarray]], c: Cell) -> Iterator[pa.RecordBatch]:
    """Edges as they are found, in batches of both arcs of some."""
    a, b, common = [], [], []
    n = 0
    for r, met, shares in chain(found, [(0, None, None)]):
        if n and (met is None or n > 1 << 18):
            yield from both_ways(c, np.concatenate(a), np.concatenate(b), np.concatenate(common))
            a, b, common, n = [], [], [], 0
        if met is not None:
            a.append(np.full(len(met), r))
            b.append(met)
            common.append(shares)
            n += len(met)


def edge_support(g: Graph, kernel: str = "bits", cutoff: int | None = None) -> DataFrame:
    """src, dst, common by counting bits, or by a kernel on a cell's lists as compressed sparse rows; merged in pieces of ``cutoff``, if given."""

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        if kernel != "bits" and dense(c):
            yield from together(by_longer(c, kernel, cutoff), c)
            return
        found = list(c.edges())
        if not found:
            return
        a, b = np.repeat([r for r, _ in found], [len(m) for _, m in found]), np.concatenate([m for _, m in found])
        if kernel == "bits":
            n = np.concatenate([shared(c, r, m) for r, m in found])
        else:
            from ..functions.kernels import common_rows

            n = common_rows(*c.csr(), a, b, kernel, cutoff)
        yield from both_ways(c, a, b, n)

    return over(g.groups, g.ends.count(), run, "src long, dst long, common long", least=LEAST if kernel == "bits" else WORK)


#: Lists on each side of a tile, and their entries, at most; a longer list is a side alone.
TILE, TILE_ENTRIES = 64, 1 << 17


def builtin_support(g: Graph) -> DataFrame:
    """src, dst, common by array_intersect: a cell hands out tiles, some lists of each block, in which an edge is a pair of places.

    Twins share an edge's count, so the lists are those of one vertex a set (and of a second one for the edges inside), with all their neighbours.
    """
    groups, sets = alike(g)
    place = pa.struct([("i", pa.int32()), ("j", pa.int32()), ("inside", pa.bool_())])

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        of = np.searchsorted(sets.v, c.names)
        begin, many = sets.starts[of], sets.many[of]
        to = c.left if c.right is None else c.right

        def nested(xs: list[np.ndarray]) -> pa.Array:
            inner = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, xs)]), pa.int32()), pa.array(np.concatenate(xs)))
            return pa.ListArray.from_arrays(pa.array([0, len(xs)], pa.int32()), inner)

        def lists(rows: np.ndarray, nth: int = 0) -> pa.Array:
            """Neighbours, as places among all members, of the nth member of each row's set."""
            near, at = [c.row(r) for r in rows], c.rows[rows]
            return nested([np.concatenate([runs(begin[x], many[x]), np.delete(begin[k] + np.arange(many[k]), nth)]).astype(np.int32) for x, k in zip(near, at, strict=True)])

        def tile(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray, a: pa.Array, b: pa.Array, inside: bool) -> pa.RecordBatch:
            s, t = (nested([sets.members[begin[k] : begin[k] + many[k]] for k in c.rows[z]]) for z in (x, y))
            places = pa.StructArray.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(np.full(len(i), inside))], fields=list(place))
            return pa.RecordBatch.from_arrays([s, t, a, b, pa.ListArray.from_arrays(pa.array([0, len(i)], pa.int32()), places)], ["s", "t", "a", "b", "at"])

        longest = max((int(many[c.row(r)].sum() + many[at]) for r, at in enumerate(c.rows)), default=1)
        size = max(1, min(TILE, TILE_ENTRIES // longest))
        met = np.zeros((len(c.left), len(to)), dtype=bool)
        column = {r: k for k, r in enumerate(to)}
        for k, r in enumerate(c.left):
            met[k] = (c.bits[r][c.rows[to] >> 6] >> (c.rows[to] & 63).astype(np.uint64)) & np.uint64(1)
            if c.right is None:
                met[k, : column[r] + 1] = False
        for x in range(0, len(c.left), size):
            left, a = c.left[x : x + size], None
            for y in range(0, len(to), size):
                i, j = np.nonzero(met[x : x + size, y : y + size])
                if len(i):
                    a = lists(left) if a is None else a
                    yield tile(left, to[y : y + size], i, j, a, lists(to[y : y + size]), False)
        if c.right is None:
            twin = c.left[many[c.rows[c.left]] > 1]
            for x in range(0, len(twin), size):
                some = twin[x : x + size]
                each = np.arange(len(some))
                yield tile(some, some, each, each, lists(some), lists(some, 1), True)

    tiles = over(groups, len(sets.v), run, "s array<array<long>>, t array<array<long>>, a array<array<int>>, b array<array<int>>, at array<struct<i: int, j: int, inside: boolean>>", least=WORK)
    met = tiles.select("s", "t", "a", "b", F.explode("at").alias("e")).selectExpr("s[e.i] AS s", "t[e.j] AS t", "e.inside", "bigint(size(array_intersect(a[e.i], b[e.j]))) AS common")
    met = met.select("t", "inside", "common", F.explode("s").alias("src")).select("src", "inside", "common", F.explode("t").alias("dst")).where("NOT inside OR src < dst")
    ends = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return met.select("common", F.explode(ends).alias("e")).select("e.src", "e.dst", "common")


def per_vertex(g: Graph, upper: bool = False) -> DataFrame:
    """v, triangles for vertices with any: half of what their edges share. ``upper`` counts for each arc only what lies beyond its far end.

    Twins count at once; in the order that ``upper`` needs they follow each other.
    """
    groups, sets = alike(g)

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        of = np.searchsorted(sets.v, c.names)
        w = sets.many[of]
        own, at = w[c.rows], c.rows >> 6
        n, found = np.zeros(len(c.rows), dtype=np.int64), [(r, met.astype(np.int32)) for r, met in c.edges()]
        for lo in range(0, c.bits.shape[1], STRIP):  # words that stay near the processor
            hi = min(lo + STRIP, c.bits.shape[1])
            strip, counted = np.ascontiguousarray(c.bits[:, lo:hi]), counter(c, w, lo, hi)
            if not upper:
                for r, met in found:
                    x = counted(strip, met, strip[r])
                    n[r] += own[met] @ x
                    n[met] += own[r] * x
                continue
            before, inside = np.searchsorted(at, [lo, hi])  # rows whose own bit lies before the strip, and up to its end
            beyond = past(strip[before:inside], c.rows[before:inside] - 64 * lo)
            for r, met in found:  # what is beyond the far end
                cut = np.searchsorted(met, [before, inside])
                if r < before:  # all of the strip is beyond r
                    x = counted(strip, met, strip[r])
                    n[met] += own[r] * x
                    n[r] += own[met[: cut[0]]] @ x[: cut[0]]
                else:
                    if r < inside:
                        n[met] += own[r] * counted(strip, met, beyond[r - before])
                    n[r] += own[met[: cut[0]]] @ counted(strip, met[: cut[0]], strip[r])
                some = met[cut[0] : cut[1]]
                if len(some):
                    n[r] += own[some] @ counted(beyond, some - before, strip[r])
        for r, met in found:
            a, b = own[r], own[met]
            if upper:  # in the far end's own set, and between it and the near end's twins; others are counted above
                n[r] += (b * (b - 1) // 2 + b * (a - 1)).sum()
                n[met] += a * (a - 1) // 2 + a * (b - 1)
            else:  # the ends' own twins are common neighbours, too
                n[r] += (b * (a + b - 2)).sum()
                n[met] += a * (a + b - 2)
        weight = weigher(c, w)
        if c.right is None:  # edges among twins
            x = own[c.left]
            n[c.left] += (x - 1) * (x - 2) // 2 if upper else (x - 1) * (weight(c.bits[c.left]) + x - 2)
        yield batch(("v", sets.members[runs(sets.starts[of[c.rows]], own)]), ("n", np.repeat(n, own)))

    sums = over(groups, len(sets.v), run, "v long, n long").groupBy("v").agg(F.sum("n").alias("n")).where("n > 0")
    return sums.select("v", (F.col("n") if upper else F.expr("n div 2")).alias("triangles"))


#: Entries of a batch of corners, about; bytes of rows that a vertex's edges are worked on at a time.
CORNERS, SPREAD = 1 << 20, 1 << 24


def corners(g: Graph) -> DataFrame:
    """a, b, cs for the edges a < b that have any: the common neighbours c > b. Each edge meets in one cell, so a triangle is found once."""

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        beyond, at = c.beyond(), c.rows
        step = max(1, SPREAD // (c.bits.shape[1] * 64))
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        n = 0

        def ended() -> pa.RecordBatch:
            a, b, many, cs = (np.concatenate(x) for x in zip(*held, strict=True))
            lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *many]), pa.int32()), pa.array(c.names[cs]))
            return pa.RecordBatch.from_arrays([pa.array(c.names[a]), pa.array(c.names[b]), lists], ["a", "b", "cs"])

        for r, all_met in c.edges():
            near = c.row(r)
            near = near[near > at[r]]  # c is past the higher end, hence past r's
            first = int(at[r]) >> 6
            for lo in range(0, len(all_met), step):
                met = all_met[lo : lo + step]
                later = (met > r)[:, None]
                both = np.where(later, beyond[met, first:], c.bits[met, first:]) & beyond[r, first:]
                spread = np.unpackbits(both.view(np.uint8), axis=1, bitorder="little").take(near - first * 64, axis=1)
                found = np.flatnonzero(spread.view(bool))
                many = np.bitwise_count(both).sum(axis=1, dtype=np.int64)
                some = many > 0
                held.append((np.minimum(at[r], at[met])[some], np.maximum(at[r], at[met])[some], many[some], near[found - np.repeat(np.arange(len(met)) * len(near), many)]))
                n += len(found)
                if n > CORNERS:
                    yield ended()
                    held.clear()
                    n = 0
        if n:
            yield ended()

    return over(g.groups, g.ends.count(), run, "a long, b long, cs array<long>", least=WORK)


def twins(g: Graph, members: bool = False) -> tuple[DataFrame, DataFrame]:
    """(ms) and (v, w): the groups of one vertex for each set of vertices that are in the same groups, and how many it stands for (``members``: vs, which).

    Such vertices are neighbours and have the same other neighbours.
    """
    of = settle(g.groups.select(F.monotonically_increasing_id().alias("g"), "ms"), "numbered").select("g", F.explode("ms").alias("v"))
    which = [F.sort_array(F.collect_list("v")).alias("vs")] if members else []
    alike = of.groupBy("v").agg(F.sort_array(F.collect_list("g")).alias("gs")).groupBy("gs").agg(F.min("v").alias("v"), F.count(F.lit(1)).alias("w"), *which)
    alike = settle(alike, "twins")
    return alike.select("v", F.explode("gs").alias("g")).groupBy("g").agg(F.collect_list("v").alias("ms")).select("ms"), alike.drop("gs")


@dataclass
class Sets:
    """Twins: the least vertex of each set (ascending) and how many it has; all members, one set after the other, and where each set begins."""

    v: np.ndarray
    many: np.ndarray
    starts: np.ndarray
    members: np.ndarray


def alike(g: Graph) -> tuple[DataFrame, Sets]:
    """The groups of one vertex of each set, and the sets; for graphs that are ``usable``, whose vertices fit a task."""
    groups, found = twins(g, members=True)
    t = found.select("v", "w", F.explode("vs").alias("m")).toArrow()
    v, w, m = (t[k].to_numpy() for k in ("v", "w", "m"))
    order = np.lexsort((m, v))
    v, starts = np.unique(v[order], return_index=True)
    return groups, Sets(v, w[order][starts], starts, m[order])


def runs(starts: np.ndarray, many: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each run, one after the other."""
    before = np.cumsum(many) - many
    return np.arange(many.sum()) + np.repeat(starts - before, many)


#: Words of a strip of bit rows (at most 1023: its bits are summed in 16 bits), and words of it that are counted at a time, in the same place.
STRIP, PIECE = 256, 1 << 17


def counter(c: Cell, w: np.ndarray, lo: int, hi: int) -> Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
    """For a strip of words lo to hi: the weights of what each of its rows ``met`` has in common with ``row``."""
    step = max(1, PIECE // (hi - lo))
    both, bits = np.empty((step, hi - lo), dtype=np.uint64), np.empty((step, hi - lo), dtype=np.uint8)
    weight = weigher(c, w, lo, hi) if int(w.max(initial=1)) > 1 else None

    def count(strip: np.ndarray, met: np.ndarray, row: np.ndarray) -> np.ndarray:
        n = np.empty(len(met), dtype=np.int64)
        for k in range(0, len(met), step):
            m = min(step, len(met) - k)
            x = strip.take(met[k : k + m], axis=0, out=both[:m], mode="clip")
            np.bitwise_and(x, row, out=x)
            n[k : k + m] = weight(x) if weight else np.bitwise_count(x, out=bits[:m]).sum(axis=1, dtype=np.uint16)
        return n

    return count


def weigher(c: Cell, w: np.ndarray, lo: int = 0, hi: int | None = None) -> Callable[[np.ndarray], np.ndarray]:
    """Sums of the weights of the names whose bits are set, of each bit row; ``lo``, ``hi``: of rows cut to these words."""
    if int(w.max(initial=1)) == 1:
        return lambda x: np.bitwise_count(x).sum(axis=-1, dtype=np.int64)
    planes = []  # the weights' binary digits, as bit rows
    for k in range(int(w.max()).bit_length()):
        row = np.zeros(c.bits.shape[1] * 8, dtype=np.uint8)
        digit = np.packbits((w >> k & 1).astype(bool), bitorder="little")
        row[: len(digit)] = digit
        planes.append(row.view(np.uint64)[lo:hi])
    return lambda x: sum(np.bitwise_count(x & p).sum(axis=-1, dtype=np.int64) << k for k, p in enumerate(planes))


def reads(g: Graph, names: np.ndarray, part: np.ndarray) -> DataFrame:
    """part, dst, deg, c: how many neighbours of each vertex are in each part but its own, and its degree; ``names`` (ascending) are in ``part``.

    Twins have the same neighbours but for each other, so a set's parts are counted once.
    """
    groups, sets = alike(g)
    n_parts = int(part.max(initial=0)) + 1
    own = part[np.searchsorted(names, sets.members)]
    held = np.bincount(np.repeat(np.arange(len(sets.v)), sets.many) * n_parts + own, minlength=len(sets.v) * n_parts).reshape(-1, n_parts)

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        of = np.searchsorted(sets.v, c.names)
        total = np.array([held[of[c.row(r)]].sum(axis=0) for r in c.left], dtype=np.int64).reshape(-1, n_parts)
        k = of[c.rows[c.left]]
        total += held[k]
        row, at = np.repeat(np.arange(len(k)), sets.many[k]), runs(sets.starts[k], sets.many[k])
        for lo in range(0, len(at), 1 << 16):
            i, m = row[lo : lo + (1 << 16)], at[lo : lo + (1 << 16)]
            n = total[i]
            n[np.arange(len(m)), own[m]] = 0
            x, p = np.nonzero(n)
            yield batch(("part", p.astype(np.int32)), ("dst", sets.members[m[x]]), ("deg", total.sum(axis=1)[i[x]] - 1), ("c", n[x, p]))

    return over(groups, len(sets.v), run, "part int, dst long, deg long, c long", least=WORK, alone=True)


def count(g: Graph) -> DataFrame | None:
    """One row: triangles, a third of what all edges share. Twins count at once; None: too many vertices even so."""
    groups, weights = twins(g)
    n, most = weights.agg(F.count(F.lit(1)), F.coalesce(F.max("w"), F.lit(1))).first()
    if blocks_of(n) > MOST:
        return None
    of = weights.where("w > 1").toArrow() if most > 1 else None  # at most as many as MOST blocks hold

    def run(c: Cell) -> Iterator[pa.RecordBatch]:
        w = np.ones(len(c.names), dtype=np.int64)
        if of is not None:
            vs, ws = of["v"].to_numpy(), of["w"].to_numpy()
            at = np.minimum(np.searchsorted(c.names, vs), len(c.names) - 1)
            held = c.names[at] == vs
            w[at[held]] = ws[held]
        weight = weigher(c, w)
        own, total = w[c.rows], 0
        for r, met in c.edges():
            common = weight(c.bits[met] & c.bits[r]) + own[r] + own[met] - 2  # the ends' own twins are common neighbours, too
            total += int((common * own[met]).sum()) * int(own[r])
        if c.right is None:
            for r in c.left:  # edges among twins
                total += int(own[r]) * (int(own[r]) - 1) // 2 * (int(weight(c.bits[r])) + int(own[r]) - 2)
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.decimal128(38, 0))], ["n"])

    return over(groups, n, run, "n decimal(38, 0)").agg(F.expr("coalesce(bigint(sum(n) / 3), 0L)").alias("triangles"))


#: Bytes of the bit rows of a whole graph that a task holds, at most.
WHOLE_BYTES = 1 << 28


def rounds(g: Graph, parts: DataFrame, share: int, residues: int) -> DataFrame | None:
    """v, round, triangles: each vertex's pairs of neighbours j < k are questions, numbered by (v, j, k) among those of the same parts of v and j
    and the same remainder of v; ``share`` numbers make a round. None: too many vertices.

    A question's number is a sum of degrees and places in lists, so none is written. Every task gets the groups and works on some vertices.
    """
    n = g.ends.count()
    if n * n // 8 > WHOLE_BYTES:
        return None
    of = parts.select("v", "part").toArrow().sort_by("v")
    owner = of["part"].to_numpy()
    tasks, n_parts = 4 * WORK, int(owner.max(initial=0)) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        ms = pa.concat_arrays([b.column("ms") for b in held])
        task, ends = held[0].column("task")[0].as_py(), ms.offsets.to_numpy().astype(np.int64)
        c = cell(ms.values.to_numpy()[ends[0] : ends[-1]], ends - ends[0], 0, 0, 1)  # all vertices, in the order of ``parts``
        sums = np.zeros((n_parts, residues, n_parts), dtype=np.int64)
        for v in range(len(c.names)):
            near = c.row(v)
            own, later = owner[near], len(near) - 1 - np.arange(len(near))
            key = owner[v], int(c.names[v] % residues)
            base = sums[key].copy()
            sums[key] += np.bincount(own, weights=later, minlength=n_parts).astype(np.int64)
            if v % tasks != task:
                continue
            at = []
            for o in np.unique(own):
                j = np.flatnonzero(own == o)
                yes = np.unpackbits(c.bits[near[j]].view(np.uint8), axis=1, bitorder="little")[:, near]
                yes[np.arange(len(near)) <= j[:, None]] = 0
                row, k = np.nonzero(yes)
                begin = base[o] + np.cumsum(later[j]) - later[j] - j - 1
                at.append((begin[row] + k) // share)
            at = np.concatenate(at)
            if len(at):
                low = at.min()
                if at.max() - low <= 16 * len(at):
                    count = np.bincount(at - low)
                    r = np.flatnonzero(count)
                    r, count = r + low, count[r]
                else:
                    r, count = np.unique(at, return_counts=True)
                yield batch(("v", np.full(len(r), c.names[v])), ("round", r.astype(np.int32)), ("triangles", count.astype(np.int64)))

    sent = g.groups.select("ms", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"))
    return sent.repartitionById(tasks, F.col("task")).mapInArrow(run, "v long, round int, triangles long")
