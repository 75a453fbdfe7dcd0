"""Lists written out as rows of bits over numbered vertices, and exchanged as such: a dense list travels as an eighth of a byte a vertex,
and lists that meet in a task are counted without a row for their arc."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from ..sources.tables import settle
from . import cells
from .csr import adjacency

#: Bytes of rows that a task of an exchange keeps on either side, about; words of rows that are counted at a time.
KEPT_BYTES, WORDS = 1 << 26, 1 << 17
#: Blocks of an exchange at least.
LEAST = 4


def numbers(g: Graph) -> np.ndarray:
    """The vertices, ascending; a vertex's number is its place."""
    return np.sort(g.ends.toArrow()["v"].to_numpy())


def dealt(n: int) -> np.ndarray:
    """The block of each number: ranges, as many as keep a block's rows within a task."""
    blocks = max(LEAST, -(-n * -(-n // 64) * 8 // KEPT_BYTES))
    return np.arange(n) * blocks // max(1, n)


def written(g: Graph, names: np.ndarray, **kinds: np.ndarray) -> DataFrame:
    """at, bits and a column for each of ``kinds``, which say what kind each number is of: the kinds that the list has an entry of. Written out."""
    words = -(-len(names) // 64)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column("nbrs")
            at, ends = np.searchsorted(names, lists.values.to_numpy()), lists.offsets.to_numpy().astype(np.int64)
            own = np.searchsorted(names, b.column("v").to_numpy()).astype(np.int32)
            step = max(1, WORDS // words)
            for lo in range(0, len(own), step):
                hi = min(len(own), lo + step)
                near, row = at[ends[lo] : ends[hi]], np.repeat(np.arange(hi - lo), np.diff(ends[lo : hi + 1]))
                flags = np.zeros((hi - lo, words * 64), dtype=bool)
                flags[row, near] = True
                bits = np.packbits(flags, axis=1, bitorder="little")
                cuts = np.arange(hi - lo + 1, dtype=np.int32) * (words * 8)
                columns = [pa.array(own[lo:hi]), pa.Array.from_buffers(pa.binary(), hi - lo, [None, pa.py_buffer(cuts), pa.py_buffer(bits)])]
                for kind in kinds.values():
                    met = np.zeros((hi - lo, int(kind.max(initial=0)) + 1), dtype=bool)
                    met[row, kind[near]] = True
                    columns.append(pa.ListArray.from_arrays(pa.array(np.cumsum([0, *met.sum(axis=1)]), pa.int32()), pa.array(np.nonzero(met)[1].astype(np.int32))))
                yield pa.RecordBatch.from_arrays(columns, ["at", "bits", *kinds])

    schema = ", ".join(["at int, bits binary", *(f"{k} array<int>" for k in kinds)])
    return settle(adjacency(g).select("v", "nbrs").mapInArrow(pack, schema), "rows")


def exchanged(asking: DataFrame, own: DataFrame, tasks: int, run: Callable[..., Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """What ``run`` makes in every cell of the rows that ask and of those that are kept there (cell, at, bits of both): numbers and bits of each."""
    side = lambda rows, asks: rows.select("cell", F.lit(asks).alias("asks"), "at", "bits")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, bool], tuple[list[np.ndarray], list[np.ndarray]]] = {}
        for b in batches:
            if not b.num_rows:
                continue
            cell, asks, at, sent = b.column("cell").to_numpy(), b.column("asks").to_numpy(zero_copy_only=False), b.column("at").to_numpy(), b.column("bits")
            ends = np.frombuffer(sent.buffers()[1], np.int32)[sent.offset :]
            rows = np.frombuffer(sent.buffers()[2], np.uint8)[ends[0] : ends[len(at)]].view(np.uint64).reshape(len(at), -1)
            for key in {*zip(cell.tolist(), asks.tolist(), strict=True)}:
                which = np.flatnonzero((cell == key[0]) & (asks == key[1]))
                found = held.setdefault(key, ([], []))
                found[0].append(at[which])
                found[1].append(rows[which])
        for k in sorted({k for k, _ in held}):
            ask, keep = held.pop((k, True), None), held.pop((k, False), None)
            if ask and keep:
                yield from run(*map(np.concatenate, ask), *map(np.concatenate, keep))

    return side(asking, True).unionByName(side(own, False)).repartitionById(tasks, F.col("cell")).mapInArrow(work, schema)


def sums(names: np.ndarray, beyond: bool) -> Callable[..., Iterator[pa.RecordBatch]]:
    """v, n: what the list of each row that asks shares with those of its neighbours that are kept here; ``beyond``: past that neighbour alone."""

    def run(a_at: np.ndarray, a: np.ndarray, b_at: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
        place = np.full(len(names), -1)
        place[b_at] = np.arange(len(b_at))
        kept = cells.past(b, b_at) if beyond else b
        n, step = np.zeros(len(a_at), dtype=np.int64), max(1, WORDS // a.shape[1])
        for i, row in enumerate(a):
            met = place[np.flatnonzero(np.unpackbits(row.view(np.uint8), bitorder="little"))]
            met = met[met >= 0]
            for lo in range(0, len(met), step):
                n[i] += np.bitwise_count(kept[met[lo : lo + step]] & row).sum(dtype=np.int64)
        yield cells.batch(("v", names[a_at]), ("n", n))

    return run


def closed(g: Graph, beyond: bool) -> DataFrame:
    """v, n: what each list shares with its neighbours' lists, after an exchange of all lists. Vertices are dealt into blocks; a list goes once to each
    block that it has an entry of, and once to each set of askers, where it is kept."""
    names = numbers(g)
    block = dealt(len(names))
    blocks = int(block.max(initial=0)) + 1
    rows = written(g, names, near=block)
    mine = f"int(pmod(at, {blocks}))"
    asking = rows.select("at", "bits", F.expr(mine).alias("i"), F.explode("near").alias("j"))
    own = rows.select("at", "bits", F.expr(f"int(bigint(at) * {blocks} div {max(1, len(names))})").alias("j"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("i"))
    at = [x.withColumn("cell", F.expr(f"i * {blocks} + j")) for x in (asking, own)]
    return exchanged(*at, blocks * blocks, sums(names, beyond), "v long, n long").groupBy("v").agg(F.sum("n").alias("n"))


def copies(g: Graph, parts: DataFrame) -> DataFrame:
    """v, n: what each list shares with those of its neighbours past them, in the vertex's part, which has a copy of all lists next to it. A copy lies in
    blocks of bounded size, to each of which the part's own lists go that have an entry of it."""
    names = numbers(g)
    block = dealt(len(names))
    blocks = int(block.max(initial=0)) + 1
    given = parts.select("v", "part").toArrow().sort_by("v")
    part = given["part"].to_numpy()[np.searchsorted(given["v"].to_numpy(), names)]
    rows = written(g, names, near=block, beside=part)
    of = settle(rows.sparkSession.createDataFrame(pa.table({"at": np.arange(len(names), dtype=np.int32), "part": part.astype(np.int32)})), "parts")
    mine = rows.join(of, "at").select("at", "bits", "part", F.explode("near").alias("j"))
    copy = rows.select("at", "bits", F.explode("beside").alias("part"), F.expr(f"int(bigint(at) * {blocks} div {max(1, len(names))})").alias("j"))
    at = [x.withColumn("cell", F.expr(f"part * {blocks} + j")) for x in (mine, copy)]
    return exchanged(*at, (int(part.max(initial=0)) + 1) * blocks, sums(names, True), "v long, n long").groupBy("v").agg(F.sum("n").alias("n"))
