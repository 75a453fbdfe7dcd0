"""Sequence packing by non-negative least squares over a length histogram.

1. One pass tokenises every document, cuts it into full windows and a tail, and writes the pieces (not the ids) with their crc32 and
   their rank among the pieces of equal length in their partition.
2. The histogram of lengths (at most one row for each length) gives the plan: combinations of up to three length classes that fill a
   window are enumerated, their repeat counts solve a non-negative least-squares problem against the histogram, counts are rounded
   down, and what is left is packed greedily, longest first into the tightest open window. The greedy step works on counts too, so
   the plan's size depends on the window and not on the number of documents.
3. Each piece finds its place from its length and rank alone.

Defined results: a null text is empty and its document is the end id alone; repeated rows are packed as often as they occur; an empty
table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import load, materialise

WINDOW = 2048
END = 1
#: Width of a length class of the least-squares step.
QUANTUM = 8
#: Entries of a worker's cache of tokenised pieces; beyond that it starts anew.
CACHE = 700_000


def byte_alphabet() -> dict[str, int]:
    """The printable characters that stand for bytes in a byte-level BPE vocabulary."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Ids:
    """Text to ids (little-endian unsigned 32-bit), as the tokenizer file has it: the string of an added token is that token."""

    def __init__(self, path: str, pattern: str):
        import tiktoken

        letters = byte_alphabet()
        with open(path, encoding="utf-8") as f:
            file = json.load(f)
        vocab = file["model"]["vocab"]
        # longest first, as one may begin another
        self.added = {t["content"]: np.array([t["id"]], dtype="<u4").tobytes() for t in sorted(file.get("added_tokens", []), key=lambda t: -len(t["content"]))}
        self.cut = re.compile("(" + "|".join(map(re.escape, self.added)) + ")") if self.added else None
        ranks = {bytes(letters[c] for c in t): i for t, i in vocab.items() if t not in self.added and all(c in letters for c in t)}
        self.encode = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.crosses = re.compile(r" \s|\s ").search
        self.after_space: dict[str, bytes] = {}

    def ids(self, text: str) -> bytes:
        return np.array(self.encode(text), dtype="<u4").tobytes()

    def of(self, text: str) -> bytes:
        if self.cut is None or not self.cut.search(text):
            return self.between(text)
        return b"".join(self.added[x] if i % 2 else self.between(x) for i, x in enumerate(self.cut.split(text)) if x)

    def between(self, text: str) -> bytes:
        """A match never crosses the start of a space that has no other white space beside it, so such pieces are encoded once."""
        if self.crosses(text):
            return self.ids(text)
        first, *rest = text.split(" ")
        known = self.after_space
        try:
            return self.ids(first) + b"".join(map(known.__getitem__, rest))
        except KeyError:
            if len(known) > CACHE:
                known.clear()
            for x in set(rest).difference(known):
                known[x] = self.ids(" " + x)
            return self.ids(first) + b"".join(map(known.__getitem__, rest))


_IDS: dict[tuple[str, str], Ids] = {}


def pieces(docs: DataFrame, path: str, pattern: str, window: int = WINDOW, end: int = END) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, and (part, rank): the rank among the partition's pieces of that length."""
    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part int, rank long"
    last = end.to_bytes(4, "little")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = _IDS.get((path, pattern)) or _IDS.setdefault((path, pattern), Ids(path, pattern))
        part, seen = TaskContext.get().partitionId(), defaultdict(int)
        for b in batches:
            rows = []
            for doc_id, text in zip(b["doc_id"].tolist(), b["text"], strict=True):
                ids = own.of(text or "") + last
                n = len(ids) // 4
                for start in range(0, n, window):
                    size = min(window, n - start)
                    rows.append((doc_id, start, size, zlib.crc32(ids[4 * start : 4 * (start + size)]), n, part, seen[size]))
                    seen[size] += 1
            out = pd.DataFrame(rows, columns=[x.split()[0] for x in schema.split(", ")])
            yield out.astype({"doc_id": "Int64"}) if b["doc_id"].isna().any() else out

    return docs.select("doc_id", "text").mapInPandas(run, schema)


def combinations_filling(total: int, have: np.ndarray) -> list[tuple[int, ...]]:
    """All multisets of one, two or three classes with documents that sum to ``total``."""
    k = [int(x) for x in np.flatnonzero(have) if x > 0]
    there = set(k)
    found: list[tuple[int, ...]] = [(total,)] if total in there else []
    found += [(a, total - a) for a in k if a <= total - a and total - a in there]
    return found + [(a, b, total - a - b) for i, a in enumerate(k) for b in k[i:] if b <= total - a - b and total - a - b in there]


def nnls(a: np.ndarray, b: np.ndarray, rounds: int | None = None) -> np.ndarray:
    """min |a x - b|, x >= 0, by the active-set method: columns enter by gradient, and leave when their weight would turn negative."""
    x, chosen = np.zeros(a.shape[1]), np.zeros(a.shape[1], dtype=bool)
    # counts are rounded afterwards: a smaller gradient moves less than one piece
    gram_b, tol = a.T @ b, 1e-2
    for _ in range(rounds or 3 * a.shape[0]):
        gradient = gram_b - a.T @ (a[:, chosen] @ x[chosen])
        gradient[chosen] = -np.inf
        j = int(np.argmax(gradient)) if len(gradient) else -1
        if j < 0 or gradient[j] <= tol:
            break
        chosen[j] = True
        while True:
            at = np.flatnonzero(chosen)
            part = a[:, at]
            z = np.linalg.solve(part.T @ part + 1e-9 * np.eye(len(at)), gram_b[at])
            if (z > 0).all():
                break
            low = z <= 0
            step = np.min(x[at][low] / np.maximum(x[at][low] - z[low], 1e-300))
            x[at] += step * (z - x[at])
            chosen[at[(x[at] <= 1e-12) & low]] = False
            x[~chosen] = 0
            if not chosen.any():
                break
        x[:] = 0
        x[at] = np.maximum(z, 0) * chosen[at]
    return x


def make_plan(counts: dict[int, int], window: int = WINDOW, quantum: int = QUANTUM) -> dict[str, np.ndarray]:
    """Where the i-th piece of each length goes. Arrays only; their size is bounded by the window."""
    lengths = np.zeros(window + 1, dtype=np.int64)
    for n, c in counts.items():
        lengths[n] = c
    top = window // quantum
    cls = -(-np.arange(window + 1) // quantum)  # a class stands for its largest length
    have = np.bincount(cls, weights=lengths, minlength=top + 1).astype(np.int64)
    below = np.zeros(window + 1, dtype=np.int64)  # pieces of shorter lengths of the same class
    for n in range(2, window + 1):
        below[n] = below[n - 1] + lengths[n - 1] if cls[n] == cls[n - 1] else 0

    sequences: list[tuple[tuple[int, ...], int]] = []  # slots as keys, repeat count; a key under or at top is a class, above it a length
    fills = combinations_filling(top, have)
    used = np.zeros(top + 1, dtype=np.int64)
    if fills:
        a = np.zeros((top + 1, len(fills)))
        for j, f in enumerate(fills):
            for c in f:
                a[c, j] += 1
        scale = 1 / np.sqrt(np.maximum(have, 1))
        x = nnls(a * scale[:, None], have * scale)
        left = have.copy()
        for j in np.argsort(-x):
            need = {c: fills[j].count(c) for c in fills[j]}
            n = min(int(x[j] + 1e-6), *(int(left[c] // m) for c, m in need.items()))
            if n > 0:
                sequences.append((fills[j], n))
                for c, m in need.items():
                    left[c] -= n * m
        used = have - left
    rest = lengths.copy()
    for n in range(1, window + 1):
        taken = min(lengths[n], max(0, used[cls[n]] - below[n]))
        rest[n] -= taken

    # greedy on counts: longest first, into the tightest open kind of window
    open_kinds: dict[int, list[list]] = defaultdict(list)  # free room: [slots, count]
    for n in range(window, 0, -1):
        c = int(rest[n])
        while c:
            room = min((r for r, kinds in open_kinds.items() if r >= n and kinds), default=None)
            if room is None:
                fit = window // n
                if c >= fit:
                    open_kinds[window - fit * n].append([(n + top,) * fit, c // fit])
                if c % fit:
                    open_kinds[window - (c % fit) * n].append([(n + top,) * (c % fit), 1])
                break
            kind = open_kinds[room][-1]
            m = min(c, kind[1])
            open_kinds[room - n].append([(*kind[0], n + top), m])
            kind[1] -= m
            if not kind[1]:
                open_kinds[room].pop()
            c -= m
    sequences += [(tuple(slots), count) for kinds in open_kinds.values() for slots, count in kinds]

    given: dict[int, int] = defaultdict(int)
    rows, base = [], 0
    for slots, count in sequences:
        for key in dict.fromkeys(slots):
            m = slots.count(key)
            rows.append((key, given[key], m, base, slots.index(key)))
            given[key] += m * count
        base += count
    rows.sort()
    key, first, many, base_id, slot = (np.array(x, dtype=np.int64) for x in zip(*rows, strict=True)) if rows else (np.zeros(0, dtype=np.int64),) * 5
    return {"cls": cls, "below": below, "used": used, "top": np.int64(top), "at": (key << 44) + first, "first": first, "many": many, "base": base_id, "slot": slot}


def place(plan: dict[str, np.ndarray], length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, slot) of the rank-th piece of each length."""
    c, low = plan["cls"][length], plan["below"][length]
    i = low + rank
    fitted = plan["used"][c]
    regular = i < fitted
    key = np.where(regular, c, length + plan["top"])
    i = np.where(regular, i, i - np.maximum(fitted, low))
    j = np.searchsorted(plan["at"], (key << 44) + i, side="right") - 1
    d = i - plan["first"][j]
    return plan["base"][j] + d // plan["many"][j], plan["slot"][j] + d % plan["many"][j]


def pack(cut: DataFrame, window: int = WINDOW) -> DataFrame:
    """Adds sequence_id and offset to written pieces (see ``pieces``)."""
    plan = make_plan({r.length: r.n for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}, window)
    sent = cut.sparkSession.sparkContext.broadcast(plan)
    ordered = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    shifts = cut.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n")).select("part", "length", F.coalesce(F.sum("n").over(ordered), F.lit(0)).alias("shift"))

    @F.pandas_udf("sequence_id long, slot long")
    def put(length: pd.Series, rank: pd.Series) -> pd.DataFrame:
        sequence, slot = place(sent.value, length.to_numpy(np.int64), rank.to_numpy(np.int64))
        return pd.DataFrame({"sequence_id": sequence, "slot": slot})

    placed = cut.join(shifts, ["part", "length"]).withColumn("p", put("length", F.col("rank") + F.col("shift")))
    before = W.partitionBy("sequence_id").orderBy("slot").rowsBetween(W.unboundedPreceding, -1)
    return (
        placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "p.sequence_id", "p.slot")
        .withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0)))
        .drop("slot")
    )


def pack_documents(docs: DataFrame) -> DataFrame:
    import public_tokenizers as tokenizers

    return pack(materialise(pieces(docs, tokenizers.path("byte_bpe_50k.json"), tokenizers.PATTERN), "pieces"))


def padding(packed: DataFrame, window: int = WINDOW) -> DataFrame:
    """One row: sequences, tokens, padded slots (a sequence whose fill is a power of two isn't padded) and the padded share."""
    sums = packed.groupBy("sequence_id").agg(F.sum("length").alias("fill"))
    pad = F.when(F.bit_count("fill") == 1, F.lit(0)).otherwise(F.lit(window) - F.col("fill"))
    one = sums.agg(F.count(F.lit(1)).alias("n_sequences"), F.sum("fill").alias("n_tokens"), F.sum(pad).alias("n_padding"))
    return one.withColumn("padding_share", F.round(F.col("n_padding") / (F.col("n_padding") + F.col("n_tokens")), 6))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents"))


def packing_padding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return padding(op6_packing(spark, sf_dir))


QUERIES = {"op6_packing": op6_packing, "packing_padding": packing_padding}
SQL: dict[str, str] = {}
