"""Byte-level BPE encoding and decoding by recursive DuckDB queries, one in-process database for each Python worker.

The distinct pre-tokens of a batch become rows of tokens and of the ranks of their neighbouring pairs. A recursive query contracts, in
every round, the leftmost pair of least rank of each word and joins only the two pairs that this makes with the merge table; words
without a pair leave the recursion. Ordered aggregation through the vocabulary gives each word's decoded bytes. A document's ids are
those of its words in order: texts are cut at spaces, equal pieces are split once, and Arrow arrays of bytes put words together again.

Words that were met before are kept in a cache of bounded size. Words longer than ``LONG_WORD`` bytes would need as many rounds
as bytes, so the same rule is applied to them with a heap (also exact; tests compare both).

Defined results: null text is empty: 0 tokens and the hashes of no bytes. Repeated rows give repeated rows; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from .common import load

LONG_WORD = 400
#: Words and bytes of a worker's cache; beyond either the half that was used last stays.
CACHE, CACHE_BYTES = 900_000, 32_000_000
#: Characters of texts that go through together (one text may have more).
GROUP = 8_000_000
#: Words of a query, and the sum of their squared lengths: the recursion keeps all its rounds.
WORDS, SQUARES = 100_000, 40_000_000
#: No rank: what stands at a word's ends, and pairs that aren't merged.
NONE = 2**31 - 1

# toks has a mark at both ends, so that every pair has neighbours; ranks[i] belongs to toks[i] and toks[i + 1]
_ROUNDS = f"""
WITH RECURSIVE s(word, toks, ranks, best) AS (
  SELECT word, toks, ranks, list_min(ranks) FROM start
  UNION ALL
  SELECT word, toks, ranks, list_min(ranks) FROM (
    SELECT word,
      list_concat(toks[:pos - 1], [best], toks[pos + 2:]) AS toks,
      list_concat(ranks[:pos - 2], [coalesce(a.rank, {NONE}), coalesce(b.rank, {NONE})], ranks[pos + 2:]) AS ranks
    FROM (SELECT word, toks, ranks, best, list_position(ranks, best) AS pos FROM s WHERE best < {NONE}) q
    LEFT JOIN merges a ON a.pair = (toks[pos - 1]::BIGINT << 32) + best
    LEFT JOIN merges b ON b.pair = (best::BIGINT << 32) + toks[pos + 2]
  )
),
ended AS MATERIALIZED (SELECT word, toks[2:len(toks) - 1] AS toks FROM s WHERE best = {NONE})
SELECT word, toks, bytes FROM ended
JOIN (SELECT word, string_agg(hx, '' ORDER BY pos) AS bytes FROM (SELECT word, unnest(range(1, len(toks) + 1)) AS pos, unnest(toks) AS id FROM ended) JOIN vocab USING (id) GROUP BY word) USING (word)
ORDER BY word
"""


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def heap_encode(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same contraction with a heap over a linked list; for words of any length."""
    part = [word[i : i + 1] for i in range(len(word))]
    after, before = list(range(1, len(word) + 1)), list(range(-1, len(word) - 1))
    heap = [(r, i, 1, 1) for i in range(len(word) - 1) if (r := ranks.get(part[i] + part[i + 1])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, a, b = heapq.heappop(heap)
        j = after[i] if part[i] else len(part)
        if j >= len(part) or len(part[i]) != a or len(part[j]) != b:
            continue  # one of the two was contracted meanwhile
        part[i] += part[j]
        part[j] = b""
        after[i] = after[j]
        if after[i] < len(part):
            before[after[i]] = i
        for x in (before[i], i):
            if x >= 0 and (y := after[x]) < len(part) and (r := ranks.get(part[x] + part[y])) is not None:
                heapq.heappush(heap, (r, x, len(part[x]), len(part[y])))
    return [ranks[p] for p in part if p]


def _bytes(ends: np.ndarray, data: pa.Buffer) -> pa.LargeBinaryArray:
    """The pieces of ``data`` between neighbouring ``ends`` (the first of them 0)."""
    return pa.Array.from_buffers(pa.large_binary(), len(ends) - 1, [None, pa.py_buffer(np.ascontiguousarray(ends, dtype=np.int64)), data])


def _joined(pieces: pa.LargeBinaryArray, at: np.ndarray, ends: np.ndarray) -> pa.LargeBinaryArray:
    """For neighbouring ``ends`` (the first of them 0): the concatenation of the pieces whose numbers stand in ``at`` between them."""
    taken = pieces.take(pa.array(at))
    places = np.frombuffer(taken.buffers()[1], dtype=np.int64) if len(taken) else np.zeros(1, dtype=np.int64)
    return _bytes(places[ends], taken.buffers()[2] or pa.py_buffer(b""))


def _ends(sizes) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)]).astype(np.int64)


class Codec:
    """Encodes and decodes batches of texts; built once in each Python worker."""

    def __init__(self, path: str, pattern: str):
        import duckdb
        import regex

        self.ranks = read_ranks(path)
        self.vocab = {i: t for t, i in self.ranks.items()}
        self.split = regex.compile(pattern).findall
        # a space next to other white space: its match reaches over the space
        self.crosses = re.compile(r" \s|\s ").search
        self.cut = re.compile(r"(?<!\s) (?!\s)").split
        self.single = np.array([*(self.ranks[bytes([b])] for b in range(256)), NONE], dtype=np.int32)
        self.double = np.full((257, 257), NONE, dtype=np.int32)
        for t, i in self.ranks.items():
            if len(t) == 2:
                self.double[t[0], t[1]] = i
        #: Numbers of the words that are kept; their ids and bytes, and the group that used each last, by number.
        self.words: dict[str, int] = {}
        self.ids = self.back = pa.array([], pa.large_binary())
        self.used = np.array([], dtype=np.int64)
        self.groups = 0
        self.db = duckdb.connect(":memory:", config={"threads": 1, "memory_limit": "300MB"})
        pairs = [(a, b, rank) for t, rank in self.ranks.items() for k in range(1, len(t)) if (a := self.ranks.get(t[:k])) is not None and (b := self.ranks.get(t[k:])) is not None]
        given = pd.DataFrame(pairs, columns=["l", "r", "rank"]).astype("int64")
        names = pd.DataFrame({"id": list(self.vocab), "hx": [t.hex() for t in self.vocab.values()]})
        self.db.register("given", given)
        self.db.register("names", names)
        self.db.execute("CREATE TABLE merges AS SELECT (l << 32) + r AS pair, rank::INT AS rank FROM given")
        self.db.execute("CREATE TABLE vocab AS SELECT id::INT AS id, hx FROM names")
        self.db.unregister("given")
        self.db.unregister("names")

    def rounds(self, words: list[bytes]) -> tuple[pa.LargeBinaryArray, pa.LargeBinaryArray]:
        """Ids and decoded bytes of each word, by the recursive query."""
        ends = _ends([len(w) + 2 for w in words])  # of the words with their marks
        inner = np.ones(ends[-1], dtype=bool)
        inner[ends[:-1]] = inner[ends[1:] - 1] = False
        symbols = np.full(ends[-1], 256)
        symbols[inner] = np.frombuffer(b"".join(words), dtype=np.uint8)
        ranks = np.delete(self.double[symbols[:-1], symbols[1:]], ends[1:-1] - 1)
        start = pa.table({
            "word": pa.array(np.arange(len(words), dtype=np.int32)),
            "toks": pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(self.single[symbols])),
            "ranks": pa.ListArray.from_arrays(pa.array((ends - np.arange(len(ends))).astype(np.int32)), pa.array(ranks)),
        })
        self.db.register("start", start)
        done = self.db.sql(_ROUNDS).to_arrow_table().combine_chunks()
        self.db.unregister("start")
        toks, hexes = done["toks"].combine_chunks(), done["bytes"].combine_chunks()
        ids = np.ascontiguousarray(toks.flatten().to_numpy(), dtype="<u4")
        back = bytes.fromhex("".join(hexes.to_pylist()))
        return _bytes(4 * _ends(pc.list_value_length(toks).to_numpy()), pa.py_buffer(ids.tobytes())), _bytes(_ends(pc.binary_length(hexes).to_numpy() // 2), pa.py_buffer(back))

    def contracted(self, words: list[bytes]) -> tuple[pa.LargeBinaryArray, pa.LargeBinaryArray]:
        """Ids as little-endian unsigned 32-bit integers, and decoded bytes, of each word."""
        order: list[int] = []
        simple: list[tuple[bytes, bytes]] = []
        short = []
        for k, w in enumerate(words):
            if (whole := self.ranks.get(w)) is not None:
                simple.append((whole.to_bytes(4, "little"), self.vocab[whole]))
                order.append(k)
            elif len(w) > LONG_WORD:
                ids = heap_encode(w, self.ranks)
                simple.append((np.array(ids, dtype="<u4").tobytes(), b"".join(map(self.vocab.__getitem__, ids))))
                order.append(k)
            else:
                short.append(k)
        parts = [tuple(pa.array(x, pa.large_binary()) for x in ([i for i, _ in simple], [t for _, t in simple]))]
        short.sort(key=lambda k: len(words[k]))  # few words take part in many rounds
        order += short
        squares = np.cumsum([len(words[k]) ** 2 for k in short])
        at = 0
        while at < len(short):
            room = SQUARES + (squares[at - 1] if at else 0)
            upto = min(at + WORDS, max(at + 1, int(np.searchsorted(squares, room, side="right"))))
            parts.append(self.rounds([words[k] for k in short[at:upto]]))
            at = upto
        place = pa.array(np.argsort(np.array(order, dtype=np.int64)))
        return pa.concat_arrays([x for x, _ in parts]).take(place), pa.concat_arrays([x for _, x in parts]).take(place)

    def contract(self, words: list[bytes]) -> list[tuple[bytes, bytes]]:
        """(ids as little-endian unsigned 32-bit integers, decoded bytes) of each word."""
        ids, back = self.contracted(words)
        return list(zip(ids.to_pylist(), back.to_pylist(), strict=True))

    def forget(self) -> None:
        """Keep the words that were used last, half the cache of them."""
        sizes = pc.binary_length(self.back).to_numpy()
        if len(self.used) <= CACHE and sizes.sum() <= CACHE_BYTES:
            return
        kept = np.argsort(-self.used, kind="stable")[: CACHE // 2]
        kept = kept[np.cumsum(sizes[kept]) <= CACHE_BYTES // 2]
        names = list(self.words)
        self.words = {names[k]: n for n, k in enumerate(kept.tolist())}
        self.ids, self.back, self.used = self.ids.take(pa.array(kept)), self.back.take(pa.array(kept)), self.used[kept]

    def numbers(self, words: list[str]) -> np.ndarray:
        """The words' numbers in the cache, where they are put if need be."""
        if new := list(set(words).difference(self.words)):
            ids, back = self.contracted([w.encode() for w in new])
            self.words.update(zip(new, range(len(self.words), len(self.words) + len(new)), strict=True))
            self.ids, self.back = pa.concat_arrays([self.ids, ids]), pa.concat_arrays([self.back, back])
            self.used = np.concatenate([self.used, np.zeros(len(new), dtype=np.int64)])
        found = np.fromiter(map(self.words.__getitem__, words), dtype=np.int64, count=len(words))
        self.used[found] = self.groups
        return found

    def pieces(self, texts: list[str]) -> tuple[pa.LargeStringArray, np.ndarray, list[int]]:
        """Texts cut at spaces: pieces, where each text's begin and end among them, and the order of texts in which they come.

        No match crosses the start of a space that has no other white space beside it, so a text may be cut there.
        """
        odd = [k for k, t in enumerate(texts) if self.crosses(t)]
        rest = set(odd)
        even = [k for k in range(len(texts)) if k not in rest]
        lists = pc.split_pattern(pa.array([texts[k] for k in even], pa.large_string()), " ")
        own = [self.cut(texts[k]) for k in odd]
        found = pa.concat_arrays([lists.flatten(), pa.array([c for cs in own for c in cs], pa.large_string())])
        return found, _ends([*pc.list_value_length(lists).to_pylist(), *map(len, own)]), even + odd

    def encode(self, texts: list[str]) -> Iterator[tuple[bytes, bytes]]:
        """(ids, decoded bytes) of every text; texts go through in groups of a few million characters."""
        group: list[str] = []
        size = 0
        for t in texts:
            group.append(t)
            size += len(t)
            if size > GROUP:
                yield from self._coded(group)
                group, size = [], 0
        yield from self._coded(group)

    def _coded(self, group: list[str]) -> Iterator[tuple[bytes, bytes]]:
        if not group:
            return
        self.forget()
        self.groups += 1
        found, ends, order = self.pieces(group)
        heads = found.take(pa.array(ends[:-1])).to_pylist()
        coded = found.dictionary_encode()
        at = coded.indices.to_numpy().astype(np.int64)
        later = np.ones(len(at), dtype=bool)
        later[ends[:-1]] = False
        present = np.zeros(len(coded.dictionary), dtype=bool)
        present[at[later]] = True
        distinct = coded.dictionary.filter(pa.array(present)).to_pylist()
        # pieces without white space but inside, and without spaces, are split together, each behind its space
        easy = np.array([" " not in c and c.strip() == c != "" for c in distinct], dtype=bool)
        words = self.split("".join([" " + c for c, e in zip(distinct, easy, strict=True) if e]))
        begins = np.flatnonzero([w[0] == " " for w in words])
        sizes = np.diff(np.append(begins, len(words))).tolist()
        for c in [*(" " + c for c, e in zip(distinct, easy, strict=True) if not e), *heads]:
            words += (own := self.split(c))
            sizes.append(len(own))
        row = np.zeros(len(present), dtype=np.int64)
        row[np.flatnonzero(present)[np.argsort(~easy, kind="stable")]] = np.arange(len(distinct))
        at = row[at]
        at[~later] = len(distinct) + np.arange(len(heads))
        numbers, cuts = self.numbers(words), _ends(sizes)
        ids, back = (_joined(_joined(kept, numbers, cuts), at, ends) for kept in (self.ids, self.back))
        for k in np.argsort(order).tolist():
            yield ids[k].as_py(), back[k].as_py()


_CODECS: dict[tuple[str, str], Codec] = {}


def codec(path: str, pattern: str) -> Codec:
    if (path, pattern) not in _CODECS:
        _CODECS[path, pattern] = Codec(path, pattern)
    return _CODECS[path, pattern]


def tokenise(docs: DataFrame, path: str, pattern: str, keep_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids as binary, if asked for) of every document; a narrow map, no shuffle."""
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * keep_ids

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = codec(path, pattern)
        for b in batches:
            n, ids_hash, text_hash, kept = [], [], [], []
            for ids, decoded in own.encode([t or "" for t in b["text"]]):
                n.append(len(ids) // 4)
                ids_hash.append(hashlib.sha256(ids).hexdigest())
                text_hash.append(hashlib.sha256(decoded).hexdigest())
                if keep_ids:
                    kept.append(ids)
            out = pd.DataFrame({"doc_id": b["doc_id"], "n_tokens": n, "ids_sha256": ids_hash, "decoded_sha256": text_hash})
            yield out.assign(ids=kept) if keep_ids else out

    return docs.select("doc_id", "text").mapInPandas(run, schema)


def decode_ids(rows: DataFrame, path: str, pattern: str, ids: str = "ids") -> DataFrame:
    """Decode a column of little-endian unsigned 32-bit ids: token rows join the vocabulary, ordered aggregation joins the bytes."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = codec(path, pattern)
        for b in batches:
            lists = [np.frombuffer(x or b"", dtype="<u4") for x in b[ids]]
            sizes = [len(x) for x in lists]
            given = pd.DataFrame({"doc": np.repeat(np.arange(len(lists)), sizes), "pos": np.concatenate([np.arange(n) for n in sizes] or [np.array([], dtype=int)]), "tok": np.concatenate(lists or [np.array([], dtype="<u4")]).astype("int64")})
            own.db.register("given", given)
            found = dict(own.db.execute("SELECT doc, string_agg(hx, '' ORDER BY pos) FROM given JOIN vocab ON vocab.id = given.tok GROUP BY doc").fetchall())
            own.db.unregister("given")
            yield pd.DataFrame({"doc_id": b["doc_id"], "decoded": [bytes.fromhex(found.get(i, "")) for i in range(len(lists))]})

    return rows.select("doc_id", ids).mapInPandas(run, "doc_id long, decoded binary")


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as tokenizers

    return tokenise(load(spark, sf_dir, "documents"), tokenizers.path("byte_bpe_multi_50k.tiktoken"), tokenizers.PATTERN)


QUERIES = {"op3_byte_bpe": op3_byte_bpe}
SQL: dict[str, str] = {}
