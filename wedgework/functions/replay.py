"""A read cache as a plain state machine: the same class serves batch replays, table functions and streams."""

from __future__ import annotations

import bisect
import heapq
from collections import OrderedDict

from ..schema import CacheConfig


class Buffer:
    """A byte buffer with free regions; entries of any size, first or best fit."""

    def __init__(self, size: int, fit: str):
        self.size, self.fit = size, fit
        self.starts, self.lengths = ([0], [size]) if size else ([], [])

    def place(self, n: int) -> int | None:
        fits = [(length, i) for i, length in enumerate(self.lengths) if length >= n]
        if not fits:
            return None
        i = min(fits)[1] if self.fit == "best" else min(i for _, i in fits)
        at = self.starts[i]
        if self.lengths[i] == n:
            del self.starts[i], self.lengths[i]
        else:
            self.starts[i] += n
            self.lengths[i] -= n
        return at

    def free(self, at: int, n: int) -> None:
        i = bisect.bisect_left(self.starts, at)
        self.starts.insert(i, at)
        self.lengths.insert(i, n)
        if i + 1 < len(self.starts) and at + n == self.starts[i + 1]:
            self.lengths[i] += self.lengths[i + 1]
            del self.starts[i + 1], self.lengths[i + 1]
        if i and self.starts[i - 1] + self.lengths[i - 1] == at:
            self.lengths[i - 1] += self.lengths[i]
            del self.starts[i], self.lengths[i]

    def beside(self, at: int, n: int) -> int:
        """Free bytes that adjoin the entry."""
        i = bisect.bisect_left(self.starts, at)
        after = self.lengths[i] if i < len(self.starts) and self.starts[i] == at + n else 0
        before = self.lengths[i - 1] if i and self.starts[i - 1] + self.lengths[i - 1] == at else 0
        return after + before


class ReadCache:
    """One window's cache of one part."""

    def __init__(self, cfg: CacheConfig):
        self.cfg, self.slots, self.capacity = cfg, cfg.slots, cfg.capacity_bytes
        self.touched: set[int] = set()
        self.clock = self.reads = 0
        self.recent = {"conflict": 0, "capacity": 0}
        self.flush()

    def flush(self) -> None:
        self.held: OrderedDict[int, tuple[int, int, float, int]] = OrderedDict()  # key: (size, address, score, time)
        self.bytes = 0
        self.index: dict[int, list[int]] = {}
        self.heap: list[tuple[float, int, int]] = []
        self.buffer = Buffer(self.capacity, self.cfg.fit) if self.cfg.fragmentation else None
        self.lost: dict[int, str] = {}

    def _drop(self, key: int, why: str) -> None:
        size, at, _, _ = self.held.pop(key)
        self.bytes -= size
        self.lost[key] = why
        if self.slots:
            self.index[hash_slot(key, self.slots)].remove(key)
        if self.buffer:
            self.buffer.free(at, size)

    def _victim(self, score: float) -> int | None:
        if not self.held:
            return None
        if self.cfg.score == "lru":
            return next(iter(self.held))
        if self.cfg.score == "lru_positional":
            beside = self.buffer.beside if self.buffer else lambda at, n: 0
            return min(self.held, key=lambda k: (self.held[k][3] - self.cfg.position_weight * beside(self.held[k][1], self.held[k][0]), k))
        while self.heap:
            low, time, key = self.heap[0]
            if key in self.held and self.held[key][3] == time:
                return key if low < score else None
            heapq.heappop(self.heap)
        return None

    def read(self, key: int, size: int, score: float = 0.0, flush_before: bool = False) -> tuple[str, int]:
        """(outcome, evicted entries): hit, or a compulsory, conflict or capacity miss."""
        cfg = self.cfg
        if (cfg.mode == "user" and flush_before) or (cfg.mode == "transparent" and cfg.epoch_len and self.reads and self.reads % cfg.epoch_len == 0):
            self.flush()
        self.reads += 1
        self.clock += 1
        if key in self.held:
            n, at, s = *self.held[key][:2], score
            self.held[key] = (n, at, s, self.clock)
            self.held.move_to_end(key)
            if cfg.score == "app":
                heapq.heappush(self.heap, (s, self.clock, key))
            return "hit", 0
        outcome = "compulsory" if key not in self.touched else self.lost.get(key, "capacity")
        self.touched.add(key)
        evicted = 0
        slot = hash_slot(key, self.slots) if self.slots else None
        if slot is not None and len(own := self.index.setdefault(slot, [])) >= cfg.ways:
            worst = min(own, key=lambda k: (self.held[k][2], self.held[k][3]) if cfg.score == "app" else (self.held[k][3],))
            if cfg.score == "app" and self.held[worst][2] >= score:
                self.lost[key] = "conflict"
                return self._count(outcome), 0
            self._drop(worst, "conflict")
            evicted += 1
        if size > self.capacity:
            self.lost[key] = "capacity"
            return self._count(outcome), evicted
        at = 0
        while (at := self.buffer.place(size)) is None if self.buffer else self.bytes + size > self.capacity:
            victim = self._victim(score)
            if victim is None:
                self.lost[key] = "capacity"
                return self._count(outcome), evicted
            self._drop(victim, "capacity")
            evicted += 1
        self.held[key] = (size, at or 0, score, self.clock)
        self.bytes += size
        if cfg.score == "app":
            heapq.heappush(self.heap, (score, self.clock, key))
        if slot is not None:
            self.index.setdefault(slot, []).append(key)
        return self._count(outcome), evicted

    def _count(self, outcome: str) -> str:
        if outcome in self.recent:
            self.recent[outcome] += 1
        cfg = self.cfg
        if cfg.adaptive and self.reads % cfg.adapt_every == 0:
            grow_slots = self.slots and self.recent["conflict"] > cfg.conflict_threshold * cfg.adapt_every
            grow_bytes = self.recent["capacity"] > cfg.capacity_threshold * cfg.adapt_every
            self.recent = {"conflict": 0, "capacity": 0}
            if grow_slots or grow_bytes:
                self.slots *= 2 if grow_slots else 1
                self.capacity *= 2 if grow_bytes else 1
                self.flush()
        return outcome


def hash_slot(key: int, slots: int) -> int:
    return ((key * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF) >> 20) % slots


def reuse_hits(keys: list[int], entries: list[int]) -> list[int]:
    """Hits of recency caches of equal-size entries, for several capacities at once: a read hits if fewer distinct keys lie between (a tree of counts)."""
    n = len(keys)
    tree = [0] * (n + 1)

    def add(i: int, x: int) -> None:
        while i <= n:
            tree[i] += x
            i += i & -i

    def upto(i: int) -> int:
        s = 0
        while i:
            s += tree[i]
            i -= i & -i
        return s

    last: dict[int, int] = {}
    distances = []
    for i, k in enumerate(keys, 1):
        if k in last:
            distances.append(upto(i - 1) - upto(last[k]))
            add(last[k], -1)
        add(i, 1)
        last[k] = i
    distances.sort()
    return [bisect.bisect_left(distances, e) for e in entries]
