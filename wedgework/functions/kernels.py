"""Intersection kernels over Arrow list buffers: binary search, sorted merge and the hybrid of both; one numpy call sequence for a batch.

Searching puts all longer lists of a batch into one ascending array (each list shifted into a range of its own), so that one
``searchsorted`` answers all keys. Merging lays both sides, each ascending as a whole, end to end; the stable sort finds the two runs and
merges them in linear time, and equal neighbours are counted.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def _flat(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    offsets = lists.offsets.to_numpy().astype(np.int64)
    return lists.values.to_numpy(zero_copy_only=False).astype(np.int64)[offsets[0] : offsets[-1]], offsets - offsets[0]


def _take(values: np.ndarray, offsets: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    sizes = (offsets[1:] - offsets[:-1])[rows]
    ends = np.cumsum(sizes)
    at = np.arange(int(ends[-1]) if len(ends) else 0) - np.repeat(ends - sizes, sizes) + np.repeat(offsets[:-1][rows], sizes)
    return values[at], np.repeat(np.arange(len(rows)), sizes)


def _keys(va, ra, vb, rb) -> tuple[np.ndarray, np.ndarray]:
    low = min(va.min(initial=0), vb.min(initial=0))
    span = max(va.max(initial=0), vb.max(initial=0)) - low + 1
    return ra * span + (va - low), rb * span + (vb - low)


def search(va, ra, vb, rb, n: int) -> np.ndarray:
    """Keys a are looked up in the (longer) lists b."""
    ka, kb = _keys(va, ra, vb, rb)
    if not len(kb):
        return np.zeros(n, dtype=np.int64)
    i = np.minimum(np.searchsorted(kb, ka), len(kb) - 1)
    return np.bincount(ra[kb[i] == ka], minlength=n)


def merge(va, ra, vb, rb, n: int) -> np.ndarray:
    low = min(va.min(initial=0), vb.min(initial=0))
    span = max(va.max(initial=0), vb.max(initial=0)) - low + 1
    both = np.concatenate([ra * span + (va - low), rb * span + (vb - low)])
    both.sort(kind="stable")
    return np.bincount(both[1:][both[1:] == both[:-1]] // span, minlength=n)


#: What a step of merging costs, in steps of searching, in these kernels: merging copies both lists, searching copies none. Measured.
MERGE_COST = 6.0


def use_merge(small: np.ndarray, large: np.ndarray, cost: float = 1.0) -> np.ndarray:
    """The size rule: merge when cost * (small + large) <= small * log2(large); with cost 1, when large / small <= log2(large) - 1."""
    s, b = small.astype(np.float64), large.astype(np.float64)
    return (s > 0) & (s * (np.log2(np.maximum(b, 1)) - cost) >= cost * b)


#: Values in all lists' range for each longer list and key, up to which longer lists meet their partners together.
LONG = 1.0


def _meet(keys: np.ndarray, whole: np.ndarray, by_merge: bool, cutoff: int | None) -> np.ndarray:
    """What two ascending lists share. A merge takes the second in pieces, each against those keys that lie in its range."""
    if not by_merge:
        return keys[whole[np.minimum(np.searchsorted(whole, keys), len(whole) - 1)] == keys]
    cutoff = cutoff or len(whole)
    piece = np.searchsorted(whole[::cutoff], keys, side="right") - 1
    keys, piece = keys[piece >= 0], piece[piece >= 0]
    span = int(max(whole[-1], keys[-1] if len(keys) else 0)) + 1
    both = np.concatenate([piece * span + keys, np.arange(len(whole)) // cutoff * span + whole])
    both.sort(kind="stable")
    return both[1:][both[1:] == both[:-1]] % span


def _by_long(values, offsets, small, large, rows, by_merge: bool, first: int, wide: int, cutoff: int | None, out: np.ndarray) -> None:
    """Each longer list meets the distinct keys of its partners once, by search or merge; then every partner counts its own keys among those found."""
    if not len(rows):
        return
    rows = rows[np.argsort(large[rows], kind="stable")]
    cuts = np.flatnonzero(np.diff(large[rows], prepend=-1))
    size = np.diff(offsets)
    marked = np.zeros(wide, dtype=bool)
    for lo, hi in zip(cuts, np.append(cuts[1:], len(rows)), strict=True):
        b = large[rows[lo]]
        whole = values[offsets[b] : offsets[b + 1]] - first
        for at in _chunks(size[small[rows[lo:hi]]], 1 << 20):
            own = rows[lo:hi][at]
            key = np.concatenate([values[offsets[k] : offsets[k + 1]] for k in small[own]]) - first
            marked[key] = True
            keys = np.flatnonzero(marked)
            marked[keys] = False
            found = _meet(keys, whole, by_merge, cutoff)
            marked[found] = True
            out[own] = np.add.reduceat(marked[key], np.cumsum(size[small[own]]) - size[small[own]], dtype=np.int64)
            marked[found] = False


def _rule(kernel: str, small: np.ndarray, large: np.ndarray) -> np.ndarray:
    if kernel in ("merge", "search"):
        return np.full(len(small), kernel == "merge")
    return use_merge(small, large, MERGE_COST if kernel == "tuned" else 1.0)


def _chunks(sizes: np.ndarray, most: int = 1 << 22) -> list[slice]:
    """Runs of rows whose sizes add up to about ``most``."""
    if not len(sizes):
        return []
    cuts = np.unique(np.searchsorted(np.cumsum(sizes), np.arange(most, int(sizes.sum()) + most, most), side="right"))
    edges = [0, *(int(c) for c in cuts if 0 < c < len(sizes)), len(sizes)]
    return [slice(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True)]


def common(a: pa.ListArray, b: pa.ListArray, kernel: str = "hybrid") -> np.ndarray:
    """Sizes of the intersections of two columns of ascending distinct lists."""
    va, oa = _flat(a)
    vb, ob = _flat(b)
    na, nb = np.diff(oa), np.diff(ob)
    n = len(na)
    swap = na > nb  # the longer list is the one that is searched
    out = np.zeros(n, dtype=np.int64)
    by_merge = _rule(kernel, np.minimum(na, nb), np.maximum(na, nb))
    for flipped in (False, True):
        for merged in (False, True):
            rows = np.flatnonzero((swap == flipped) & (by_merge == merged) & (np.minimum(na, nb) > 0))
            if len(rows):
                small, large = ((vb, ob), (va, oa)) if flipped else ((va, oa), (vb, ob))
                out[rows] = (merge if merged else search)(*_take(*small, rows), *_take(*large, rows), len(rows))
    return out


def common_rows(values: np.ndarray, offsets: np.ndarray, a: np.ndarray, b: np.ndarray, kernel: str = "hybrid", cutoff: int | None = None) -> np.ndarray:
    """Sizes of the intersections of the rows a and b of compressed sparse rows (each row ascending and distinct).

    Every row is shifted into a range of its own, so the whole array ascends and keys are looked up in it as it stands: no list is copied
    for being searched. Only rows that are merged are gathered, some millions of entries at a time. Kernel 'tuned' is the hybrid with its rule
    weighted by what the steps cost here. Where lists are dense, each longer one meets its partners together (``_by_long``); there, merging
    takes it in pieces of ``cutoff``.
    """
    size = np.diff(offsets)
    n = len(a)
    small, large = np.where(size[a] <= size[b], a, b), np.where(size[a] <= size[b], b, a)
    live = size[small] > 0
    merged = live & _rule(kernel, size[small], size[large])
    out = np.zeros(n, dtype=np.int64)
    first = int(values.min(initial=0))
    wide = int(values.max(initial=0)) - first + 1
    if wide * len(np.unique(large[live])) <= LONG * int(size[small[live]].sum()):
        for by_merge in (True, False):
            _by_long(values, offsets, small, large, np.flatnonzero(live & (merged == by_merge)), by_merge, first, wide, cutoff, out)
        return out
    rows = np.flatnonzero(merged)
    for at in _chunks((size[small] + size[large])[rows]):
        own = rows[at]
        out[own] = merge(*_take(values, offsets, small[own]), *_take(values, offsets, large[own]), len(own))
    rows = np.flatnonzero(live & ~merged)
    if len(rows):
        low, span = int(values.min()), int(values.max()) - int(values.min()) + 1
        whole = np.repeat(np.arange(len(size)) * span - low, size) + values
        rows = rows[np.argsort(large[rows], kind="stable")]  # neighbouring keys then fall into the same list
        for at in _chunks(size[small][rows]):
            own = rows[at]
            key, of = _take(values, offsets, small[own])
            key = large[own][of] * span - low + key
            i = np.minimum(np.searchsorted(whole, key), len(whole) - 1)
            out[own] = np.bincount(of[whole[i] == key], minlength=len(own))
    return out
