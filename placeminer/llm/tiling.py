"""Benchmark decontamination by greedy string tiling (op 8).

Words are lower-cased and stripped of ASCII punctuation. Karp-Rabin hashes of all windows of ``MIN_TILE``
words of a benchmark item are the seeds; windows of documents that hash to a seed are joined to it. In
a document with seeds, matches that start on the same diagonal run on while words agree; the longest match
whose words are unmarked on both sides becomes a tile and is marked, a match that is partly marked goes back with
what is left of it, and so on down to ``MIN_TILE`` words; of equally long ones the first in the document goes first, then the
first in the item. Where the pairs of matching windows are more than ``PAIRS`` (a text that repeats itself), they are not listed: the
longest match is then searched by hashes of windows of falling width over the unmarked words, with equal tiles. The tiles of an item may stand in any order, so
reordered passages count too. The share of an item's words under tiles is its coverage; at ``threshold`` or
above the document is contaminated.

The items are a stated query set: their seeds are sorted once on the driver and broadcast in blocks of at most ``BLOCK`` windows
(about 80 MB), one pass over the documents a block, so nothing that is broadcast grows with either table.

Edge cases: null and empty texts match nothing; items of fewer than ``MIN_TILE`` words have no tile and match
nothing; repeated items and repeated rows are each reported; very long documents are read whole; clashing
columns are kept as they are by :func:`clean` and not read by :func:`matches`; empty tables match nothing.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .words import MULTIPLIERS, WordHashes, mixed, slices, tidy, windows

MIN_TILE = 5
THRESHOLD = 0.5
#: Seed windows that are broadcast at once.
BLOCK = 2_000_000
#: Pairs of windows of one document and one item that are listed.
PAIRS = 100_000
BASE = MULTIPLIERS[3]
PUNCTUATION = bytes(c for c in range(33, 127) if not chr(c).isalnum())


COLUMNS = ("doc_id", "item_id", "n_tiles", "covered", "item_words", "longest", "coverage")


def normal(text: str | None) -> list[bytes]:
    return text.lower().encode().translate(None, PUNCTUATION).split() if text else []


def tiles(doc: np.ndarray, item: np.ndarray, at: np.ndarray, seed: np.ndarray) -> list[tuple[int, int, int]]:
    """Tiles (document position, item position, words) from the pairs of matching windows (``at``, ``seed``).

    The pairs of a diagonal whose positions follow one another are one match; true words are compared at every seed.
    """
    if not len(at):
        return []
    same = np.ones(len(at), bool)
    for i in range(MIN_TILE):
        same &= doc[at + i] == item[seed + i]
    at, seed = at[same], seed[same]
    if not len(at):
        return []
    order = np.lexsort((at, at - seed))
    at, seed = at[order], seed[order]
    cut = np.flatnonzero((np.diff(at - seed) != 0) | (np.diff(at) != 1)) + 1
    first = np.concatenate(([0], cut))
    length = np.diff(np.concatenate((first, [len(at)]))) + MIN_TILE - 1
    heap = [(-int(n), int(a), int(s)) for n, a, s in zip(length, at[first], seed[first])]
    heapq.heapify(heap)
    doc_marked, item_marked, out = np.zeros(len(doc), bool), np.zeros(len(item), bool), []
    while heap:
        n, a, s = heapq.heappop(heap)
        free = ~(doc_marked[a : a - n] | item_marked[s : s - n])
        if free.all():
            doc_marked[a : a - n] = item_marked[s : s - n] = True
            out.append((a, s, -n))
            continue
        edge = np.flatnonzero(np.diff(np.concatenate(([0], free.view(np.int8), [0]))))
        for b, e in zip(edge[::2].tolist(), edge[1::2].tolist()):
            if e - b >= MIN_TILE:
                heapq.heappush(heap, (b - e, a + b, s + b))
    return out


def verified_windows(h: np.ndarray, width: int) -> np.ndarray:
    """Karp-Rabin hashes of all windows of any width, from running sums of a polynomial in word hashes."""
    with np.errstate(over="ignore"):
        power = np.cumprod(np.full(len(h) + 1, BASE, np.uint64))
        sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(h * power[:-1], dtype=np.uint64)))
        # All are brought to the highest power, so that equal windows are equal wherever they stand.
        at = np.arange(len(h) - width + 1)
        return mixed((sums[at + width] - sums[at]) * power[len(h) - width - at])


def tiles_by_width(doc: np.ndarray, item: np.ndarray, at: np.ndarray) -> list[tuple[int, int, int]]:
    """The same tiles as :func:`tiles`, from the document's positions ``at`` of seed windows alone, in memory proportional to the texts."""
    # Only words under seed windows matter; a word of its own between two stretches keeps them apart.
    cover = np.zeros(len(doc) + 1, np.int32)
    np.add.at(cover, at, 1), np.add.at(cover, at + MIN_TILE, -1)
    under = np.flatnonzero(np.cumsum(cover[:-1]) > 0)
    gap = np.flatnonzero(np.diff(under) > 1) + 1
    where = np.insert(under, gap, -1)
    words = np.where(where >= 0, doc[where], np.uint64(0))
    size = max(len(words), len(item))
    pad = lambda h: np.concatenate((h, np.zeros(size - len(h), np.uint64)))
    doc_free, item_free, out = where >= 0, np.ones(len(item), bool), []
    long_doc, long_item = pad(words), pad(item)

    def open_(free: np.ndarray, width: int) -> np.ndarray:
        """Positions from which ``width`` words are unmarked."""
        taken = np.concatenate(([0], np.cumsum(~free)))
        return np.flatnonzero(taken[width:] == taken[:-width]) if len(free) >= width else np.empty(0, np.int64)

    def shared(width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Document positions and item positions of unmarked windows that both have, with their hashes."""
        a, s = open_(doc_free, width), open_(item_free, width)
        if not len(a) or not len(s):
            return a[:0], s[:0], words[:0], item[:0]
        ha, hs = verified_windows(long_doc, width)[a], verified_windows(long_item, width)[s]
        ka, ks = np.isin(ha, hs), np.isin(hs, ha)
        return a[ka], s[ks], ha[ka], hs[ks]

    high = len(item)
    while high >= MIN_TILE:
        low, top = MIN_TILE - 1, high
        while low < top:  # the widest window that both have
            mid = (low + top + 1) // 2
            low, top = (mid, top) if len(shared(mid)[0]) else (low, mid - 1)
        if low < MIN_TILE:
            break
        a, s, ha, hs = shared(low)
        places: dict[int, list[int]] = {}
        for h, x in zip(hs.tolist(), s.tolist()):
            places.setdefault(h, []).append(x)
        after = 0
        for x, h in zip(a.tolist(), ha.tolist()):
            if x < after:
                continue
            held = places.get(h)
            if not held:
                if not places:
                    break
                continue
            free = [y for y in held if item_free[y : y + low].all()]
            if not free:
                del places[h]
                continue
            y = free[0]
            places[h] = free
            if not (words[x : x + low] == item[y : y + low]).all():
                continue
            doc_free[x : x + low] = item_free[y : y + low] = False
            out.append((int(where[x]), y, low))
            after = x + low
        high = low - 1
    return out


class Seeds:
    """Sorted seed windows of a block of items."""

    def __init__(self, rows: list[tuple[int, str | None]]):
        words = WordHashes()
        self.items = [(i, words.of(w)) for i, w in ((i, normal(t)) for i, t in rows) if len(w) >= MIN_TILE]
        hashes = [windows(h, MIN_TILE) for _, h in self.items]
        owner = np.repeat(np.arange(len(hashes)), [len(h) for h in hashes])
        place = np.concatenate([np.arange(len(h)) for h in hashes]) if hashes else np.empty(0, np.int64)
        joined = np.concatenate(hashes) if hashes else np.empty(0, np.uint64)
        order = np.argsort(joined, kind="stable")
        self.hash, self.owner, self.place = joined[order], owner[order], place[order]
        #: One bit for the top 20 bits of each seed, so that most windows need no search.
        self.gate = np.zeros(1 << 20, bool)
        self.gate[(self.hash >> np.uint64(44)).astype(np.int64)] = True

    def found(self, h: np.ndarray) -> Iterator[tuple[int, int, int, int, int]]:
        """(item, tiles, covered words, item words, longest tile) for each item with a tile in a document of word hashes."""
        w = windows(h, MIN_TILE)
        near = np.flatnonzero(self.gate[(w >> np.uint64(44)).astype(np.int64)])
        if not len(near):
            return
        lo = np.searchsorted(self.hash, w[near], "left")
        near = near[self.hash[np.minimum(lo, len(self.hash) - 1)] == w[near]]
        if not len(near):
            return
        # Equal windows of the document stand together; seeds meet them as groups, one item at a time.
        near = near[np.argsort(w[near], kind="stable")]
        key, first, times = np.unique(w[near], return_index=True, return_counts=True)
        lo, hi = np.searchsorted(self.hash, key, "left"), np.searchsorted(self.hash, key, "right")
        group = np.repeat(np.arange(len(key)), hi - lo)
        row = ranges(lo, hi - lo)
        owner, place = self.owner[row], self.place[row]
        order = np.argsort(owner, kind="stable")
        owner, place, group = owner[order], place[order], group[order]
        cut = np.concatenate(([0], np.flatnonzero(np.diff(owner)) + 1, [len(owner)]))
        for b, e in zip(cut[:-1].tolist(), cut[1:].tolist()):
            item, words = self.items[owner[b]]
            g = group[b:e]
            if times[g].sum() <= PAIRS:
                t = tiles(h, words, near[ranges(first[g], times[g])], np.repeat(place[b:e], times[g]))
            else:
                g = np.unique(g)
                t = tiles_by_width(h, words, near[ranges(first[g], times[g])])
            if t:
                yield item, len(t), sum(x[2] for x in t), len(words), max(x[2] for x in t)


def ranges(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """first[0], first[0] + 1, ... n[0] of them, then those of the next."""
    return np.repeat(first - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())


def blocks(benchmark: DataFrame, size: int = BLOCK) -> Iterator[list[tuple[int, str | None]]]:
    """The benchmark's items in blocks of at most about ``size`` words."""
    block, words = [], 0
    for r in benchmark.select("item_id", "text").toLocalIterator():
        n = len(r["text"] or "") // 2
        if block and words + n > size:
            yield block
            block, words = [], 0
        block.append((r["item_id"], r["text"]))
        words += n
    yield block


def matches(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, item_id, n_tiles, covered, item_words, longest, coverage of every pair at or above the threshold."""
    out = None
    for block in blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(Seeds(block))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            seeds, words = shared.value, WordHashes()
            for batch in (part for whole in batches for part in slices(whole)):
                rows = []
                for d, t in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                    rows += [(d, *f, f[2] / f[3]) for f in seeds.found(words.of(normal(t))) if f[2] >= threshold * f[3]]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.float64() if n == "coverage" else pa.int64()) for n, c in zip(COLUMNS, zip(*rows))], names=list(COLUMNS))

        found = docs.select("doc_id", "text").mapInArrow(tidy(run), "doc_id long, item_id long, n_tiles long, covered long, item_words long, longest long, coverage double")
        out = found if out is None else out.unionAll(found)
    return out


def clean(docs: DataFrame, benchmark: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that no item contaminates, with all their columns."""
    out = docs
    for block in blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(Seeds(block))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            seeds, words = shared.value, WordHashes()
            for batch in (part for whole in batches for part in slices(whole)):
                keep = [not any(f[2] >= threshold * f[3] for f in seeds.found(words.of(normal(t)))) for t in batch.column("text").to_pylist()]
                yield batch.filter(pa.array(keep, pa.bool_()))

        out = out.mapInArrow(tidy(run), out.schema)
    return out
