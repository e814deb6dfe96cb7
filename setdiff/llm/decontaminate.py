"""Benchmark decontamination by SimHash windows of the items' own sizes.

Texts and items are lower-cased and split into word runs; five words make a shingle (an item of fewer
words is one shingle). A window has as many shingles as an item; its fingerprint is the bitwise majority of its shingle hashes.
Fingerprints of items lie in a multi-index: the 64 bits in five blocks of 12 or 13, each block with every value within three bits
of an item's. Two fingerprints within 19 bits agree within three bits on some block, so the index finds every item
within the radius. At similarity 0.8 fingerprints lie about 10 bits apart; beyond 19 are about one in two thousand. Candidates are then verified exactly: the weighted Jaccard similarity of the two multisets of shingles (a shingle weighs
as often as it occurs) has to reach ``similarity``.

A window that shares no shingle with an item has similarity zero, so windows are only laid where a shingle of
some item of that size occurs; this drops no result, and keeps the pass over the text at a few operations a word.

The benchmark is the small side: it is taken in blocks of ``BLOCK_ITEMS`` items, one pass over the documents each.
Null and empty texts match nothing; an item without words matches nothing; repeated rows give rows of their own, a repeated
item counts once; further columns are left alone; an empty table on either side gives no rows.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from itertools import combinations, pairwise
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, small, stowed

SHINGLE, WITHIN = 5, 3
#: Where the blocks of a fingerprint begin and end.
EDGES = (0, 13, 26, 39, 52, 64)
#: Every fingerprint within this many bits is found: some block then differs in WITHIN bits at most.
RADIUS = (len(EDGES) - 1) * (WITHIN + 1) - 1
#: Windows looked up together.
AT_ONCE = 1024
BLOCK_ITEMS = 4000
_WORD = re.compile(rb"[0-9a-z_\x80-\xff]+")
_ODD = np.array([(0x9E3779B97F4A7C15 * (k + 1) ** 2) % 2**64 | 1 for k in range(SHINGLE)], np.uint64)


def words_of(text: str | None) -> list[bytes]:
    return _WORD.findall((text or "").lower().encode("utf-8", "surrogatepass"))


def shingle_hashes(words: list[bytes], size: int) -> np.ndarray:
    """64-bit hash of each run of ``size`` words."""
    n = len(words) - size + 1
    if n < 1:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(crc32, words), np.uint64, len(words))
    h = (h + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    total = np.zeros(n, np.uint64)
    for k in range(size):
        total += h[k : k + n] * _ODD[k]
    total ^= total >> np.uint64(31)
    total *= np.uint64(0x94D049BB133111EB)
    return total ^ (total >> np.uint64(29))


def window_fingerprints(h: np.ndarray, k: int) -> np.ndarray:
    """Fingerprint of every run of ``k`` shingle hashes."""
    bits = np.unpackbits(h.view(np.uint8), bitorder="little").reshape(-1, 64)
    run = np.zeros((len(h) + 1, 64), np.int32)
    np.cumsum(bits, axis=0, out=run[1:])
    return np.packbits(2 * (run[k:] - run[:-k]) > k, axis=1, bitorder="little").view("<u8")[:, 0]


def _block(fp: np.ndarray, low: int, high: int) -> np.ndarray:
    return ((fp >> np.uint64(low)) & np.uint64(2 ** (high - low) - 1)).astype(np.int64)


class ItemIndex:
    """Fingerprints and shingles of some benchmark items."""

    def __init__(self, items: list[tuple[int, str | None]]):
        self.items = []
        for item, text in items:
            words = words_of(text)
            if words:
                size = min(SHINGLE, len(words))
                self.items.append((item, size, Counter(tuple(words[i : i + size]) for i in range(len(words) - size + 1)), shingle_hashes(words, size)))
        self.sizes = sorted({x[1] for x in self.items})
        self.length = np.array([len(x[3]) for x in self.items], np.int64)
        fps = np.array([window_fingerprints(x[3], len(x[3]))[0] for x in self.items], np.uint64)
        self.fps = fps
        self.tables = []
        for low, high in pairwise(EDGES if len(fps) else ()):
            near = np.array([sum(1 << b for b in c) for t in range(WITHIN + 1) for c in combinations(range(high - low), t)], np.int64)
            key = (_block(fps, low, high)[:, None] ^ near[None, :]).ravel().astype(np.int32)
            order = np.argsort(key, kind="stable")
            self.tables.append((np.searchsorted(key[order], np.arange(2 ** (high - low) + 1)), np.repeat(np.arange(len(fps)), len(near))[order].astype(np.int32)))
        self.marks, self.owners = {}, {}
        for size in self.sizes:
            mark = np.zeros(1 << 20, bool)
            own: dict[int, set[int]] = {}
            for i, x in enumerate(self.items):
                if x[1] == size:
                    mark[(x[3] >> np.uint64(44)).astype(np.int64)] = True
                    for h in x[3].tolist():
                        own.setdefault(h, set()).add(len(x[3]))
            self.marks[size], self.owners[size] = mark, own

    def within(self, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(window number, item number) of all pairs within the radius."""
        wins, items = [], []
        for (low, high), (start, held) in zip(pairwise(EDGES), self.tables, strict=True):
            v = _block(fp, low, high)
            n = start[v + 1] - start[v]
            w = np.repeat(np.arange(len(fp)), n)
            first = np.repeat(start[v] - np.cumsum(n) + n, n)
            wins.append(w)
            items.append(held[first + np.arange(len(w))])
        w, i = np.concatenate(wins), np.concatenate(items)
        ok = np.bitwise_count(fp[w] ^ self.fps[i]) <= RADIUS
        pairs = np.unique(w[ok] * len(self.fps) + i[ok])
        return pairs // len(self.fps), pairs % len(self.fps)

    def find(self, text: str | None, similarity: float) -> list[tuple[int, float, int, int, int]]:
        """Best match of each item found: (item_id, similarity, Hamming distance, first word, words)."""
        if not self.items or not text:
            return []
        words, best = words_of(text), {}
        for size in self.sizes:
            h = shingle_hashes(words, size)
            at = np.flatnonzero(self.marks[size][(h >> np.uint64(44)).astype(np.int64)])
            starts: dict[int, set[int]] = {}
            for p in at.tolist():
                for k in self.owners[size].get(int(h[p]), ()):
                    starts.setdefault(k, set()).update(range(max(0, p - k + 1), min(p, len(h) - k) + 1))
            for k, some in starts.items():
                begin = np.array(sorted(some), np.int64)
                for run in np.split(begin, np.flatnonzero(np.diff(begin) > 1) + 1):
                    for a in range(0, len(run), AT_ONCE):
                        first, last = int(run[a]), int(run[min(a + AT_ONCE, len(run)) - 1])
                        fp = window_fingerprints(h[first : last + k], k)
                        for w, i in zip(*(x.tolist() for x in self.within(fp)), strict=True):
                            if self.length[i] != k or self.items[i][1] != size:
                                continue
                            p = first + w
                            there = Counter(tuple(words[j : j + size]) for j in range(p, p + k))
                            item = self.items[i][2]
                            both = sum((there & item).values())
                            sim = both / (2 * k - both)
                            if sim >= similarity and (i not in best or sim > best[i][0]):
                                best[i] = (sim, int(np.bitwise_count(fp[w] ^ self.fps[i])), p, k + size - 1)
        return [(self.items[i][0], *v) for i, v in sorted(best.items())]


_HELD: list[tuple[bytes, ItemIndex]] = []


def _index(items: list[tuple[int, str | None]]) -> ItemIndex:
    """The index of this process for some items."""
    import hashlib

    key = hashlib.sha256(repr(items).encode("utf-8", "surrogatepass")).digest()
    if not _HELD or _HELD[0][0] != key:
        _HELD[:] = [(key, ItemIndex(items))]
    return _HELD[0][1]


def forget_index() -> None:
    """Drops the index of this process."""
    _HELD.clear()


def _blocks(benchmark: DataFrame) -> Iterator[list[tuple[int, str | None]]]:
    """The items in blocks of about BLOCK_ITEMS, each small enough for the driver."""
    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).distinct()
    parts = -(-rows.count() // BLOCK_ITEMS)
    for p in range(parts):
        yield sorted(((r["item_id"], r["text"]) for r in rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == p).collect()), key=repr)


def find_leaks(docs: DataFrame, benchmark: DataFrame, similarity: float = 0.8) -> DataFrame:
    """One row per document row and item found in it: doc_id, item_id, similarity, hamming, first_word, n_words."""
    schema = "doc_id long, item_id long, similarity double, hamming int, first_word long, n_words long"
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = None
    for items in _blocks(benchmark):

        def run(batches: Iterator[pa.RecordBatch], items=items) -> Iterator[pa.RecordBatch]:
            index = _index(items)
            for b in small(batches):
                got = [(doc, *x) for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True) for x in index.find(text, similarity)]
                kinds = [pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int64(), pa.int64()]
                yield pa.RecordBatch.from_arrays([pa.array([g[i] for g in got], k) for i, k in enumerate(kinds)], [x.split()[0] for x in schema.split(", ")])

        found = rows.mapInArrow(lean(run, forget_index), schema)
        out = found if out is None else out.union(found)
    return docs.sparkSession.createDataFrame([], schema) if out is None else out


def drop_leaks(docs: DataFrame, benchmark: DataFrame, similarity: float = 0.8) -> DataFrame:
    """The rows of ``docs`` in which no item is found; all columns are kept as they are, whatever their names."""
    out = stowed(docs).withColumn("text", F.col("_row.text").cast("string"))
    for items in _blocks(benchmark):

        def run(batches: Iterator[pa.RecordBatch], items=items) -> Iterator[pa.RecordBatch]:
            index = _index(items)
            for b in small(batches):
                clean = [not index.find(t, similarity) for t in b.column("text").to_pylist()]
                yield b.filter(pa.array(clean, pa.bool_()))

        out = out.mapInArrow(lean(run, forget_index), out.schema)
    return out.select("_row.*")
