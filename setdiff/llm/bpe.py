"""Byte-level BPE by a rank queue under a hierarchical bitmap.

Every merge rank has a bucket of linked-list positions whose pair has that rank. A bitmap of three
levels of 64-way words marks the buckets that hold anything, so the next rank to merge is found with
three find-first-set steps, whatever the vocabulary's size. Entries are never removed from the middle of a
bucket: a position whose pair has changed since is stale and skipped when its turn comes. A
pre-token of n bytes so takes about n log n steps however long it is.

``RankQueue`` merges one pre-token. ``merge_many`` runs one queue over the linked lists of many pre-tokens laid
end to end and takes whole buckets at a time; pre-tokens don't touch each other, so the
order across them doesn't matter. Where one could (a merge that makes a pair of a rank not above its own),
the pre-token is done again alone, so both give the library's ids.

Null and empty texts encode to no ids. Rows are encoded one by one; other columns and repeated rows
make no difference.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections import defaultdict
from collections.abc import Iterable, Iterator
from heapq import heappop, heappush
from itertools import chain, count, islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, small

#: Characters of text that are encoded together, and pre-tokens that a worker remembers between batches.
TOGETHER, REMEMBERED = 4 << 20, 200_000
#: Fewer new pre-tokens than this are merged one at a time.
FEW = 400


class RankBitmap:
    """A set of small integers with find-first-set over three levels of 64-bit words."""

    def __init__(self, size: int):
        self.low = [0] * ((size >> 6) + 1)
        self.mid = [0] * ((size >> 12) + 1)
        self.top = 0

    def add(self, r: int) -> None:
        self.low[r >> 6] |= 1 << (r & 63)
        self.mid[r >> 12] |= 1 << (r >> 6 & 63)
        self.top |= 1 << (r >> 12)

    def discard(self, r: int) -> None:
        self.low[r >> 6] &= ~(1 << (r & 63))
        if not self.low[r >> 6]:
            self.mid[r >> 12] &= ~(1 << (r >> 6 & 63))
            if not self.mid[r >> 12]:
                self.top &= ~(1 << (r >> 12))

    def first(self) -> int:
        """The least member, or -1."""
        if not self.top:
            return -1
        a = (self.top & -self.top).bit_length() - 1
        w = self.mid[a]
        a = a << 6 | (w & -w).bit_length() - 1
        w = self.low[a]
        return a << 6 | (w & -w).bit_length() - 1


class Vocabulary:
    """Ranks of byte strings, as in a rank file: base64 of the token, a blank, its rank, one a line."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (x.split() for x in f if x.strip())}
        self.pattern = regex.compile(pattern)
        self.size = max(self.ranks.values()) + 1
        self.longest = max(map(len, self.ranks))
        self.bytes_of: list[bytes] = [b""] * self.size
        for t, r in self.ranks.items():
            self.bytes_of[r] = t
        self.names = [str(i) for i in range(self.size)]
        self.byte_rank = np.array([self.ranks[bytes([b])] for b in range(256)], np.int32)
        pairs = {}
        for t, r in self.ranks.items():
            for i in range(1, len(t)):
                a, b = self.ranks.get(t[:i]), self.ranks.get(t[i:])
                if a is not None and b is not None:
                    pairs[a * self.size + b] = r
        keys = np.fromiter(pairs, np.int64, len(pairs))
        order = np.argsort(keys)
        self.pair_keys, self.pair_ranks = keys[order], np.fromiter(pairs.values(), np.int32, len(pairs))[order]

    def pair_rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of the token that each pair of tokens makes, or -1."""
        key = a.astype(np.int64) * self.size + b
        at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
        return np.where(self.pair_keys[at] == key, self.pair_ranks[at], np.int32(-1))

    def merge_one(self, piece: bytes) -> list[int]:
        """Ids of one pre-token."""
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        n, get = len(piece), self.ranks.get
        end, prev, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        pair: list[int] = [-1] * n
        buckets: dict[int, list[int]] = {}
        marks = RankBitmap(self.size)

        def file(p: int) -> None:
            q = end[p]
            r = -1 if q >= n or end[q] - p > self.longest else get(piece[p : end[q]], -1)
            pair[p] = r
            if r >= 0:
                if r in buckets:
                    heappush(buckets[r], p)
                else:
                    buckets[r] = [p]
                    marks.add(r)

        for p in range(n - 1):
            file(p)
        while (r := marks.first()) >= 0:
            held = buckets[r]
            p = heappop(held)
            if not held:
                del buckets[r]
                marks.discard(r)
            if pair[p] != r or not alive[p]:
                continue
            q = end[p]
            alive[q], pair[q], end[p] = False, -1, end[q]
            if end[p] < n:
                prev[end[p]] = p
            file(p)
            if prev[p] >= 0:
                file(prev[p])
        return [get(piece[p : end[p]]) for p in range(n) if alive[p]]

    def merge_many(self, pieces: list[bytes]) -> list[list[int]]:
        """Ids of each pre-token, all through one queue."""
        lens = np.fromiter(map(len, pieces), np.int64, len(pieces))
        ends = np.cumsum(lens)
        n = int(ends[-1]) if len(pieces) else 0
        if not n:
            return [[] for _ in pieces]
        raw = np.frombuffer(b"".join(pieces), np.uint8)
        tok = self.byte_rank[raw]
        nxt = np.arange(1, n + 1, dtype=np.int32)
        prv = np.arange(-1, n - 1, dtype=np.int32)
        nxt[ends[lens > 0] - 1] = -1
        prv[(ends - lens)[lens > 0]] = -1
        pair = np.full(n, -1, np.int32)
        at = np.flatnonzero(nxt >= 0)
        pair[at] = self.pair_rank(tok[at], tok[nxt[at]])
        alive = np.ones(n, bool)
        buckets: dict[int, list[np.ndarray]] = {}
        marks, again = RankBitmap(self.size), []

        def file(p: np.ndarray, r: np.ndarray) -> None:
            ok = r >= 0
            p, r = p[ok], r[ok]
            order = np.argsort(r, kind="stable")
            p, r = p[order], r[order]
            cut = np.flatnonzero(r[1:] != r[:-1]) + 1
            edges = [0, *cut.tolist(), len(r)]
            for i, k in zip(edges, edges[1:], strict=False):
                if k > i:
                    rank = int(r[i])
                    if rank in buckets:
                        buckets[rank].append(p[i:k])
                    else:
                        buckets[rank] = [p[i:k]]
                        marks.add(rank)

        file(at, pair[at])
        while (r := marks.first()) >= 0:
            held = buckets.pop(r)
            marks.discard(r)
            p = held[0] if len(held) == 1 else np.concatenate(held)
            p = p[pair[p] == r]
            if len(held) > 1 or len(p) > 1:
                p = np.unique(p)
            if not len(p):
                continue
            if len(p) > 1:  # of pairs that overlap, the leftmost, then every other one
                linked = np.zeros(len(p), bool)
                linked[1:] = nxt[p[:-1]] == p[1:]
                if linked.any():
                    start = np.maximum.accumulate(np.where(linked, 0, np.arange(len(p))))
                    p = p[(np.arange(len(p)) - start) % 2 == 0]
            q = nxt[p]
            far = nxt[q]
            tok[p], nxt[p], alive[q], pair[q] = r, far, False, -1
            has = far >= 0
            prv[far[has]] = p[has]
            new = np.full(len(p), -1, np.int32)
            new[has] = self.pair_rank(tok[p[has]], tok[far[has]])
            pair[p] = new
            left = prv[p]
            left = left[left >= 0]
            made = self.pair_rank(tok[left], tok[nxt[left]])
            pair[left] = made
            both, ranks = np.concatenate([p, left]), np.concatenate([new, made])
            low = (ranks >= 0) & (ranks <= r)
            if low.any():
                again.append(both[low])
            file(both, ranks)
        got = tok[alive].tolist()
        held = np.add.reduceat(alive, (ends - lens)[lens > 0], dtype=np.int64)
        sizes = np.zeros(len(pieces), np.int64)
        sizes[lens > 0] = held
        stop = np.cumsum(sizes).tolist()
        out = [got[a:b] for a, b in zip([0, *stop], stop, strict=False)]
        for i in np.unique(np.searchsorted(ends, np.concatenate(again), side="right")).tolist() if again else ():
            out[i] = self.merge_one(pieces[i])
        return out


class Encoder:
    """Encodes texts; remembers the ids of pre-tokens between calls."""

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        self.forget()

    def forget(self) -> None:
        self.code: dict[str, int] = defaultdict(count().__next__)
        self.ids: list[tuple[int, ...]] = []

    def _learn(self, new: list[str]) -> None:
        raw = [p.encode("utf-8", "surrogatepass") for p in new]
        whole = [self.v.ranks.get(b) for b in raw]
        rest = [b for b, w in zip(raw, whole, strict=True) if w is None]
        done = iter(self.v.merge_many(rest) if len(rest) > FEW else map(self.v.merge_one, rest))
        self.ids.extend(tuple(next(done)) if w is None else (w,) for w in whole)

    def encode_all(self, texts: Iterable[str | None]) -> Iterator[list[int]]:
        """Ids of each text, in order."""
        if len(self.ids) > REMEMBERED:
            self.forget()
        held: list[array] = []
        size = 0

        def flush() -> Iterator[list[int]]:
            if len(self.code) > len(self.ids):
                self._learn(list(islice(self.code, len(self.ids), None)))
            for codes in held:
                yield list(chain.from_iterable(map(self.ids.__getitem__, codes)))

        for text in texts:
            pieces = self.v.pattern.findall(text) if text else ()
            held.append(array("i", map(self.code.__getitem__, pieces)))
            size += len(text or "")
            if size >= TOGETHER:
                yield from flush()
                held, size = [], 0
                if len(self.ids) > REMEMBERED:
                    self.forget()
        yield from flush()

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.v.bytes_of.__getitem__, ids))


_ENCODERS: dict[tuple[str, str], Encoder] = {}


def encoder(path: str, pattern: str) -> Encoder:
    """The encoder of this process for a rank file."""
    if (path, pattern) not in _ENCODERS:
        _ENCODERS[path, pattern] = Encoder(Vocabulary(path, pattern))
    return _ENCODERS[path, pattern]


def forget_encoders() -> None:
    """Drops the pre-tokens that this process's encoders remember; the vocabularies (15 MB each) stay."""
    for e in _ENCODERS.values():
        e.forget()


def encode_documents(docs: DataFrame, path: str, pattern: str, with_ids: bool = True) -> DataFrame:
    """Per row: doc_id, n_tokens, ids_sha256, decoded_sha256 and, unless left out, the ids.

    The decoded digest is of the bytes that the ids decode to, not of the text.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(path, pattern)
        names, value = e.v.names, e.v.bytes_of
        ids_of: list[pa.Array] = []
        done: list[tuple] = []

        def pack() -> pa.RecordBatch:
            cols = [pa.chunked_array(ids_of, pa.int64()).combine_chunks(), *(pa.array([x[i] for x in done], t) for i, t in enumerate((pa.int64(), pa.string(), pa.string())))]
            if with_ids:
                cols.append(pa.array([x[3] for x in done], pa.list_(pa.int32())))
            return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids])

        def texts() -> Iterator[str | None]:
            for b in small(batches):
                ids_of.append(b.column(0))
                yield from b.column(1).to_pylist()

        for got in e.encode_all(texts()):
            ids = hashlib.sha256(",".join(map(names.__getitem__, got)).encode()).hexdigest()
            back = hashlib.sha256(b"".join(map(value.__getitem__, got))).hexdigest()
            done.append((len(got), ids, back, np.array(got, np.int32) if with_ids else None))
            if len(done) == len(ids_of[0]):
                rest = ids_of[1:]
                del ids_of[1:]
                yield pack()
                ids_of[:] = rest
                done.clear()

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(run, forget_encoders), schema)
