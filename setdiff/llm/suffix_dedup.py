"""Removal of long repeated byte strings by a distributed merge sort of front-coded suffix runs.

A byte goes if it lies in a string of ``LENGTH`` bytes that also starts anywhere else in the corpus.

Which suffixes are sorted. Every window of LENGTH bytes has an anchor: the leftmost of its GRAM-byte grams with the least
hash. Equal windows have equal anchors at equal offsets, so only suffixes that start at anchors have to
be compared: about one in 190 positions. The windows of one anchor are consecutive; with the bytes they cover, left and right of the
anchor, they form a segment. Anchors whose gram occurs once in the corpus (found by a map-side combined count of gram
hashes) can't have a repeat and are left out before any text is moved.

How they are sorted. Each task sorts its candidate suffixes and cuts them by gram into runs; a run is front-coded (common
prefix with the suffix before, rest) and packed. Runs are exchanged by gram and merged by a loser tree that carries, for each run, the
common prefix with the last winner: unequal prefixes decide a match at once, equal ones are compared from there on, so no known
prefix is read twice. The merge yields the sorted suffixes and their common prefixes. Suffixes that share a gram are
neighbours; two of them repeat a window if common prefix plus common left context reach LENGTH, and then every byte of that stretch goes.

Skew. Copies of a whole text are one text throughout (grouped by a 128-bit hash with map-side combination) and are known to go. Equal
segments of one task are settled there, one of them goes on. A gram in more than ``HOT`` texts is never gathered: its windows are
compared by 128-bit hash in a combined count and a join that adaptive execution can split; no window is dropped.

Word windows, on demand: so many words that repeat go too, however few bytes they take. Every word of a text becomes four bytes (a hash), and the
same search runs over those, word by word; stretches are drawn in to whole words, and whatever stands between them goes with them.

Texts are hashed, and anchors chosen, for some ``CHUNK_BYTES`` of consecutive texts at once; windows that would cross texts are left out.

Matches never cross documents; texts are bytes; null is empty; texts shorter than LENGTH repeat nothing. Repeated rows and ids are rows of their own: copies of
a text of LENGTH bytes or more go entirely. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD_SPACE, bounded_broadcast, discard, keep, lean, small, stowed

LENGTH, GRAM = 400, 64
#: Bytes that stand for a word.
CODE = 4
_WORD = re.compile(rb"[^ \t\n\r\x0b\x0c]+")
#: Texts that may share a gram and still be compared in one task.
HOT = 512
#: Bytes of segments that a task sorts into one set of runs; bytes of segments that a merge takes.
RUN_BYTES, MERGE_BYTES = 16 << 20, 4 << 20
#: Groups up to this size are compared pair by pair, larger ones by classes.
PAIRWISE = 20
#: Bytes of texts that are hashed at once.
CHUNK_BYTES = 1 << 16

_IN_WORD = ~np.isin(np.arange(256), list(WORD_SPACE))
_M = 0x9E3779B97F4A7C15
_M2 = 0xC2B2AE3D27D4EB4F
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(m: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd multiplier and of its inverse, modulo 2**64."""
    if m not in _POWERS or len(_POWERS[m][0]) < n:
        size = max(1 << 17, 1 << (n - 1).bit_length())
        up, down = np.full(size, m, np.uint64), np.full(size, pow(m, -1, 1 << 64), np.uint64)
        up[0] = down[0] = 1
        _POWERS[m] = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
    return _POWERS[m]


def forget_powers() -> None:
    """Drops the powers of this process."""
    _POWERS.clear()


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


def _sums(a: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(sums before every position, of elements times powers; the inverse powers)."""
    up, down = _powers(m, len(a) + 1)
    terms = a.astype(np.uint64)
    terms += np.uint64(1)
    terms *= up[: len(a)]
    total = np.zeros(len(a) + 1, np.uint64)
    np.cumsum(terms, out=total[1:])
    return total, down


def string_hashes(a: np.ndarray, length: int, m: int = _M) -> np.ndarray:
    """64-bit hash of the ``length`` elements from every position."""
    if len(a) < length:
        return np.zeros(0, np.uint64)
    total, down = _sums(a, m)
    h = total[length:] - total[:-length]
    h *= down[: len(h)]
    return _mixed(h)


def sliding_least(keys: np.ndarray, wide: int) -> np.ndarray:
    """The least of every ``wide`` neighbouring keys, by doubling."""
    held = 1
    while 2 * held <= wide:
        keys = np.minimum(keys[:-held], keys[held:])
        held *= 2
    return keys if held == wide else np.minimum(keys[: len(keys) - wide + held], keys[wide - held :])


def anchors(a: np.ndarray, bounds: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, gram hash, anchor position, first window, last window) of every run of windows with the same anchor, in order.

    ``a`` holds the elements of texts one after the other, ``bounds`` where each begins and the last ends; positions count in ``a``.
    """
    h = string_hashes(a, gram)
    wide = length - gram + 1
    if len(h) < wide:
        none = np.zeros(0, np.int64)
        return none, none.view(np.uint64), none, none, none
    # half a hash above the position: the least key is the leftmost gram with the least hash
    keys = h & np.uint64(0xFFFFFFFF00000000)
    keys |= np.arange(len(h), dtype=np.uint64)
    least = sliding_least(keys, wide)
    first = np.concatenate([[0], np.flatnonzero(least[1:] != least[:-1]) + 1])
    last = np.append(first[1:] - 1, len(least) - 1)
    at = (least[first] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    text = np.searchsorted(bounds, at, "right") - 1
    first, last = np.maximum(first, bounds[text]), np.minimum(last, bounds[text + 1] - length)
    inside = first <= last
    at = at[inside]
    return text[inside], h[at], at, first[inside], last[inside]


def chunks(batches: Iterator[pa.RecordBatch], column: str = "raw") -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(rows, bytes of their texts, bounds of the texts in those) for some ``CHUNK_BYTES`` of texts, one text at least."""
    for batch in batches:
        col = batch.column(column)
        wide = np.int64 if pa.types.is_large_binary(col.type) else np.int32
        _, ends, data = col.buffers()
        ends = np.frombuffer(ends, wide)[col.offset : col.offset + len(col) + 1].astype(np.int64) if len(col) else np.zeros(1, np.int64)
        data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
        i = 0
        while i < len(col):
            j = max(i + 1, int(np.searchsorted(ends, ends[i] + CHUNK_BYTES, "right")) - 1)
            yield batch.slice(i, j - i), data[ends[i] : ends[j]], ends[i : j + 1] - ends[i]
            i = j


def common_prefix(a: bytes, b: bytes, known: int = 0) -> int:
    """Length of the common prefix, from ``known`` equal bytes on."""
    n = min(len(a), len(b))
    x = int.from_bytes(a[known:n], "big") ^ int.from_bytes(b[known:n], "big")
    return n - (x.bit_length() + 7) // 8


def common_suffix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    x = int.from_bytes(a[len(a) - n :], "big") ^ int.from_bytes(b[len(b) - n :], "big")
    return ((x & -x).bit_length() - 1) // 8 if x else n


# A member is (right, left, t1, t2, place, settled): the segment's bytes from the anchor on, those before it, the key of the text, the anchor's
# position there, and whether all its windows are known to repeat.


def pack_run(run: list[tuple]) -> bytes:
    """A sorted run, front-coded."""
    shared = [0] + [common_prefix(a[0], b[0]) for a, b in zip(run, run[1:], strict=False)]
    rests = [m[0][k:] for m, k in zip(run, shared, strict=True)]
    nums = np.array([[len(r), k, len(m[1]), m[5]] for m, k, r in zip(run, shared, rests, strict=True)], np.uint16)
    keys = np.array([m[2:5] for m in run], np.int64)
    body = len(run).to_bytes(4, "little") + nums.tobytes() + keys.tobytes() + b"".join(rests) + b"".join(m[1] for m in run)
    return zstandard.ZstdCompressor(level=1).compress(body)


def unpack_run(blob: bytes) -> Iterator[tuple[int, tuple]]:
    """(common prefix with the member before, member) of a packed run, in order."""
    body = zstandard.ZstdDecompressor().decompress(blob)
    n = int.from_bytes(body[:4], "little")
    nums = np.frombuffer(body, np.uint16, 4 * n, 4).reshape(n, 4).tolist()
    keys = np.frombuffer(body, np.int64, 3 * n, 4 + 8 * n).reshape(n, 3).tolist()
    at = 4 + 32 * n
    left_at = at + sum(x[0] for x in nums)
    last = b""
    for (size, shared, left, settled), (t1, t2, place) in zip(nums, keys, strict=True):
        last = last[:shared] + body[at : at + size]
        at += size
        yield shared, (last, body[left_at : left_at + left], t1, t2, place, settled)
        left_at += left


def merge_runs(runs: list[Iterator[tuple[int, tuple]]]) -> Iterator[tuple[int, tuple]]:
    """(common prefix with the member before, member) of all runs in sorted order, through a loser tree."""
    k = 1
    while k < len(runs):
        k *= 2
    head: list[tuple | None] = [None] * k
    known = [0] * k

    def advance(r: int) -> None:
        got = next(runs[r], None) if r < len(runs) else None
        known[r], head[r] = got if got else (0, None)

    def match(a: int, b: int) -> tuple[int, int]:
        """(winner, loser); the loser's known prefix becomes the one it shares with the winner."""
        x, y = head[a], head[b]
        if x is None or y is None:
            return (b, a) if x is None else (a, b)
        if known[a] != known[b]:
            return (a, b) if known[a] > known[b] else (b, a)
        x, y = x[0], y[0]
        n = common_prefix(x, y, known[a])
        if n == len(x) or n < len(y) and x[n] < y[n]:
            known[b] = n
            return a, b
        known[a] = n
        return b, a

    for r in range(k):
        advance(r)
    losers = [0] * k
    winners = [0] * k + list(range(k))
    for i in range(k - 1, 0, -1):
        winners[i], losers[i] = match(winners[2 * i], winners[2 * i + 1])
    best = winners[1]
    while head[best] is not None:
        yield known[best], head[best]
        advance(best)
        i = (best + k) // 2
        while i:
            best, losers[i] = match(best, losers[i])
            i //= 2


def repeats(group: list[tuple], shared: list[int], length: int = LENGTH) -> Iterator[tuple[int, int, int, int]]:
    """(t1, t2, begin, end) of stretches that go, for members that share a gram, sorted; shared[i] is the prefix that i shares with i - 1."""
    n = len(group)
    if n <= PAIRWISE:
        for i in range(n):
            right = length
            for j in range(i + 1, n):
                right = min(right, shared[j])
                left = common_suffix(group[i][1], group[j][1])
                if left + right >= length:
                    for m in (group[i], group[j]):
                        if not m[5]:
                            yield m[2], m[3], m[4] - left, m[4] + right
        return
    depth_right = np.array(shared)
    depth_right[0] = -1
    order = sorted(range(n), key=lambda i: group[i][1][::-1])
    depth_left = np.array([-1] + [common_suffix(group[a][1], group[b][1]) for a, b in zip(order, order[1:], strict=False)])
    order = np.array(order)
    hit = np.zeros((length + 1, n), bool)
    for left in range(max(len(m[1]) for m in group) + 1):
        a = np.cumsum(depth_right < length - left)
        b = np.empty(n, np.int64)
        b[order] = np.cumsum(depth_left < left)
        both = a * (n + 1) + b
        by = np.argsort(both, kind="stable")
        same = both[by[1:]] == both[by[:-1]]
        hit[left, by[1:][same]] = True
        hit[left, by[:-1][same]] = True
    for i, m in enumerate(group):
        if not m[5]:
            lefts = np.flatnonzero(hit[:, i])
            for run in np.split(lefts, np.flatnonzero(np.diff(lefts) > 1) + 1) if len(lefts) else ():
                yield m[2], m[3], m[4] - int(run[-1]), m[4] - int(run[0]) + length


_PARTS = "kind int, bucket int, blob binary, w1 long, w2 long, t1 long, t2 long, a long, b long"
_STRETCH, _RUN, _WINDOWS = 0, 1, 2


def _rows(kind: int, n: int, **cols) -> pa.RecordBatch:
    names = [x.split() for x in _PARTS.split(", ")]
    types = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    full = {"kind": np.full(n, kind, np.int32)} | cols
    return pa.RecordBatch.from_arrays([pa.array(full[k], types[t]) if k in full else pa.nulls(n, types[t]) for k, t in names], [k for k, _ in names])


def _cut_runs(members: list[tuple[int, tuple]]) -> Iterator[pa.RecordBatch]:
    """Sorts the (bucket, member) pairs of a task, settles equal segments, and packs one run a bucket."""
    members.sort(key=lambda x: (x[0], x[1][0], x[1][1]))
    goes: list[tuple[int, int, int, int]] = []
    runs: dict[int, list[tuple]] = {}
    last = None
    for bucket, m in members:
        run = runs.setdefault(bucket, [])
        if last is not None and run and last[0] == m[0] and last[1] == m[1]:
            if not run[-1][5]:
                goes.append((last[2], last[3], last[4] - len(last[1]), last[4] + len(last[0])))
                run[-1] = (*last[:5], 1)
            goes.append((m[2], m[3], m[4] - len(m[1]), m[4] + len(m[0])))
            continue
        run.append(m)
        last = m
    if goes:
        g = np.array(goes, np.int64)
        yield _rows(_STRETCH, len(g), t1=g[:, 0], t2=g[:, 1], a=g[:, 2], b=g[:, 3])
    for bucket, run in runs.items():
        yield _rows(_RUN, 1, bucket=[bucket], blob=[pack_run(run)])


def _cut_windows(windows: list[np.ndarray], length: int, unit: int) -> Iterator[pa.RecordBatch]:
    """Settles equal windows of a task's hot grams, given text by text in order; one of each goes on, marked in ``b`` if it is settled."""
    if not windows:
        return
    w = np.concatenate(windows, axis=1)
    by = np.lexsort((w[1], w[0]))
    new = np.ones(len(by), bool)
    new[1:] = (w[0, by[1:]] != w[0, by[:-1]]) | (w[1, by[1:]] != w[1, by[:-1]])
    which = np.cumsum(new) - 1
    often = np.bincount(which) > 1
    goes = np.zeros(len(by), bool)
    goes[by] = often[which]
    g = w[2:, goes]
    if g.shape[1]:
        cut = np.ones(g.shape[1], bool)
        cut[1:] = (g[:2, 1:] != g[:2, :-1]).any(0) | (g[2, 1:] != g[2, :-1] + 1)
        begin = np.flatnonzero(cut)
        end = np.append(begin[1:], g.shape[1]) - 1
        yield _rows(_STRETCH, len(begin), t1=g[0, begin], t2=g[1, begin], a=g[2, begin] * unit, b=(g[2, end] + length) * unit)
    one = w[:, by[new]]
    for at in range(0, one.shape[1], 1 << 16):
        c = one[:, at : at + (1 << 16)]
        yield _rows(_WINDOWS, c.shape[1], w1=c[0], w2=c[1], t1=c[2], t2=c[3], a=c[4] * unit, b=often[at : at + c.shape[1]].astype(np.int64))


def repeated_stretches(texts: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT, unit: int = 1) -> DataFrame:
    """(t1, t2, a, b), written: stretches to remove, by key of the text; ``texts`` (t1, t2, raw binary) may hold copies of a text.

    With ``unit`` 4, texts are sequences of four-byte elements and windows begin at elements only; all lengths and positions stay in bytes.
    Copies of a whole text count once here; see ``remove_repeats`` for them.
    """
    spark = texts.sparkSession
    n_window, kind = length // unit, f"<u{unit}"
    n_gram = max(1, min(gram // unit, n_window))
    gram = n_gram * unit

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, bounds in chunks(batches):
            text, h, *_ = anchors(data.view(kind), bounds // unit, n_window, n_gram)
            if not len(h):
                continue
            by = np.lexsort((h, text))
            text, h = text[by], h[by].view(np.int64)
            new = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (text[1:] != text[:-1])))
            twice = np.diff(np.append(new, len(h))) > 1
            t1, t2 = (rows.column(c).to_numpy()[text[new]] for c in ("t1", "t2"))
            yield pa.RecordBatch.from_arrays([pa.array(h[new]), pa.array(twice), pa.array(t1), pa.array(t2)], ["gram", "twice", "t1", "t2"])

    grams = keep(texts.where(F.octet_length("raw") >= length).mapInArrow(lean(find, forget_powers), "gram long, twice boolean, t1 long, t2 long"), "grams")
    shared = (
        grams.groupBy("gram").agg(F.min("t1").alias("lo"), F.max("t1").alias("hi"), F.max("twice").alias("twice"), F.count(F.lit(1)).alias("n"))
        .where("twice or lo <> hi").select("gram", (F.col("n") > hot).alias("hot"))
    )
    wanted = keep(
        grams.select("gram", "t1", "t2").join(shared, "gram").groupBy("t1", "t2")
        .agg(F.collect_set(F.struct("gram", "hot")).alias("g")).select("t1", "t2", "g.gram", "g.hot"), "wanted",
    )
    discard(grams)
    total = wanted.agg(F.sum(F.size("gram"))).first()[0] or 0
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = max(parts, int(total * 1.5 * length) // MERGE_BYTES)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        members: list[tuple[int, tuple]] = []
        windows: list[np.ndarray] = []
        size = 0
        for rows, data, bounds in chunks(batches):
            # which grams are wanted and hot doesn't depend on the text
            some, is_hot = rows.column("gram").flatten().to_numpy().view(np.uint64), rows.column("hot").flatten().to_numpy(zero_copy_only=False)
            data, bounds = data.view(kind), bounds // unit
            text, h, at, first, last = anchors(data, bounds, n_window, n_gram)
            t1, t2 = (rows.column(c).to_numpy() for c in ("t1", "t2"))
            mild = np.flatnonzero(np.isin(h, some[~is_hot]))
            if len(mild):
                raw, of = data.tobytes(), text[mild]
                place, begin, stop = at[mild], first[mild], last[mild] + n_window
                into = (h[mild] % np.uint64(buckets)).tolist()
                own = ((place - bounds[of]) * unit).tolist()
                for k, p, s, e, x, y, o in zip(into, (place * unit).tolist(), (begin * unit).tolist(), (stop * unit).tolist(), t1[of].tolist(), t2[of].tolist(), own, strict=True):
                    members.append((k, (raw[p:e], raw[s:p], x, y, o, 0)))
                size += int((stop - begin).sum()) * unit + 200 * len(mild)
            warm = np.flatnonzero(np.isin(h, some[is_hot]))
            if len(warm):
                w1, w2 = string_hashes(data, n_window), string_hashes(data, n_window, _M2)
                n = last[warm] - first[warm] + 1
                of = np.repeat(text[warm], n)
                starts = np.arange(n.sum()) + np.repeat(first[warm] - np.cumsum(n) + n, n)
                windows.append(np.stack([w1[starts].view(np.int64), w2[starts].view(np.int64), t1[of], t2[of], starts - bounds[of]]))
                size += 80 * len(starts)
            if size > RUN_BYTES:
                yield from _cut_runs(members)
                yield from _cut_windows(windows, n_window, unit)
                members, windows, size = [], [], 0
        yield from _cut_runs(members)
        yield from _cut_windows(windows, n_window, unit)

    distinct = texts.groupBy("t1", "t2").agg(F.first("raw").alias("raw"))
    cuts = keep(distinct.join(wanted, ["t1", "t2"]).select("t1", "t2", "raw", "gram", "hot").mapInArrow(lean(cut, forget_powers), _PARTS), "runs")
    discard(wanted)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[bytes] = []
        now = None

        def work() -> Iterator[pa.RecordBatch]:
            out, group, shared_of = [], [], []
            for k, m in merge_runs([unpack_run(x) for x in held]):
                if k < gram and group:
                    if len(group) > 1:
                        out += repeats(group, shared_of, length)
                    group, shared_of = [], []
                group.append(m)
                shared_of.append(k)
            if len(group) > 1:
                out += repeats(group, shared_of, length)
            g = np.array(out, np.int64).reshape(-1, 4)
            yield pa.RecordBatch.from_arrays([pa.array(g[:, i].copy()) for i in range(4)], ["t1", "t2", "a", "b"])

        for b in batches:
            for bucket, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if bucket != now and held:
                    yield from work()
                    held = []
                now = bucket
                held.append(blob)
        if held:
            yield from work()

    runs = cuts.where(F.col("kind") == _RUN).select("bucket", "blob").repartition(buckets, "bucket").sortWithinPartitions("bucket")
    merged = runs.mapInArrow(lean(merge), "t1 long, t2 long, a long, b long")
    windows = cuts.where(F.col("kind") == _WINDOWS).select("w1", "w2", "t1", "t2", "a", F.col("b").alias("settled"))
    again = windows.groupBy("w1", "w2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("w1", "w2")
    of_hot = windows.where("settled = 0").join(again, ["w1", "w2"]).select("t1", "t2", "a", (F.col("a") + length).alias("b"))
    settled = cuts.where(F.col("kind") == _STRETCH).select("t1", "t2", "a", "b")
    found = keep(settled.union(merged).union(of_hot), "stretches")
    discard(cuts)
    return found


def join_stretches(found: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs of the bytes that any stretch covers."""
    out: list[list[int]] = []
    for a, b in sorted(found):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def at_characters(raw: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans drawn in to whole UTF-8 characters, so that what is left decodes."""
    out = []
    for a, b in spans:
        while a < b and raw[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(raw) and raw[b] & 0xC0 == 0x80:
            b -= 1
        if b > a:
            out.append((a, b))
    return out


def codes_of(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(a four-byte hash of every word, number of words of every text) of texts that stand one after the other."""
    n = len(data)
    edge = np.zeros(n + 1, bool)
    edge[bounds] = True
    word = np.zeros(n + 2, bool)
    word[1:-1] = _IN_WORD[data]
    begin = np.flatnonzero(word[1:-1] & (~word[:-2] | edge[:-1]))
    end = np.flatnonzero(word[1:-1] & (~word[2:] | edge[1:])) + 1
    total, down = _sums(data, _M)
    h = _mixed((total[end] - total[begin]) * down[begin])
    return (h >> np.uint64(32)).astype("<u4"), np.diff(np.searchsorted(begin, bounds))


def word_codes(texts: DataFrame, words: int) -> DataFrame:
    """(t1, t2, raw): the words of every text of ``words`` words or more, CODE bytes each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, bounds in chunks(batches):
            codes, n = codes_of(data, bounds)
            ends = np.append(0, np.cumsum(n) * CODE).astype(np.int32)
            raw = pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer(ends), pa.py_buffer(codes)])
            yield pa.RecordBatch.from_arrays([rows.column("t1"), rows.column("t2"), raw], ["t1", "t2", "raw"])

    return texts.mapInArrow(lean(run, forget_powers), "t1 long, t2 long, raw binary").where(F.octet_length("raw") >= CODE * words)


def word_runs(found: list[tuple[int, int]], words: int) -> list[tuple[int, int]]:
    """Those stretches of word codes that hold ``words`` whole words or more, counted in words."""
    whole = [(-(-a // CODE), b // CODE) for a, b in join_stretches(found)]
    return [(i, j) for i, j in whole if j - i >= words]


def word_spans(raw: bytes, found: list[tuple[int, int]], words: int) -> list[tuple[int, int]]:
    """The bytes of ``word_runs``."""
    whole = word_runs(found, words)
    at = [m.span() for m in _WORD.finditer(raw)] if whole else []
    return [(at[i][0], at[j - 1][1]) for i, j in whole]


def _keys(docs: DataFrame) -> DataFrame:
    """``docs`` with its text as bytes and the two halves of its text's key."""
    raw = F.coalesce(F.col("text").cast("binary"), F.lit(b""))
    return docs.withColumn("raw", raw).withColumn("t1", F.xxhash64("raw")).withColumn("t2", F.xxhash64(F.lit(1), "raw", F.octet_length("raw")))


def repeat_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT) -> tuple[DataFrame, DataFrame]:
    """(spans, copies): (t1, t2, stretches) of texts with something to remove, and the keys (t1, t2) of texts that go entirely.

    ``stretches`` may overlap; see ``join_stretches``.
    """
    texts = _keys(docs.select("text")).select("t1", "t2", "raw")
    found = repeated_stretches(texts, length, gram, hot)
    spans = found.groupBy("t1", "t2").agg(F.collect_set(F.struct("a", "b")).alias("stretches"))
    copies = texts.where(F.octet_length("raw") >= length).groupBy("t1", "t2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("t1", "t2")
    return spans, copies


def word_repeats(texts: DataFrame, words: int, gram: int = GRAM, hot: int = HOT) -> tuple[DataFrame, DataFrame]:
    """(stretches, copies) as in ``repeat_spans``, of runs of ``words`` words or more that repeat; ``stretches`` count in word codes, see ``word_spans``."""
    codes = keep(word_codes(texts, words), "codes")
    found = repeated_stretches(codes, CODE * words, gram, hot, CODE)
    copies = keep(codes.groupBy("t1", "t2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("t1", "t2"), "copies")
    discard(codes)
    return found.groupBy("t1", "t2").agg(F.collect_set(F.struct("a", "b")).alias("stretches")), copies


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT, with_text: bool = False, words: int | None = None) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, on demand, ``clean_text``: what is left, cut at whole characters.

    With ``words``, also ``n_word_spans``: maximal runs of so many words or more that occur elsewhere too, however few bytes they take (they are
    counted, not removed), and ``repeats``: whether the row holds a repeat of either kind.
    """
    stretches = "array<struct<a:bigint,b:bigint>>"
    keyed = _keys(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"))
    spans, copies = repeat_spans(docs, length, gram, hot)
    marks = spans.select("t1", "t2", F.col("stretches").alias("_gone")).join(copies.withColumn("_all", F.lit(True)), ["t1", "t2"], "full")
    if words:
        by_words, same_words = word_repeats(keyed.select("t1", "t2", "raw"), words, gram, hot)
        marks = marks.join(by_words.select("t1", "t2", F.col("stretches").alias("_words")), ["t1", "t2"], "full").join(same_words.withColumn("_all_words", F.lit(True)), ["t1", "t2"], "full")
    else:
        marks = marks.withColumn("_words", F.lit(None).cast(stretches)).withColumn("_all_words", F.lit(False))
    marks = keep(marks, "marks")
    # Texts are read only where a stretch has to be cut or counted: copies are known to go, and to be one run of words.
    cut = marks.where("(_gone is not null and _all is null) or (_words is not null and not coalesce(_all_words, false))")
    # only keys are broadcast, never stretches, whose number a row is not bounded
    some = bounded_broadcast(cut.select("t1", "t2"), 100_000)
    texts = keyed.select("t1", "t2", "raw").join(some, ["t1", "t2"], "left_semi").groupBy("t1", "t2").agg(F.first("raw").alias("raw"))
    texts = texts.join(cut.hint("merge").select("t1", "t2", "_gone", "_words"), ["t1", "t2"])
    texts = texts.select("t1", "t2", "raw", "_gone.a", "_gone.b", F.col("_words.a").alias("wa"), F.col("_words.b").alias("wb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            rows = []
            for t1, t2, raw, begin, end, wa, wb in zip(*(c.to_pylist() for c in b.columns), strict=True):
                gone = join_stretches(list(zip(begin or (), end or (), strict=True)))
                left, at = [], 0
                for x, y in gone:
                    left.append(raw[at:x])
                    at = y
                left.append(raw[at:])
                text = None
                if with_text:
                    whole, at = [], 0
                    for x, y in at_characters(raw, gone):
                        whole.append(raw[at:x])
                        at = y
                    text = b"".join([*whole, raw[at:]]).decode("utf-8", "replace")
                by_word = len(word_runs(list(zip(wa, wb, strict=True)), words)) if wa else 0
                rows.append((t1, t2, sum(y - x for x, y in gone), len(gone), by_word, hashlib.sha256(b"".join(left)).hexdigest(), text))
            kinds = [pa.int64()] * 5 + [pa.string()] * 2
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], ["t1", "t2", "_removed", "_spans", "_by_word", "_sha", "_left"])

    done = texts.mapInArrow(lean(run), "t1 long, t2 long, _removed long, _spans long, _by_word long, _sha string, _left string")
    whole = marks.where("_all or _all_words").select("t1", "t2", "_all", "_all_words")
    done = keep(done.join(whole, ["t1", "t2"], "full"), "removed")
    size = F.octet_length("raw").cast("long")
    everything = F.coalesce("_all", F.lit(False))
    rows = keyed.select("doc_id", "t1", "t2", size.alias("n_bytes"), F.sha2("raw", 256).alias("_whole"), *["text"] * with_text)
    out = rows.join(bounded_broadcast(done, 100_000), ["t1", "t2"], "left")
    zero, empty = F.lit(0).cast("long"), F.lit(hashlib.sha256(b"").hexdigest())
    removed = F.when(everything, F.col("n_bytes")).otherwise(F.coalesce("_removed", zero))
    cols = [
        "doc_id", "n_bytes", removed.alias("n_removed"),
        F.when(everything, F.lit(1).cast("long")).otherwise(F.coalesce("_spans", zero)).alias("n_spans"),
        F.when(everything, empty).otherwise(F.coalesce("_sha", "_whole")).alias("kept_sha256"),
    ]
    if words:
        by_word = F.when(F.col("_all_words"), F.lit(1).cast("long")).otherwise(F.coalesce("_by_word", zero))
        cols += [by_word.alias("n_word_spans"), ((removed > 0) | (by_word > 0)).alias("repeats")]
    if with_text:
        cols.append(F.when(everything, F.lit("")).when(F.col("_left").isNotNull(), F.col("_left")).otherwise(F.col("text")).alias("clean_text"))
    return out.select(*cols)


def clean_documents(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT, words: int | None = None) -> DataFrame:
    """``docs`` with every repeated string cut out of its text, at whole characters, and n_chars set anew; rows left without text are dropped.

    With ``words``, strings of so many words that repeat are cut out as well. All columns are kept, whatever their names; rows with a null text pass.
    """
    spans, copies = repeat_spans(docs, length, gram, hot)
    spans = spans.select("t1", "t2", F.col("stretches").alias("_gone"), F.lit(None).cast("array<struct<a:bigint,b:bigint>>").alias("_words"))
    if words:
        by_words, same_words = word_repeats(_keys(docs.select("text")).select("t1", "t2", "raw"), words, gram, hot)
        spans = spans.drop("_words").join(by_words.withColumnRenamed("stretches", "_words"), ["t1", "t2"], "full")
        copies = copies.union(same_words).distinct()
    nothing = [F.lit(None).cast("array<struct<a:bigint,b:bigint>>").alias(c) for c in ("_gone", "_words")]
    everything = copies.select("t1", "t2", F.lit(True).alias("_all"), *nothing)
    some = spans.join(copies, ["t1", "t2"], "left_anti").select("t1", "t2", F.lit(False).alias("_all"), "_gone", "_words")
    marks = keep(everything.union(some), "marks")
    rows = _keys(stowed(docs).withColumn("text", F.col("_row.text").cast("string")))
    joined = rows.join(marks, ["t1", "t2"], "left").where("not coalesce(_all, false)")
    joined = joined.select("_row", "text", *[F.col(f"{c}.{x}").alias(f"{c}_{x}") for c in ("_gone", "_words") for x in "ab"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            texts, stay = [], []
            for text, a, z, wa, wz in zip(*(b.column(c).to_pylist() for c in ("text", "_gone_a", "_gone_b", "_words_a", "_words_b")), strict=True):
                new = None
                if a or wa:
                    raw, left, at = text.encode("utf-8", "surrogatepass"), [], 0
                    gone = list(zip(a or (), z or (), strict=True)) + (word_spans(raw, list(zip(wa, wz, strict=True)), words) if wa else [])
                    for x, y in at_characters(raw, join_stretches(gone)):
                        left.append(raw[at:x])
                        at = y
                    new = b"".join([*left, raw[at:]]).decode("utf-8", "replace") if at else None
                texts.append(new)
                stay.append(new is None or bool(new.strip()))
            yield pa.RecordBatch.from_arrays([b.column("_row"), pa.array(texts, pa.string())], ["_row", "_new"]).filter(pa.array(stay, pa.bool_()))

    whole = rows.select("_row", F.lit(None).cast("string").alias("_new")).schema
    new = {"text": F.col("_new"), "n_chars": F.length("_new")}
    old = lambda f: F.col("_row").getField(f.name)
    cols = [(F.when(F.col("_new").isNull(), old(f)).otherwise(new[f.name].cast(f.dataType)) if f.name in new else old(f)).alias(f.name) for f in docs.schema.fields]
    return joined.mapInArrow(lean(run), whole).select(*cols)
