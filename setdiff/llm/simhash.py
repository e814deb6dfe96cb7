"""SimHash near-duplicates by a generalised pigeonhole search.

A text's 64-bit fingerprint is the bitwise majority of the XXH64 of its word shingles. Fingerprints within
``radius`` bits are linked; linked documents are one group.

The search splits the 64 bits into parts and gives each part its own threshold (-1 leaves a part out). If the
thresholds plus one sum to more than the radius, two fingerprints within the radius agree within the threshold on at least
one part. Correlated bits are put in the same part, so that parts stay selective; a dynamic
programme allots the thresholds, and the number of parts is chosen, by the estimated number of keys and candidate pairs.
A threshold of t is probed with keys that leave out every choice of t bits of the part: two values
within t bits share such a key. All of this only decides cost; the links found are always all of them.

Equal fingerprints are joined first (map-side combined). A bucket of fingerprints that
share a key is compared inside one sorted run with vectorised popcounts and leaves a chain through each
group it finds, not all its pairs. A bucket over ``BUCKET`` rows is cut into chunks by hash and every pair of chunks
becomes a run of its own, so a bucket of any size spreads over the cluster and no candidate is dropped.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_broadcast, keep, lean, small, stowed
from .components import connected

SEED, WIDTH = 42, 64
#: Rows of a bucket that are compared in one run.
BUCKET = 4096
#: Fingerprints that the cost estimate compares with each other.
ESTIMATE = 2048


def shingle_hashes(text: str, size: int) -> np.ndarray:
    """XXH64 of each run of ``size`` words of the ASCII-lower-cased text (of the whole sequence if it is shorter)."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= size:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = [0, *ends[: len(words) - size].tolist()]
    stops = (ends[size - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)), np.uint64, len(stops))


def majority(h: np.ndarray) -> int:
    """The bitwise majority of hashes, unsigned; zero for none."""
    if not len(h):
        return 0
    counts = np.zeros(WIDTH, np.int64)
    for at in range(0, len(h), 1 << 15):
        counts += np.unpackbits(h[at : at + (1 << 15)].view(np.uint8), bitorder="little").reshape(-1, WIDTH).sum(0, dtype=np.int32)
    return int(np.packbits(2 * counts > len(h), bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, size: int = 4) -> int:
    """The fingerprint, unsigned; zero for a null text and one without words."""
    return majority(shingle_hashes(text or "", size))


def fingerprints(docs: DataFrame, size: int = 4) -> DataFrame:
    """(doc_id, fp) of every row; ``fp`` is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            fp = np.array([fingerprint(t, size) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp)], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(run), "doc_id long, fp long")


def _bits(fp: np.ndarray) -> np.ndarray:
    return np.unpackbits(np.ascontiguousarray(fp).view(np.uint8), bitorder="little").reshape(-1, WIDTH)


def bit_correlation(fps: DataFrame) -> np.ndarray:
    """Correlation of the 64 bits over all rows of ``fps`` (fp)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((WIDTH + 1, WIDTH + 1))
        for b in batches:
            x = np.hstack([_bits(b.column(0).to_numpy()), np.ones((b.num_rows, 1), np.uint8)]).astype(np.float32)
            total += x.T @ x
        i, j = np.triu_indices(WIDTH + 1)
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total[i, j].astype(np.int64))], ["i", "j", "n"])

    got = fps.mapInArrow(lean(run), "i int, j int, n long").groupBy("i", "j").agg(F.sum("n").alias("n")).toPandas()
    both = np.zeros((WIDTH + 1, WIDTH + 1))
    both[got["i"], got["j"]] = both[got["j"], got["i"]] = got["n"]
    n = max(both[WIDTH, WIDTH], 1)
    mean = both[:WIDTH, WIDTH] / n
    cov = both[:WIDTH, :WIDTH] / n - np.outer(mean, mean)
    dev = np.sqrt(np.maximum(np.diag(cov), 1e-12))
    return np.clip(cov / np.outer(dev, dev), -1, 1)


def group_bits(corr: np.ndarray, parts: int) -> list[list[int]]:
    """Bits 0..63 in ``parts`` groups of nearly equal size, correlated bits together."""
    strength, left, out = np.abs(corr) - np.eye(WIDTH), set(range(WIDTH)), []
    for p in range(parts):
        size = len(left) // (parts - p)
        free = sorted(left)
        group = [max(free, key=lambda b: strength[b, free].sum())]  # noqa: B023
        left.discard(group[0])
        while len(group) < size:
            best = max(sorted(left), key=lambda b: strength[b, group].mean())  # noqa: B023
            group.append(best)
            left.discard(best)
        out.append(sorted(group))
    return out


def plan_parts(n: int, corr: np.ndarray, sample: np.ndarray, radius: int, pair_cost: float = 0.02) -> list[tuple[list[int], int]]:
    """Parts of the bits and a threshold for each, of least estimated cost for ``n`` distinct fingerprints."""
    best, least = None, np.inf
    diff = np.zeros((0, WIDTH), np.uint8)
    if len(sample) > 1:
        rng = np.random.default_rng(5)
        a, b = rng.integers(0, len(sample), (2, 200_000))
        diff = _bits((sample[a] ^ sample[b])[a != b])
    for m in range(1, min(radius + 1, 8) + 1):
        groups = group_bits(corr, m)
        table = []
        for g in groups:
            w, apart = len(g), diff[:, g].sum(1) if len(diff) else np.zeros(0)
            costs = {-1: 0.0}
            for t in range(radius + 1):
                if comb(w, t) > 300:
                    break
                pairs = sum(comb(w - d, t - d) * max(float((apart == d).mean()) if len(apart) else 0.0, comb(w, d) / 2.0**w) for d in range(t + 1))
                costs[t] = n * comb(w, t) + pair_cost * pairs * n * n / 2
            table.append(costs)
        best_of: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
        for costs in table:  # best_of: by the sum of thresholds plus one, held to radius + 1
            nxt: dict[int, tuple[float, list[int]]] = {}
            for s, (c, ts) in best_of.items():
                for t, x in costs.items():
                    to = min(s + t + 1, radius + 1)
                    if to not in nxt or c + x < nxt[to][0]:
                        nxt[to] = (c + x, [*ts, t])
            best_of = nxt
        if radius + 1 in best_of and best_of[radius + 1][0] < least:
            least, best = best_of[radius + 1][0], list(zip(groups, best_of[radius + 1][1], strict=True))
    return best


def key_masks(parts: list[tuple[list[int], int]]) -> list[int]:
    """The masks, signed, under which two fingerprints within the radius agree at least once."""
    masks = [sum(1 << b for b in set(g) - set(out)) for g, t in parts if t >= 0 for out in itertools.combinations(g, t)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _chains(fp: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Chains through the groups of distinct fingerprints linked within ``radius``, all pairs compared in blocks."""
    n = len(fp)
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    any_link = False
    step = max(1, (1 << 22) // n)
    for at in range(0, n, step):
        i, j = np.nonzero(np.bitwise_count(fp[at : at + step, None] ^ fp[None, :]) <= radius)
        up = i + at < j
        i, j = i[up] + at, j[up]
        if len(i) > 4 * n:  # one pass over the first neighbours settles most of a dense group
            _, one = np.unique(j, return_index=True)
            for a, b in zip(i[one].tolist(), j[one].tolist(), strict=True):
                root[find(a)] = find(b)
            name = np.array([find(x) for x in range(n)])
            apart = name[i] != name[j]
            i, j = i[apart], j[apart]
            any_link = True
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            root[find(a)] = find(b)
            any_link = True
    if not any_link:
        return []
    last: dict[int, int] = {}
    out = []
    for x in range(n):
        r = find(x)
        if r in last:
            out.append((last[r], x))
        last[r] = x
    return out


def links(fps: DataFrame, radius: int, parts: list[tuple[list[int], int]]) -> DataFrame:
    """(a, b) edges that join, directly or in chains, all rows of ``fps`` (fp, distinct) within ``radius`` bits."""
    masks = F.array(*[F.lit(m).cast("long") for m in key_masks(parts)])
    keys = fps.select(F.explode(F.transform(masks, lambda m: F.xxhash64(m, F.col("fp").bitwiseAND(m)))).alias("key"), "fp")
    hot = keep(keys.groupBy("key").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > BUCKET), "hot")
    cuts = F.coalesce(F.ceil(F.col("_n") / BUCKET), F.lit(1)).cast("long")
    own = F.pmod(F.xxhash64("fp", F.lit("chunk")), F.col("_cuts"))
    runs = (
        keys.join(bounded_broadcast(hot, 100_000), "key", "left").withColumn("_cuts", cuts).withColumn("_own", own)
        .select(F.explode(F.when(F.col("_cuts") == 1, F.array(F.col("key"))).otherwise(
            F.transform(F.sequence(F.lit(0).cast("long"), F.col("_cuts") - 1), lambda c: F.xxhash64("key", F.least("_own", c), F.greatest("_own", c)))
        )).alias("run"), "fp")
    )

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest_run, rest_fp = np.zeros(0, np.int64), np.zeros(0, np.int64)

        def work(run: np.ndarray, fp: np.ndarray) -> pa.RecordBatch:
            edges = np.flatnonzero(run[1:] != run[:-1]) + 1
            starts = np.concatenate([[0], edges])
            sizes = np.diff(np.concatenate([starts, [len(run)]]))
            found = []
            for s, k in zip(starts[sizes > 1].tolist(), sizes[sizes > 1].tolist(), strict=True):
                x = fp[s : s + k].view(np.uint64)
                x = np.unique(x) if k > 2 else x
                found += [(int(x[a]), int(x[b])) for a, b in _chains(x, radius)] if len(x) > 1 else []
            ab = np.array(found, np.uint64).reshape(-1, 2).view(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(ab[:, 0].copy()), pa.array(ab[:, 1].copy())], ["a", "b"])

        for b in batches:
            run = np.concatenate([rest_run, b.column(0).to_numpy()])
            fp = np.concatenate([rest_fp, b.column(1).to_numpy()])
            if not len(run):
                continue
            tail = int(np.searchsorted(run, run[-1]))
            if tail:
                yield work(run[:tail], fp[:tail])
            rest_run, rest_fp = run[tail:], fp[tail:]
        if len(rest_run):
            yield work(rest_run, rest_fp)

    n = int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return runs.repartition(n, "run").sortWithinPartitions("run").mapInArrow(lean(compare), "a long, b long")


def planned_links(fps: DataFrame, radius: int) -> DataFrame:
    """``links`` under the parts of least estimated cost."""
    n = fps.count()
    share = min(1.0, ESTIMATE / max(n, 1))
    sample = fps.where(F.pmod(F.xxhash64("fp", F.lit("sample")), F.lit(1 << 20)) < F.lit(int(share * (1 << 20)) + 1)).limit(4 * ESTIMATE).toPandas()["fp"].to_numpy(np.int64)
    return links(fps, radius, plan_parts(n, bit_correlation(fps), sample, radius))


def near_duplicates(docs: DataFrame, size: int = 4, radius: int = 4) -> DataFrame:
    """Per row: doc_id, fp (signed long) and component_id, the smallest doc_id reachable over links.

    Null texts and texts without words have fingerprint zero and are linked like any other. Rows with a
    null id join their group but never name it; a group of such rows alone has a null component. Repeated ids and rows
    are rows of their own; an empty table gives no rows.
    """
    rows = keep(fingerprints(docs, size), "fingerprints")
    nodes = keep(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "nodes")
    roots = connected(planned_links(nodes.select("fp"), radius))
    named = nodes.join(roots.toDF("fp", "root"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    names = named.groupBy("root").agg(F.min("least").alias("component_id"))
    place = keep(named.join(names, "root").select("fp", "component_id"), "place")
    return rows.join(place, "fp", "left").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, size: int = 4, radius: int = 4) -> DataFrame:
    """One row of each group: that of the smallest doc_id (nulls last), then of the least text hash. Columns are kept, whatever their names.

    Repeated rows and rows with a null id are members like any other, so of a group exactly one row stays.
    """
    rows = keep(stowed(docs).withColumn("row", F.monotonically_increasing_id()), "rows")
    # the row number stands in for the id, so that equal or missing ids can't be taken for each other
    groups = near_duplicates(rows.select(F.col("row").alias("doc_id"), F.col("_row.text").alias("text")), size, radius)
    order = F.struct(F.col("_row.doc_id").isNull().alias("none"), F.col("_row.doc_id").alias("id"), F.xxhash64(F.col("_row.text").cast("string")).alias("text"), "row")
    placed = groups.select(F.col("doc_id").alias("row"), "component_id").join(rows.select("row", order.alias("order")), "row")
    stay = placed.groupBy("component_id").agg(F.min("order").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("component_id", F.col("first.row").alias("stays"))
    gone = placed.join(bounded_broadcast(stay, 100_000), "component_id").where("row <> stays").select(F.col("row").alias("_gone"))
    return rows.join(gone, F.col("row") == F.col("_gone"), "left_anti").select("_row.*")
