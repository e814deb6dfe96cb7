"""Near copies by SimHash and exact Jaccard similarity of word shingles; one row of each group is kept.

Texts whose 64-bit majority fingerprints lie within ``RADIUS`` bits are candidates (the pigeonhole search of ``simhash``). Texts at similarity 0.8 have
fingerprints about ten bits apart, where no pigeonhole key is selective, so min-hash keys add candidates beyond that radius: ``BANDS`` keys of ``ROWS``
minima each. Two texts of similarity s share a key with
chance 1 - (1 - s^ROWS)^BANDS, 1 - 3e-6 at 0.8. Nothing is linked by that: pairs in a bucket whose minima agree in fewer than ``LEAST`` of all
places are left out (0.8 lies almost five deviations above). Candidates of either kind form groups, and inside a candidate group every pair is compared by
its exact sets of shingle hashes. Linked rows, directly or in chains, are one group.

Texts with the same set of shingles are one node throughout (map-side combined). A task compares a group by walking it: a
text is compared with those not reached yet, so a dense group costs a few passes and leaves a tree, not its pairs. Buckets
and candidate groups over a bound are cut into chunks by hash and every pair of chunks is a run of its own; no candidate is dropped.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_broadcast, discard, keep, lean, small, stowed
from .components import connected
from .simhash import majority, planned_links, shingle_hashes

SIZE, SIMILARITY = 5, 0.8
BANDS, ROWS = 24, 4
#: Bits in which the fingerprints of two candidates may differ.
RADIUS = 4
#: Minima that have to agree, of BANDS * ROWS.
LEAST = 58
#: Nodes of a bucket that are compared in one run; nodes and shingles of a chunk of a candidate group.
BUCKET, CHUNK, CHUNK_SHINGLES = 2048, 512, 1 << 18
_RNG = np.random.default_rng(11)
_XOR, _ODD = (_RNG.integers(0, 2**64, BANDS * ROWS, dtype=np.uint64) | np.uint64(k) for k in (0, 1))


def shingle_set(text: str | None, size: int = SIZE) -> np.ndarray:
    """The sorted hashes of the text's shingles, each once."""
    return np.unique(shingle_hashes(text or "", size))


def minima(s: np.ndarray) -> bytes:
    """Sixteen bits of the least value of the set under each hash function."""
    least = np.full(BANDS * ROWS, 2**64 - 1, np.uint64)
    for at in range(0, len(s), 4096):
        h = (s[at : at + 4096, None] ^ _XOR) * _ODD
        h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        least = np.minimum(least, h.min(0))
    return ((least ^ (least >> np.uint64(29))) & np.uint64(0xFFFF)).astype("<u2").tobytes()


def trees(n: int, near: Callable[[int, np.ndarray], np.ndarray]) -> list[tuple[int, int]]:
    """Edges that join all of 0..n-1 linked by ``near`` (which of some are near to one), directly or in chains."""
    left, out = np.arange(n), []
    while len(left) > 1:
        todo, left = [int(left[0])], left[1:]
        while todo and len(left):
            x = todo.pop()
            hit = near(x, left)
            found = left[hit].tolist()
            out += [(x, y) for y in found]
            todo += found
            left = left[~hit]
    return out


def alike(rows: list[bytes]) -> Callable[[int, np.ndarray], np.ndarray]:
    m = np.frombuffer(b"".join(rows), "<u2").reshape(len(rows), -1)
    return lambda x, some: (m[some] == m[x]).sum(1) >= LEAST


def similar(rows: list[bytes], similarity: float) -> Callable[[int, np.ndarray], np.ndarray]:
    """Exact test on sets of shingle hashes; those that only one set has are counted, not compared."""
    sets = [np.frombuffer(r, np.uint64) for r in rows]
    size = np.array([len(s) for s in sets], np.int64)
    values, which, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    place = np.cumsum(often > 1) - 1
    width = -(-(int(place[-1]) + 1) // 64) if len(values) else 0
    bits = np.empty((len(sets), max(width, 1)), np.uint64)
    for i, mine in enumerate(np.split(which, np.cumsum(size)[:-1])):
        held = np.zeros(bits.shape[1] * 64, bool)
        held[place[mine[often[mine] > 1]]] = True
        bits[i] = np.packbits(held).view(np.uint64)

    def near(x: int, some: np.ndarray) -> np.ndarray:
        both = np.zeros(len(some), np.int64)
        step = max(1, (1 << 20) // bits.shape[1])
        for at in range(0, len(some), step):
            both[at : at + step] = np.bitwise_count(bits[some[at : at + step]] & bits[x]).sum(1, dtype=np.int64)
        whole = size[some] + size[x] - both
        return (both >= similarity * whole - 1e-9) | (whole == 0)

    return near


def _cut_up(rows: DataFrame, key: str, cuts: str) -> DataFrame:
    """``rows`` with a ``run`` for every pair of the ``cuts`` chunks that a row of ``key`` belongs to."""
    own = F.pmod(F.xxhash64("node", F.lit("chunk")), F.col(cuts))
    pairs = F.transform(F.sequence(F.lit(0).cast("long"), F.col(cuts) - 1), lambda c: F.xxhash64(key, F.least("_own", c), F.greatest("_own", c)))
    return rows.withColumn("_own", own).withColumn("run", F.explode(F.when(F.col(cuts) == 1, F.array(F.col(key))).otherwise(pairs)))


def _compared(runs: DataFrame, near_of: Callable[[list[bytes]], Callable[[int, np.ndarray], np.ndarray]]) -> DataFrame:
    """(a, b) edges of all runs; ``runs`` is (run, node, data binary)."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, nodes, data = None, [], []

        def work() -> pa.RecordBatch:
            ab = [(nodes[a], nodes[b]) for a, b in trees(len(nodes), near_of(data))] if len(nodes) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([x[i] for x in ab], pa.int64()) for i in (0, 1)], ["a", "b"])

        for b in small(batches):
            for run, node, some in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if run != now:
                    if len(nodes) > 1:
                        yield work()
                    now, nodes, data = run, [], []
                nodes.append(node)
                data.append(some)
        if len(nodes) > 1:
            yield work()

    n = int(runs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return runs.select("run", "node", "data").repartition(n, "run").sortWithinPartitions("run").mapInArrow(lean(compare), "a long, b long")


def candidates(nodes: DataFrame) -> DataFrame:
    """(a, b) edges between ``nodes`` (node, minima) that share a key and agree in LEAST minima."""
    bands = F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda i: F.xxhash64(i, F.substring("minima", 2 * ROWS * i + 1, F.lit(2 * ROWS))))
    keys = nodes.select("node", F.explode(bands).alias("key"))
    shared = keys.groupBy("key").agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select("key", F.ceil(F.col("_n") / BUCKET).cast("long").alias("_cuts"))
    runs = _cut_up(keys.join(shared, "key"), "key", "_cuts").select("run", "node")
    return _compared(runs.join(nodes, "node").select("run", "node", F.col("minima").alias("data")), alike)


def simhash_candidates(nodes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(a, b) edges that join, directly or in chains, all ``nodes`` (node, fp) whose fingerprints are within ``radius`` bits; equal ones by their least node."""
    of = keep(nodes.groupBy("fp").agg(F.min("node").alias("least")), "fps")
    equal = nodes.join(of, "fp").where("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b"))
    near = planned_links(of.select("fp"), radius).toDF("_a", "_b")
    near = near.join(of.toDF("_a", "a"), "_a").join(of.toDF("_b", "b"), "_b").select("a", "b")
    return equal.union(near)


def links(rows: DataFrame, size: int = SIZE, similarity: float = SIMILARITY) -> DataFrame:
    """(a, b) edges, written, that join, directly or in chains, all nodes of ``rows`` (text, node, minima, fp, shingles) of at least ``similarity``."""
    nodes = rows.where("shingles > 0").groupBy("node").agg(F.first("minima").alias("minima"), F.first("fp").alias("fp"), F.first("shingles").alias("shingles"))
    nodes = keep(nodes, "nodes")
    roots = connected(simhash_candidates(nodes.select("node", "fp")).union(candidates(nodes.select("node", "minima"))))
    most = lambda c, bound: F.ceil(c / bound)
    groups = (
        roots.join(nodes.select("node", "shingles"), "node").groupBy("root").agg(F.count(F.lit(1)).alias("_n"), F.sum("shingles").alias("_s"))
        .select("root", F.greatest(most(F.col("_n"), CHUNK), most(F.col("_s"), CHUNK_SHINGLES)).cast("long").alias("_cuts"))
    )

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            found = [shingle_set(t, size).tobytes() for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("node"), pa.array(found, pa.binary())], ["node", "data"])

    texts = rows.select("node", "text").join(bounded_broadcast(roots.select("node"), 100_000), "node", "left_semi")
    data = keep(texts.groupBy("node").agg(F.first("text").alias("text")).select("node", "text").mapInArrow(lean(sets), "node long, data binary"), "sets")
    runs = _cut_up(roots.join(groups, "root"), "root", "_cuts").select("run", "node")
    edges = keep(_compared(runs.join(data, "node"), lambda x: similar(x, similarity)), "links")
    discard(nodes, data, roots)
    return edges


def prepared(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """(_row, node, minima, fp, shingles) of every row; ``node`` is the hash of its set of shingles, alike for all rows without words, ``fp`` its fingerprint."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            got = [shingle_set(t, size) for t in b.column("text").to_pylist()]
            node = np.array([xxhash.xxh64_intdigest(s.tobytes()) for s in got], np.uint64).view(np.int64)
            cols = [b.column("_row"), pa.array(node), pa.array([minima(s) for s in got], pa.binary()), pa.array(np.array([majority(s) for s in got], np.uint64).view(np.int64)), pa.array([len(s) for s in got], pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, ["_row", "node", "minima", "fp", "shingles"])

    rows = stowed(docs).select("_row", F.col("_row.text").cast("string").alias("text"))
    schema = rows.select("_row", F.lit(0).cast("long").alias("node"), F.lit(b"").alias("minima"), F.lit(0).cast("long").alias("fp"), F.lit(0).cast("long").alias("shingles")).schema
    return rows.mapInArrow(lean(run), schema)


def keep_one(docs: DataFrame, size: int = SIZE, similarity: float = SIMILARITY) -> DataFrame:
    """One row of each group of near copies: that of the smallest doc_id (nulls last), then of the least text hash. Columns are kept, whatever their names.

    Repeated rows and rows with a null id are members like any other, so of a group exactly one row stays.
    """
    rows = keep(prepared(docs, size).withColumn("row", F.monotonically_increasing_id()), "prepared")
    known = rows.select(F.col("_row.doc_id").alias("doc_id"), F.col("_row.text").cast("string").alias("text"), "node", "minima", "fp", "shingles", "row")
    roots = connected(links(known, size, similarity))
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", F.xxhash64("text").alias("text"), "row")
    placed = known.select("row", "node", order.alias("order")).join(roots, "node", "left").select("row", "order", F.coalesce("root", "node").alias("root"))
    stay = placed.groupBy("root").agg(F.min("order").alias("first"), F.count(F.lit(1)).alias("_n")).where("_n > 1").select("root", F.col("first.row").alias("stays"))
    gone = placed.join(bounded_broadcast(stay, 100_000), "root").where("row <> stays").select(F.col("row").alias("_gone"))
    return rows.join(gone, F.col("row") == F.col("_gone"), "left_anti").select("_row.*")
