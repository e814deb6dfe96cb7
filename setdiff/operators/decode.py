"""Decoding of binary BCH syndromes: which bins differ, or that it can't be told.

All groups of a batch are decoded together with table look-ups. ``bm`` finds the locator by the shortest linear
recurrence, ``toeplitz`` by a recursion on the structured system, ``gauss`` by plain elimination; the latter two are for
comparison. A result is given only if the locator's degree is within the capacity, it has as many distinct roots, and
the roots reproduce the syndromes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setdiff.functions.gf import Field, field, packed_table, unpack
from setdiff.operators import binparity as S
from setdiff.session import written


def all_syndromes(odd: np.ndarray, f: Field) -> np.ndarray:
    """(groups, 2t) syndromes 1..2t: an even one is the square of the one at half its index."""
    g, t = odd.shape
    s = np.zeros((g, 2 * t + 1), np.int64)
    s[:, 1::2] = odd
    for k in range(2, 2 * t + 1, 2):
        s[:, k] = f.mul(s[:, k // 2], s[:, k // 2])
    return s[:, 1:]


def locator_bm(s: np.ndarray, f: Field) -> tuple[np.ndarray, np.ndarray]:
    """(coefficients (groups, t+1), degree) of each group's shortest recurrence."""
    g, two_t = s.shape
    wide = two_t // 2 + 2
    c, b = np.zeros((g, wide), np.int64), np.zeros((g, wide), np.int64)
    c[:, 0] = b[:, 0] = 1
    size, scale = np.zeros(g, np.int64), np.ones(g, np.int64)
    for i in range(two_t):
        b[:, 1:] = b[:, :-1].copy()
        b[:, 0] = 0
        gap = s[:, i].copy()
        for j in range(1, min(i, wide - 1) + 1):
            gap ^= f.mul(c[:, j], s[:, i - j])
        off = gap != 0
        grow = off & (2 * size <= i)
        old = c.copy()
        c ^= f.mul(np.where(off, f.div(gap, scale), 0)[:, None], b)
        b = np.where(grow[:, None], old, b)
        scale = np.where(grow, gap, scale)
        size = np.where(grow, i + 1 - size, size)
    return c, size


def _solve(a: np.ndarray, y: np.ndarray, f: Field) -> np.ndarray | None:
    """Elimination; None if the matrix is singular."""
    n = len(y)
    m = np.concatenate([a, y[:, None]], axis=1).astype(np.int64)
    for col in range(n):
        pivot = next((r for r in range(col, n) if m[r, col]), None)
        if pivot is None:
            return None
        m[[col, pivot]] = m[[pivot, col]]
        m[col] = f.div(m[col], m[col, col])
        for r in range(n):
            if r != col and m[r, col]:
                m[r] ^= f.mul(m[col], m[r, col])
    return m[:, n]


def _levinson(s: np.ndarray, v: int, f: Field) -> np.ndarray | None:
    """Locator of degree v from the Toeplitz system of the syndromes by growing solutions; None where a leading minor vanishes."""
    # rows i: sum_j x_j * s[v - 1 + i - j] = s[v + i], i and j from 0; unknowns x_0.. are the coefficients 1..v
    entry = lambda k: int(s[v - 1 + k])
    if entry(0) == 0:
        return None
    inv = lambda x: int(f.div(1, x))
    fwd, bwd = np.array([inv(entry(0))]), np.array([inv(entry(0))])
    x = f.mul(np.array([int(s[v])]), fwd)
    for n in range(1, v):
        ef = int(np.bitwise_xor.reduce(f.mul(np.array([entry(n - j) for j in range(n)]), fwd)))
        eb = int(np.bitwise_xor.reduce(f.mul(np.array([entry(-1 - j) for j in range(n)]), bwd)))
        den = 1 ^ int(f.mul(ef, eb))
        if den == 0:
            return None
        k = inv(den)
        f0, b0 = np.append(fwd, 0), np.insert(bwd, 0, 0)
        fwd, bwd = f.mul(k, f0 ^ f.mul(ef, b0)), f.mul(k, b0 ^ f.mul(eb, f0))
        ex = int(np.bitwise_xor.reduce(f.mul(np.array([entry(n - j) for j in range(n)]), x)))
        x = np.append(x, 0) ^ f.mul(int(s[v + n]) ^ ex, bwd)
    return x


def locator_direct(s: np.ndarray, f: Field, solver: str) -> tuple[np.ndarray, np.ndarray]:
    """The same by solving the system of the largest non-singular size, group by group."""
    g, two_t = s.shape
    t = two_t // 2
    c, size = np.zeros((g, t + 2), np.int64), np.zeros(g, np.int64)
    c[:, 0] = 1
    for i in range(g):
        row = s[i]
        for v in range(t, 0, -1) if row.any() else ():
            x = _levinson(row, v, f) if solver == "toeplitz" else None
            if x is None:
                x = _solve(np.array([[row[v - 1 + a - b] for b in range(v)] for a in range(v)]), row[v : 2 * v], f)
            if x is not None:
                c[i, 1 : v + 1], size[i] = x, v
                break
        else:
            size[i] = t + 1 if row.any() else 0
    return c, size


def decode(lanes: np.ndarray, m: int, t: int, solver: str = "bm") -> tuple[np.ndarray, list[np.ndarray]]:
    """(ok, bins) of each group's packed syndrome difference (groups, lanes)."""
    f, table = field(m), packed_table(m, t)
    lanes = np.asarray(lanes, np.int64).reshape(-1, table.shape[0])
    ok, bins = np.ones(len(lanes), bool), [np.zeros(0, np.int64)] * len(lanes)
    live = np.flatnonzero(lanes.any(1))
    step = max(1, (1 << 22) // f.n)
    for at in range(0, len(live), step):
        some = live[at : at + step]
        s = all_syndromes(unpack(lanes[some], m, t), f)
        c, size = locator_bm(s, f) if solver == "bm" else locator_direct(s, f, solver)
        value = np.zeros((len(some), f.n), np.int64)
        b = np.arange(f.n)
        for j in range(min(t, c.shape[1] - 1) + 1):
            has = c[:, j] != 0
            value[has] ^= f.exp[(f.log[c[has, j]][:, None] - j * b[None, :]) % f.n]
        zero = value == 0
        good = (size <= t) & (zero.sum(1) == size)
        for k, i in enumerate(some.tolist()):
            roots = np.flatnonzero(zero[k]) if good[k] else None
            if roots is None or (np.bitwise_xor.reduce(table[:, roots], axis=1) != lanes[i]).any():
                ok[i] = False
            else:
                bins[i] = roots
    return ok, bins


def decode_batches(keys: list[str], m: int, t: int, solver: str = "bm"):
    """For mapInArrow: rows (keys..., cw array<bigint>) become (keys..., ok, bins)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            lanes = b.column("cw").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            ok, bins = decode(lanes, m, t, solver)
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(ok), pa.array(bins, pa.list_(pa.int64()))], [*keys, "ok", "bins"])

    return run


def differing_bins(df: DataFrame, keys: list[str], m: int, t: int, ways: int = 3) -> DataFrame:
    """(keys, bin): the bins of ``df`` (keys, bin; both hosts' rows) with odd counts, decoded from codewords, however many a group has.

    A group over capacity, or whose bins don't hash to the XOR that was sent along, is coded again in classes of its bins: modulo ``ways``, then its
    square and so on. A class of t bins or fewer is always within capacity, so the classes end however large the difference is.
    """
    parts, n_open, n = 1, 0, (1 << m) - 1
    open_ = out = None
    while True:
        rows = df.withColumn("_part", F.col("bin") % parts)
        if open_ is not None:
            rows = rows.join(F.broadcast(open_) if n_open <= S.BROADCAST_ROWS else open_, [*keys, "_part"], "left_semi")
        looked, lanes = S.lane_columns(rows, m, t)
        sketch = looked.groupBy(*keys, "_part").agg(F.array(*[F.bit_xor(x) for x in lanes]).alias("cw"), F.bit_xor(F.xxhash64(F.col("bin").cast("long"))).alias("_chk"))
        held = [*keys, "_part", "_chk"]
        types = ", ".join(f"{c} {dict(sketch.dtypes)[c]}" for c in held)
        got = sketch.mapInArrow(decode_batches(held, m, t), f"{types}, ok boolean, bins array<bigint>")
        seen = F.aggregate("bins", F.lit(0).cast("long"), lambda x, b: x.bitwiseXOR(F.xxhash64(b)))
        got = written(got.withColumn("ok", F.col("ok") & (seen == F.col("_chk"))), "decoded_bins")
        right = got.where("ok").select(*keys, F.explode("bins").alias("bin"))
        out = right if out is None else out.union(right)
        finer = F.array(*[F.col("_part") + parts * i for i in range(ways)])
        open_ = got.where("not ok").select(*keys, F.explode(finer).alias("_part"))
        n_open = open_.count()
        if not n_open:
            return out
        if parts >= n:
            raise ValueError("a single bin can't be decoded")
        parts *= ways
