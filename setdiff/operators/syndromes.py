"""Syndromes of the signatures themselves over GF(2**32): the whole-set code, and the same inside hash groups.

The sketch of a set is the XOR over its elements of their odd powers; t of them tell up to t differences. Up to ``DIRECT_SUMS`` of them, encoding takes t
products an element, up to ``DIRECT`` decoding about t**2, and finding the roots of the locator in a field of 2**32 elements another t**2 times 32, as in
the comparison. Beyond, polynomials are multiplied by transforms (``functions/poly32``): all of it is near linear in elements and capacity, and a locator
is split into pieces that are solved in tasks of their own.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setdiff.functions import poly32 as L
from setdiff.functions.gf import inv32, mul32
from setdiff.operators import binparity as S
from setdiff.operators.binparity import NODE
from setdiff.plans.params import Params
from setdiff.session import written

#: Elements whose powers are held at a time, and elements whose sums are taken by products of polynomials.
CHUNK, LONG_CHUNK = 1 << 16, 1 << 20
#: Capacities up to this are decoded product by product, those up to the second encoded so.
DIRECT, DIRECT_SUMS = 512, 48
#: Capacity above which a decoding takes so long that keys are dealt out to tasks by their number.
SPREAD = 32
#: Degree up to which one task finds all roots of a polynomial.
PIECE = 2048


def _chunks(batches: Iterator[pa.RecordBatch], chunk: int) -> Iterator[pa.Table]:
    """Batches put together until they have ``chunk`` rows, as sums have a cost for each chunk, and each group in it, too."""
    held: list[pa.RecordBatch] = []
    n = 0
    for b in batches:
        if held and n + b.num_rows > chunk:
            yield pa.Table.from_batches(held)
            held, n = [], 0
        held.append(b)
        n += b.num_rows
    if held:
        yield pa.Table.from_batches(held)


def encode(df: DataFrame, keys: list[str], t: int) -> DataFrame:
    """(keys, k, s): syndrome k = 0..t-1 is the XOR of the (2k+1)-th powers. Partial XORs leave the Python workers, group by group."""
    kinds = dict(df.dtypes)
    chunk = LONG_CHUNK if t > DIRECT_SUMS else CHUNK

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _chunks(batches, chunk):
            for at in range(0, b.num_rows, chunk):
                c = b.slice(at, chunk).to_pandas()
                c = c.sort_values(keys, kind="stable") if keys else c
                x = c["sig"].to_numpy().astype(np.uint64)
                change = np.ones(len(c), bool)
                if keys:
                    change[1:] = (c[keys].to_numpy()[1:] != c[keys].to_numpy()[:-1]).any(1)
                else:
                    change[1:] = False
                starts = np.flatnonzero(change)
                heads = c[keys].iloc[starts] if keys else pd.DataFrame(index=range(len(starts)))
                if t > DIRECT_SUMS:
                    for i, at_ in enumerate(starts):
                        rows = L.to_tower(x[at_ : starts[i + 1] if i + 1 < len(starts) else len(x)])
                        out = heads.iloc[[i]].loc[lambda h: h.index.repeat(t)].reset_index(drop=True)
                        out["k"], out["s"] = np.arange(t), L.from_tower(_power_sums(rows, t)).astype(np.int64)
                        yield pa.RecordBatch.from_pandas(out.astype({"k": "int32"}), preserve_index=False)
                    continue
                sq, p = mul32(x, x), x
                for k in range(t):
                    out = heads.copy()
                    out["k"], out["s"] = k, np.bitwise_xor.reduceat(p, starts).astype(np.int64)
                    yield pa.RecordBatch.from_pandas(out.astype({"k": "int32"}), preserve_index=False)
                    if k + 1 < t:
                        p = mul32(p, sq)

    schema = "".join(f"{c} {kinds[c]}, " for c in keys) + "k int, s long"
    return df.select(*keys, "sig").mapInArrow(run, schema).groupBy(*keys, "k").agg(F.bit_xor("s").alias("s"))


def _power_sums(x: np.ndarray, t: int) -> np.ndarray:
    """Odd power sums of a chunk, in blocks of some capacities, as what a block costs beside its elements goes with the capacity."""
    block = min(1 << (len(x) - 1).bit_length(), max(1024, 8 << (t - 1).bit_length()))
    rows = np.zeros((-(-len(x) // block), block), np.uint32)
    rows.ravel()[: len(x)] = x
    return np.bitwise_xor.reduce(L.odd_power_sums(rows, t), axis=0)


def _trim(p: np.ndarray) -> np.ndarray:
    nz = np.flatnonzero(p)
    return p[: nz[-1] + 1] if len(nz) else p[:0]


def _mod(a: np.ndarray, f: np.ndarray) -> np.ndarray:
    """Remainder by a monic polynomial; coefficients from the constant up."""
    a, n = a.copy(), len(f) - 1
    for i in range(len(a) - 1, n - 1, -1):
        if a[i]:
            a[i - n : i + 1] ^= mul32(a[i], f)
    return _trim(a[:n])


def _mod_rows(a: np.ndarray, f: np.ndarray) -> np.ndarray:
    """Remainders of many polynomials, one a row, by a monic one."""
    a, n = a.copy(), len(f) - 1
    for i in range(a.shape[1] - 1, n - 1, -1):
        a[:, i - n : i + 1] ^= mul32(a[:, i, None], f[None, :])
    return a[:, :n]


def _monic(a: np.ndarray) -> np.ndarray:
    return mul32(a, inv32(a[-1:]))


def _gcd(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    while len(b):
        a, b = b, _mod(a, _monic(b))
    return _monic(a) if len(a) else a


def _div(a: np.ndarray, f: np.ndarray) -> np.ndarray:
    """Quotient by a monic divisor."""
    a, n = a.copy(), len(f) - 1
    q = np.zeros(len(a) - n, np.uint64)
    for i in range(len(a) - 1, n - 1, -1):
        q[i - n] = a[i]
        if a[i]:
            a[i - n : i + 1] ^= mul32(a[i], f)
    return q


@cache
def _conjugates() -> np.ndarray:
    """(32, 32): row i has 2**i and its repeated squares."""
    x = np.uint64(1) << np.arange(32, dtype=np.uint64)
    out = [x]
    for _ in range(31):
        out.append(mul32(out[-1], out[-1]))
    return np.stack(out, axis=1)


def roots32(f: np.ndarray) -> np.ndarray | None:
    """All roots of a monic polynomial that is a product of different linear factors, by trace splitting; None if it isn't one."""
    n = len(f) - 1
    if n == 0:
        return np.zeros(0, np.uint64)
    if n == 1:
        return f[:1]
    # squares of x**i modulo f, so that a squaring is one product and one XOR of rows
    rows = np.zeros((n, n), np.uint64)
    r = np.zeros(n, np.uint64)
    r[0] = 1
    for i in range(n):
        rows[i] = r
        for _ in range(2):
            r = np.concatenate([[np.uint64(0)], r[:-1]]) ^ mul32(r[-1], f[:n])
    x = np.zeros(n, np.uint64)
    x[1] = 1
    powers = [x]
    for _ in range(32):
        p = powers[-1]
        powers.append(np.bitwise_xor.reduce(mul32(mul32(p, p)[:, None], rows), axis=0))
    if (powers[32] != x).any():
        return None

    def split(f: np.ndarray, powers: np.ndarray, bit: int) -> list[np.ndarray]:
        if len(f) == 2:
            return [f[:1]]
        for i in range(bit, 32):
            trace = np.bitwise_xor.reduce(mul32(_conjugates()[i][:, None], powers), axis=0)
            g = _gcd(f, _trim(trace))
            if 1 < len(g) < len(f):
                h = _div(f, g)
                return [r for part in (g, h) for r in split(part, _mod_rows(powers, part), i + 1)]
        return []

    got = split(f, np.array(powers[:32]), 0)
    return np.concatenate(got) if got else None


def decode32(odd: np.ndarray) -> np.ndarray | None:
    """The differences that t odd syndromes tell, or None."""
    t = len(odd)
    if not odd.any():
        return np.zeros(0, np.uint64)
    s = np.zeros(2 * t + 1, np.uint64)
    s[1::2] = odd
    for k in range(2, 2 * t + 1, 2):
        s[k] = mul32(s[k // 2], s[k // 2])
    s = s[1:]
    c, b = np.zeros(t + 2, np.uint64), np.zeros(t + 2, np.uint64)
    c[0] = b[0] = 1
    size, scale = 0, np.uint64(1)
    for i in range(2 * t):
        b = np.concatenate([[np.uint64(0)], b[:-1]])
        j = np.arange(0, min(i, t + 1) + 1)
        gap = np.bitwise_xor.reduce(mul32(c[j], s[i - j]))
        if gap:
            old = c.copy()
            c = c ^ mul32(mul32(gap, inv32(scale)), b)
            if 2 * size <= i:
                size, b, scale = i + 1 - size, old, gap
    if size > t or not c[size]:
        return None
    found = roots32(_monic(c[: size + 1][::-1].copy()))
    if found is None or len(found) != size:
        return None
    p, sq = found, mul32(found, found)
    for k in range(t):
        if np.bitwise_xor.reduce(p) != odd[k]:
            return None
        p = mul32(p, sq)
    return found


def decode(sketch: DataFrame, keys: list[str], t: int) -> DataFrame:
    """(keys, ok, sigs) from the XOR of both hosts' syndromes (keys, k, s)."""
    kinds = dict(sketch.dtypes)
    rows = sketch.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("k", "s"))).alias("v")).select(*keys, F.col("v.s").alias("s"))
    if t > SPREAD and keys:
        rows = _by_key(written(rows, "syndromes"), keys)
    if t > DIRECT:
        return _decode_by_pieces(rows, keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [decode32(np.array(s, np.int64).astype(np.uint64)) for s in b.column("s").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [*(b.column(k) for k in keys), pa.array([g is not None for g in got], pa.bool_()), pa.array([[] if g is None else g.astype(np.int64).tolist() for g in got], pa.list_(pa.int64()))],
                [*keys, "ok", "sigs"],
            )

    return rows.mapInArrow(run, "".join(f"{c} {kinds[c]}, " for c in keys) + "ok boolean, sigs array<bigint>")


def _decode_by_pieces(rows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, ok, sigs) from (keys, s): the locator of each key, split until every factor has degree ``PIECE`` at most, then the roots of each factor.

    Polynomials are monic, leading coefficient first, in tower coordinates; null: not a product of different linear factors.
    """
    kinds = dict(rows.dtypes)
    of_keys = "".join(f"{c} {kinds[c]}, " for c in keys)
    rows = rows if keys else written(rows, "syndromes")
    longs = pa.list_(pa.int64())
    tower = lambda p: None if p is None else np.array(p, np.int64).astype(np.uint32)
    plain = lambda p: None if p is None else p.astype(np.int64)

    def locate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            odd = [L.to_tower(np.array(s, np.int64).astype(np.uint64)) for s in b.column("s").to_pylist()]
            got = [plain(L.locator(s) if s.any() else np.ones(1, np.uint32)) for s in odd]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array([""] * len(got)), pa.array(got, longs)], [*keys, "part", "f"])

    def split(bit: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for i, (part, f) in enumerate(zip(b.column("part").to_pylist(), b.column("f").to_pylist(), strict=True)):
                    got = [tower(f)] if f is None or len(f) <= PIECE + 1 else L.split([tower(f)], bit)[0] or [None]
                    yield pa.RecordBatch.from_arrays(
                        [*(b.column(k).take(pa.array([i] * len(got))) for k in keys), pa.array([f"{part}{j}" for j in range(len(got))]), pa.array([plain(p) for p in got], longs)], [*keys, "part", "f"]
                    )

        return run

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            f = [tower(p) for p in b.column("f").to_pylist()]
            x = iter(L.roots([p for p in f if p is not None]))
            got = [None if p is None else plain(next(x)) for p in f]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(got, longs)], [*keys, "x"])

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = []
            for s, x in zip(b.column("s").to_pylist(), b.column("x").to_pylist(), strict=True):
                s, x = L.to_tower(np.array(s, np.int64).astype(np.uint64)), tower(x)
                right = x is not None and (not s.any() if not len(x) else (_power_sums(x, len(s)) == s).all())
                got.append(L.from_tower(x).astype(np.int64) if right else None)
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array([g is not None for g in got], pa.bool_()), pa.array([[] if g is None else g for g in got], longs)], [*keys, "ok", "sigs"])

    pieces = written(rows.mapInArrow(locate, f"{of_keys}part string, f array<bigint>"), "locators")
    for bit in range(32):
        n, most = pieces.agg(F.count(F.lit(1)), F.max(F.size("f"))).first()
        if (most or 0) <= PIECE + 1:
            break
        pieces = written(_spread(pieces, keys, n).mapInArrow(split(bit), f"{of_keys}part string, f array<bigint>"), "pieces")
    solved = _spread(pieces, keys, min(n, rows.sparkSession.sparkContext.defaultParallelism)).mapInArrow(solve, f"{of_keys}x array<bigint>")
    found = solved.groupBy(*keys).agg(F.when(F.count("x") == F.count(F.lit(1)), F.flatten(F.collect_list("x"))).alias("x"))
    return rows.join(written(found, "roots"), keys).mapInArrow(check, f"{of_keys}ok boolean, sigs array<bigint>")


def _by_key(rows: DataFrame, keys: list[str]) -> DataFrame:
    """A task for each key, a thousand at most: each has few bytes, but much to be done."""
    return rows.repartitionByRange(max(1, min(rows.count(), 1000)), *keys)


def _spread(pieces: DataFrame, keys: list[str], n: int) -> DataFrame:
    """So many tasks, a thousand at most."""
    return pieces.repartitionByRange(min(n, 1000), *keys, "part") if n > 1 else pieces


def _both(a: DataFrame, b: DataFrame, keys: list[str], t: int, sketches: Sequence[DataFrame] | None = None) -> DataFrame:
    """The XOR of both hosts' syndromes; ``sketches``: theirs, where they are at hand."""
    x, y = sketches or (encode(a, keys, t), encode(b, keys, t))
    return x.union(y).groupBy(*keys, "k").agg(F.bit_xor("s").alias("s"))


def _sides(a: DataFrame, sigs: DataFrame) -> DataFrame:
    mine = S.among(a, sigs, ["inst", "sig"], sigs.count()).withColumn("_in", F.lit(True))
    return sigs.join(mine, ["inst", "sig"], "left").select("inst", "sig", F.when(F.col("_in"), "A_only").otherwise("B_only").alias("side"))


def verified(a: DataFrame, b: DataFrame, found: DataFrame, keys: list[str]) -> DataFrame:
    """(keys) whose sums of signatures agree once the differences ``found`` (keys, sig, side) are taken out; sums are exact, by halves of 32 bits."""
    high, low = F.shiftright("sig", 32), F.col("sig").bitwiseAND(F.lit((1 << 32) - 1))
    of = F.when(F.col("side") == "A_only", F.lit(-1)).otherwise(F.lit(1))
    parts = [x.groupBy(*keys).agg(F.sum(high * s).alias("_h"), F.sum(low * s).alias("_l")) for x, s in ((a, F.lit(1)), (b, F.lit(-1)), (found, of))]
    whole = [F.sum(F.col(c).cast("decimal(20,0)")) for c in ("_h", "_l")]
    return parts[0].union(parts[1]).union(parts[2]).groupBy(*keys).agg((whole[0] * F.lit(1 << 32).cast("decimal(10,0)") + whole[1]).alias("_s")).where("_s = 0").select(*keys)


def whole_syndrome_checked(a: DataFrame, b: DataFrame, t: int, sketches: Sequence[DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """((inst, sig, side), (inst, ok)): instances with over t differences, or whose checksums don't agree afterwards, give nothing and are not ok."""
    a, b = S.with_inst(a), S.with_inst(b)
    got = written(decode(_both(a, b, ["inst"], t, sketches), ["inst"], t), "whole")
    sided = written(_sides(a, got.where("ok").select("inst", F.explode("sigs").alias("sig"))), "sided")
    right = written(verified(a, b, sided, ["inst"]).join(got.where("ok"), "inst", "left_semi"), "right")
    status = got.select("inst").join(right.withColumn("ok", F.lit(True)), "inst", "left").select("inst", F.coalesce("ok", F.lit(False)).alias("ok"))
    return sided.join(F.broadcast(right), "inst", "left_semi").select("inst", "sig", "side"), status


def whole_syndrome(a: DataFrame, b: DataFrame, t: int, complete: bool = False, sketches: Sequence[DataFrame] | None = None) -> DataFrame:
    """(inst, sig, side); an instance that fails (see ``whole_syndrome_checked``) gives nothing, or with ``complete`` is exchanged in full."""
    from setdiff.operators.relational import symmetric_difference

    a, b = S.with_inst(a), S.with_inst(b)
    found, status = whole_syndrome_checked(a, b, t, sketches)
    if not complete:
        return found
    failed = written(status.where("not ok").select("inst"), "failed")
    if failed.isEmpty():
        return found
    x, y = (d.join(F.broadcast(failed), "inst", "left_semi") for d in (a, b))
    return found.union(symmetric_difference(x, y, ["inst", "sig"]).select("inst", "sig", "side"))


def grouped_syndrome(a: DataFrame, b: DataFrame, p: Params, most_rounds: int = 64, sketches: Sequence[DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """(diff, rounds): the code inside each hash group; groups that fail, or whose checksums don't agree afterwards, are split.

    ``rounds``: (inst, round, root, path, ok, n). Groups that are not ok in the last round, of which there are none unless the rounds are capped
    (``p.max_rounds``), are left out of the diff; ``unresolved`` names their instances.
    """
    a, b = S.with_inst(a), S.with_inst(b)
    found = log = open_ = None
    n_open = levels = 0
    for k in range(1, (p.max_rounds or most_rounds) + 1):
        x, y = (S.with_node(d, p, open_, levels, n_open) for d in (a, b))
        got = decode(_both(x, y, NODE, p.t, sketches if k == 1 else None), NODE, p.t).withColumn("round", F.lit(k))
        got = written(got, "grouped")
        sigs = got.where("ok").select(*NODE, F.explode("sigs").alias("sig"))
        sigs = sigs.where((S.root_of(p) == F.col("root")) & S.split_path(p, levels).startswith(F.col("path")))
        sided = written(sigs.join(_sides(a, written(sigs.select("inst", "sig").distinct(), "sigs")), ["inst", "sig"]).select(*NODE, "sig", "side"), "sided")
        right = verified(x.select(*NODE, "sig"), y.select(*NODE, "sig"), sided, NODE).withColumn("_right", F.lit(True))
        got = written(got.join(right, NODE, "left").withColumn("ok", F.col("ok") & F.coalesce("_right", F.lit(False))).drop("_right"), "checked")
        sigs = sided.join(got.where("ok").select(*NODE), NODE, "left_semi").select("inst", "sig", "side")
        found = sigs if found is None else found.union(sigs)
        one = got.select("inst", "round", "root", "path", "ok", F.size("sigs").alias("n"))
        log = one if log is None else log.union(one)
        digits = F.explode(F.array(*[F.lit(str(i)) for i in range(p.ways)])).alias("_d")
        open_ = written(got.where("not ok").select("inst", "root", "path", digits).select("inst", "root", F.concat("path", "_d").alias("path")), "open")
        n_open, levels = open_.agg(F.count(F.lit(1)), F.coalesce(F.max(F.length("path")), F.lit(0))).first()
        if not n_open:
            break
    return found.distinct(), log


def unresolved(log: DataFrame) -> DataFrame:
    """(inst) of the instances with groups that the last round of ``grouped_syndrome`` left open."""
    last = log.agg(F.max("round").alias("round"))
    return log.join(F.broadcast(last), "round", "left_semi").where("not ok").select("inst").distinct()

