"""Cell-table digests: encode, subtract, peel; and the filter that comes before a small one.

A set is added to ``k`` cells of a table cut into k equal stripes, one cell a stripe; a cell holds a signed count, the XOR of its
signatures and the XOR of their 32-bit check hashes. After subtraction a cell with count 1 or -1 whose check fits its signature
gives a difference; taking it out of its other cells may lay bare more.
"""

from __future__ import annotations

from collections.abc import Sequence
from math import ceil, log, log2, sqrt


import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setdiff.functions import hashing as H
from setdiff.operators.binparity import with_inst
from setdiff.session import written

#: Bytes of a filter's bitmap bucket, and of a filter that is broadcast.
BUCKET_BYTES, BROADCAST_BYTES = 4096, 64 << 20
CHECK_SEED = H.seed_of(H.CHECK)


def hashes_for(d_hat: float) -> int:
    """Three hash functions above 200 expected differences, four up to that."""
    return 3 if d_hat > 200 else 4


def cells_for(d_hat: float, k: int) -> int:
    """Two cells a difference, a whole number in each stripe."""
    return max(1, ceil(2 * d_hat / k)) * k


def check_hash(sig: str = "sig") -> Column:
    return F.pmod(F.xxhash64(F.col(sig), F.lit(CHECK_SEED)), F.lit(1 << 32))


def cell_ids(cells: int, k: int, sig: str = "sig", family: str = "fast") -> Column:
    stripe = cells // k
    return F.array(*[H.bucket(sig, H.seed_of(H.CELL, i), stripe, family) + i * stripe for i in range(k)])


def cell_table(df: DataFrame, cells: int, k: int, family: str = "fast") -> DataFrame:
    """(inst, cell, cnt, id_xor, hash_xor)."""
    rows = with_inst(df).withColumn("_h", check_hash()).select("inst", "sig", "_h", F.explode(cell_ids(cells, k, family=family)).alias("cell"))
    return rows.groupBy("inst", "cell").agg(F.count(F.lit(1)).alias("cnt"), F.bit_xor("sig").alias("id_xor"), F.bit_xor("_h").alias("hash_xor"))


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """Cell by cell, a less b; empty cells are left out."""
    zero = F.lit(0).cast("long")
    both = a.toDF("inst", "cell", "_c", "_i", "_h").join(b.toDF("inst", "cell", "_d", "_j", "_g"), ["inst", "cell"], "full")
    out = both.select(
        "inst", "cell", (F.coalesce("_c", zero) - F.coalesce("_d", zero)).alias("cnt"),
        F.coalesce("_i", zero).bitwiseXOR(F.coalesce("_j", zero)).alias("id_xor"), F.coalesce("_h", zero).bitwiseXOR(F.coalesce("_g", zero)).alias("hash_xor"),
    )
    return out.where("cnt <> 0 or id_xor <> 0 or hash_xor <> 0")


def _spark_xxhash(sig: int, seed: int) -> int:
    """xxhash64(sig, seed) as the engine computes it over a BIGINT and an INT or BIGINT literal."""
    h = xxhash.xxh64_intdigest(sig.to_bytes(8, "little", signed=True), 42)
    wide = 4 if seed < 1 << 31 else 8
    return xxhash.xxh64_intdigest(seed.to_bytes(wide, "little", signed=True), h)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _check(sig: int) -> int:
    return _signed(_spark_xxhash(sig, CHECK_SEED)) % (1 << 32)


def _cells_of(sig: int, cells: int, k: int) -> list[int]:
    stripe = cells // k
    return [_signed(_spark_xxhash(sig, H.seed_of(H.CELL, i))) % stripe + i * stripe for i in range(k)]


def peel_grouped(diff: DataFrame, cells: int, k: int) -> DataFrame:
    """(inst, sig, side, complete): each instance peeled by one task; a row with a null sig stands for an instance without differences found.

    For many small tables. A single table of many cells goes through ``peel_rounds``.
    """

    def run(t: pd.DataFrame) -> pd.DataFrame:
        inst = int(t["inst"].iloc[0])
        table = {c: [n, i, h] for c, n, i, h in zip(t["cell"].tolist(), t["cnt"].tolist(), t["id_xor"].tolist(), t["hash_xor"].tolist(), strict=True)}
        todo, found = list(table), []
        while todo:
            c = todo.pop()
            n, sig, h = table.get(c, (0, 0, 0))
            if n not in (1, -1) or _check(sig) != h or c not in _cells_of(sig, cells, k):
                continue
            found.append((sig, "A_only" if n == 1 else "B_only"))
            for o in _cells_of(sig, cells, k):
                x = table.setdefault(o, [0, 0, 0])
                x[0] -= n
                x[1] ^= sig
                x[2] ^= h
                todo.append(o)
        done = not any(any(x) for x in table.values())
        return pd.DataFrame([(inst, s, side, done) for s, side in found] or [(inst, None, None, done)], columns=["inst", "sig", "side", "complete"]).astype({"sig": "Int64"})

    return diff.groupBy("inst").applyInPandas(run, "inst long, sig long, side string, complete boolean")


def peel_rounds(diff: DataFrame, cells: int, k: int, most: int = 40) -> tuple[DataFrame, DataFrame]:
    """(found (inst, sig, side), cells left): every pass takes out all differences that lie bare, in one job."""
    left, found = written(diff, "cells"), None
    for _ in range(most):
        bare = left.where("abs(cnt) = 1").where(check_hash("id_xor") == F.col("hash_xor"))
        new = written(bare.select("inst", F.col("id_xor").alias("sig"), F.col("cnt").alias("sign"), F.col("hash_xor").alias("_h")).distinct(), "bare")
        if new.isEmpty():
            break
        found = new.select("inst", "sig", "sign") if found is None else found.union(new.select("inst", "sig", "sign"))
        out = new.select("inst", "sig", "sign", "_h", F.explode(cell_ids(cells, k)).alias("cell"))
        moved = out.select("inst", "cell", (-F.col("sign")).alias("cnt"), F.col("sig").alias("id_xor"), F.col("_h").alias("hash_xor"))
        left = left.union(moved).groupBy("inst", "cell").agg(F.sum("cnt").alias("cnt"), F.bit_xor("id_xor").alias("id_xor"), F.bit_xor("hash_xor").alias("hash_xor"))
        left = written(left.where("cnt <> 0 or id_xor <> 0 or hash_xor <> 0"), "cells")
    if found is None:
        found = left.sparkSession.createDataFrame([], "inst long, sig long, sign long")
    side = F.when(F.col("sign") > 0, "A_only").otherwise("B_only")
    return found.select("inst", "sig", side.alias("side")), left


def cell_digest_checked(a: DataFrame, b: DataFrame, d_hat: float, grouped: bool = False, tables: Sequence[DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """((inst, sig, side), (inst) of the instances that are not peeled to the end) of a table of twice ``d_hat`` cells; ``tables``: both hosts', where they are at hand."""
    k = hashes_for(d_hat)
    cells = cells_for(d_hat, k)
    diff = subtract(*(tables or (cell_table(a, cells, k), cell_table(b, cells, k))))
    if grouped:
        got = written(peel_grouped(diff, cells, k), "peeled")
        return got.where("sig is not null").select("inst", "sig", "side"), got.where("not complete").select("inst").distinct()
    found, left = peel_rounds(diff, cells, k)
    return found, left.select("inst").distinct()


def cell_digest(a: DataFrame, b: DataFrame, d_hat: float, grouped: bool = False, complete: bool = False, doublings: int = 6, tables: Sequence[DataFrame] | None = None) -> DataFrame:
    """(inst, sig, side) of what a table of twice ``d_hat`` cells gives back; it is partial where peeling stalls (see ``cell_digest_checked``).

    With ``complete``, instances that stall are done again with twice the cells, and after ``doublings`` of that by full exchange.
    """
    from setdiff.operators.relational import symmetric_difference

    a, b = with_inst(a), with_inst(b)
    found, stalled = cell_digest_checked(a, b, d_hat, grouped, tables)
    if not complete:
        return found
    out = None
    for k in range(doublings + 1):
        stalled = written(stalled, "stalled")
        sound = found.join(F.broadcast(stalled), "inst", "left_anti").select("inst", "sig", "side")
        out = sound if out is None else out.union(sound)
        if stalled.isEmpty():
            return out
        a, b = (x.join(F.broadcast(stalled), "inst", "left_semi") for x in (a, b))
        d_hat *= 2
        if k < doublings:
            found, stalled = cell_digest_checked(a, b, d_hat, grouped)
    return out.union(symmetric_difference(a, b, ["inst", "sig"]).select("inst", "sig", "side"))


# The filter: bits are classes of k hashes; a signature passes if all its bits are set.


def filter_shape(size: int, rate: float) -> tuple[int, int]:
    """(bits, hash functions) of a filter of ``size`` elements with a false-positive rate."""
    bits = max(64, ceil(size * log(1 / rate) / log(2) ** 2))
    return bits, max(1, round(log2(1 / rate)))


def filter_positions(bits: int, k: int, family: str = "fast") -> Column:
    return F.array(*[H.bucket("sig", H.seed_of(H.FILTER, i), bits, family) for i in range(k)])


def filter_rows(df: DataFrame, bits: int, k: int, family: str = "fast") -> DataFrame:
    """(inst, pos): the bits that are set."""
    return with_inst(df).select("inst", F.explode(filter_positions(bits, k, family)).alias("pos")).distinct()


def filter_message(df: DataFrame, bits: int, k: int) -> DataFrame:
    """(inst, bucket, bits BINARY): the filter as it would be sent."""
    rows = filter_rows(df, bits, k)
    return rows.groupBy("inst", F.bitmap_bucket_number(F.col("pos") + 1).alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("pos") + 1)).alias("bits"))


def passes(df: DataFrame, message: DataFrame, bits: int, k: int, family: str = "fast") -> DataFrame:
    """Rows of ``df`` (inst, sig) whose bits are all set in ``message`` (see ``filter_message``).

    One join a hash function on the bucket, each dropping the rows whose bit is not set: rows are neither multiplied nor grouped. A message of up to
    BROADCAST_BYTES is broadcast, so ``df`` stays where it is; a larger one is joined by shuffle.
    """
    message = written(message, "filter")
    if message.count() * BUCKET_BYTES <= BROADCAST_BYTES:
        message = F.broadcast(message)
    rows = with_inst(df).select("inst", "sig")
    for i in range(k):
        at = H.bucket("sig", H.seed_of(H.FILTER, i), bits, family) + 1
        keyed = rows.withColumn("bucket", F.bitmap_bucket_number(at)).withColumn("_p", F.bitmap_bit_position(at))
        byte = F.conv(F.hex(F.substring("bits", (F.col("_p") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
        rows = keyed.join(message, ["inst", "bucket"]).where(F.getbit(byte, (F.col("_p") % 8).cast("int")) == 1).select("inst", "sig")
    return rows


def best_rate(size_b: int, d: float, cell_bits: float = 192.0) -> float:
    """Rate that makes filter bits and cells for the false positives cheapest; 1 or more means no filter."""
    return size_b / (log(2) ** 2 * cell_bits * max(d, 1e-9))


def filter_breakeven(size_b: int, cell_bits: float = 192.0) -> float:
    """Differences from which a filter pays."""
    return size_b / (log(2) ** 2 * cell_bits)


def passing(rate: float, d: float) -> float:
    """Elements to lay the cell table out for, once the filter has been by: its false positives with a margin of three deviations."""
    return rate * d + 3 * sqrt(rate * d) + 8


def filter_cells(a: DataFrame, b: DataFrame, d_hat: float, size_b: int, grouped: bool = False, complete: bool = False, message: DataFrame | None = None, tables: Sequence[DataFrame] | None = None) -> tuple[DataFrame, dict]:
    """(inst, sig, side), and what was sent: B's filter, if it pays, rids A of most of what B lacks; a cell table settles the rest.

    ``complete`` is that of ``cell_digest``; without it the result is partial where peeling stalls. ``message`` and ``tables``: the filter and, where
    none pays, both hosts' cells, if they are at hand.
    """
    a, b = with_inst(a), with_inst(b)
    rate = best_rate(size_b, d_hat)
    if rate >= 1:
        k = hashes_for(d_hat)
        cells = cells_for(d_hat, k)
        return cell_digest(a, b, d_hat, grouped, complete, tables=tables), {"filter_bits": 0, "cells": cells}
    bits, fk = filter_shape(size_b, rate)
    kept = passes(a, filter_message(b, bits, fk) if message is None else message, bits, fk)
    kept = written(kept, "passed")
    gone = a.join(kept, ["inst", "sig"], "left_anti").withColumn("side", F.lit("A_only"))
    rest = passing(rate, d_hat)
    k = hashes_for(rest)
    return gone.union(cell_digest(kept, b, rest, grouped, complete)), {"filter_bits": bits, "cells": cells_for(rest, k)}
