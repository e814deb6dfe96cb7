"""Checksums: additive, hashed additive, XOR of hashes, and a hash tree over a whole set."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setdiff.plans.params import Params

#: Signatures of a leaf of the hash tree, children of a node, levels above the leaves.
LEAF, FANOUT, LEVELS = 256, 64, 6
KINDS = ("sum", "hashed_sum", "mset_xor")


def value(p: Params) -> Column:
    """What an element adds to the checksum."""
    if p.checksum == "sum":
        return F.col("sig")
    h = F.xxhash64("sig", F.lit(97))
    return F.pmod(h, F.lit(1 << 32)) if p.checksum == "hashed_sum" and p.w == 32 else h


def combine(p: Params, v: Column, summed: bool = False) -> Column:
    """Aggregate of element values (of sums of them), null-free; sums over 32 bits are decimals, as BIGINT could overflow."""
    if p.checksum == "mset_xor":
        return F.coalesce(F.bit_xor(v), F.lit(0).cast("long"))
    v = v if p.w == 32 or summed else v.cast("decimal(20,0)")
    kind = "long" if p.w == 32 else "decimal(38,0)"
    return F.coalesce(F.sum(v).cast(kind), F.lit(0).cast(kind))


def agrees(p: Params, a: Column, adjust: Column, b: Column) -> Column:
    """Whether checksum a, adjusted for the differences found, is checksum b."""
    if p.checksum == "mset_xor":
        return a.bitwiseXOR(F.coalesce(adjust, F.lit(0))).bitwiseXOR(b) == 0
    kind = "long" if p.w == 32 else "decimal(38,0)"
    whole = a.cast(kind) + F.coalesce(adjust, F.lit(0)).cast(kind) - b.cast(kind)
    return whole % F.lit(str(1 << min(p.w, 64))).cast(kind if p.w == 32 else "decimal(38,0)") == 0


def checksum(df: DataFrame, keys: list[str], w: int = 32) -> DataFrame:
    """(keys, chk): sum of signatures modulo 2**w."""
    return df.groupBy(*keys).agg((F.sum(F.col("sig").cast("decimal(20,0)")) % F.lit(str(1 << w)).cast("decimal(38,0)")).alias("chk"))


def multiset_hash(df: DataFrame) -> DataFrame:
    """One row (lane0..lane3, n): XOR of the sha-256 of every signature, and the count."""
    h = F.sha2(F.col("sig").cast("string"), 256)
    lanes = [F.bit_xor(F.conv(F.substring(h, 16 * i + 1, 15), 16, 10).cast("long")).alias(f"lane{i}") for i in range(4)]
    return df.agg(*lanes, F.count(F.lit(1)).alias("n"))


def leaves_for(df: DataFrame) -> int:
    """Leaves that hold about LEAF signatures each, however many there are."""
    return max(1, -(-df.count() // LEAF))


def merkle_leaves(df: DataFrame, leaves: int | None = None) -> DataFrame:
    """(leaf, hash): md5 of the ordered signatures with each remainder; without ``leaves`` as many as the count asks for.

    Remainders of signatures that were not mixed may be uneven; hash them first.
    """
    leaves = leaves or leaves_for(df)
    text = F.array_join(F.transform(F.array_sort(F.collect_list("sig")), lambda s: s.cast("string")), ",")
    return df.groupBy((F.col("sig") % leaves).alias("leaf")).agg(F.md5(text).alias("hash"))


def merkle_root(df: DataFrame, leaves: int | None = None, fanout: int = FANOUT, levels: int = LEVELS) -> DataFrame:
    """(hash): root of the tree over ``merkle_leaves``, ``levels`` levels above the leaves whatever their number (at most fanout**levels).

    Both hosts have to use the same ``leaves``; by default each takes its own count's, so sets of sizes far apart differ at once.
    """
    leaves = leaves or leaves_for(df)
    if leaves > fanout**levels:
        raise ValueError(f"{leaves} leaves need more than {levels} levels of {fanout}")
    level = merkle_leaves(df, leaves)
    for _ in range(levels):
        joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("leaf", "hash"))), lambda x: x["hash"]), "")
        level = level.groupBy(F.floor(F.col("leaf") / fanout).alias("leaf")).agg(F.md5(joined).alias("hash"))
    return level.select("hash")
