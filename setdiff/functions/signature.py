"""Signatures: fixed-length ids of rows, never zero, one row each."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Odd multiplier of the 32-bit bijection (a fixed value).
MIX = 2_654_435_761


def identity(key: str) -> Column:
    """key + 1: keys of the given tables start at zero, and zero can't be a signature."""
    return (F.col(key).cast("long") + 1).cast("long")


def mix32(key: str) -> Column:
    """A bijection of 1..2**32-1 that spreads consecutive keys."""
    return F.expr(f"((cast({key} as bigint) + 1) * {MIX}L) % 4294967296L")


def mix32_text(key: str) -> str:
    return f"((({key}) + 1) * {MIX}) % 4294967296"


def _text(cols: list[str]) -> Column:
    return F.concat_ws("|", *[F.coalesce(F.expr(c).cast("string"), F.lit("\\N")) for c in cols])


def portable_row_hash(cols: list[str]) -> Column:
    """32 bits of the md5 of a row's text; nulls have a text of their own; zero becomes 2**32 - 1."""
    h = F.conv(F.substring(F.md5(_text(cols)), 1, 8), 16, 10).cast("long")
    return F.when(h == 0, F.lit(4_294_967_295)).otherwise(h)


def portable_row_text(cols: list[str]) -> str:
    """The same in DuckDB's SQL."""
    parts = ", ".join(f"coalesce(cast({c} as varchar), '\\N')" for c in cols)
    h = f"(('0x' || md5(concat_ws('|', {parts}))[1:8])::bigint)"
    return f"(case when {h} = 0 then 4294967295 else {h} end)"


def row_hash64(cols: list[str]) -> Column:
    """64 bits of any columns, nested ones too; zero becomes 1."""
    h = F.xxhash64(*[F.col(c) for c in cols])
    return F.when(h == 0, F.lit(1).cast("long")).otherwise(h)


def row_hash256(cols: list[str]) -> Column:
    """Four lanes of 64 bits of the sha-256 of a row's text."""
    h = F.sha2(_text(cols), 256)
    lanes = [F.conv(F.substring(h, 16 * i + 1, 16), 16, -10).cast("long") for i in range(4)]
    return F.struct(*[x.alias(f"l{i}") for i, x in enumerate(lanes)])


def as_set(df: DataFrame, sig: Column, unique: bool = False) -> DataFrame:
    """(sig) of ``df``: nulls dropped, and repeats too unless the caller knows there are none."""
    out = df.select(sig.alias("sig")).where("sig is not null and sig <> 0")
    return out if unique else out.distinct()


def dictionary(df: DataFrame, sig: Column, keys: list[str]) -> DataFrame:
    """(sig, keys): turns signatures back into rows."""
    return df.select(sig.alias("sig"), *keys).dropDuplicates(["sig"])


def rows_of(df: DataFrame, sig: Column, found: DataFrame) -> DataFrame:
    """The rows of ``df`` whose signature is in ``found`` (sig)."""
    return df.withColumn("_sig", sig).join(found.select(F.col("sig").alias("_sig")), "_sig", "left_semi").drop("_sig")
