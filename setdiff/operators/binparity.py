"""The sketches of the bin-parity scheme and what is read off them.

Rows are (inst, sig): ``inst`` numbers independent set pairs, so that many of them run in one job. A group is (inst, root, path): ``root`` is the
first-level hash class, ``path`` the split digits of a group that failed before.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setdiff.functions import hashing as H
from setdiff.functions.gf import packed_table
from setdiff.plans.params import Params

NODE = ["inst", "root", "path"]
#: Per-bin tables up to this many bins are literals of the plan; larger ones (their size is n, fixed by the plan) are joined.
LITERAL_BINS = 511
#: Open groups or flagged bins up to this many are broadcast; more are joined by shuffle.
BROADCAST_ROWS = 1_000_000


#: Lanes of signatures over 64 bits; ``sig`` is then a 64-bit hash of them, for hashing and checksums.
WIDE = ("l0", "l1", "l2", "l3")


def wide_columns(df: DataFrame) -> list[str]:
    return [c for c in WIDE if c in df.columns]


def wide_set(df: DataFrame, lanes: Column) -> DataFrame:
    """(sig, l0..l3) of distinct 256-bit signatures, from a struct of lanes."""
    rows = df.select(lanes.alias("_l")).where("_l is not null").select("_l.*").distinct()
    return rows.select(F.xxhash64(*WIDE).alias("sig"), *WIDE)


def with_inst(df: DataFrame) -> DataFrame:
    inst = F.col("inst") if "inst" in df.columns else F.lit(0)
    return df.select(inst.cast("long").alias("inst"), "sig", *wide_columns(df))


def with_bin(df: DataFrame, n: int, seed: int, family: str = "fast") -> DataFrame:
    """Adds ``bin``, the class 0..n-1 of the second-level hash."""
    return df.withColumn("bin", H.bucket("sig", seed, n, family))


def bin_of(p: Params, round_: int) -> Column:
    return H.bucket("sig", H.seed_of(H.BIN, round_, p.seed), p.n, p.family)


def root_of(p: Params) -> Column:
    return H.bucket("sig", H.seed_of(H.GROUP, 0, p.seed), p.g, p.family)


def split_path(p: Params, levels: int) -> Column:
    """The split digits of a signature down to ``levels``."""
    digits = [H.bucket("sig", H.seed_of(H.SPLIT, k, p.seed), p.ways, p.family).cast("string") for k in range(levels)]
    return F.concat(*digits) if digits else F.lit("")


def with_node(df: DataFrame, p: Params, open_: DataFrame | None, levels: int, n_open: int = 0) -> DataFrame:
    """Adds root and path; with ``open_`` only rows of those groups stay."""
    df = df.withColumn("root", root_of(p))
    if open_ is None:
        return df.withColumn("path", F.lit(""))
    nodes = open_.select(*NODE)
    if n_open <= BROADCAST_ROWS:
        df, nodes = alike(df, nodes, ["inst", "root"]), F.broadcast(nodes)
    return df.withColumn("_split", split_path(p, levels)).join(nodes, ["inst", "root"]).where(F.col("_split").startswith(F.col("path"))).drop("_split")


def alike(df: DataFrame, some: DataFrame, cols: list[str]) -> DataFrame:
    """Rows of ``df`` whose ``cols`` have the hash of those of a row of ``some``, which is small: one long as key leaves few rows to an exact join."""
    h = F.xxhash64(*cols)
    return df.join(F.broadcast(some.select(h.alias("_key"))), h == F.col("_key"), "left_semi")


def among(df: DataFrame, some: DataFrame, cols: list[str], n: int) -> DataFrame:
    """Rows of ``df`` whose ``cols`` are those of one of the ``n`` rows of ``some``."""
    some = some.select(*cols)
    if n > BROADCAST_ROWS:
        return df.join(some.hint("shuffle_hash"), cols, "left_semi")
    return alike(df, some, cols).join(F.broadcast(some), cols, "left_semi")


def parity_bins(df: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, bin) of bins with an odd number of elements."""
    return df.groupBy(*keys, "bin").agg(F.count(F.lit(1)).alias("_n")).where("_n % 2 = 1").select(*keys, "bin")


def parity_bitmap(df: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, bits): the parity bitmap as BINARY, bit i for bin i."""
    odd = parity_bins(df, keys)
    return odd.groupBy(*keys).agg(F.bitmap_construct_agg(F.bitmap_bit_position("bin")).alias("bits"))


def lane_columns(df: DataFrame, m: int, t: int) -> tuple[DataFrame, list[Column]]:
    """``df`` (bin) and expressions of the packed syndrome lanes of a row's bin."""
    table = packed_table(m, t)
    if table.shape[1] <= LITERAL_BINS:
        return df, [F.element_at(F.lit([int(x) for x in lane]), F.col("bin").cast("int") + 1) for lane in table]
    spark = df.sparkSession
    names = [f"_lane{i}" for i in range(len(table))]
    rows = spark.createDataFrame([(b, *(int(x) for x in table[:, b])) for b in range(table.shape[1])], "bin long, " + ", ".join(f"{c} long" for c in names))
    return df.join(F.broadcast(rows), "bin"), [F.col(c) for c in names]


def encode(df: DataFrame, keys: list[str], m: int, t: int, *more: Column) -> DataFrame:
    """(keys, cw, more): codeword lanes of each group of ``df`` (keys, bin). Even repeats of a bin cancel, so this is the code of the parity bitmap."""
    df, lanes = lane_columns(df, m, t)
    return df.groupBy(*keys).agg(F.array(*[F.bit_xor(x) for x in lanes]).alias("cw"), *more)


def xor_sums(df: DataFrame, flagged: DataFrame, keys: list[str], n_flagged: int = 0, cols: tuple[str, ...] = ("sig",)) -> DataFrame:
    """(keys, bin, cols): XOR of the signatures, or of each lane of them, in each flagged bin."""
    return among(df, flagged, [*keys, "bin"], n_flagged).groupBy(*keys, "bin").agg(*[F.bit_xor(c).alias(c) for c in cols])


def as_candidates(df: DataFrame, keys: list[str], cols: tuple[str, ...]) -> DataFrame:
    """Zero means no candidate; of a wide signature the hash is worked out from its lanes."""
    df = df.where(" or ".join(f"{c} <> 0" for c in cols))
    return df.select(*keys, "bin", *([] if "sig" in cols else [F.xxhash64(*cols).alias("sig")]), *cols)


def recover(xa: DataFrame, xb: DataFrame, keys: list[str], cols: tuple[str, ...] = ("sig",)) -> DataFrame:
    """(keys, bin, sig, lanes): XOR of both hosts' sums."""
    both = xa.toDF(*keys, "bin", *[f"_a_{c}" for c in cols]).join(xb.toDF(*keys, "bin", *[f"_b_{c}" for c in cols]), [*keys, "bin"], "full")
    zero = F.lit(0).cast("long")
    return as_candidates(both.select(*keys, "bin", *[F.coalesce(f"_a_{c}", zero).bitwiseXOR(F.coalesce(f"_b_{c}", zero)).alias(c) for c in cols]), keys, cols)


def check_candidates(found: DataFrame, p: Params, round_: int, levels: int) -> DataFrame:
    """Drops candidates that don't hash to where they were found."""
    if p.check_bin:
        found = found.where(bin_of(p, round_) == F.col("bin"))
    if p.check_group:
        found = found.where((root_of(p) == F.col("root")) & split_path(p, levels).startswith(F.col("path")))
    return found


def one_element(a: DataFrame, b: DataFrame) -> DataFrame:
    """(sig): the only difference of two sets, none if they are equal; wrong, as it has to be, if more than one differs."""
    total = lambda d, c: d.agg(F.coalesce(F.bit_xor("sig"), F.lit(0).cast("long")).alias(c))
    return total(a, "_a").crossJoin(total(b, "_b")).select(F.col("_a").bitwiseXOR(F.col("_b")).alias("sig")).where("sig <> 0")


def bitmap_exchange(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, bin): bins whose parities differ, by comparing the bitmaps outright."""
    x, y = parity_bins(a, keys).withColumn("_a", F.lit(1)), parity_bins(b, keys).withColumn("_b", F.lit(1))
    return x.join(y, [*keys, "bin"], "full").where("_a is null or _b is null").select(*keys, "bin")


def classify_bins(diff: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, bin, n, kind) of the bins that true differences fall into: ideal, even (nothing seen) or odd of three or more (a fake)."""
    n = F.count(F.lit(1))
    kind = F.when(F.col("n") == 1, "ideal").when(F.col("n") % 2 == 0, "even").otherwise("odd")
    return diff.groupBy(*keys, "bin").agg(n.alias("n")).withColumn("kind", kind)
