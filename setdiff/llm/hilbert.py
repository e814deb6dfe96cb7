"""Sharding along a Hilbert curve over several metadata dimensions.

Each dimension is quantised to ``2**bits`` levels, the cell of a row gets its
place on the curve through the levels, rows are ranked by that place and the
ranking is cut into runs. Rows of one run are close in every dimension, so a
reader that filters on any of them can skip most files by their min/max values.

Only DataFrame functions are used. The curve index is worked out once per occupied
cell (at most ``2**(bits*dims)`` rows, held to 16,384), never per row. Ranks come from two small
histograms and a ``row_number`` inside slices whose size is held to about
``1/4096`` of the table whatever the skew: a cell that holds a third of all rows is cut
into hash slices. So no task ranks an unbounded group, and no row is moved twice.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import keep, stowed

#: Slices that a table is cut into for ranking; bounds the offsets that are broadcast.
SLICES = 4096
#: Most cells of the grid, so that the cell table can be broadcast.
MOST_CELLS = 1 << 14


def quantise_number(df: DataFrame, column: str, bits: int) -> Column:
    """Level 0..2**bits-1 by approximate quantiles over all rows; null and no rows give 0."""
    parts = 1 << bits
    cuts = df.agg(F.percentile_approx(column, [i / parts for i in range(1, parts)], 10_000).alias("q")).first()["q"]
    level = F.lit(0)
    for cut in sorted(set(cuts or [])):
        level = level + F.when(F.col(column) > F.lit(cut), 1).otherwise(0)
    return level


def quantise_text(column: str, bits: int) -> Column:
    """Level of a categorical value: equal values get equal levels; null gets level 0."""
    return F.coalesce(F.pmod(F.xxhash64(F.col(column)), F.lit(1 << bits)).cast("int"), F.lit(0))


def curve_index(levels: list[str], bits: int) -> Column:
    """Place on the Hilbert curve of a cell given by its level columns.

    Works on the array of levels with higher-order functions: every (plane, axis) pair, from
    the highest plane down, either reflects the first axis or exchanges low bits with it;
    a Gray code of the result, read plane by plane, is the index.
    """
    n, start = len(levels), F.array(*[F.col(c).cast("int") for c in levels])
    planes = [(1 << b, a) for b in range(bits - 1, 0, -1) for a in range(n)]

    def turn(x: Column, step: Column) -> Column:
        q, low = step["q"], step["q"] - 1
        own, first = F.get(x, step["a"]), F.get(x, F.lit(0))
        swap = first.bitwiseXOR(own).bitwiseAND(low)
        flip = own.bitwiseAND(q) != 0
        return F.transform(
            x,
            lambda v, i: F.when(flip, F.when(i == 0, v.bitwiseXOR(low)).otherwise(v)).otherwise(
                F.when(i == step["a"], v.bitwiseXOR(swap)).when(i == 0, v.bitwiseXOR(swap)).otherwise(v)
            ),
        )

    steps = F.array(*[F.struct(F.lit(q).alias("q"), F.lit(a).alias("a")) for q, a in planes])
    turned = F.aggregate(steps, start, turn) if planes else start
    gray = F.aggregate(
        turned,
        F.array().cast("array<int>"),
        lambda got, v: F.concat(got, F.array(v.bitwiseXOR(F.coalesce(F.get(got, F.size(got) - 1), F.lit(0))))),
    )
    spill = F.aggregate(
        F.sequence(F.lit(1), F.lit(bits - 1)) if bits > 1 else F.array().cast("array<int>"),
        F.lit(0),
        lambda t, b: F.when(
            F.get(gray, F.lit(n - 1)).bitwiseAND(F.pow(F.lit(2), b).cast("int")) != 0, t.bitwiseXOR(F.pow(F.lit(2), b).cast("int") - 1)
        ).otherwise(t),
    )
    fixed = F.transform(gray, lambda v: v.bitwiseXOR(spill))
    index = F.lit(0).cast("long")
    for b in range(bits - 1, -1, -1):
        for a in range(n):
            index = index * 2 + F.shiftright(F.get(fixed, F.lit(a)), b).bitwiseAND(F.lit(1))
    return index


def hilbert_order(df: DataFrame, levels: list[str], bits: int, tie: list[str]) -> DataFrame:
    """Adds ``curve`` (long) and ``rank`` (long, 0.. without gaps) to ``df``.

    ``df`` must be stable when read again (a written table). ``tie`` columns decide the slices and the order
    inside a cell. An empty table gives an empty result.
    """
    if bits * len(levels) > MOST_CELLS.bit_length() - 1:
        raise ValueError("bits times dimensions is held to 14, so that the cell table stays small")
    cell = F.lit(0)
    for c in levels:
        cell = cell * (1 << bits) + F.col(c)
    rows = df.withColumn("_cell", cell.cast("int"))
    per_slice = F.greatest(F.lit(1), F.ceil(F.sum("_n").over(Window.partitionBy()) / SLICES))
    parts = {c: F.shiftright(F.col("_cell"), bits * (len(levels) - 1 - i)).bitwiseAND(F.lit((1 << bits) - 1)) for i, c in enumerate(levels)}
    cells = (
        rows.groupBy("_cell").agg(F.count(F.lit(1)).alias("_n"))
        .withColumn("_cuts", F.ceil(F.col("_n") / per_slice))
        .select("_cell", "_cuts", *[e.alias(f"_l{i}") for i, e in enumerate(parts.values())])
        .withColumn("curve", curve_index([f"_l{i}" for i in range(len(levels))], bits))
        .select("_cell", "_cuts", "curve")
    )
    sliced = rows.join(F.broadcast(cells), "_cell").withColumn(
        "_slice", F.floor(F.pmod(F.xxhash64(*tie), F.lit(1 << 20)) * F.col("_cuts") / F.lit(1 << 20))
    )
    order = Window.orderBy("curve", "_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = (
        sliced.groupBy("curve", "_slice").agg(F.count(F.lit(1)).alias("_n"))
        .withColumn("_start", F.coalesce(F.sum("_n").over(order), F.lit(0)))
        .select("curve", "_slice", "_start")
    )
    inside = Window.partitionBy("curve", "_slice").orderBy(*tie)
    return (
        sliced.withColumn("_row", F.row_number().over(inside) - 1)
        .join(F.broadcast(starts), ["curve", "_slice"])
        .withColumn("rank", F.col("_start") + F.col("_row"))
        .drop("_cell", "_cuts", "_slice", "_row", "_start")
    )


def cut_runs(ranked: DataFrame, n_rows: int, shards: int) -> DataFrame:
    """Cuts ranks into ``shards`` runs whose row counts differ by one at most; adds ``shard`` and ``slot``."""
    n = max(n_rows, 1)
    return ranked.withColumn("shard", F.expr(f"cast(rank * {shards} div {n} as int)")).withColumn(
        "slot", F.expr(f"rank - (shard * {n}L + {shards - 1}) div {shards}")
    )


def hilbert_shards(docs: DataFrame, shards: int = 16, bits: int = 3, row: str | None = None) -> DataFrame:
    """Shards documents by language, source, size and id order.

    Per row: doc_id, lang, source, size (UTF-8 bytes plus one; null text: 1), text_crc32, curve, rank, shard, slot.
    Law ``rows``: shard counts differ by one at most. Null ids, null metadata, repeated rows and
    empty texts are ordinary rows; other columns are ignored. ``row`` names a column of unique
    longs (of a written table) that comes out as ``_row_id``, to join the rows by.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    narrow = keep(
        docs.select(
            "doc_id", "lang", "source",
            (F.octet_length(text) + 1).cast("long").alias("size"),
            F.crc32(text).alias("text_crc32"),
            (F.col(row) if row else F.monotonically_increasing_id()).alias("_row_id"),
        ),
        "hilbert",
    )
    n_rows = narrow.count()
    leveled = (
        narrow.withColumn("_lang", quantise_text("lang", bits))
        .withColumn("_source", quantise_text("source", bits))
        .withColumn("_size", quantise_number(narrow, "size", bits))
        .withColumn("_age", quantise_number(narrow, "doc_id", bits))
    )
    ranked = hilbert_order(leveled, ["_lang", "_source", "_size", "_age"], bits, ["doc_id", "_row_id"])
    return cut_runs(ranked, n_rows, shards).drop("_lang", "_source", "_size", "_age", *[] if row else ["_row_id"])


def shard_extents(sharded: DataFrame) -> DataFrame:
    """Smallest and largest value of each dimension per shard: what file pruning works with."""
    dims = ("lang", "source", "size", "doc_id")
    return sharded.groupBy("shard").agg(
        F.count(F.lit(1)).alias("n_rows"), F.sum("size").alias("bytes"),
        *[f(c).alias(f"{n}_{c}") for c in dims for n, f in (("min", F.min), ("max", F.max))],
    )


def write_shards(docs: DataFrame, path: str, shards: int = 16, bits: int = 3, files_per_shard: int = 4) -> DataFrame:
    """Writes every row of ``docs`` once, as one folder per shard of about ``files_per_shard`` files cut from the curve; returns the shards as ``hilbert_shards`` does.

    Rows are joined to their places by a row number, so null and repeated ids are ordinary rows. The folders' column is
    ``shard``, or ``shard_``, ``shard__`` and so on where ``docs`` has such a column. An empty table writes no folder.
    """
    name = "shard"
    while name in docs.columns:
        name += "_"
    numbered = keep(stowed(docs).withColumn("_number", F.monotonically_increasing_id()), "numbered")
    meta = [F.col(f"_row.{c}").alias(c) for c in ("doc_id", "text", "lang", "source")]
    sharded = keep(hilbert_shards(numbered.select(*meta, "_number"), shards, bits, "_number"), "shards")
    placed = numbered.join(sharded.select(F.col("_row_id").alias("_number"), "rank", F.col("shard").alias("_shard")), "_number")
    (placed.repartitionByRange(shards * files_per_shard, "rank").sortWithinPartitions("rank")
     .select("_row.*", F.col("_shard").alias(name)).write.partitionBy(name).parquet(path))
    return sharded.drop("_row_id")
