"""Relational helpers around the methods: set operations, as-of and interval joins, reports, readers and writers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def full_exchange(a: DataFrame, b: DataFrame) -> DataFrame:
    """(sig, side): one host sends everything; one shuffle of both sets and a count of sides per signature."""
    rows = a.select("sig", F.lit(1).alias("_a"), F.lit(0).alias("_b")).union(b.select("sig", F.lit(0), F.lit(1)))
    sides = rows.groupBy("sig").agg(F.max("_a").alias("_a"), F.max("_b").alias("_b")).where("_a <> _b")
    return sides.select("sig", F.when(F.col("_a") == 1, "A_only").otherwise("B_only").alias("side"))


def symmetric_difference(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, side) of rows of one side only; nulls compare as equal, repeats count once."""
    left, right = a.select(*keys), b.select(*keys)
    return left.subtract(right).withColumn("side", F.lit("A_only")).union(right.subtract(left).withColumn("side", F.lit("B_only")))


def exclude_exact_d(df: DataFrame, key: str, d: int) -> DataFrame:
    """``df`` without the d rows that come first by the md5 of the key: a top-d, no global sort."""
    first = df.select(F.col(key).alias("_k")).orderBy(F.md5(F.col(key).cast("string")), key).limit(d)
    return df.join(F.broadcast(first) if d <= 1_000_000 else first, F.col(key) == F.col("_k"), "left_anti")


def toggle(a: DataFrame, delta: DataFrame, key: str = "sig") -> DataFrame:
    """a with the elements of delta switched: out if they were in, in if they were out."""
    return a.join(delta, key, "left_anti").select(key).union(delta.join(a, key, "left_anti").select(key))


def semi_filter(df: DataFrame, flags: DataFrame, on: list[str], most: int = 1_000_000) -> DataFrame:
    """Rows of ``df`` with a flag; the flags are broadcast after their count is seen to be within ``most``."""
    small = flags.limit(most + 1).count() <= most
    return df.join(F.broadcast(flags) if small else flags.hint("shuffle_hash"), on, "left_semi")


def asof_latest(df: DataFrame, key: str, ts: str, cut: Column | str) -> DataFrame:
    """The last row of each key up to a time: one map-side combined maximum, no window."""
    cut = F.to_timestamp(F.lit(cut)) if isinstance(cut, str) else cut
    best = df.where(F.col(ts) <= cut).groupBy(key).agg(F.max(F.struct(F.col(ts), *[c for c in df.columns if c not in (key, ts)])).alias("_m"))
    return best.select(key, "_m.*").select(*df.columns)


def interval_match(a: DataFrame, b: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Pairs of equal key whose times are within ``seconds``: equal time buckets or neighbouring ones, then the exact test."""
    at = F.col(ts).cast("timestamp").cast("double")
    bucket = F.floor(at / seconds)
    x = a.select(F.col(key), at.alias("ts_a"), bucket.alias("_b"))
    y = b.select(F.col(key), at.alias("ts_b"), F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("_b"))
    return x.join(y, [key, "_b"]).where(F.abs(F.col("ts_a") - F.col("ts_b")) <= seconds).drop("_b")


def rollup_metrics(df: DataFrame, dims: list[str], values: list[str]) -> DataFrame:
    return df.rollup(*dims).agg(F.count(F.lit(1)).alias("n"), *[F.sum(v).alias(f"sum_{v}") for v in values], *[F.avg(v).alias(f"avg_{v}") for v in values])


def topk(df: DataFrame, k: int, *by) -> DataFrame:
    return df.orderBy(*by).limit(k)


def cumulative_share(df: DataFrame, by: list[str], order: str, value: str) -> DataFrame:
    """Running share of ``value`` within ``by``."""
    w = Window.partitionBy(*by)
    run = w.orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn("share", F.sum(value).over(run) / F.sum(value).over(w))


def pivot_report(df: DataFrame, rows: str, cols: str, value: str, wanted: list | None = None) -> DataFrame:
    g = df.groupBy(rows)
    return (g.pivot(cols, wanted) if wanted else g.pivot(cols)).agg(F.first(value))


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON, Avro-free text: whatever the session's sources read."""
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def write_sketch(df: DataFrame, path: str, params_id: str) -> None:
    """A host's sketches as a message: one folder per parameter set, rows of a group together."""
    df.withColumn("params_id", F.lit(params_id)).repartition("root").sortWithinPartitions("root").write.mode("append").partitionBy("params_id").parquet(path)


def read_sketch(spark: SparkSession, path: str, params_id: str) -> DataFrame:
    return spark.read.parquet(path).where(F.col("params_id") == params_id).drop("params_id")
