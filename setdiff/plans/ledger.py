"""What crosses between the hosts, message by message.

``model_bits`` counts the four parts the paper counts (codewords, positions, XOR sums, checksums); ``wire_bytes`` is what our own encoding
would send, with failure flags and, from the second round on, group ids.
"""

from __future__ import annotations

from functools import reduce
from math import ceil, log2

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setdiff.plans.params import Params

COLUMNS = ["scheme", "inst", "round", "direction", "kind", "items", "model_bits", "wire_bytes"]


def message(rows: DataFrame, scheme: str, direction: str, kind: str, items, model_bits_each: int, wire_bits_each: int | None = None) -> DataFrame:
    """One ledger row for each row of ``rows`` (inst, round)."""
    items = F.coalesce(items, F.lit(0)).cast("long")
    wire = model_bits_each if wire_bits_each is None else wire_bits_each
    return rows.select(
        F.lit(scheme).alias("scheme"), "inst", F.col("round").cast("int").alias("round"), F.lit(direction).alias("direction"), F.lit(kind).alias("kind"),
        items.alias("items"), (items * model_bits_each).cast("long").alias("model_bits"), F.ceil(items * wire / 8).cast("long").alias("wire_bytes"),
    )


def bin_parity_ledger(a: DataFrame, b: DataFrame, decoded: list[DataFrame], p: Params) -> DataFrame:
    """Messages of a bin-parity run. In round one all g groups are open, empty ones too."""
    parts = []
    insts = a.union(b).select("inst").distinct()
    for k, one in enumerate(decoded, 1):
        of = one.groupBy("inst").agg(F.count(F.lit(1)).alias("open"), F.sum(F.when(F.col("ok"), F.size("bins")).otherwise(0)).alias("bins"))
        if k == 1:
            of = insts.join(of, "inst", "left").withColumn("open", F.lit(p.g))
        of = of.withColumn("round", F.lit(k))
        m, ident = p.m, 0 if k == 1 else max(1, ceil(log2(max(p.g, 2))))
        n_open, n_bins = F.col("open"), F.col("bins")
        parts += [
            message(of, "bin_parity", "A>B", "codeword", n_open, p.t * m), message(of, "bin_parity", "B>A", "positions", n_bins, m),
            message(of, "bin_parity", "B>A", "xor_sums", n_bins, p.w), message(of, "bin_parity", "B>A", "checksum", n_open, p.w),
            message(of, "bin_parity", "B>A", "fail_flag", n_open, 0, 1), message(of, "bin_parity", "A>B", "group_id", n_open, 0, ident),
        ]
    return reduce(DataFrame.union, parts)


def totals(ledger: DataFrame, w: int, d: DataFrame) -> DataFrame:
    """(scheme, inst, model_bits, wire_bytes, ratio) against the minimum of d*w bits; ``d``: (inst, d)."""
    out = ledger.groupBy("scheme", "inst").agg(F.sum("model_bits").alias("model_bits"), F.sum("wire_bytes").alias("wire_bytes"))
    return out.join(d, "inst").withColumn("ratio", F.col("model_bits") / (F.col("d") * w))


def spark_costs(spark, run) -> dict[str, int]:
    """Jobs, stages and tasks that a call causes."""
    import uuid

    group = uuid.uuid4().hex
    spark.sparkContext.setJobGroup(group, "measured")
    try:
        run()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    tracker = spark.sparkContext.statusTracker()
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    stages = [tracker.getStageInfo(s) for j in jobs if j for s in j.stageIds]
    return {"jobs": len(jobs), "stages": len(stages), "tasks": sum(s.numTasks for s in stages if s)}


def field_operations(groups: int, t: int, n: int) -> int:
    """Products in the field that decoding takes: the recurrence of 2t steps over t coefficients, and the locator at n points."""
    return groups * (2 * t * t + n * t)


def min_bits(d: int, w: int) -> int:
    """The theoretical minimum."""
    return d * w
