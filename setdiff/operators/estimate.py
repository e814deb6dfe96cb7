"""How many elements differ: tug-of-war sketches, and the estimators they are said to beat."""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, log2

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setdiff.functions import hashing as H
from setdiff.operators.binparity import with_inst

ELL, GAMMA = 128, 1.38
#: Sums of one aggregate; beyond about a hundred columns code generation gives up.
TOGETHER = 64


def tow_sketch(df: DataFrame, ell: int = ELL, family: str = "fast", seed: int = 0) -> DataFrame:
    """(inst, y array<long>, n): sums of ``ell`` hashed signs. ``fast`` takes 64 signs from one hash; ``portable`` is four-wise independent."""
    df = with_inst(df)
    out = None
    for at in range(0, ell, TOGETHER):
        k = min(TOGETHER, ell - at)
        if family == "fast":
            rows = df.withColumn("_h", F.xxhash64("sig", F.lit(H.seed_of(H.SIGN, at, seed))))
            cols = [F.count(F.lit(1)) - 2 * F.sum(F.shiftrightunsigned("_h", i).bitwiseAND(F.lit(1))) for i in range(k)]
        else:
            rows = df
            cols = [F.sum(F.expr(H.sign_text("sig", H.seed_of(H.SIGN, at + i, seed)))) for i in range(k)]
        part = rows.groupBy("inst").agg(F.array(*cols).alias(f"_y{at}"), *([F.count(F.lit(1)).alias("n")] if at == 0 else []))
        out = part if out is None else out.join(part, "inst")
    return out.select("inst", F.concat(*[F.col(f"_y{at}") for at in range(0, ell, TOGETHER)]).alias("y"), "n")


def tow_estimate(ya: DataFrame, yb: DataFrame, ell: int = ELL) -> DataFrame:
    """(inst, d_hat): mean squared difference of the sketches. A side without rows counts as zeros."""
    zeros = F.array_repeat(F.lit(0).cast("long"), ell)
    both = ya.select("inst", F.col("y").alias("_a")).join(yb.select("inst", F.col("y").alias("_b")), "inst", "full")
    gaps = F.zip_with(F.coalesce("_a", zeros), F.coalesce("_b", zeros), lambda a, b: (a - b).cast("double"))
    return both.select("inst", (F.aggregate(gaps, F.lit(0.0), lambda s, x: s + x * x) / ell).alias("d_hat"))


def estimate_d(a: DataFrame, b: DataFrame, ell: int = ELL, seed: int = 0) -> DataFrame:
    return tow_estimate(tow_sketch(a, ell, seed=seed), tow_sketch(b, ell, seed=seed), ell)


def tow_variance(d: int, ell: int = ELL) -> float:
    return (2 * d * d - 2 * d) / ell


def tow_bits(ell: int, size: int) -> int:
    """Bits of the sketches of a set of ``size``: each sum lies within plus and minus the size."""
    return ell * ceil(log2(2 * size + 1))


def calibrate_gamma(spark: SparkSession, ds: list[int], ells: list[int], trials: int = 20_000, conf: float = 0.99) -> DataFrame:
    """(d, ell, gamma, bias, var_ratio, covered): the least factor that covers d with the wanted confidence; simulated sketches, all trials in one job."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for i, d, ell, n in zip(part["i"], part["d"], part["ell"], part["n"], strict=True):
                rng = np.random.default_rng([int(i), int(d), int(ell)])
                y = 2.0 * rng.binomial(int(d), 0.5, (int(n), int(ell))) - d
                yield pd.DataFrame({"d": d, "ell": ell, "est": (y * y).mean(1)})

    chunk = 1000
    jobs = spark.createDataFrame([(i, d, e, chunk) for d in ds for e in ells for i in range(ceil(trials / chunk))], "i long, d long, ell long, n long")
    sims = jobs.repartition(8).mapInPandas(run, "d long, ell long, est double")
    ratio = F.col("d") / F.col("est")
    return sims.groupBy("d", "ell").agg(
        F.percentile(ratio, F.lit(conf)).alias("gamma"), (F.avg("est") / F.first("d") - 1).alias("bias"),
        (F.var_samp("est") * F.first("ell") / (2.0 * F.first("d") * F.first("d"))).alias("var_ratio"), F.avg((F.col("d") <= GAMMA * F.col("est")).cast("double")).alias("covered"),
    )


def f2_estimate(df: DataFrame, key: str, ell: int = ELL) -> DataFrame:
    """(f2): second frequency moment of a column with repeats, by the same sketch over a bag."""
    y = tow_sketch(df.select((F.col(key).cast("long") + 1).alias("sig")), ell)
    return y.select((F.aggregate("y", F.lit(0.0), lambda s, x: s + (x * x).cast("double")) / ell).alias("f2"))


def hll_estimate(a: DataFrame, b: DataFrame, lg: int = 14) -> DataFrame:
    """(d_hat): twice the union less both sizes, by distinct-count sketches."""
    x = a.agg(F.hll_sketch_agg("sig", lg).alias("x"), F.count(F.lit(1)).alias("na"))
    y = b.agg(F.hll_sketch_agg("sig", lg).alias("y"), F.count(F.lit(1)).alias("nb"))
    return x.crossJoin(y).select((2 * F.hll_sketch_estimate(F.hll_union("x", "y")) - F.col("na") - F.col("nb")).cast("double").alias("d_hat"))


def theta_estimate(a: DataFrame, b: DataFrame, lg: int = 14) -> DataFrame:
    """(d_hat): both one-sided differences of theta sketches."""
    x, y = a.agg(F.theta_sketch_agg("sig", lg).alias("x")), b.agg(F.theta_sketch_agg("sig", lg).alias("y"))
    size = lambda p, q: F.theta_sketch_estimate(F.theta_difference(p, q))
    return x.crossJoin(y).select((size("x", "y") + size("y", "x")).cast("double").alias("d_hat"))


def minhash_estimate(a: DataFrame, b: DataFrame, k: int = 64) -> DataFrame:
    """(d_hat): from the share of equal minima, an estimate of the resemblance, and the sizes."""
    mins = lambda c: F.array(*[F.min(F.xxhash64("sig", F.lit(i))) for i in range(k)]).alias(c)
    x, y = a.agg(mins("x"), F.count(F.lit(1)).alias("na")), b.agg(mins("y"), F.count(F.lit(1)).alias("nb"))
    same = F.aggregate(F.zip_with("x", "y", lambda p, q: (p == q).cast("double")), F.lit(0.0), lambda s, v: s + v) / k
    return x.crossJoin(y).select(((F.col("na") + F.col("nb")) * (1 - same) / (1 + same)).alias("d_hat"))


def strata_estimate(a: DataFrame, b: DataFrame, cells: int = 80, levels: int = 32) -> DataFrame:
    """(d_hat): small cell tables per level of trailing zero bits; the levels that peel, scaled by the first that doesn't."""
    from setdiff.operators.cells import cell_table, peel_grouped, subtract

    def leveled(df: DataFrame) -> DataFrame:
        h = F.xxhash64("sig", F.lit(H.seed_of(H.CELL, 99)))
        low = h.bitwiseAND(-h)
        return df.select(F.least(F.when(h == 0, F.lit(levels - 1)).otherwise(F.bit_count(low - 1)), F.lit(levels - 1)).cast("long").alias("inst"), "sig")

    found = peel_grouped(subtract(cell_table(leveled(a), cells, 4), cell_table(leveled(b), cells, 4)), cells, 4)
    per = found.groupBy("inst").agg(F.min(F.col("complete").cast("int")).alias("ok"), F.sum(F.col("sig").isNotNull().cast("int")).alias("n"))
    worst = per.where("ok = 0").agg(F.coalesce(F.max("inst"), F.lit(-1)).alias("worst"))
    return per.crossJoin(F.broadcast(worst)).where("inst > worst").groupBy("worst").agg(F.sum("n").alias("n")).select((F.col("n") * F.pow(F.lit(2.0), F.col("worst") + 1)).alias("d_hat"))
