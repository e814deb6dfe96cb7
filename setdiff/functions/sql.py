"""SQL surface: functions a session can use by name, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import LongType

from setdiff.functions import hashing as H
from setdiff.functions.gf import field
from setdiff.operators.decode import decode
from setdiff.plans import model as M
from setdiff.plans import tune as T


@udtf(returnType="bin: int")
class DecodeBins:
    """Bins that differ, from both hosts' packed codewords; no rows if they can't be told."""

    def eval(self, cw_a: list, cw_b: list, m: int, t: int) -> Iterator[tuple]:
        ok, bins = decode(np.array([[x ^ y for x, y in zip(cw_a, cw_b, strict=True)]]), m, t)
        for b in bins[0] if ok[0] else ():
            yield (int(b),)


@udtf(returnType="k: int, value: int")
class AntilogTable:
    def eval(self, m: int) -> Iterator[tuple]:
        for k, v in enumerate(field(m).exp.tolist()):
            yield (k, v)


@udtf(returnType="g: int, n: int, t: int, bound: double, objective: int, feasible: boolean")
class TuningGrid:
    def eval(self, d: int, delta: int, r: int, p0: float) -> Iterator[tuple]:
        for x in T.grid(int(d), int(delta), int(r), float(p0)):
            yield (x[4], x[5], x[6], x[8], x[9], x[10])


@udtf(returnType="i: int, j: int, p: double")
class TransitionMatrix:
    def eval(self, n: int, t: int) -> Iterator[tuple]:
        for i, row in enumerate(M.transition_matrix(n, t)):
            for j, p in enumerate(row[: i + 1]):
                yield (i, j, float(p))


@pandas_udf(LongType())
def gf_mul(a: pd.Series, b: pd.Series, m: pd.Series) -> pd.Series:
    """Products in GF(2**m), tables per m."""
    out = pd.Series(0, index=a.index)
    for k in m.unique():
        at = m == k
        out[at] = field(int(k)).mul(a[at].to_numpy(), b[at].to_numpy())
    return out


def register(spark: SparkSession) -> None:
    """Makes sd_sig, sd_gid, sd_bin, gf_mul and the table functions known to SQL."""
    group, bin_ = H.coefficients(H.seed_of(H.GROUP)), H.coefficients(H.seed_of(H.BIN, 1))
    spark.sql("create or replace temporary function sd_sig(k bigint) returns bigint return k + 1")
    for name, (a, b, c) in (("sd_gid", group), ("sd_bin", bin_)):
        spark.sql(
            f"create or replace temporary function {name}(sig bigint, n bigint) returns bigint "
            f"return (({a}L * (sig div 65536) + {b}L * (sig % 65536) + {c}L) % {H.PRIME}L) % n"
        )
    spark.udf.register("gf_mul", gf_mul)
    for name, f in (("decode_bins", DecodeBins), ("antilog_table", AntilogTable), ("tuning_grid", TuningGrid), ("transition_matrix", TransitionMatrix)):
        spark.udtf.register(name, f)


def sdiff(spark: SparkSession, view_a: str, view_b: str, p0: float = 0.99) -> DataFrame:
    """(sig, side) of two views with ``sig``, for SQL users: estimate, tune, reconcile."""
    from setdiff.plans.planner import reconcile_auto

    pick = lambda v: spark.table(v).select(F.col("sig").cast("long").alias("sig")).distinct()
    return reconcile_auto(pick(view_a), pick(view_b), p0)[0]
