"""Sketches of streams: counts, sums and XORs are additive, so a stream's sketch is a running aggregate.

An event delivered twice would flip a parity back, so duplicates go first, within the watermark. An event that comes too late is
dropped from the sketch and so is found as ``A_only`` by the next reconciliation.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from setdiff.functions import hashing as H
from setdiff.operators import binparity as S
from setdiff.plans.params import Params

DELAY = "10 minutes"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The stream of event files that land in ``path``."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def signed_events(events: DataFrame, delay: str | None = DELAY) -> DataFrame:
    """Events with ``sig``, each once; ``delay`` None for a batch."""
    out = events.withColumn("sig", (F.col("event_id") + 1).cast("long"))
    if delay is None:
        return out.dropDuplicates(["event_id"])
    return out.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def keyed(df: DataFrame, p: Params) -> DataFrame:
    root, bin_ = H.seed_of(H.GROUP, 0, p.seed), H.seed_of(H.BIN, 1, p.seed)
    return df.withColumn("root", H.bucket("sig", root, p.g, p.family)).withColumn("bin", H.bucket("sig", bin_, p.n, p.family))


def sketch(df: DataFrame, p: Params, keys: list[str] | None = None) -> DataFrame:
    """(keys, root, cw, chk, cnt): codeword, checksum and count of each group; of a stream in update or complete mode, or of a batch."""
    rows, lanes = S.lane_columns(keyed(df, p), p.m, p.t)
    return rows.groupBy(*(keys or []), "root").agg(F.array(*[F.bit_xor(x) for x in lanes]).alias("cw"), F.sum("sig").alias("chk"), F.count(F.lit(1)).alias("cnt"))


def windowed(df: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", gap: str = "30 minutes") -> DataFrame:
    """Events per window (and user, for sessions): window start, end, count, XOR and sum of signatures."""
    if kind == "session":
        keys = [F.session_window("ts", gap).alias("w"), F.col("user_id")]
    else:
        keys = [F.window("ts", size, slide if kind == "sliding" else size).alias("w")]
    out = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.bit_xor("sig").alias("xs"), F.sum("sig").alias("chk"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *[c for c in out.columns if c != "w"])


def merge_sketches(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sketch of the union of two disjoint parts."""
    lanes = lambda x, y: F.zip_with(F.coalesce(x, y), F.when(x.isNotNull(), y), lambda p, q: p.bitwiseXOR(F.coalesce(q, F.lit(0))))
    both = a.toDF("root", "_c", "_s", "_n").join(b.toDF("root", "_d", "_t", "_m"), "root", "full")
    zero = F.lit(0).cast("long")
    cw = F.when(F.col("_c").isNull(), F.col("_d")).when(F.col("_d").isNull(), F.col("_c")).otherwise(lanes(F.col("_c"), F.col("_d")))
    return both.select("root", cw.alias("cw"), (F.coalesce("_s", zero) + F.coalesce("_t", zero)).alias("chk"), (F.coalesce("_n", zero) + F.coalesce("_m", zero)).alias("cnt"))


class SketchState(StatefulProcessor):
    """Per group: count, checksum and XOR of signatures so far; every batch gives the group's new values."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getValueState("held", "cnt long, chk long, xs long")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        cnt, chk, xs = self.held.get() if self.held.exists() else (0, 0, 0)
        for part in rows:
            sig = part["sig"].astype("int64")
            cnt, chk = cnt + len(sig), chk + int(sig.sum())
            for s in sig:
                xs ^= int(s)
        self.held.update((cnt, chk, xs))
        yield pd.DataFrame({"root": [key[0]], "cnt": [cnt], "chk": [chk], "xs": [xs]})

    def close(self) -> None:
        pass


def stateful_sketch(df: DataFrame, p: Params) -> DataFrame:
    """(root, cnt, chk, xs) as an explicit stateful operator, in update mode."""
    return keyed(df, p).select("root", "sig").groupBy("root").transformWithStateInPandas(SketchState(), "root long, cnt long, chk long, xs long", "Update", "None")


def tow_stream(df: DataFrame, ell: int = 64, seed: int = 0) -> DataFrame:
    """(y, n): the running tug-of-war sketch of a stream, complete mode; y is additive, so windows leave by subtraction."""
    h = F.xxhash64("sig", F.lit(H.seed_of(H.SIGN, 0, seed)))
    sums = [F.count(F.lit(1)) - 2 * F.sum(F.shiftrightunsigned("_h", i).bitwiseAND(F.lit(1))) for i in range(ell)]
    return df.withColumn("_h", h).agg(F.array(*sums).alias("y"), F.count(F.lit(1)).alias("n"))
