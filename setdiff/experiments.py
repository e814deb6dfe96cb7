"""The experiments of the evaluation, re-expressed: every point is a batch of independent instances in one Spark job."""

from __future__ import annotations

import time
from math import ceil

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setdiff.operators import binparity as S
from setdiff.operators import cells as C
from setdiff.operators import estimate as E
from setdiff.operators import syndromes as Y
from setdiff.operators.rounds import host_sketch, reconcile
from setdiff.plans import model as M
from setdiff.plans import tune as T
from setdiff.plans.params import Params, groups_for, published
from setdiff.sources.workloads import first_by_hash, hashed_anew, instances, orders_a_day, per_load, table, without
from setdiff.session import written

SCHEMES = ("bin_parity", "whole_syndrome", "cell_table", "filter_cells", "grouped_syndrome", "full_exchange")
METRICS = "scheme string, d long, instances long, success double, model_bytes double, ratio double, enc_ms double, dec_ms double, rounds double"


def _ms(f) -> float:
    t = time.perf_counter()
    f()
    return (time.perf_counter() - t) * 1000


def _exact(diff: DataFrame, truth: DataFrame, count: int) -> float:
    """Share of instances whose result is the truth."""
    both = truth.select("inst", "sig", F.lit(1).alias("_t")).join(diff.select("inst", "sig", F.lit(1).alias("_g")).distinct(), ["inst", "sig"], "full")
    bad = both.where("_t is null or _g is null").select("inst").distinct().count()
    return 1 - bad / count


def run_scheme(scheme: str, a: DataFrame, b: DataFrame, truth: DataFrame, d: int, count: int, size: int, p0: float = 0.99, r: int = 3, p: Params | None = None, gamma: float = 1.0, w: int = 32) -> tuple:
    """One metrics row: all instances of one scheme at one d. ``gamma`` inflates d as an estimator would make the hosts do."""
    want = max(1, ceil(gamma * d))
    p = p or T.tuned(want, 5, r, p0)
    rounds = 1.0
    if scheme == "bin_parity":
        sketches, held = [], []
        enc = _ms(lambda: sketches.extend(written(host_sketch(x, p), "sketch") for x in (a, b)))
        whole = enc + _ms(lambda: held.append(reconcile(a, b, p.with_(sidecar=False), sketches)))  # both sets are written tables already
        got = held[0]
        success, bits = _exact(got.diff, truth, count), got.ledger.agg(F.sum("model_bits")).first()[0] / count
        rounds = got.status().agg(F.avg("rounds")).first()[0]
    elif scheme == "whole_syndrome":
        t = want
        sketches, held = [], []
        enc = _ms(lambda: sketches.extend(written(Y.encode(x, ["inst"], t), "syndromes") for x in (a, b)))
        whole = enc + _ms(lambda: held.append(written(Y.whole_syndrome(a, b, t, sketches=sketches), "whole")))
        success, bits = _exact(held[0], truth, count), t * w
    elif scheme == "grouped_syndrome":
        sketches, held = [], []
        enc = _ms(lambda: sketches.extend(written(Y.encode(S.with_node(x, p, None, 0), S.NODE, p.t), "syndromes") for x in (a, b)))
        whole = enc + _ms(lambda: held.append(Y.grouped_syndrome(a, b, p, sketches=sketches)))
        diff, log = held[0]
        success = _exact(diff, truth, count)
        later = log.where("round > 1").count()
        bits = (p.g * count + later) * (p.t * w + w) / count
        rounds = log.groupBy("inst").agg(F.max("round").alias("r")).agg(F.avg("r")).first()[0]
    elif scheme == "cell_table":
        k = C.hashes_for(d)  # two cells for each of the estimated differences, without the safety factor
        cells = C.cells_for(d, k)
        tables, held = [], []
        enc = _ms(lambda: tables.extend(written(C.cell_table(x, cells, k), "cell_table") for x in (a, b)))
        whole = enc + _ms(lambda: held.append(written(C.cell_digest(a, b, d, grouped=True, tables=tables), "cells")))
        success, bits = _exact(held[0], truth, count), cells * 3 * w
    elif scheme == "filter_cells":
        size_b = size - d
        enc_parts: list = []
        sent_ahead, held = {}, []
        want = d
        rate = C.best_rate(size_b, want)
        if rate < 1:
            bits_f, fk = C.filter_shape(size_b, rate)
            enc_parts.append(_ms(lambda: sent_ahead.update(message=written(C.filter_message(b, bits_f, fk), "message"))))
        k = C.hashes_for(want)
        enc_parts.append(_ms(lambda: sent_ahead.update(tables=[written(C.cell_table(x, C.cells_for(want, k), k), "cell_table") for x in (a, b)])))
        enc = sum(enc_parts)
        if rate < 1:  # the cells that follow a filter are those of the rows that pass it
            sent_ahead.pop("tables")
        whole = enc + _ms(lambda: held.append(C.filter_cells(a, b, want, size_b, grouped=True, **sent_ahead)))
        diff, sent = held[0]
        diff = written(diff, "filtered")
        success, bits = _exact(diff, truth, count), sent["filter_bits"] + sent["cells"] * 3 * w
    else:
        from setdiff.operators.relational import symmetric_difference

        enc, held = 0.0, []
        whole = _ms(lambda: held.append(written(symmetric_difference(a, b, ["inst", "sig"]), "full")))
        success, bits = _exact(held[0], truth, count), (size - d) * w
    return scheme, d, count, success, bits / 8, bits / (d * w), enc, max(0.0, whole - enc), float(rounds or 0)


def compare(
    spark: SparkSession, sf_dir: str, schemes: tuple[str, ...], ds: tuple[int, ...], count: int = 20, size: int | None = None, p0: float = 0.99, gamma: float = E.GAMMA, most: dict[str, int] | None = None
) -> DataFrame:
    """Metrics of schemes over a grid of d; the setting of all three comparisons.

    Points with d over half of the set are left out. ``most`` names the largest d a scheme is run at, for those whose decoding time forbids more.
    The hashed sets, and their signatures in the order in which they are dropped, are the same for every d and are laid out once.
    """
    rows = []
    a, n = hashed_anew(spark, sf_dir, count, size)
    ds = tuple(x for x in ds if 2 * x <= n)
    if ds:
        a = written(a, "a")
        dropped = written(first_by_hash(a, max(ds), n, count), "dropped")
    for d in ds:
        truth = dropped.where(F.col("place") <= d).select("inst", "sig")
        b = written(without(a, truth, count * d), "b")
        rows += [run_scheme(s, a, b, truth, d, count, n, p0, gamma=gamma) for s in schemes if d <= (most or {}).get(s, d)]
    return spark.createDataFrame(rows, METRICS)


def decode_growth(spark: SparkSession, ds: tuple[int, ...] = (50, 100, 200, 400, 800)) -> DataFrame:
    """(scheme, d, decode_ms): decoding alone, in one process, without any engine around it: how each scheme grows with d."""
    schema = "scheme string, d long, decode_ms double"

    def run(parts):
        from setdiff.functions.gf import mul32, packed_table
        from setdiff.operators import decode as D

        for part in parts:
            for d in part["d"]:
                d = int(d)
                rng = np.random.default_rng(d)
                sig = rng.choice(2**32 - 1, d, replace=False).astype(np.uint64) + np.uint64(1)
                table, g = packed_table(7, 13), groups_for(d)
                lanes = np.zeros((g, len(table)), np.int64)
                for root, b in zip(rng.integers(0, g, d).tolist(), rng.integers(0, 127, d).tolist(), strict=True):
                    lanes[root] ^= table[:, b]
                D.decode(lanes, 7, 13)
                rows = [("bin_parity", d, _ms(lambda: D.decode(lanes, 7, 13)))]  # noqa: B023
                odd, p, sq = [], sig, mul32(sig, sig)
                for _ in range(ceil(E.GAMMA * d)):
                    odd.append(np.bitwise_xor.reduce(p))
                    p = mul32(p, sq)
                Y.decode32(np.array(odd[:8]))  # builds the field's tables, like the first decode above
                rows.append(("whole_syndrome", d, _ms(lambda: Y.decode32(np.array(odd)))))  # noqa: B023
                yield pd.DataFrame(rows, columns=["scheme", "d", "decode_ms"])

    return spark.createDataFrame([(d,) for d in ds], "d long").repartition(len(ds), "d").mapInPandas(run, schema)


def signature_lengths(spark: SparkSession, d: int = 1000, p0: float = 0.99) -> DataFrame:
    """(w, scheme, ratio): what longer signatures do to each scheme, by the formulas of the ledger."""
    p = T.tuned(E.GAMMA * d, 5, 3, p0)
    rows = []
    for w in (32, 64, 256):
        k = C.hashes_for(d)
        bits = {
            "bin_parity": p.g * (p.t * p.m + w) + d * (p.m + w), "grouped_syndrome": p.g * (p.t * w + w), "whole_syndrome": ceil(E.GAMMA * d) * w, "cell_table": C.cells_for(d, k) * 3 * w,
        }
        rows += [(w, s, x / (d * w)) for s, x in bits.items()]
    return spark.createDataFrame(rows, "w int, scheme string, ratio double")


def delta_sweep(spark: SparkSession, sf_dir: str, deltas: tuple[int, ...] = (2, 5, 10, 20), d: int = 100, count: int = 10, size: int | None = None) -> DataFrame:
    """(delta, n, t, model_bits, ratio, dec_ms): larger groups cost fewer bits and more decoding."""
    a, b, size = instances(spark, sf_dir, count, d, size)
    a, b = written(a, "a"), written(b, "b")
    truth, rows = written(a.join(b, ["inst", "sig"], "left_anti"), "truth"), []
    for delta in deltas:
        p = T.tuned(d, delta, 3, 0.99)
        x = run_scheme("bin_parity", a, b, truth, d, count, size, p=p)
        rows.append((delta, p.n, p.t, x[4] * 8, x[5], x[7]))
    return spark.createDataFrame(rows, "delta int, n int, t int, model_bits double, ratio double, dec_ms double")


def measured_shares(spark: SparkSession, sf_dir: str, d: int = 100, count: int = 20, size: int | None = None) -> DataFrame:
    """(round, measured, expected): share of the differences recovered in each round at n = 127, t = 13."""
    from setdiff.operators.rounds import share_by_round

    a, b, _ = instances(spark, sf_dir, count, d, size)
    got = {r["round"]: r["n"] for r in share_by_round(reconcile(a, b, published(d))).collect()}
    want = M.expected_shares(127, 13, d, groups_for(d), 4)
    return spark.createDataFrame([(k, got.get(k, 0) / (d * count), want[k - 1]) for k in range(1, 5)], "round int, measured double, expected double")


def estimator_accuracy(spark: SparkSession, ds: tuple[int, ...] = (10, 100, 1000), ells: tuple[int, ...] = (32, 128), trials: int = 4000) -> DataFrame:
    return E.calibrate_gamma(spark, list(ds), list(ells), trials)


def split_ways(spark: SparkSession) -> DataFrame:
    """(ways, model, simulated): chance that a split fails again."""
    rng = np.random.default_rng(9)
    rows = []
    for ways in (2, 3):
        x = rng.binomial(1000, 1 / 200, 4_000_000)
        x = x[x > 13]
        child = rng.multinomial(x, [1 / ways] * ways)
        rows.append((ways, float(M.p_split_overflow(ways, 1000, 200, 13)), float((child.max(1) > 13).mean())))
    return spark.createDataFrame(rows, "ways int, model double, simulated double")


def bin_kinds(spark: SparkSession, trials: int = 100_000, d: int = 5, n: int = 255) -> DataFrame:
    """(kind, share): how often d elements fall ideally, into an even bin, into an odd bin of three or more."""
    sets = spark.range(trials * d).select(F.floor(F.col("id") / d).alias("inst"), (F.col("id") + 1).alias("sig"))
    bins = S.with_bin(sets, n, 123).groupBy("inst", "bin").agg(F.count(F.lit(1)).alias("n"))
    per = bins.groupBy("inst").agg(F.max((F.col("n") % 2 == 0).cast("int")).alias("even"), F.max(((F.col("n") % 2 == 1) & (F.col("n") > 2)).cast("int")).alias("odd"))
    shares = per.agg(F.avg(((F.col("even") == 0) & (F.col("odd") == 0)).cast("double")).alias("ideal"), F.avg("even").alias("even"), F.avg("odd").alias("odd"))
    return shares.selectExpr("stack(3, 'ideal', ideal, 'even', even, 'odd', odd) as (kind, share)")


def fake_candidates(spark: SparkSession, sf_dir: str, d: int = 150, count: int = 20, size: int | None = None) -> DataFrame:
    """(check, proposed, fakes_left): what the test of a candidate against its bin removes in the first round."""
    a, b, size = instances(spark, sf_dir, count, d, size)
    a, b = written(a, "a"), written(b, "b")
    truth, rows = written(a.join(b, ["inst", "sig"], "left_anti"), "truth"), []
    p = Params(g=groups_for(d, 10), n=63, t=17, max_rounds=1)
    for on in (False, True):
        q = p.with_(check_bin=on, check_group=False)
        got = reconcile(a, b, q)
        cands = got.candidates[0]
        left = S.check_candidates(cands, q, 1, 0)
        rows.append(("on" if on else "off", cands.count(), left.join(truth, ["inst", "sig"], "left_anti").count()))
    return spark.createDataFrame(rows, "check string, proposed long, fakes_left long")


def filter_use(spark: SparkSession, size: int = 1_000_000, ds: tuple[int, ...] = (1000, 5000, 10_000, 12_000, 16_000, 30_000, 100_000)) -> DataFrame:
    """(d, filter_used, model_bytes): from which d on the hybrid sends a filter."""
    rows = []
    for d in ds:
        rate = C.best_rate(size - d, d)
        k = C.hashes_for(d)
        plain = C.cells_for(d, k) * 96
        bits = plain if rate >= 1 else C.filter_shape(size - d, rate)[0] + C.cells_for(C.passing(rate, d), 4) * 96
        rows.append((d, bool(rate < 1), bits / 8))
    return spark.createDataFrame(rows, "d long, filter_used boolean, model_bytes double")


def tuning_by_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d, model, r, n, t, bits): the optimum by rounds for the differences that a missed day makes."""
    models = (("split_aware", {}), ("truncated_plain", {"tail_model": "truncated", "bound": "plain"}))
    rows = lambda d: [(d, model, *x) for model, how in models for x in T.round_tradeoff(d, **how)]
    return per_load(orders_a_day(spark, sf_dir), "d long, model string, r int, n int, t int, bits int", rows)


def per_group_capacity(spark: SparkSession, sf_dir: str, delta: int = 5) -> DataFrame:
    """(d, plan, bits): the rejected alternative of measuring every group: what its estimates cost against what smaller codes save.

    The set is all orders, d what a missed day makes.
    """

    def rows(d: int, size: int) -> list[tuple]:
        g, p = groups_for(d, delta), published(d)
        pmf = M.binom_pmf(d, 1 / g, 40)
        saved = g * sum(pmf[x] * max(0, p.t - x) for x in range(41)) * p.m
        whole = float(g * p.t * p.m)
        return [(d, "uniform", whole), (d, "per_group", whole - float(saved) + g * E.tow_bits(E.ELL, size // g))]

    size = table(spark, sf_dir, "orders").agg(F.count("o_orderkey").alias("size"))
    return per_load(orders_a_day(spark, sf_dir).crossJoin(size), "d long, plan string, bits double", rows)
