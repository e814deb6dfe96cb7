"""What shows only with large differences: made tables whose sets are further apart than those of the given ones."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from setdiff.plans import model as M
from setdiff.plans import planner as P
from setdiff.plans import tune as T
from setdiff.queries import registry


def test_decoded_bins_of_groups_over_capacity(spark, tmp_path):
    """Twenty differences a group, more than the code corrects: every bin is found all the same."""
    import duckdb

    for name, col, n in (("orders", "o_orderkey", 20_000), ("lineitem", "l_orderkey", 16_000)):
        spark.range(n).select(F.pmod(F.xxhash64("id"), F.lit(10**8)).alias(col)).distinct().coalesce(1).write.parquet(f"{tmp_path}/{name}.parquet")
    run, sql = registry()["decoded_bins_w3"]
    con = duckdb.connect()
    for name in ("orders", "lineitem"):
        con.execute(f"create view {name} as select * from '{tmp_path}/{name}.parquet/*.parquet'")
    want = con.execute(f"select root, bin from ({sql})").fetchall()
    got = [(r["root"], r["bin"]) for r in run(spark, str(tmp_path)).collect()]
    assert len(got) > 200 * 13 and sorted(got) == sorted(want)


@pytest.mark.parametrize("bins", [range(127), range(0, 127, 2), range(14), range(13), []])
def test_differing_bins_of_one_group(spark, bins):
    from setdiff.operators import decode as D

    rows = spark.createDataFrame([(0, b) for b in [*bins, 5, 5]], "root long, bin long")
    got = [r["bin"] for r in D.differing_bins(rows, ["root"], 7, 13).collect()]
    assert sorted(got) == list(bins)


def test_plan_for_tens_of_millions_of_differences():
    for d in (10**6, 2 * 10**7, 10**9):
        pmf = M.binom_pmf(d, 5 / d, M.MOST)
        assert abs(pmf.sum() - 1) < 1e-12 and np.isclose(pmf[5], np.exp(-5) * 5**5 / 120, rtol=1e-5)
    assert T.tuned(2e7).g == 4_000_000
    assert P.choose_scheme(2e7, 9_000_000, 18_000_000).scheme == "full_exchange"
    assert P.choose_scheme(1e9, 10**12, 10**12).scheme == "bin_parity"


def test_instances_of_a_grid_are_those_of_single_points(spark, sf):
    """The sets laid out once for a whole grid are the ones that every point would lay out for itself."""
    from setdiff.sources import workloads as W

    rows, n = W.hashed_anew(spark, sf, 3, 200)
    dropped = W.first_by_hash(rows, 50)
    for d in (7, 50):
        a, b, size = W.instances(spark, sf, 3, d, 200)
        mine = W.without(rows, dropped.where(F.col("place") <= d), 3 * d)
        assert size == n == 200 and a.exceptAll(rows).isEmpty() and mine.exceptAll(b).isEmpty()
        assert mine.count() == b.count() == 3 * (200 - d)


def test_shape_counts_the_bins_of_every_instance(spark):
    from setdiff.operators.rounds import choose_shape
    from setdiff.plans.params import Params

    p = Params(g=276, n=255)
    assert choose_shape(p, 30_000_000) == "bins" and choose_shape(p, 30_000_000, 200) == "two_pass"


@pytest.mark.parametrize("name", ["binomial_tail", "bits_per_group_grid", "expected_share_by_round", "metrics_rollup", "overhead_formula_grid", "p_ideal", "per_group_capacity", "planner_bits", "round_tradeoff", "topk_params"])
def test_formulas_are_worked_out_over_a_table(spark, sf, name):
    assert registry()[name][0](spark, sf).inputFiles()


def test_optimum_by_rounds_of_a_day(spark, sf):
    """Row by row what the tuner says for the orders of each day."""
    days = {r["n"] for r in spark.read.parquet(f"{sf}/orders.parquet").groupBy("o_orderdate").agg(F.count("*").alias("n")).collect()}
    got = {tuple(r) for r in registry()["round_tradeoff"][0](spark, sf).collect()}
    assert {x for x in got if x[1] == "split_aware"} == {(d, "split_aware", *x) for d in days for x in T.round_tradeoff(d)}
    assert {x[0] for x in got} == days


def test_first_comparison_runs_every_scheme_at_every_point(spark, sf, monkeypatch):
    from setdiff import experiments as X

    seen = []
    monkeypatch.setattr(X, "run_scheme", lambda scheme, a, b, truth, d, *_, **__: seen.append((scheme, d)) or (scheme, d, 1, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0))
    registry()["x1_whole_and_cells"][0](spark, sf)
    assert seen == [(s, d) for d in (10, 100) for s in ("bin_parity", "whole_syndrome", "cell_table")]  # 1,500 orders: half of them is less than 1,000


def test_sums_of_middle_capacities_go_by_polynomials(spark, monkeypatch):
    """Several instances mixed up in one task, capacities on both sides of the bound: the same sums, and no element by element products beyond it."""
    from setdiff.operators import syndromes as Y

    rows = spark.range(3000).select((F.col("id") % 3).alias("inst"), F.pmod(F.xxhash64("id"), F.lit(2**32 - 1)).alias("sig")).coalesce(1)
    short = {(r["inst"], r["k"]): r["s"] for r in Y.encode(rows, ["inst"], Y.DIRECT_SUMS).collect()}
    long = {(r["inst"], r["k"]): r["s"] for r in Y.encode(rows, ["inst"], Y.DIRECT_SUMS + 20).collect()}
    assert len(long) == 3 * (Y.DIRECT_SUMS + 20) and short.items() <= long.items()


def test_checksums_by_halves(spark):
    """Signatures of 64 bits and both signs: the sums agree only if the right differences are taken out."""
    from setdiff.operators import syndromes as Y

    rows = [(i % 2, x) for i, x in enumerate([2**63 - 1, 2**63 - 2, -(2**63), 5 - 2**63, 2**62, 2**62 + 1, -1, -2, 7, 8])]
    a = spark.createDataFrame(rows, "inst long, sig long")
    b = spark.createDataFrame(rows[4:], "inst long, sig long")
    found = spark.createDataFrame([(*x, "A_only") for x in rows[:3]] + [(1, 6 - 2**63, "A_only")], "inst long, sig long, side string")
    assert [r["inst"] for r in Y.verified(a, b, found, ["inst"]).collect()] == [0]


def test_instances_are_laid_out_in_one_place_each(spark, sf):
    from setdiff.sources import workloads as W

    rows, _ = W.hashed_anew(spark, sf, 5)
    places = rows.select("inst", F.spark_partition_id().alias("at")).distinct()
    assert places.count() == 5 and rows.count() == rows.distinct().count()
    few, every = W.first_by_hash(rows, 20, 1500, 5), W.first_by_hash(rows, 20)
    assert few.count() == 100 and few.exceptAll(every).isEmpty()


def test_rounds_from_sketches_at_hand(spark, sf):
    """Hosts' sketches that were written before give what a run without them gives; rounds after the first read rows of open groups only."""
    from setdiff.operators import rounds as R
    from setdiff.plans.params import Params
    from setdiff.session import written
    from setdiff.sources import workloads as W

    a, b, _ = W.instances(spark, sf, 4, 60)
    a, b = written(a, "a"), written(b, "b")
    for more in ({"check_group": False}, {"checksum": "mset_xor"}):
        p = Params(g=3, n=63, t=8, **more)  # too few groups: some split
        sketches = [R.host_sketch(x, p) for x in (a, b)]
        got, want = R.reconcile(a, b, p, sketches), a.join(b, ["inst", "sig"], "left_anti")
        assert got.diff.where("side = 'A_only'").select("inst", "sig").exceptAll(want).isEmpty() and got.diff.count() == want.count() == 240
        assert len(got.decoded) > 1
