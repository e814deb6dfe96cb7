"""Every scheme against the exact difference; crafted sets for each way a round can fail."""

import pytest
from pyspark.sql import functions as F

from setdiff.functions import hashing as H
from setdiff.functions import signature as G
from setdiff.operators import binparity as S
from setdiff.operators import cells as C
from setdiff.operators import estimate as E
from setdiff.operators import relational as R
from setdiff.operators import syndromes as Y
from setdiff.operators import verify as V
from setdiff.operators.rounds import bin_parity_small, reconcile, reconcile_iter
from setdiff.plans import ledger as L
from setdiff.plans import model as M
from setdiff.plans import planner as P
from setdiff.plans import tune as T
from setdiff.plans.params import Params, published
from setdiff.sources.workloads import WORKLOADS, instances


def sets(spark, *values):
    return tuple(spark.createDataFrame([(int(x),) for x in v], "sig long") for v in values)


def got(df):
    return {(r["sig"], r["side"]) for r in df.collect()}


def truth(a, b):
    a, b = set(a), set(b)
    return {(x, "A_only") for x in a - b} | {(x, "B_only") for x in b - a}


@pytest.mark.parametrize("name", ["w1_d10", "w3", "w6", "w9"])
def test_workloads_exact(spark, sf, duck, name):
    a, b = WORKLOADS[name].pair(spark, sf)
    want = {tuple(r) for r in duck.execute(WORKLOADS[name].difference_sql()).fetchall()}
    r = reconcile(a, b, published(max(5, len(want))))
    assert got(r.diff) == want
    row = r.status().first()
    assert row["success"] and row["rounds"] >= 1


@pytest.mark.parametrize("more", [{"shape": "bins"}, {"shape": "two_pass"}, {"checksum": "mset_xor"}, {"checksum": "hashed_sum"}, {"w": 64}, {"family": "portable", "n": 1023, "t": 9}])
def test_variants_exact(spark, more):
    a, b = range(1, 400), [*range(20, 400), *range(1000, 1010)]
    assert got(reconcile(*sets(spark, a, b), published(29, **more)).diff) == truth(a, b)


def test_overflow_splits(spark):
    """Sixty differences in one group of capacity eight: decoding fails, three-way splits make it exact."""
    a, b = range(1, 200), range(61, 200)
    r = reconcile(*sets(spark, a, b), Params(g=1, n=63, t=8))
    assert got(r.diff) == truth(a, b)
    assert not r.decoded[0].first()["ok"] and r.decoded_all().agg(F.max(F.length("path"))).first()[0] >= 2


def test_zero_one_and_two_elements(spark):
    one = lambda a, b: [r["sig"] for r in S.one_element(*sets(spark, a, b)).collect()]
    assert one([5, 9, 12], [5, 9]) == [12] and one([5, 9], [9, 5]) == [] and one([5, 9, 12], [5]) == [9 ^ 12]
    keys = spark.createDataFrame([(0,), (1,), (1,), (None,)], "k long")
    assert sorted(r["sig"] for r in G.as_set(keys, G.identity("k")).collect()) == [1, 2]
    # the single-element answer to two differences is wrong; with its checksum the round is not accepted
    r = reconcile(*sets(spark, [5, 9, 12], [5]), Params(g=1, n=63, t=8, max_rounds=None))
    assert got(r.diff) == {(9, "A_only"), (12, "A_only")}


def test_degenerate(spark):
    none = sets(spark, [])[0]
    some = sets(spark, range(1, 20))[0]
    assert got(bin_parity_small(some, some).diff) == set()
    assert got(bin_parity_small(some, none, t=20).diff) == {(x, "A_only") for x in range(1, 20)}
    assert got(bin_parity_small(none, none).diff) == set()


def _same_bin(spark, count, n=63, seed=0):
    rows = spark.range(1, 20_000).select(F.col("id").alias("sig")).withColumn("bin", S.bin_of(Params(g=1, n=n, seed=seed), 1))
    return [r["sig"] for r in rows.where("bin = 7").orderBy("sig").limit(count).collect()]


def test_even_and_odd_bins(spark):
    for count in (2, 3):
        xs = _same_bin(spark, count)
        a = sets(spark, [*xs, 50_000])[0]
        b = sets(spark, [50_000])[0]
        steps = list(reconcile_iter(a, b, Params(g=1, n=63, t=8, max_rounds=1), "bins"))
        first = {r["sig"] for r in steps[0]["new"].collect()}
        assert not first & set(xs), "an even bin shows nothing, the XOR of three is dropped by its hash"
        assert got(reconcile(a, b, Params(g=1, n=63, t=8)).diff) == {(x, "A_only") for x in xs}
    diff = sets(spark, _same_bin(spark, 3))[0].withColumn("root", F.lit(0)).withColumn("bin", S.bin_of(Params(g=1, n=63), 1))
    assert S.classify_bins(diff, ["root"]).first()["kind"] == "odd"


def test_bitmap_equals_decoder(spark):
    keyed = lambda d: d.withColumn("root", F.lit(0)).withColumn("bin", S.bin_of(Params(g=1), 1))
    a, b = (keyed(x) for x in sets(spark, range(1, 300), range(8, 300)))
    from setdiff.operators.decode import decode_batches

    word = S.encode(a.union(b), ["root"], 7, 13).mapInArrow(decode_batches(["root"], 7, 13), "root int, ok boolean, bins array<bigint>").first()
    assert word["ok"] and sorted(word["bins"]) == sorted(r["bin"] for r in S.bitmap_exchange(a, b, ["root"]).collect())
    both = {r["root"]: r["cw"] for r in S.encode(a.union(b), ["root"], 7, 13).collect()}
    ones = [S.encode(x, ["root"], 7, 13).first()["cw"] for x in (a, b)]
    assert both[0] == [x ^ y for x, y in zip(*ones, strict=True)]
    assert S.parity_bitmap(a, ["root"]).count() == 1


def test_many_instances_and_ledger(spark, sf):
    a, b, _ = instances(spark, sf, 12, 20, 200)
    p = published(20)
    r = reconcile(a, b, p)
    want = {(x["inst"], x["sig"]) for x in a.join(b, ["inst", "sig"], "left_anti").collect()}
    assert {(x["inst"], x["sig"]) for x in r.a_only.collect()} == want and r.b_only.count() == 0
    assert r.status().where("success").count() == 12
    kinds = {x["kind"]: x["b"] for x in r.ledger.where("round = 1").groupBy("kind").agg(F.sum("model_bits").alias("b")).collect()}
    bins = sum(len(x["bins"]) for x in r.decoded[0].collect())
    assert kinds["codeword"] == 12 * p.g * p.t * p.m and kinds["checksum"] == 12 * p.g * p.w
    assert kinds["positions"] == bins * p.m and kinds["xor_sums"] == bins * p.w
    assert L.totals(r.ledger, 32, r.diff.groupBy("inst").agg(F.count(F.lit(1)).alias("d"))).agg(F.avg("ratio")).first()[0] < 4


def test_success_rate_of_tuned_runs(spark, sf):
    a, b, _ = instances(spark, sf, 150, 30, 150)
    r = reconcile(a, b, T.tuned(30))
    assert r.status().agg(F.avg(F.col("success").cast("double"))).first()[0] >= 0.96


def test_baselines(spark):
    a, b = range(1, 500), [*range(31, 500), *range(2000, 2010)]
    x, y = sets(spark, a, b)
    want = truth(a, b)
    assert got(R.full_exchange(x, y)) == want
    assert got(R.symmetric_difference(x, y, ["sig"])) == want
    assert got(Y.whole_syndrome(x, y, 48)) == want and got(Y.whole_syndrome(x, y, 10)) == set()
    assert got(Y.grouped_syndrome(x, y, Params(g=4, t=8))[0]) == want
    assert got(C.cell_digest(x, y, 60)) == want and got(C.cell_digest(x, y, 60, grouped=True)) == want
    assert got(C.filter_cells(x, y, 40, 479)[0]) == want and C.filter_cells(x, y, 40, 479)[1]["filter_bits"] > 0
    few = C.peel_grouped(C.subtract(C.cell_table(x, 16, 4), C.cell_table(y, 16, 4)), 16, 4)
    assert not few.first()["complete"]


def test_filter_breakeven_range():
    assert 10_000 < C.filter_breakeven(10**6) < 16_000


def test_checksums(spark):
    x = sets(spark, [3, 2**63 - 1, 5])[0].union(sets(spark, [-7])[0])
    chk = V.checksum(x.withColumn("root", F.lit(0)), ["root"], 64).first()["chk"]
    assert int(chk) % 2**64 == (3 + 2**63 - 1 + 5 - 7) % 2**64
    a, b = sets(spark, range(1, 100), range(1, 100))
    assert V.merkle_root(a).first() == V.merkle_root(b.orderBy(F.desc("sig"))).first() != V.merkle_root(a.where("sig < 99")).first()
    assert V.multiset_hash(a).first() == V.multiset_hash(b.repartition(3)).first()


def test_signed_64_bit_edges(spark):
    a, b = [-(2**63) + 1, -5, 2**63 - 1, 9], [9, -5]
    assert got(reconcile(*sets(spark, a, b), Params(g=1, n=63, t=8, w=64)).diff) == truth(a, b)


@pytest.mark.parametrize("shape", ["bins", "two_pass"])
def test_wide_signatures(spark, shape):
    """256 bits: all four lanes come back for what only B has."""
    lanes = lambda lo, hi: S.wide_set(spark.range(lo, hi).withColumnRenamed("id", "k"), G.row_hash256(["k"]))
    a, b = lanes(0, 300), lanes(12, 310)
    r = reconcile(a, b, published(22, w=256, shape=shape))
    full = lambda d: {tuple(x) for x in d.select("sig", *S.WIDE).collect()}
    assert full(r.b_only) == full(lanes(300, 310)) and full(r.a_only) == full(lanes(0, 12)) and full(r.union()) == full(lanes(0, 310))
    row = r.ledger.where("kind = 'xor_sums' and round = 1").first()
    assert row["model_bits"] == 256 * row["items"]


def test_costs(spark):
    c = L.spark_costs(spark, lambda: spark.range(10).count())
    assert c["jobs"] >= 1 and c["tasks"] >= 1 and L.field_operations(2, 3, 7) == 2 * (18 + 21) and L.min_bits(3, 32) == 96


def test_capped_rounds_report_failure(spark):
    a, b = range(1, 200), range(61, 200)
    r = reconcile(*sets(spark, a, b), Params(g=1, n=63, t=8, max_rounds=1))
    assert not r.status().first()["success"]


def test_estimators(spark):
    a, b = sets(spark, range(1, 3000), range(401, 3000))
    assert 280 < E.estimate_d(a, b).first()["d_hat"] < 560
    assert 250 < E.theta_estimate(a, b).first()["d_hat"] < 550
    assert E.strata_estimate(a, b).first()["d_hat"] > 100
    assert E.tow_bits(128, 10**6) // 8 == 336
    row = E.calibrate_gamma(spark, [100], [128], 4000).first()
    assert row["covered"] >= 0.985 and abs(row["bias"]) < 0.02 and 0.9 < row["var_ratio"] < 1.1


def test_auto_and_planner(spark):
    a, b = sets(spark, range(1, 2000), range(40, 2005))
    diff, report = P.reconcile_auto(a, b)
    assert got(diff) == truth(range(1, 2000), range(40, 2005)) and report["scheme"] == "bin_parity"
    diff, report = P.reconcile_auto(*sets(spark, range(1, 300), range(500, 800)))
    assert report["scheme"] == "full_exchange" and diff.count() == 599
    c = P.choose_scheme(1000, 10**6, 10**6)
    assert c.scheme == "bin_parity" and "bin_parity" in c.explain_choice()
    bits = P.predicted_bits(1000, 10**6, 10**6)
    assert bits["whole_syndrome"] < bits["bin_parity"] < bits["grouped_syndrome"] < bits["cell_table"] < bits["full_exchange"]


def test_overhead_formula_range():
    assert 2.13 <= M.overhead_formula(127, 13, 5, 32, E.GAMMA) / 32 <= 2.87


def test_relational(spark):
    df = spark.createDataFrame([(1, "2024-01-01 00:00:00", 1), (1, "2024-01-02 00:00:00", 2), (2, "2024-01-03 00:00:00", 3)], "k long, t string, v long").withColumn("t", F.to_timestamp("t"))
    assert {(r["k"], r["v"]) for r in R.asof_latest(df, "k", "t", "2024-01-02 12:00:00").collect()} == {(1, 2)}
    assert R.interval_match(df, df, "k", "t", 86_400).count() == 5
    a, b = sets(spark, [1, 2, 3], [3, 4])
    assert sorted(r["sig"] for r in R.toggle(a, b).collect()) == [1, 2, 4]
    assert R.exclude_exact_d(a, "sig", 2).count() == 1
    assert R.semi_filter(a, b, ["sig"]).count() == 1


def test_formats(spark, sf, tmp_path):
    n = spark.read.parquet(f"{sf}/nation.parquet")
    for fmt in ("parquet", "orc", "json", "csv"):
        n.write.format(fmt).option("header", True).save(str(tmp_path / fmt))
        back = R.read_any(spark, str(tmp_path / fmt), fmt, "n_nationkey int, n_name string, n_regionkey int", header=True)
        assert got(R.symmetric_difference(n.select(G.identity("n_nationkey").alias("sig")), back.select(G.identity("n_nationkey").alias("sig")), ["sig"])) == set()


def test_sql_templates(spark):
    a = sets(spark, range(1, 200))[0]
    a.createOrReplaceTempView("one_shot")
    p = published(20, family="portable")
    t = P.one_shot_sql("one_shot", p)
    keyed = a.withColumn("root", S.root_of(p)).withColumn("bin", S.bin_of(p, 1))
    assert set(spark.sql(t["parity_bins"]).collect()) == set(S.parity_bins(keyed, ["root"]).collect())
    assert spark.sql(t["checksums"]).count() == keyed.select("root").distinct().count() and spark.sql(t["bin_table"]).count() == keyed.select("root", "bin").distinct().count()


def test_sketch_store_round_trip(spark, tmp_path):
    a = sets(spark, range(1, 50))[0]
    sk = S.encode(S.with_node(S.with_inst(a), published(5), None, 0).withColumn("bin", S.bin_of(published(5), 1)), S.NODE, 7, 13)
    R.write_sketch(sk, str(tmp_path / "s"), "p1")
    back = R.read_sketch(spark, str(tmp_path / "s"), "p1")
    assert {(r["root"], tuple(r["cw"])) for r in sk.collect()} == {(r["root"], tuple(r["cw"])) for r in back.collect()}


def test_signatures_back_to_rows(spark, sf):
    o = spark.read.parquet(f"{sf}/orders.parquet")
    assert G.rows_of(o, G.mix32("o_orderkey"), o.limit(3).select(G.mix32("o_orderkey").alias("sig"))).count() == 3
    assert o.select(G.row_hash256(["o_orderkey"]).alias("h")).distinct().count() == o.count()
    assert G.dictionary(o, G.mix32("o_orderkey"), ["o_orderkey"]).count() == o.count()


def test_plan_shape(spark, sf):
    """No Python above the row scan, a partial aggregate below the exchange, only the key column read."""
    o = spark.read.parquet(f"{sf}/orders.parquet")
    p = published(100)
    sk = S.encode(S.with_node(S.with_inst(o.select(G.mix32("o_orderkey").alias("sig"))), p, None, 0).withColumn("bin", S.bin_of(p, 1)), S.NODE, p.m, p.t)
    plan = sk._jdf.queryExecution().executedPlan().toString()
    assert "partial_bit_xor" in plan and "ReadSchema: struct<o_orderkey:bigint>" in plan and "Python" not in plan and "Arrow" not in plan


def test_seeds_differ():
    seen = {H.seed_of(p, i, s) for p in range(7) for i in range(50) for s in range(3)}
    assert len(seen) == 7 * 50 * 3


def _many(spark, per):
    """Instances inst -> (a, b) as two frames (inst, sig)."""
    return tuple(spark.createDataFrame([(i, s) for i, ab in per.items() for s in ab[k]], "inst long, sig long") for k in (0, 1))


def test_baselines_say_where_they_fail(spark):
    """Each baseline is given too little room for one instance of two: the other is right, the failure is flagged, and completion makes the result whole."""
    per = {1: (range(1, 300), range(4, 300)), 2: (range(1, 300), range(80, 310))}
    a, b = _many(spark, per)
    want = {i: {(s, "A_only") for s in set(x) - set(y)} | {(s, "B_only") for s in set(y) - set(x)} for i, (x, y) in per.items()}
    of = lambda df, i: {(r["sig"], r["side"]) for r in df.where(f"inst = {i}").collect()}
    found, status = Y.whole_syndrome_checked(a, b, 10)
    assert of(found, 1) == want[1] and of(found, 2) == set() and {r["inst"]: r["ok"] for r in status.collect()} == {1: True, 2: False}
    whole = Y.whole_syndrome(a, b, 10, complete=True)
    assert all(of(whole, i) == want[i] for i in want)
    for grouped in (False, True):
        found, stalled = C.cell_digest_checked(a, b, 12, grouped)
        assert [r["inst"] for r in stalled.collect()] == [2] and of(found, 1) == want[1] and of(found, 2) != want[2]
        whole = C.cell_digest(a, b, 12, grouped, complete=True, doublings=1)
        assert all(of(whole, i) == want[i] for i in want)
    capped, log = Y.grouped_syndrome(a, b, Params(g=2, t=6, max_rounds=1))
    assert [r["inst"] for r in Y.unresolved(log).collect()] == [2] and of(capped, 1) == want[1]
    whole, log = Y.grouped_syndrome(a, b, Params(g=2, t=6))
    assert Y.unresolved(log).isEmpty() and all(of(whole, i) == want[i] for i in want)


def test_checksum_refuses_wrong_differences(spark):
    a, b = _many(spark, {1: (range(1, 20), range(3, 20)), 2: (range(1, 20), range(2, 20))})
    claim = spark.createDataFrame([(1, 1, "A_only"), (1, 2, "A_only"), (2, 7, "A_only")], "inst long, sig long, side string")
    assert [r["inst"] for r in Y.verified(a, b, claim, ["inst"]).collect()] == [1]


def test_filter_passes_by_brute_force(spark, monkeypatch):
    """What passes is what the set bits say, with the message broadcast or joined by shuffle, over several buckets; the set is neither exploded nor grouped."""
    x, y = sets(spark, range(1, 3000), range(1, 3000, 3))
    bits, k = 100_000, 3
    message = C.filter_message(y, bits, k)
    assert message.count() == 4
    on = {r["pos"] for r in C.filter_rows(y, bits, k).collect()}
    at = {r["sig"]: set(r["p"]) for r in x.select("sig", C.filter_positions(bits, k).alias("p")).collect()}
    want = {s for s, p in at.items() if p <= on}
    assert set(range(1, 3000, 3)) <= want
    for most in (64 << 20, 0):
        monkeypatch.setattr(C, "BROADCAST_BYTES", most)
        df = C.passes(x, message, bits, k)
        assert {r["sig"] for r in df.collect()} == want
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert "Generate" not in plan and "Aggregate" not in plan


def test_hash_tree_follows_the_count(spark):
    x = sets(spark, range(1, 2001), [1])[0]
    leaves = V.merkle_leaves(x).collect()
    assert len(leaves) == 8 == V.leaves_for(x)
    with pytest.raises(ValueError, match="levels"):
        V.merkle_root(x, leaves=65, levels=1)
