"""The near linear whole-set code against definitions, and with thousands of differences."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from setdiff.functions import poly32 as L
from setdiff.functions.gf import mul32
from setdiff.operators import syndromes as Y
from setdiff.queries import registry


def some(n, seed=1, most=1 << 32):
    x = np.unique(np.random.default_rng(seed).integers(1, most, 2 * n, dtype=np.uint64))
    return np.random.default_rng(seed).permutation(x)[:n]


def sums(x, t):
    out, p, sq = [], x, mul32(x, x)
    for _ in range(t):
        out.append(np.bitwise_xor.reduce(p))
        p = mul32(p, sq)
    return np.array(out)


def test_field_and_transforms():
    x, y = some(500), some(500, 2)
    a, b = L.to_tower(x), L.to_tower(y)
    assert (L.from_tower(L.mul(a, b)) == mul32(x, y)).all() and (L.mul(L.inverse(a), a) == 1).all() and (L.square(a) == L.mul(a, a)).all()
    assert not L.mul(a, np.zeros_like(a)).any()
    for m in range(9):
        f = L.to_tower(some(3 << m)).reshape(3, 1 << m)
        assert (L.to_plain(L.to_novel(f)) == f).all() and (L.interpolate(L.transform(f)) == f).all()
        g = L.multiply(f, f[::-1])
        want = np.zeros_like(g)
        for i in range(1 << m):
            want[:, i : i + (1 << m)] ^= L.mul(f[:, i : i + 1], f[::-1])
        assert (g == want).all()


@pytest.mark.parametrize("n,t", [(1, 1), (1, 9), (2, 2), (3, 40), (64, 64), (100, 138), (700, 800)])
def test_power_sums_and_what_they_tell(n, t):
    for most in (1 << 32, 4 * n + 4):
        x = some(n, most=most)
        odd = L.odd_power_sums(L.to_tower(x)[None], t)[0]
        assert (L.from_tower(odd) == sums(x, t)).all()
        assert sorted(L.from_tower(L.decode(odd)).tolist()) == sorted(x.tolist())


def test_over_capacity_is_seen():
    for n, t in ((11, 10), (50, 20), (300, 200)):
        assert L.decode(L.odd_power_sums(L.to_tower(some(n))[None], t)[0]) is None


def test_instances_by_pieces(spark, monkeypatch):
    """Several instances over the direct capacity: split into pieces, one equal, one with too many differences."""
    monkeypatch.setattr(Y, "DIRECT", 20)
    monkeypatch.setattr(Y, "PIECE", 16)
    ids = spark.range(900).select((F.col("id") % 3).alias("inst"), (F.pmod(F.xxhash64("id"), F.lit((1 << 32) - 1)) + 1).alias("sig"), F.col("id"))
    a, b = ids.select("inst", "sig"), ids.where("inst = 0 or inst = 1 and id > 150 or inst = 2 and id > 600").select("inst", "sig")
    found, status = Y.whole_syndrome_checked(a, b, 70)
    assert {r["inst"]: r["ok"] for r in status.collect()} == {0: True, 1: True, 2: False}
    want = {(r["inst"], r["sig"], "A_only") for r in ids.where("inst = 1 and id <= 150").collect()}
    assert {tuple(r) for r in found.collect()} == want and len(want) == 50
    assert Y.whole_syndrome(a, b, 70, complete=True).count() == 50 + ids.where("inst = 2 and id <= 600").count()


def test_thousands_of_differences_in_time(spark, tmp_path):
    """5,000 differences: minutes with quadratic decoding."""
    import duckdb

    rows = spark.range(40_000).select((F.col("id") % 20_000).alias("l_partkey"), F.expr("make_date(1996 + cast(id >= 20000 as int), 5, 1)").alias("l_shipdate"))
    rows.where("pmod(xxhash64(l_partkey, l_shipdate), 8) <> 0").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    run, sql = registry()["whole_syndrome_w5"]
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{tmp_path}/lineitem.parquet/*.parquet'")
    want = con.execute(sql).fetchall()
    start = time.perf_counter()
    got = [tuple(r) for r in run(spark, str(tmp_path)).collect()]
    assert len(want) > 4000 and sorted(got) == sorted(want)
    assert time.perf_counter() - start < 120
