"""Streams give what batches give; duplicates don't flip parities; late events show up as differences; SQL surface."""

import uuid

from pyspark.sql import functions as F

from setdiff.functions.sql import register, sdiff
from setdiff.plans.params import published
from setdiff.streaming import sketches as K


def _run(spark, df, mode="complete"):
    name = f"t_{uuid.uuid4().hex}"
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def test_stream_equals_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    path = str(tmp_path / "in")
    events.union(events.limit(50)).coalesce(1).write.parquet(path)
    p = published(50)
    batch = {r["root"]: (list(r["cw"]), r["chk"], r["cnt"]) for r in K.sketch(K.signed_events(events, None), p).collect()}
    streamed = _run(spark, K.sketch(K.signed_events(K.read_events(spark, path), "60 days"), p))
    assert {r["root"]: (list(r["cw"]), r["chk"], r["cnt"]) for r in streamed.collect()} == batch
    tow = _run(spark, K.tow_stream(K.signed_events(K.read_events(spark, path), "60 days"))).first()
    assert tow["n"] == events.count() and len(tow["y"]) == 64


def test_merge_is_additive(spark, sf):
    e, p = K.signed_events(spark.read.parquet(f"{sf}/events.parquet"), None), published(50)
    whole = {r["root"]: (list(r["cw"]), r["chk"], r["cnt"]) for r in K.sketch(e, p).collect()}
    parts = K.merge_sketches(K.sketch(e.where("event_id % 2 = 0"), p), K.sketch(e.where("event_id % 2 = 1"), p))
    assert {r["root"]: (list(r["cw"]), r["chk"], r["cnt"]) for r in parts.collect()} == whole


def test_late_events_are_differences(spark, sf):
    from setdiff.operators.rounds import reconcile

    e = K.signed_events(spark.read.parquet(f"{sf}/events.parquet"), None).select("sig")
    seen = e.where("sig % 100 <> 0")
    got = reconcile(e, seen, published(10))
    assert {r["sig"] for r in got.a_only.collect()} == {r["sig"] for r in e.where("sig % 100 = 0").collect()}


def test_windows(spark, sf):
    e = K.signed_events(spark.read.parquet(f"{sf}/events.parquet"), None)
    n = e.count()
    assert K.windowed(e).agg(F.sum("n")).first()[0] == n
    assert K.windowed(e, "sliding").agg(F.sum("n")).first()[0] == 4 * n
    assert K.windowed(e, "session").agg(F.sum("n")).first()[0] == n


def test_stateful_operator(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    path = str(tmp_path / "in")
    events.coalesce(1).write.parquet(path)
    p = published(50)
    want = {r["root"]: (r["chk"], r["cnt"]) for r in K.sketch(K.signed_events(events, None), p).collect()}
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        df = K.stateful_sketch(K.signed_events(K.read_events(spark, path), "60 days"), p)
        rows = _run(spark, df, "update").collect()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)
    last = {}
    for r in rows:
        if r["cnt"] >= last.get(r["root"], (0, 0))[1]:
            last[r["root"]] = (r["chk"], r["cnt"])
    assert last == want


def test_sql_surface(spark, sf):
    register(spark)
    assert spark.sql("select gf_mul(3L, 7L, 7L) as x").first()["x"] == 9
    assert spark.sql("select count(*) as n from antilog_table(7)").first()["n"] == 127
    assert spark.sql("select sum(p) as s from transition_matrix(127, 5)").first()["s"] > 5.99
    assert spark.sql("select count(*) as n from tuning_grid(100, 5, 3, 0.99D) where feasible").first()["n"] > 10
    from setdiff.functions.gf import packed_table

    a = ",".join(f"{int(x)}L" for x in packed_table(7, 13)[:, 5])
    assert [r["bin"] for r in spark.sql(f"select * from decode_bins(array({a}), array(0L, 0L), 7, 13)").collect()] == [5]
    spark.range(1, 100).selectExpr("id as sig").createOrReplaceTempView("va")
    spark.range(3, 103).selectExpr("id as sig").createOrReplaceTempView("vb")
    assert sdiff(spark, "va", "vb").count() == 5
