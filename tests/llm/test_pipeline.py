"""The pipeline's stages do what they say, one after the other."""

import random

from pyspark.sql import functions as F

import corpus_pipeline as cp


def test_stage_names_and_order():
    assert [n for n, _ in cp.STAGES] == ["language_id", "simhash_near_dedup", "suffix_array_dedup", "benchmark_decontamination", "byte_bpe"]


def test_whole_run(spark, sf):
    """Copies, letterless texts, leaks and repeated passages go; clean documents stay with their own text."""
    d = spark.read.parquet(f"{sf}/documents.parquet")
    item = spark.read.parquet(f"{sf}/benchmark.parquet").where("item_id = 3").first()["text"]
    rng = random.Random(7)
    vocab = [r["text"] for r in d.where("lang = 'en'").limit(5).collect()]
    words = " ".join(vocab).split()
    text = lambda n: " ".join(rng.choice(words) for _ in range(n)) + "."
    clean, passage = text(80), text(90)
    extra = [(9001, clean), (9002, clean), (9003, "12345 !!! 678"), (9004, text(60) + "\n" + item + "\n" + text(60)), (9005, text(70) + "\n" + passage + "\n" + text(70)), (9006, text(75) + "\n" + passage + "\n" + text(65)), (9007, None)]
    docs = d.union(spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in extra], d.schema))
    left = docs
    steps = {}
    for name, stage in cp.STAGES:
        left = cp.keep(stage(spark, left, sf), name)
        steps[name] = {r["doc_id"]: r for r in left.where("doc_id > 9000").collect()}
        if name != "byte_bpe":
            assert left.columns == docs.columns
    assert set(steps["language_id"]) == {9001, 9002, 9004, 9005, 9006}
    assert set(steps["simhash_near_dedup"]) == {9001, 9004, 9005, 9006}
    assert steps["suffix_array_dedup"][9001]["text"] == clean and passage[20:-20] not in steps["suffix_array_dedup"][9005]["text"]
    assert steps["suffix_array_dedup"][9005]["n_chars"] == len(steps["suffix_array_dedup"][9005]["text"])
    assert set(steps["benchmark_decontamination"]) == {9001, 9005, 9006} == set(steps["byte_bpe"])
    assert left.count() == left.select("doc_id").distinct().count()


def test_clashing_columns_stay(spark, sf, docs):
    """Columns that bear the names of the stages' own come out as they went in."""
    names = ["_text", "_gone", "_row", "_a", "_all", "_new", "t1", "t2", "raw", "fp", "component_id", "lang_pred", "lang_ambiguous", "text_crc32", "a.b"]
    rows = spark.read.parquet(f"{sf}/documents.parquet")
    item = spark.read.parquet(f"{sf}/benchmark.parquet").where("item_id = 3").first()["text"]
    extra = rows.schema.names
    given = rows.union(docs((9001, "before " + item + " after"), (9002, None)).select(*extra))
    for n in names:
        given = given.withColumn(n, F.concat(F.lit(n), F.col("doc_id").cast("string")))
    for name, stage in cp.STAGES[:-1]:
        left = cp.keep(stage(spark, given, sf), name)
        assert left.columns == given.columns and left.schema.simpleString() == given.schema.simpleString()
        assert 0 < left.count() <= given.count()
        wrong = [F.col(f"`{n}`") != F.concat(F.lit(n), F.col("doc_id").cast("string")) for n in names]
        assert left.where(F.array_contains(F.array(*wrong), True)).count() == 0
    assert cp.STAGES[-1][1](spark, given, sf).count() == given.count()


def test_registered():
    import __spark_entry__ as e

    q = e.queries()
    assert {f"op{n}" for n in range(1, 11)} <= {k.split("_")[0] for k in q} and "pipeline" in q
