"""Language ID, line rules, BPE, PU quality: row by row operators."""

import base64
import hashlib
import random

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F

from setdiff.llm import bpe, langid, line_rules, pu_quality
from setdiff.llm.common import id_crc_mod

from .conftest import ODD

PATH = P.path("byte_bpe_multi_50k.tiktoken")


# Language ID


def test_codewords_are_apart():
    for n in (2, 3, 4, 5, 8, 20):
        c = langid.codewords(n)
        assert len(c) == n and set(np.unique(c)) <= {-1.0, 1.0}
        assert min((c[i] != c[j]).sum() for i in range(n) for j in range(i)) >= (1 if n == 2 else 2 ** (n - 2) if n <= 5 else 5)


def test_blocks_count_like_one():
    text = "Straße und Über " * 200
    whole = langid.ngram_counts(text)
    block, langid.BLOCK = langid.BLOCK, 50
    try:
        assert (langid.ngram_counts(text) == whole).all()
    finally:
        langid.BLOCK = block


def test_languages_held_out(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.fit(d, id_crc_mod("doc_id", 4) != 2)
    out = langid.identify(d, model).where(id_crc_mod("doc_id", 4) == 2).select((F.col("lang") == F.col("lang_pred")).cast("double").alias("ok")).agg(F.avg("ok")).first()[0]
    assert out >= 0.97


def test_language_edge_cases(spark, docs):
    rows = docs(*ODD)
    train = docs(*[(i, "the cat and the dog sat", "en") for i in range(9)], *[(20 + i, "der Hund und die Katze", "de") for i in range(9)])
    model = langid.fit(train, F.lit(True))
    out = langid.identify(rows.withColumn("lang_pred", F.lit("clash")), model).collect()
    assert len(out) == len(ODD) and {r["lang_pred"] for r in out if r["doc_id"] in (1, 2, 3, 4)} == {"und"}
    assert all(0 <= r["lang_score"] <= 1 for r in out) and model.predict("die Katze und der Hund")[0] == "de"
    nothing = langid.fit(train.limit(0), F.lit(True))
    assert nothing.predict("text") == ("und", 0.0, True)
    assert langid.fit(train.where("lang = 'en'"), F.lit(True)).predict("text")[:2] == ("en", 1.0)
    assert langid.identify(rows.limit(0), model).count() == 0


def test_ambiguity_is_flagged(docs):
    train = docs(*[(i, "the cat and the dog sat on that mat", "en") for i in range(9)], *[(20 + i, "der Hund und die Katze sind nicht hier", "de") for i in range(9)])
    model = langid.fit(train, F.lit(True))
    model.gap = 10.0
    assert model.predict("the dog")[2]
    model.gap = 0.0
    assert not model.predict("the dog")[2]


# Line rules


def _brute(text):
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    hit = {i + k for i, w in enumerate(windows) if windows.count(w) > 1 for k in range(8)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), sum(x in lines[:i] for i, x in enumerate(lines)), len(hit)


def test_base_counts():
    rng = random.Random(3)
    texts = [None, "", "a b\xa0c\x85d\x1ce", "é ü\n\né ü\n", *(" ".join(rng.choice("ab c# é|".split()) for _ in range(60)) for _ in range(30))]
    for t in texts:
        assert line_rules.judge(t)[:5] == _brute(t)


GOOD = "This is a sentence with some words in it. Here is another one, longer than the first.\nAnd a second line follows, with words of its own.\n"


@pytest.mark.parametrize(
    ("line", "rule"),
    [("LOOK!! AT!! THIS!! NOW!!", "punctuation"), ("a### b$$$ c%%% d", "punctuation"), ("one two three four five six seven eight", "punctuation"), ("Home - About - Contact", "navigation"), ("Licensed under the Apache License, Version 2.0.", "boilerplate"), ("A plain line.", None)],
)
def test_rules(line, rule):
    assert line_rules.line_fails(line.encode(), line.encode().split(), set()) == rule


def test_verdicts(docs):
    shout = "LOOK!! AT!! THIS!! " * 10
    rows = docs((1, GOOD), (2, shout + "\n" + GOOD[:30]), (3, None), (4, GOOD + "All rights reserved.\n"), (5, "same line of words here.\n" * 30))
    out = {r["doc_id"]: r for r in line_rules.clean_lines(rows).collect()}
    assert out[1]["kept"] and out[1]["clean_text"] == GOOD
    assert not out[2]["kept"] and not out[3]["kept"] and out[3]["base_failed"]
    assert out[4]["kept"] and "rights" not in out[4]["clean_text"] and not out[5]["kept"]


def test_line_rules_edge_cases(docs):
    out = line_rules.clean_lines(docs(*ODD)).collect()
    assert len(out) == len(ODD) and line_rules.clean_lines(docs(*ODD).limit(0)).count() == 0
    assert not any(r["kept"] for r in out)


def test_line_rules_match_sql(spark, sf, duck):
    from setdiff.llm.sql import LINE_RULES

    df = line_rules.clean_lines(spark.read.parquet(f"{sf}/documents.parquet"), with_text=False)
    cur = duck.execute(LINE_RULES)
    names = [c[0] for c in cur.description]
    assert sorted(map(repr, (tuple(r[n] for n in names) for r in df.collect()))) == sorted(map(repr, cur.fetchall()))


# BPE


@pytest.fixture(scope="module")
def vocabulary():
    return bpe.Vocabulary(PATH, P.PATTERN)


@pytest.fixture(scope="module")
def library(vocabulary):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=vocabulary.ranks, special_tokens={})


def test_bitmap():
    m, held, rng = bpe.RankBitmap(50_256), set(), random.Random(1)
    for _ in range(4000):
        x = rng.randrange(50_256)
        (m.add, held.add)[0](x) if rng.random() < 0.6 else m.discard(x)
        held.add(x) if m.low[x >> 6] >> (x & 63) & 1 else held.discard(x)
        assert m.first() == min(held, default=-1)


def test_pieces_like_the_library(vocabulary, library):
    rng = random.Random(5)
    pieces = ["".join(rng.choice("ab aéñ漢字ther") for _ in range(rng.randint(1, 40))).encode() for _ in range(1500)] + [b"a" * n for n in range(1, 120)] + [bytes(rng.choices(range(256), k=20)) for _ in range(400)]
    want = [[vocabulary.ranks[p]] if p in vocabulary.ranks else library._core_bpe.encode_single_piece(p) for p in pieces]
    assert [vocabulary.merge_one(p) for p in pieces] == want
    many = vocabulary.merge_many(pieces)
    assert all(g == w for p, g, w in zip(pieces, many, want, strict=True) if p not in vocabulary.ranks)
    assert vocabulary.merge_many([]) == [] and vocabulary.merge_many([b""]) == [[]]


def test_very_long_piece(vocabulary, library):
    text = "thering" * 30_000
    assert vocabulary.merge_one(text.encode()) == library.encode_ordinary(text)


def test_documents_like_the_library(spark, sf, docs, library):
    rows = spark.read.parquet(f"{sf}/documents.parquet").union(docs(*ODD, (9, "emoji 👩‍👩‍👧 ñandú x <|endoftext|>")))
    texts = rows.select("doc_id", "text").collect()
    out = bpe.encode_documents(rows, PATH, P.PATTERN).collect()
    want = sorted((str(r["doc_id"]), library.encode_ordinary(r["text"] or ""), hashlib.sha256((r["text"] or "").encode()).hexdigest()) for r in texts)
    assert sorted((str(r["doc_id"]), list(r["ids"]), r["decoded_sha256"]) for r in out) == want
    for r in out:
        assert r["ids_sha256"] == hashlib.sha256(",".join(map(str, r["ids"])).encode()).hexdigest() and r["n_tokens"] == len(r["ids"])
    assert bpe.encode_documents(rows.limit(0), PATH, P.PATTERN).count() == 0


def test_small_memory_gives_the_same(vocabulary, monkeypatch):
    texts = ["the cat sat on " * 5, "words of several kinds %d" % 3, None, "x" * 50] * 20
    want = list(bpe.Encoder(vocabulary).encode_all(texts))
    monkeypatch.setattr(bpe, "TOGETHER", 60)
    monkeypatch.setattr(bpe, "REMEMBERED", 5)
    monkeypatch.setattr(bpe, "FEW", 2)
    assert list(bpe.Encoder(vocabulary).encode_all(texts)) == want


def test_rank_file_reads_base64():
    with open(PATH, "rb") as f:
        a, b = f.readline().split()
    assert bpe.Vocabulary(PATH, P.PATTERN).ranks[base64.b64decode(a)] == int(b)


# PU quality


def test_prior_and_risk():
    rng = np.random.default_rng(4)
    pos = lambda n: np.hstack([rng.normal(2, 1, (n, 3)), np.ones((n, 1))])
    neg = lambda n: np.hstack([rng.normal(-2, 1, (n, 3)), np.ones((n, 1))])
    for share in (0.3, 0.8):
        u = np.vstack([pos(round(4000 * share)), neg(round(4000 * (1 - share)))])[rng.permutation(4000)]
        prior = pu_quality.estimate_prior(pos(1500), u)
        assert abs(prior - share) < 0.08
        w = pu_quality.nn_pu(pos(1500), u, prior)
        assert (pos(500) @ w > 0).mean() > 0.95 and (neg(500) @ w < 0).mean() > 0.95


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    d, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = pu_quality.fit(d, labels, id_crc_mod("doc_id", 5) != 0)
    out = pu_quality.score(d, model).join(labels, "doc_id").where(id_crc_mod("doc_id", 5) == 0).toPandas()
    good, bad = out[out.quality == 1].score.to_numpy(), out[out.quality == 0].score.to_numpy()
    assert (good[:, None] > bad[None, :]).mean() > 0.95 and ((out.score >= 0.3) == (out.quality == 1)).mean() > 0.9


def test_quality_edge_cases(docs, spark):
    labels = spark.createDataFrame([(5, 1, 0), (5, 0, 0), (None, 1, 0), (99, 1, 0)], "doc_id long, quality int, toxic int")
    rows = docs(*ODD)
    out = pu_quality.score(rows, pu_quality.fit(rows, labels, F.lit(True))).collect()
    assert len(out) == len(ODD) and all(0 <= r["score"] <= 1 for r in out)
    blind = pu_quality.fit(rows, labels.limit(0), F.lit(True))
    assert {r["score"] for r in pu_quality.score(rows, blind).collect()} == {0.5}
    assert pu_quality.score(rows.limit(0), blind).count() == 0
    assert np.isfinite(pu_quality.features(None)).all()
