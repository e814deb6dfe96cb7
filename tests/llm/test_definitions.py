"""Language codes, positive-unlabelled risk and Hilbert order against their definitions, worked out one value at a time."""

import math
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from setdiff.llm import hilbert, langid, pu_quality
from setdiff.llm.common import id_crc_mod, keep

# Language ID


def _ngrams(text):
    letters = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in text.lower().encode("utf-8", "replace"))
    raw, out = b" " + b" ".join(letters.split()) + b" ", Counter()
    for k in (1, 2, 3, 4):
        for i in range(len(raw) - k + 1):
            h = 0
            for c in raw[i : i + k]:
                h = (h * 257 + c + 1) % 2**32
            out[((h * 2654435761 % 2**32) ^ (k * 0x5BD1E995 % 2**32)) >> 18] += 1
    return out


def test_languages_by_definition(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").where(F.length("text") < 6000)
    train = id_crc_mod("doc_id", 4) != 2
    model = langid.fit(docs, train)
    draw = F.pmod(F.xxhash64("doc_id", F.lit("language sample")), F.lit(1 << 20)) / F.lit(1 << 20)
    rows = docs.select("doc_id", "text", "lang", draw.alias("u"), F.coalesce(train, F.lit(False)).alias("train")).collect()
    grams = {r["doc_id"]: _ngrams(r["text"]) for r in rows if r["text"] is not None}
    usable = [r for r in rows if r["train"] and r["lang"] is not None and r["text"] is not None]
    langs = sorted({r["lang"] for r in usable})
    assert model.langs == langs and max(Counter(r["lang"] for r in usable).values()) <= 3000
    total = {v: Counter() for v in langs}
    for r in usable:
        if r["u"] < 0.5:
            total[r["lang"]] += grams[r["doc_id"]]
    freq = {v: [(c[b] + 0.5) / (sum(c.values()) + 0.5 * langid.BUCKETS) for b in range(langid.BUCKETS)] for v, c in total.items()}
    bits = range(model.code.shape[1])
    assert len({tuple(word) for word in model.code.tolist()}) == len(langs)

    def mean(bit, sign, b):
        some = [freq[v][b] for v, word in zip(langs, model.code, strict=True) if word[bit] == sign]
        return sum(some) / len(some)

    weights = [[math.log(mean(j, 1, b)) - math.log(mean(j, -1, b)) for j in bits] for b in range(langid.BUCKETS)]
    margin = lambda c: [sum(n * weights[b][j] for b, n in c.items()) / max(sum(c.values()), 1) for j in bits]
    margins = {d: margin(c) for d, c in grams.items()}
    tried = [r for r in usable if r["u"] >= 0.5]
    trust = {}
    for v, word in zip(langs, model.code, strict=True):
        mine = [margins[r["doc_id"]] for r in tried if r["lang"] == v]
        right = [(sum(f[j] * word[j] > 0 for f in mine) + 1) / (len(mine) + 2) for j in bits]
        trust[v] = [x / sum(right) for x in right]
    scale = [4 / (sum(abs(margins[r["doc_id"]][j]) for r in tried) / len(tried)) for j in bits]
    got = {r["doc_id"]: r for r in langid.identify(docs, model).collect()}
    for r in rows:
        mine = got[r["doc_id"]]
        if r["text"] is None or not any(c.isalpha() for c in r["text"]):
            assert (mine["lang_pred"], mine["lang_score"], mine["lang_ambiguous"]) == (langid.UNDETERMINED, 0.0, True)
            continue
        loss = {v: sum(t * math.log1p(math.exp(-w * f * s)) for t, w, f, s in zip(trust[v], word, margins[r["doc_id"]], scale, strict=True)) for v, word in zip(langs, model.code, strict=True)}
        first, second = sorted(loss.values())[:2]
        assert loss[mine["lang_pred"]] == pytest.approx(first, abs=1e-9)
        assert mine["lang_score"] == pytest.approx(1 / sum(math.exp(2 * (first - x)) for x in loss.values()), abs=1e-6)
        assert mine["lang_ambiguous"] == (second - first < model.gap) or abs(second - first - model.gap) < 1e-6


# Positive-unlabelled quality


@pytest.mark.parametrize("prior", [0.2, 0.6])
def test_gradient_of_the_risk_by_differences(monkeypatch, prior):
    rng = np.random.default_rng(5)
    p, u = rng.normal(0.7, 1, (40, 4)), rng.normal(-0.2, 1, (90, 4))
    monkeypatch.setattr(pu_quality, "_descend", lambda grad, n: grad)
    grad = pu_quality.nn_pu(p, u, prior)

    def softplus(z):
        return sum(math.log1p(math.exp(x)) for x in z.tolist()) / len(z)

    def parts(w):
        """What positives cost, and what negatives cost: unlabelled rows less the positives among them."""
        return prior * softplus(-(p @ w)), softplus(u @ w) - prior * softplus(p @ w)

    signs = set()
    for w in [*rng.normal(0, 0.5, (6, 4)), np.full(4, 2.0), np.full(4, 6.0), np.array([9.0, 9.0, -9.0, 9.0])]:
        below = parts(w)[1] < 0
        signs.add(below)
        # the step goes down the whole risk, and up the negative part where that is below zero
        f = (lambda x: -parts(x)[1]) if below else (lambda x: sum(parts(x)))
        want = [(f(w + e) - f(w - e)) / 2e-5 for e in 1e-5 * np.eye(4)]
        assert grad(w) == pytest.approx(want, abs=1e-6)
    assert False in signs and (prior < 0.5 or True in signs)


def test_prior_is_that_of_the_best_cut(monkeypatch):
    rng = np.random.default_rng(6)
    p = rng.normal(2, 1, (400, 1))
    u = np.concatenate([rng.normal(2, 1, (300, 1)), rng.normal(-2, 1, (700, 1))])[rng.permutation(1000)]
    monkeypatch.setattr(pu_quality, "_descend", lambda grad, n, steps: np.ones(1))
    back, rest = sorted(p[1::2, 0].tolist()), sorted(u[1::2, 0].tolist())
    best = (math.inf, 0.0)
    slack = math.sqrt(math.log(40) / 2 / len(back)) + math.sqrt(math.log(40) / 2 / len(rest))
    for cut in np.quantile(back, np.linspace(0, 0.9, 181)):
        kept = max(sum(x >= cut for x in back) / len(back), 1e-9)
        ratio = sum(x >= cut for x in rest) / len(rest) / kept
        best = min(best, (ratio + slack / kept, ratio))
    got = pu_quality.estimate_prior(p, u)
    assert got == pytest.approx(best[1], abs=1e-9) and abs(got - 0.3) < 0.08


def test_score_is_the_sigmoid_of_the_sum(docs):
    rng = np.random.default_rng(7)
    n = pu_quality.N_FEATURES
    model = pu_quality.QualityModel(rng.normal(0, 0.1, n), rng.uniform(0.5, 2, n), rng.normal(0, 0.2, n + 1), 0.4)
    texts = [(1, "Some plain words. Then more!"), (2, None), (3, "| # | $$ 12\n\n12"), (4, "é" * 300)]
    got = {r["doc_id"]: r["score"] for r in pu_quality.score(docs(*texts), model).collect()}
    for doc, text in texts:
        x = pu_quality.features(text)
        z = model.weights[n] + sum((x[i] - model.mean[i]) / model.dev[i] * model.weights[i] for i in range(n))
        assert got[doc] == pytest.approx(1 / (1 + math.exp(-z)))


# Hilbert order


@pytest.mark.parametrize(("dims", "bits"), [(2, 4), (3, 3), (4, 2)])
def test_curve_by_definition(spark, dims, bits):
    """Every cell once, neighbours one step apart, and at every scale a run of the curve fills one cube."""
    levels = [f"l{i}" for i in range(dims)]
    cells = spark.range(1 << dims * bits).select(*[F.shiftright("id", bits * i).bitwiseAND(F.lit((1 << bits) - 1)).cast("int").alias(c) for i, c in enumerate(levels)])
    got = sorted((r["at"], tuple(r[c] for c in levels)) for r in cells.withColumn("at", hilbert.curve_index(levels, bits)).collect())
    assert [at for at, _ in got] == list(range(1 << dims * bits))
    assert all(sum(abs(x - y) for x, y in zip(a, b, strict=True)) == 1 for (_, a), (_, b) in zip(got, got[1:], strict=False))
    for k in range(1, bits):
        cube = {}
        for at, cell in got:
            assert cube.setdefault(at >> dims * k, tuple(x >> k for x in cell)) == tuple(x >> k for x in cell)


def test_ranks_by_sorting(spark, monkeypatch):
    """A third of the rows lie in one cell, ties and null ids among them; slices are small enough to cut every cell."""
    monkeypatch.setattr(hilbert, "SLICES", 8)
    n, bits, levels = 900, 2, ["x", "y"]
    rows = [(None if i % 50 == 0 else i % 700, i, 1 if i % 3 == 0 else i % 4, 2 if i % 3 == 0 else i // 7 % 4) for i in range(n)]
    df = keep(spark.createDataFrame(rows, "doc_id long, row long, x int, y int"), "ranks")
    tie = F.pmod(F.xxhash64("doc_id", "row"), F.lit(1 << 20)).alias("h")
    known = df.select("*", tie, hilbert.curve_index(levels, bits).alias("curve")).collect()
    held = Counter((r["x"], r["y"]) for r in known)
    per_slice = max(1, math.ceil(n / 8))
    assert max(held.values()) > 2 * per_slice
    key = lambda r: (r["curve"], r["h"] * math.ceil(held[r["x"], r["y"]] / per_slice) >> 20, -1 if r["doc_id"] is None else r["doc_id"], r["row"])
    want = {r["row"]: i for i, r in enumerate(sorted(known, key=key))}
    ranked = hilbert.hilbert_order(df, levels, bits, ["doc_id", "row"])
    got = hilbert.cut_runs(ranked, n, 7).collect()
    assert {r["row"]: r["rank"] for r in got} == want
    edges = [math.ceil(n * s / 7) for s in range(8)]
    for r in got:
        s = max(s for s in range(7) if edges[s] <= r["rank"])
        assert (r["shard"], r["slot"]) == (s, r["rank"] - edges[s])
