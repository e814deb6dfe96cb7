"""The pipeline's near-dedup stage: linked exactly at five-word shingles and similarity 0.8, one row of each group kept."""

import random

import numpy as np
import pytest

import corpus_pipeline as cp
from pyspark.sql import functions as F

from setdiff.llm import near_copies as N

VOCAB = [f"{a}{b}" for a in "ba de fi go ku".split() for b in "lam nor set vik wun zop".split()]


def _edited(rng, words, edits):
    out = list(words)
    for at in rng.sample(range(len(out)), edits):
        out[at] = f"x{rng.random()}"
    return out


def _jaccard(a, b):
    a, b = N.shingle_set(" ".join(a)), N.shingle_set(" ".join(b))
    both = len(np.intersect1d(a, b))
    return both / (len(a) + len(b) - both)


def _pairs(n, seed=1):
    """Pairs of texts of similarity 0.8 and up to 0.84."""
    rng, out = random.Random(seed), []
    while len(out) < n:
        words = [f"{rng.choice(VOCAB)}{rng.randrange(200)}" for _ in range(rng.choice((60, 100, 200, 400)))]
        other = _edited(rng, words, max(1, round(len(words) * 0.0225)))
        if 0.8 <= _jaccard(words, other) <= 0.84:
            out.append((words, other))
    return out


def test_keys_find_pairs_at_the_similarity():
    """Of the pairs at 0.8 to 0.84, none is lost by the keys or by the share of equal minima."""
    lost = 0
    for a, b in _pairs(300):
        x, y = (np.frombuffer(N.minima(N.shingle_set(" ".join(t))), "<u2") for t in (a, b))
        same = x == y
        lost += not (same.reshape(N.BANDS, N.ROWS).all(1).any() and same.sum() >= N.LEAST)
    assert lost == 0


@pytest.mark.parametrize("chunk", [512, 3])
def test_stage_drops_near_copies_at_the_similarity(spark, sf, docs, monkeypatch, chunk):
    """Near copies at 0.8 go, texts below 0.8 stay: held against all pairs."""
    monkeypatch.setattr(N, "CHUNK", chunk)
    monkeypatch.setattr(N, "BUCKET", max(chunk, 4))
    rng = random.Random(3)
    texts = []
    for k in range(12):
        base = [f"{rng.choice(VOCAB)}{rng.randrange(200)}" for _ in range((30, 100, 200, 400)[k % 4])]
        texts += [base, *(_edited(rng, base, max(1, round(len(base) * share))) for share in (0.01, 0.015, 0.02, 0.0225, 0.03, 0.06))]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if _jaccard(texts[i], texts[j]) >= 0.8:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    given = docs(*((i, " ".join(t)) for i, t in enumerate(texts)))
    left = {r["doc_id"] for r in dict(cp.STAGES)["simhash_near_dedup"](spark, given, sf).collect()}
    assert left == set(root) and 12 < len(left) < len(texts)


def test_one_row_of_repeated_rows_and_null_ids_stays(spark, sf, docs):
    """A repeated row and a copy without an id leave one row each after near-dedup, and the suffix stage then keeps the text."""
    rng = random.Random(5)
    text = lambda: " ".join(f"{rng.choice(VOCAB)}{rng.randrange(200)}" for _ in range(120))
    twice, named, nameless, alone = text(), text(), text(), text()
    given = docs((1, twice), (1, twice), (None, named), (2, named), (None, nameless), (None, nameless), (None, alone), (3, None))
    assert min(map(len, (twice, named, nameless, alone))) > 400
    stages = dict(cp.STAGES)
    once = cp.keep(stages["simhash_near_dedup"](spark, given, sf), "once")
    want = sorted([(1, twice), (2, named), (3, None), (None, nameless), (None, alone)], key=str)
    assert sorted(((r["doc_id"], r["text"]) for r in once.collect()), key=str) == want
    assert sorted(((r["doc_id"], r["text"]) for r in stages["suffix_array_dedup"](spark, once, sf).collect()), key=str) == want


def test_stage_finds_near_copies_by_their_fingerprints(spark, sf, docs, monkeypatch):
    """With the min-hash candidates away, near fingerprints still bring copies together, and the exact test still decides."""
    rng = random.Random(8)
    text = lambda: [f"{rng.choice(VOCAB)}{rng.randrange(200)}" for _ in range(1500)]
    a, b = text(), text()
    given = docs((1, " ".join(a)), (2, " ".join([*a, "more"])), (3, " ".join(b)), (4, " ".join(["first", *b])), (5, " ".join(text())))
    monkeypatch.setattr(N, "candidates", lambda nodes: nodes.select(F.col("node").alias("a"), F.col("node").alias("b")).limit(0))
    left = {r["doc_id"] for r in dict(cp.STAGES)["simhash_near_dedup"](spark, given, sf).collect()}
    assert left == {1, 3, 5}
