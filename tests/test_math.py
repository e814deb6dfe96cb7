"""Field arithmetic, decoder, probabilistic model, tuner: against brute force and printed numbers."""

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from setdiff.functions import gf
from setdiff.functions.hashing import portable_text
from setdiff.operators import syndromes as Y
from setdiff.operators.decode import decode
from setdiff.plans import model as M
from setdiff.plans import tune as T
from setdiff.queries import GOLDEN


@pytest.mark.parametrize("m", [6, 7, 8, 11])
def test_field(m):
    f = gf.field(m)
    assert len(set(f.exp.tolist())) == f.n == 2**m - 1
    rng = np.random.default_rng(m)
    a, b, c = rng.integers(0, f.n + 1, (3, 200))
    assert (f.mul(a, b ^ c) == f.mul(a, b) ^ f.mul(a, c)).all()
    assert (f.div(f.mul(a, b), np.where(b == 0, 1, b)) == np.where(b == 0, 0, a)).all()


def test_large_field():
    x = np.random.default_rng(0).integers(1, 2**32, 300).astype(np.uint64)
    y, z = np.roll(x, 1), np.roll(x, 2)
    assert (gf.mul32(x, gf.inv32(x)) == 1).all()
    assert (gf.mul32(x, y ^ z) == gf.mul32(x, y) ^ gf.mul32(x, z)).all()
    assert gf.mul32(np.uint64(1 << 31), np.uint64(2)) == 0x8D


def test_decoder_all_small_patterns():
    table = gf.packed_table(6, 3)
    sets = [c for k in range(4) for c in itertools.combinations(range(0, 63, 4), k)]
    words = np.array([np.bitwise_xor.reduce(table[:, list(s)], axis=1) if s else np.zeros(len(table), np.int64) for s in sets])
    ok, bins = decode(words, 6, 3)
    assert ok.all() and all(tuple(b) == s for b, s in zip(bins, sets, strict=True))


@settings(max_examples=25, deadline=None)
@given(st.sampled_from([(6, 8), (7, 13), (8, 10), (9, 9)]), st.randoms(use_true_random=False))
def test_solvers_agree(mt, rnd):
    m, t = mt
    table, n = gf.packed_table(m, t), 2**m - 1
    sets = [rnd.sample(range(n), rnd.randint(0, t)) for _ in range(6)]
    words = np.array([np.bitwise_xor.reduce(table[:, s], axis=1) if s else np.zeros(len(table), np.int64) for s in sets])
    for solver in ("bm", "toeplitz", "gauss"):
        ok, bins = decode(words, m, t, solver)
        assert ok.all() and all(set(b) == set(s) for b, s in zip(bins, sets, strict=True))


def test_decoder_over_capacity_is_never_silent():
    rng, (m, t) = np.random.default_rng(1), (7, 5)
    table = gf.packed_table(m, t)
    sets = [rng.choice(127, t + int(k), replace=False) for k in rng.integers(1, 5, 400)]
    words = np.array([np.bitwise_xor.reduce(table[:, s], axis=1) for s in sets])
    ok, bins = decode(words, m, t)
    for o, b, w in zip(ok, bins, words, strict=True):
        assert not o or (np.bitwise_xor.reduce(table[:, b], axis=1) == w).all() and len(b) <= t
    assert ok.mean() < 0.05


@pytest.mark.parametrize("n", [1, 5, 20])
def test_large_field_decoder(n):
    x = np.random.default_rng(n).choice(2**32 - 1, n, replace=False).astype(np.uint64) + np.uint64(1)

    def syndromes(t):
        out, p, sq = [], x, gf.mul32(x, x)
        for _ in range(t):
            out.append(np.bitwise_xor.reduce(p))
            p = gf.mul32(p, sq)
        return np.array(out)

    assert set(Y.decode32(syndromes(n + 2)).tolist()) == set(x.tolist())
    if n > 2:
        assert Y.decode32(syndromes(n - 2)) is None


def test_printed_numbers():
    assert round(M.p_ideal(5, 255), 2) == 0.96
    assert round(M.p_type1(5, 255), 2) == 0.04
    assert 1.52e-4 < M.p_type2(5, 255) < 1.53e-4
    assert round(M.p_type2(5, 255) / 255 * 1e7) == 6
    assert M.bits_per_group(127, 13, 5, 32) == 318
    assert round(M.p_overflow(1000, 200, 13) * 1e4, 1) == 6.7
    assert round(M.p_split_overflow(2, 1000, 200, 13), 4) == 0.0012
    assert M.p_split_overflow(3, 1000, 200, 13) < M.p_split_overflow(2, 1000, 200, 13) / 50
    shares = M.expected_shares(127, 13, 1000, 200, 4)
    assert abs(shares[1] - 0.0380) < 5e-5 and abs(shares[2] - 3.61e-4) < 1e-6 and abs(shares[3] - 2.86e-6) < 1e-8
    assert M.false_verify_prob(32, 0.04) < 1e-11


def test_transition_matrix():
    m = M.transition_matrix(127, 13)
    assert np.allclose(m.sum(1), 1) and np.allclose(m, [[float(x) for x in r] for r in M.transition_exact(127, 13)], atol=1e-12)
    n = 63
    m = M.transition_matrix(n, 3)
    assert np.isclose(m[2, 2], 1 / n) and np.isclose(m[3, 2], 3 * (n - 1) / n**2) and np.isclose(m[3, 3], 1 / n**2) and m[1, 0] == 1
    rng = np.random.default_rng(3)
    balls = rng.integers(0, 31, (40_000, 6))
    left = np.array([sum(c for c in np.bincount(r) if c > 1) for r in balls])
    assert abs(left.mean() - (M.transition_matrix(31, 6)[6] * np.arange(7)).sum()) < 0.03


def test_model_pieces():
    assert M.p_done(1, 1, 127) == 1 and abs(M.p_done(2, 1, 127) - (1 - 1 / 127)) < 1e-12 and M.p_done(5, 2, 255) > M.p_done(5, 1, 255)
    assert M.alpha(1000, 200, 127, 13, 3) > M.alpha(1000, 200, 127, 13, 3, "truncated")
    from setdiff.operators.estimate import tow_variance

    assert tow_variance(10, 128) == 180 / 128


def test_tuner_golden():
    for d, bits, n, t in GOLDEN:
        row = T.best(d)
        assert (row[9], row[5], row[6]) == (bits, n, t)
    assert [x[3] for x in T.round_tradeoff(tail_model="truncated", bound="plain")][:2] == [591, 402]
    assert T.best(10_000, tail_model="truncated") is None
    bits = [x[3] for x in T.round_tradeoff()]
    assert bits == sorted(bits, reverse=True)


def test_portable_hash_is_not_linear():
    """A hash linear over XOR would let every fake through the check of its bin."""
    rng = np.random.default_rng(2)

    def h(x):
        return eval(portable_text("x", 77, 127, "//"), {"x": int(x)})

    hits = sum(h(a) == h(b) == h(c) and h(a ^ b ^ c) == h(a) for a, b, c in rng.integers(1, 2**32, (30_000, 3)).tolist())
    triples = 0
    by: dict = {}
    for x in rng.integers(1, 2**32, 3000).tolist():
        by.setdefault(h(x), []).append(x)
    fakes = 0
    for k, xs in by.items():
        for i in range(0, len(xs) - 2, 3):
            triples += 1
            fakes += h(xs[i] ^ xs[i + 1] ^ xs[i + 2]) == k
    assert hits <= 3 and fakes < 0.1 * triples
