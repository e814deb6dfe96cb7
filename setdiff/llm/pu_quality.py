"""Quality scores by positive-unlabelled learning with the non-negative risk.

Trusted positives are training rows labelled 1; everything else the fit sees is unlabelled web text. A linear model is fitted to
the non-negative unbiased risk: class prior times the positive loss, plus the unlabelled loss less the prior times what
positives would cost as negatives; when that second part falls below zero the step goes against it, so
the model can't profit from overfitting. The prior is estimated first: a plain positive-against-unlabelled model is cut where the share of
unlabelled rows above the cut, over the share of held-back positives above it, is least.

The fit uses bounded samples (``positives`` and ``unlabelled`` rows, picked by a hash of the id); whole texts are read
everywhere. Features are shares of pairs of character classes and some counts of words and
lines: they don't depend on language. Only ``text`` is an input of a score.

A null text counts as an empty one; an empty text has a score like any other. Without a positive label the score is 0.5
for all. Repeated rows, ties and further columns make no difference; repeated labels count once, as 1 if any is 1.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lean, small
from .line_rules import repeated_words

_CLASS = np.full(256, 2, np.uint8)
for _i, _set in enumerate(("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", None, "0123456789", " \t\r\f\v", "\n", ".", ",", "!", "?", "|", "#", "*", "$%&<>", "'\"-()/", ":;")):
    if _set:
        _CLASS[[ord(c) for c in _set]] = _i
_REST = [c for c in range(128) if _CLASS[c] == 2]
_CLASS[_REST] = 14
BLOCK = 1 << 20
N_FEATURES = 256 + 10


def features(text: str | None) -> np.ndarray:
    """Feature vector of a whole text."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    pairs = np.zeros(256)
    for at in range(0, max(len(raw) - 1, 0), BLOCK):
        c = _CLASS[np.frombuffer(raw[at : at + BLOCK + 1], np.uint8)]
        pairs += np.bincount(c[:-1] * np.uint8(16) + c[1:], minlength=256)
    words, lines = raw.split(), [x for x in raw.split(b"\n") if x.strip()]
    n = len(words)
    most = max(Counter(words).values(), default=0)
    seen: set[bytes] = set(lines)
    x = np.zeros(N_FEATURES)
    x[:256] = np.sqrt(pairs / max(pairs.sum(), 1))
    x[256:] = (
        np.log1p(n), (len(raw) - n) / max(n, 1) / 10, len(set(words)) / max(n, 1), most / max(n, 1), sum(map(eq, words, words[1:])) / max(n, 1),
        1 - len(seen) / max(len(lines), 1), np.log1p(len(lines)), repeated_words(words) / max(n, 1), sum(x.rstrip().endswith((b".", b"!", b"?")) for x in lines) / max(len(lines), 1), float(n == 0),
    )
    return x


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def _descend(grad, n: int, steps: int = 400, rate: float = 0.04, decay: float = 1e-4) -> np.ndarray:
    """Weights after Adam steps on ``grad``."""
    w, m, v = (np.zeros(n, np.float32) for _ in range(3))
    for t in range(1, steps + 1):
        g = grad(w) + decay * w
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = w - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w


def nn_pu(p: np.ndarray, u: np.ndarray, prior: float) -> np.ndarray:
    """Weights of least non-negative risk for the logistic loss."""

    def grad(w: np.ndarray) -> np.ndarray:
        sp, su = _sigmoid(p @ w), _sigmoid(u @ w)
        good = -prior * (p.T @ (1 - sp)) / len(p)
        bad_risk = np.logaddexp(0, u @ w).mean() - prior * np.logaddexp(0, p @ w).mean()
        bad = u.T @ su / len(u) - prior * (p.T @ sp) / len(p)
        return good + bad if bad_risk >= 0 else -bad

    return _descend(grad, p.shape[1])


def estimate_prior(p: np.ndarray, u: np.ndarray, delta: float = 0.1) -> float:
    """Share of positives among unlabelled rows, by the best bin of a positive-against-unlabelled model."""
    fit, back = p[::2], p[1::2]
    ufit, uback = u[::2], u[1::2]
    if not len(back) or not len(uback):
        return 0.5

    def grad(w: np.ndarray) -> np.ndarray:
        return -(fit.T @ (1 - _sigmoid(fit @ w))) / len(fit) + ufit.T @ _sigmoid(ufit @ w) / len(ufit)

    w = _descend(grad, p.shape[1], steps=300)
    zp, zu = np.sort(back @ w), np.sort(uback @ w)
    cuts = np.quantile(zp, np.linspace(0, 0.9, 181))
    above_p = 1 - np.searchsorted(zp, cuts) / len(zp)
    above_u = 1 - np.searchsorted(zu, cuts) / len(zu)
    slack = np.sqrt(np.log(4 / delta) / 2 / len(zp)) + np.sqrt(np.log(4 / delta) / 2 / len(zu))
    ratio = above_u / np.maximum(above_p, 1e-9)
    best = int(np.argmin(ratio + slack / np.maximum(above_p, 1e-9)))
    return float(np.clip(ratio[best], 0.02, 0.98))


@dataclass
class QualityModel:
    mean: np.ndarray
    dev: np.ndarray
    weights: np.ndarray
    prior: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = np.hstack([(x - self.mean) / self.dev, np.ones((len(x), 1))])
        return _sigmoid(z @ self.weights)


def fit(docs: DataFrame, labels: DataFrame, train: Column, positives: int = 5000, unlabelled: int = 10_000) -> QualityModel:
    """Learns from labels of rows where ``train`` (on doc_id) holds and from unlabelled texts; at most about the bounded numbers of each."""
    trusted = labels.where(train & (F.col("quality") == 1)).select("doc_id").distinct()
    draw = F.pmod(F.xxhash64("doc_id", F.lit("quality sample")), F.lit(1 << 20)) / F.lit(1 << 20)
    share = min(1.0, positives / max(trusted.count(), 1))
    picked = trusted.where(draw < share).select(F.col("doc_id").alias("_p"))
    all_share = min(1.0, unlabelled / max(docs.count(), 1))
    other = F.pmod(F.xxhash64("doc_id", F.lit("unlabelled sample")), F.lit(1 << 20)) / F.lit(1 << 20) < all_share
    seen = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(picked), F.col("doc_id") == F.col("_p"), "left")
    seen = seen.select("text", F.col("_p").isNotNull().alias("p"), F.coalesce(other, F.lit(False)).alias("u")).where("p or u")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            x = [features(t).astype(np.float32) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float32())), b.column(1), b.column(2)], ["x", "p", "u"])

    rows = seen.mapInArrow(lean(run), "x array<float>, p boolean, u boolean").toArrow()
    x = rows.column("x").combine_chunks().flatten().to_numpy().reshape(-1, N_FEATURES).astype(float) if rows.num_rows else np.zeros((0, N_FEATURES))
    isp, isu = (np.array(rows.column(c).to_pylist(), bool) for c in ("p", "u"))
    mean, dev = (x.mean(0), x.std(0) + 1e-3) if len(x) else (np.zeros(N_FEATURES), np.ones(N_FEATURES))
    z = np.hstack([(x - mean) / dev, np.ones((len(x), 1))])
    if not isp.any() or not isu.any():
        return QualityModel(mean, dev, np.zeros(N_FEATURES + 1), 0.5)
    order = np.random.default_rng(3).permutation(len(z))
    z = z[order].astype(np.float32)
    p, u = z[isp[order]], z[isu[order]]
    prior = estimate_prior(p, u)
    return QualityModel(mean, dev, nn_pu(p, u, prior), prior)


def score(docs: DataFrame, model: QualityModel) -> DataFrame:
    """(doc_id, score) of every row; the score is the model's probability of label 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            x = np.array([features(t) for t in b.column(1).to_pylist()]).reshape(-1, N_FEATURES)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.scores(x))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(run), "doc_id long, score double")
