"""Language identification by error-correcting output codes.

Every language gets a codeword; one binary n-gram classifier per bit learns to tell the
languages whose bit is one from the others; a text goes to the language whose codeword
has the least loss under the classifiers' margins. Losses are weighted by how well
each classifier did for each language on rows not used to fit it. A small gap between the best
two languages flags the text as ambiguous.

The classifiers are fitted on a bounded sample of labelled rows (``per_language`` rows of each
language, half of them for the weights) because a linear model of 2**14 features is saturated long
before; n-grams are counted in the executors and only one table (languages x features) reaches the driver.
Prediction is one narrow pass over whole texts, in blocks, so memory doesn't follow text length.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lean, small, stowed

UNDETERMINED = "und"
BUCKETS = 1 << 14
BLOCK = 1 << 20
_TABLE = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in range(256))
_ORDERS = (1, 2, 3, 4)


def ngram_counts(text: str) -> np.ndarray:
    """Counts of hashed byte n-grams of orders one to four of the lower-cased letters of a whole text."""
    raw = b" " + b" ".join(text.lower().encode("utf-8", "replace").translate(_TABLE).split()) + b" "
    total = np.zeros(BUCKETS)
    for at in range(0, max(len(raw) - 3, 1), BLOCK):
        a = np.frombuffer(raw[at : at + BLOCK + 3], np.uint8).astype(np.uint32)
        last = at + BLOCK + 3 >= len(raw)
        n = len(a) if last else BLOCK
        h = np.zeros(len(a), np.uint32)
        for k in _ORDERS:
            m = min(n, len(a) - k + 1)
            if m <= 0:
                break
            h = h[:m] * np.uint32(257) + a[k - 1 : k - 1 + m] + np.uint32(1)
            bucket = (h * np.uint32(2654435761) ^ np.uint32(k * 0x5BD1E995 % 2**32)) >> np.uint32(18)
            total += np.bincount(bucket, minlength=BUCKETS)
    return total


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """Codewords of -1 and 1, one row per language.

    Up to five languages get the exhaustive code; more get random words, the draw with the largest least distance of 64.
    """
    if n <= 1:
        return np.ones((n, 1))
    if n <= 5:
        cols = [c for c in itertools.product((1, -1), repeat=n - 1) if -1 in c]
        return np.array([[1] * len(cols), *zip(*cols, strict=True)], float)
    rng, best, far = np.random.default_rng(seed), None, -1
    bits = 12 * int(np.ceil(np.log2(n)))
    for _ in range(64):
        code = rng.choice([-1.0, 1.0], (n, bits))
        code = code[:, np.abs(code.sum(0)) < n]
        apart = min(int((code[i] != code[i + 1 :]).sum(1).min()) for i in range(n - 1))
        if apart > far:
            best, far = code, apart
    return best


@dataclass
class LanguageCodes:
    """A fitted model; small, goes to the executors with the task."""

    langs: list[str]
    code: np.ndarray
    weights: np.ndarray
    scale: np.ndarray
    trust: np.ndarray
    gap: float = 0.05

    def margins(self, text: str) -> np.ndarray:
        c = ngram_counts(text)
        return c @ self.weights / max(c.sum(), 1.0) * self.scale

    def losses(self, margins: np.ndarray) -> np.ndarray:
        return (self.trust * np.log1p(np.exp(-np.clip(self.code * margins, -30, 30)))).sum(1)

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(language, score, ambiguous); a text without any letter is undetermined with score 0."""
        if not text or not self.langs or not any(map(str.isalpha, text)):
            return UNDETERMINED, 0.0, True
        loss = self.losses(self.margins(text))
        p = np.exp(2 * (loss.min() - loss))
        i = int(loss.argmin())
        near = float(np.partition(loss, 1)[1] - loss[i]) if len(loss) > 1 else np.inf
        return self.langs[i], float(p[i] / p.sum()), near < self.gap


def fit(docs: DataFrame, train: Column, per_language: int = 3000, most_languages: int = 200) -> LanguageCodes:
    """Learns from rows of ``docs`` where ``train`` holds and text and lang are not null.

    At most about ``per_language`` rows of each language are used, picked by a hash of the id. More than ``most_languages``
    languages are refused. No usable row gives a model that knows no language.
    """
    rows = docs.where(train & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text")
    found = rows.groupBy("lang").count().orderBy("lang").limit(most_languages + 1).collect()
    if len(found) > most_languages:
        raise ValueError(f"over {most_languages} languages")
    langs = [r["lang"] for r in found]
    if not langs:
        return LanguageCodes([], np.ones((0, 1)), np.zeros((BUCKETS, 1)), np.ones(1), np.ones((0, 1)))
    share = F.create_map(*itertools.chain.from_iterable((F.lit(r["lang"]), F.lit(min(1.0, per_language / r["count"]))) for r in found))
    draw = F.pmod(F.xxhash64("doc_id", F.lit("language sample")), F.lit(1 << 20)) / F.lit(1 << 20)
    picked = rows.withColumn("_u", draw / share[F.col("lang")]).where("_u < 1")
    place = {v: i for i, v in enumerate(langs)}

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(langs), BUCKETS))
        for b in small(batches):
            for lang, text in zip(b.column("lang").to_pylist(), b.column("text").to_pylist(), strict=True):
                total[place[lang]] += ngram_counts(text)
        i, j = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total[i, j].astype(np.int64))], ["lang_no", "bucket", "n"])

    counts = np.zeros((len(langs), BUCKETS))
    sums = picked.where("_u < 0.5").mapInArrow(lean(count), "lang_no int, bucket int, n long").groupBy("lang_no", "bucket").agg(F.sum("n").alias("n"))
    got = sums.toPandas()
    counts[got["lang_no"], got["bucket"]] = got["n"]
    freq = (counts + 0.5) / (counts.sum(1, keepdims=True) + 0.5 * BUCKETS)
    code = codewords(len(langs))
    up, down = (code > 0).astype(float), (code < 0).astype(float)
    mean = lambda side: (side.T @ freq) / np.maximum(side.sum(0), 1)[:, None]
    weights = np.ones((BUCKETS, 1)) if len(langs) == 1 else (np.log(mean(up)) - np.log(mean(down))).T
    model = LanguageCodes(langs, code, weights, np.ones(code.shape[1]), np.ones(code.shape))

    def try_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, bits = np.zeros((len(langs), 1 + 2 * code.shape[1])), code.shape[1]
        for b in small(batches):
            for lang, text in zip(b.column("lang").to_pylist(), b.column("text").to_pylist(), strict=True):
                f, i = model.margins(text), place[lang]
                total[i, 0] += 1
                total[i, 1 : 1 + bits] += f * code[i] > 0
                total[i, 1 + bits :] += np.abs(f)
        i, j = np.nonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total[i, j])], ["lang_no", "what", "x"])

    tried = picked.where("_u >= 0.5").mapInArrow(lean(try_out), "lang_no int, what int, x double").groupBy("lang_no", "what").agg(F.sum("x").alias("x")).toPandas()
    seen = np.zeros((len(langs), 1 + 2 * code.shape[1]))
    seen[tried["lang_no"], tried["what"]] = tried["x"]
    bits = code.shape[1]
    right = (seen[:, 1 : 1 + bits] + 1) / (seen[:, :1] + 2)
    model.trust = right / right.sum(1, keepdims=True)
    size = seen[:, 1 + bits :].sum(0) / max(seen[:, 0].sum(), 1)
    model.scale = 4 / np.where(size > 0, size, 4)
    return model


def identify(docs: DataFrame, model: LanguageCodes) -> DataFrame:
    """Adds lang_pred, lang_score and lang_ambiguous to every row of ``docs``; other columns are kept as they are, whatever their names.

    Columns of ``docs`` that bear one of the three names are replaced. Null or letterless texts are ``und`` with score 0. Only ``text`` is looked
    at, so repeated rows get equal answers; of languages that fit equally well the first by name is taken and the row is ambiguous. An empty table gives no rows.
    """
    own = {"lang_pred": pa.string(), "lang_score": pa.float64(), "lang_ambiguous": pa.bool_()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            found = [model.predict(t) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("_row"), *(pa.array([f[k] for f in found], t) for k, t in enumerate(own.values()))], ["_row", *own])

    rows = stowed(docs).select("_row", F.col("_row.text").cast("string").alias("text"))
    schema = rows.select("_row", *(F.lit(None).cast(t).alias(n) for n, t in zip(own, ("string", "double", "boolean"), strict=True))).schema
    kept = [F.col("_row").getField(c).alias(c) for c in docs.columns if c not in own]
    return rows.mapInArrow(lean(run), schema).select(*kept, *own)
