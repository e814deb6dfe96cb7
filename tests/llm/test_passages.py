"""The pipeline's suffix stage cuts passages of more than 50 words, however short the words."""

import random

import corpus_pipeline as cp
import numpy as np
import pyarrow as pa
import pytest

from setdiff.llm import suffix_dedup


def test_passages_of_51_to_60_words_go(spark, sf, docs):
    """Passages of 51, 55 and 60 words (one of one-letter words, one wrapped anew) are cut in both documents; 50 words stay."""
    rng = random.Random(2)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrst") for _ in range(rng.randrange(3, 7)))
    words = lambda n: [word() for _ in range(n)]
    letters = [rng.choice("uvwxyz") for _ in range(51)]
    passages = [words(51), words(55), words(60), letters, words(50)]
    given = []
    for k, p in enumerate(passages):
        for at, mark in ((0, " "), (1, "\n" if k == 1 else " ")):
            before, after = words(20 + at), words(30)
            given.append((2 * k + at, " ".join(before) + " " + mark.join(p) + " " + " ".join(after), " ".join(before), " ".join(after)))
    assert max(len(" ".join(p)) for p in passages) < 400
    out = {r["doc_id"]: r["text"] for r in dict(cp.STAGES)["suffix_array_dedup"](spark, docs(*(g[:2] for g in given)), sf).collect()}
    for i, text, before, after in given:
        assert out[i] == (text if i // 2 == 4 else f"{before}  {after}")


def _batch(raws):
    """A record batch whose binary column doesn't begin at its buffer's start."""
    return pa.RecordBatch.from_arrays([pa.array([b"before", *raws], pa.binary()).slice(1)], ["raw"])


@pytest.mark.parametrize("unit", [1, 4])
def test_anchors_of_many_texts_at_once(monkeypatch, unit):
    """Every window's anchor is the leftmost least gram, by brute force text by text; no window crosses texts; short texts share a call."""
    rng = random.Random(unit)
    wide, gram = 10, 4
    n = [0, 9, 10, 11, 0, 1, 40, 300, *[rng.randint(0, 60) for _ in range(200)], 9, 0]
    raws = [bytes(rng.choice(b"ab") for _ in range(unit * k)) for k in n] + [b"x" * unit * 50]
    calls = []
    hashes = suffix_dedup.string_hashes
    monkeypatch.setattr(suffix_dedup, "string_hashes", lambda *x: calls.append(1) or hashes(*x))
    monkeypatch.setattr(suffix_dedup, "CHUNK_BYTES", 1000)
    done = 0
    for rows, data, bounds in suffix_dedup.chunks([_batch(raws), _batch([])]):
        assert rows.column("raw").to_pylist() == raws[done : done + len(rows)] and (len(rows) == 1 or len(data) <= 1000)
        text, h, at, first, last = suffix_dedup.anchors(data.view(f"<u{unit}"), bounds // unit, wide, gram)
        of = {(k, s - bounds[k] // unit): (p - bounds[k] // unit, g) for k, g, p, a, b in zip(text, h, at, first, last, strict=True) for s in range(a, b + 1)}
        assert len(of) == (last - first + 1).sum() == sum(max(0, len(r) // unit - wide + 1) for r in raws[done : done + len(rows)])
        for (k, s), (p, g) in of.items():
            own = hashes(np.frombuffer(raws[done + k], f"<u{unit}"), gram)
            near = own[s : s + wide - gram + 1] >> np.uint64(32)
            assert p == s + int(near.argmin()) and g == own[p]
        done += len(rows)
    assert done == len(raws) and len(calls) < len(raws) // 4


def test_word_codes_of_many_texts_at_once():
    """Equal words have equal codes wherever they stand, other words others; a text's last word doesn't run into the next text."""
    raws = [b"ab cd", b"cd", b"", b" \t\n", b"ab\x0bcd\r\ncd\x0cab", "é\u00a0x ab".encode(), b"a" * 70_000, b"cdab c d\x00", b"cd"]
    words = [suffix_dedup._WORD.findall(r) for r in raws]
    codes, n = [], []
    for _, data, bounds in suffix_dedup.chunks([_batch(raws)]):
        c, k = suffix_dedup.codes_of(data, bounds)
        codes += c.tolist()
        n += k.tolist()
    flat = [w for ws in words for w in ws]
    assert n == [len(w) for w in words] and len(codes) == len(flat)
    assert len(set(zip(flat, codes, strict=True))) == len(set(flat)) == len(set(codes))
