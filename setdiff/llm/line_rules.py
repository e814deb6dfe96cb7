"""Line-first cleaning: judge every line, drop the lines that fail, then judge what a document lost.

A line has words (maximal runs without space, tab, newline, vertical tab, form feed,
carriage return); lines without one are neutral. A line fails when

* ``punctuation``: three words in ten end in a double exclamation mark; or it has as many
  symbols of ``#*$%&|<>`` as half its words; or it has eight words and no sentence mark at all;
* ``navigation``: a quarter of its words are bare separators;
* ``boilerplate``: it reads as a licence, copyright, cookie or script notice, or, with four words
  or more, repeats an earlier line of the document.

A document is rejected if more than half of its words stood in failed lines.

Nulls count as no words; an empty document has no lines, fails the base rule and is not
kept. Rows are judged one by one: repeated rows, ties and further columns make no difference.
Work is linear in the text, except one sort of window hashes per document.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import WORD_SPACE, lean, small

#: Fixed values of the rules.
SYMBOLS = b"#*$%&|<>"
SEPARATORS = (b"|", b">", b"/", b"-", b"\xc2\xbb", b"\xe2\x80\xa2")
SENTENCE_MARKS = ".!?:;"
NOTICE = r"licen[cs]ed under|under the [ -~]{0,60}licen[cs]e|all rights reserved|copyright|cookie policy|privacy policy|terms of (use|service)|enable javascript"
WINDOW, MOST_REPEATED, LEAST_WORDS, MOST_LOST = 8, 30, 20, 50

_NOTICE = re.compile(NOTICE.encode(), re.I)
_MARK = re.compile(b"[" + SENTENCE_MARKS.encode() + b"]")
_SPACES = [bytes([b]) for b in WORD_SPACE]
_MIX = np.array([(0x9E3779B97F4A7C15 * (2 * k + 1) ** 3) % 2**64 | 1 for k in range(WINDOW)], dtype=np.uint64)


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a window of eight words found twice or more; windows are compared by 64-bit hashes."""
    n = len(words) - WINDOW + 1
    if n < 2:
        return 0
    h = np.fromiter(map(hash, words), np.int64, len(words)).view(np.uint64)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    total = np.zeros(n, np.uint64)
    for k in range(WINDOW):
        total += h[k : k + n] * _MIX[k]
    order = np.argsort(total, kind="stable")
    same = total[order[1:]] == total[order[:-1]]
    if not same.any():
        return 0
    hit = np.zeros(n, bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, np.int64)
    at = np.flatnonzero(hit)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + WINDOW, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def line_fails(line: bytes, words: list[bytes], seen: set[bytes]) -> str | None:
    """The rule that a line with words fails, or None."""
    n = len(words)
    if 10 * sum(w.endswith(b"!!") for w in words) >= 3 * n and b"!!" in line:
        return "punctuation"
    if 2 * sum(map(line.count, (SYMBOLS[i : i + 1] for i in range(len(SYMBOLS))))) >= n:
        return "punctuation"
    if n >= 8 and not _MARK.search(line):
        return "punctuation"
    if 4 * sum(map(words.count, SEPARATORS)) >= n:
        return "navigation"
    if _NOTICE.search(line) or n >= 4 and line in seen:
        return "boilerplate"
    return None


def judge(text: str | None) -> tuple:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_lines_removed, n_words_removed, base_failed, kept, text left)."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    chars = len(text or "") - sum(map(raw.count, _SPACES))
    symbols = sum(raw.count(SYMBOLS[i : i + 1]) for i in range(len(SYMBOLS)))
    seen: set[bytes] = set()
    dup = lines = failed = lost = 0
    left = []
    for line in raw.split(b"\n"):
        own = line.split()
        if not own:
            left.append(line)
            continue
        lines += 1
        if line_fails(line, own, seen):
            failed += 1
            lost += len(own)
        else:
            left.append(line)
        dup += line in seen
        seen.add(line)
    repeats = repeated_words(words)
    base = len(words) < LEAST_WORDS or 100 * repeats > MOST_REPEATED * len(words)
    kept = not base and 100 * lost <= MOST_LOST * len(words)
    return len(words), chars, symbols, dup, repeats, lines, failed, lost, base, kept, b"\n".join(left).decode("utf-8", "surrogatepass")


FIELDS = [
    ("n_words", "long"), ("word_chars", "long"), ("n_symbols", "long"), ("n_dup_lines", "long"), ("n_repeat_words", "long"),
    ("n_lines", "long"), ("n_lines_removed", "long"), ("n_words_removed", "long"), ("base_failed", "boolean"), ("kept", "boolean"),
]


def clean_lines(docs: DataFrame, with_text: bool = True) -> DataFrame:
    """One row per row of ``docs``: doc_id, the counts and verdicts of FIELDS and, unless left out, ``clean_text``."""
    names = [n for n, _ in FIELDS]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            found = list(zip(*(judge(t)[: 11 if with_text else 10] for t in b.column(1).to_pylist()), strict=True)) or [[]] * (11 if with_text else 10)
            cols = [b.column(0), *(pa.array(found[i], pa.bool_() if FIELDS[i][1] == "boolean" else pa.int64()) for i in range(10))]
            if with_text:
                cols.append(pa.array(found[10], pa.string()))
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", *names, *["clean_text"] * with_text])

    schema = "doc_id long, " + ", ".join(f"{n} {t}" for n, t in FIELDS) + ", clean_text string" * with_text
    return docs.selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").mapInArrow(lean(run), schema)
