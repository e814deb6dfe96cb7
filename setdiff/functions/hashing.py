"""Hash families for groups, bins, splits and signs.

``fast`` is xxhash64 with a seed; ``portable`` is a multilinear form of the 16-bit halves modulo 2**31 - 1, the
same BIGINT arithmetic in any SQL engine (needs 0 < sig < 2**32). Neither is linear over XOR: the check of a
recovered element against its bin would never fire with a linear hash.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2_147_483_647
#: For signs: a prime above 2**32, so that four-wise independence holds for all 32-bit signatures.
SIGN_PRIME = 4_294_967_311
#: Purposes of a hash; each gets seeds of its own.
GROUP, BIN, SPLIT, CELL, FILTER, CHECK, SIGN = range(7)


def seed_of(purpose: int, index: int = 0, base: int = 0) -> int:
    return (base * 1_000_003 + purpose) * 65_537 + index + 1


def coefficients(seed: int, count: int = 3, prime: int = PRIME) -> list[int]:
    return [int(x) for x in np.random.default_rng(seed).integers(1, prime - 1, count)]


def portable_text(sig: str, seed: int, n: int, divide: str = "div") -> str:
    """SQL text of the portable hash of column ``sig`` into 0..n-1; ``divide`` is the engine's integer division."""
    a, b, c = coefficients(seed)
    return f"((({a} * ({sig} {divide} 65536) + {b} * ({sig} % 65536) + {c}) % {PRIME}) % {n})"


def bucket(sig: str, seed: int, n: int, family: str = "fast") -> Column:
    """Class 0..n-1 of a signature."""
    if family == "portable":
        return F.expr(portable_text(sig, seed, n)).cast("long")
    return F.pmod(F.xxhash64(F.col(sig), F.lit(seed)), F.lit(n)).cast("long")


def sign_text(sig: str, seed: int, divide: str = "div") -> str:
    """SQL text of a four-wise independent sign (1 or -1): the low bit of a random cubic over a prime field, products in 16-bit pieces."""
    p, (a, b, c, d) = SIGN_PRIME, coefficients(seed, 4, SIGN_PRIME)

    def times(u: str) -> str:
        return f"((((({u}) * ({sig} {divide} 65536)) % {p}) * 65536 + ({u}) * ({sig} % 65536)) % {p})"

    value = str(a)
    for k in (b, c, d):
        value = f"(({times(value)} + {k}) % {p})"
    return f"(1 - 2 * ({value} % 2))"
