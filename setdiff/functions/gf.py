"""Arithmetic in GF(2**m): tables for small m, bitwise products for m = 32."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cache

import numpy as np


def _powers(m: int, poly: int) -> list[int]:
    """Powers of x modulo ``poly`` up to the first repeat of one."""
    out, x = [1], 2
    while x != 1:
        out.append(x)
        x <<= 1
        if x >> m:
            x ^= poly
        if len(out) > (1 << m):
            return []
    return out


@dataclass(frozen=True)
class Field:
    """GF(2**m) with n = 2**m - 1 non-zero elements, as powers of a generator."""

    m: int
    n: int
    exp: np.ndarray
    log: np.ndarray

    def mul(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
        return np.where((a == 0) | (b == 0), 0, self.exp[(self.log[a] + self.log[b]) % self.n])

    def div(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
        return np.where(a == 0, 0, self.exp[(self.log[a] - self.log[b]) % self.n])


@cache
def field(m: int) -> Field:
    """The field of the least primitive polynomial of degree m; that the generator has order 2**m - 1 is checked, not assumed."""
    n = (1 << m) - 1
    for poly in range((1 << m) | 1, 1 << (m + 1), 2):
        powers = _powers(m, poly)
        if len(powers) == n:
            exp, log = np.array(powers, np.int64), np.zeros(1 << m, np.int64)
            log[exp] = np.arange(n)
            return Field(m, n, exp, log)
    raise ValueError(f"no primitive polynomial of degree {m}")


@cache
def packed_table(m: int, t: int) -> np.ndarray:
    """(lanes, n): for each bin its t odd powers, m bits each, as many to a 63-bit lane as fit."""
    f, fit = field(m), 63 // m
    lanes = np.zeros((-(-t // fit), f.n), np.int64)
    for k in range(t):
        power = f.exp[(np.arange(f.n) * (2 * k + 1)) % f.n]
        lanes[k // fit] |= power << (m * (k % fit))
    return lanes


def unpack(lanes: np.ndarray, m: int, t: int) -> np.ndarray:
    """(groups, t) odd syndromes of packed lanes (groups, lanes)."""
    fit, mask = 63 // m, (1 << m) - 1
    return np.stack([(lanes[:, k // fit] >> (m * (k % fit))) & mask for k in range(t)], axis=1)


# GF(2**32): elements are uint64 arrays below 2**32. Modulus x**32 + x**7 + x**3 + x**2 + 1 (a fixed value, irreducible).
_2, _3, _7, _32, _LOW32 = (np.uint64(x) for x in (2, 3, 7, 32, 0xFFFFFFFF))
_HOLES32 = [np.uint64(0x11111111 << k) for k in range(4)]
_HOLES64 = [np.uint64(0x1111111111111111 << k) for k in range(4)]


def mul32(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products, element by element.

    Carry-less products by integer ones: each factor is cut into four parts with every fourth bit, so that up to eight
    ones that meet leave their carries in the holes.
    """
    a, b = np.asarray(a, np.uint64), np.asarray(b, np.uint64)
    x, y = [a & h for h in _HOLES32], [b & h for h in _HOLES32]
    out = np.zeros(np.broadcast(a, b).shape, np.uint64)
    for k in range(4):
        part = x[0] * y[k]
        for i in (1, 2, 3):
            part = part ^ x[i] * y[(k - i) % 4]
        out |= part & _HOLES64[k]
    for _ in range(2):
        high = out >> _32
        out = (out & _LOW32) ^ high ^ (high << _2) ^ (high << _3) ^ (high << _7)
    return out


#: x**32 + x**7 + x**3 + x**2 + 1 as an integer.
_MODULUS32 = (1 << 32) | 0x8D


def _inverse32(x: int) -> int:
    """Inverse of one element by the extended Euclidean algorithm on polynomials over GF(2)."""
    r, s, u, v = _MODULUS32, x, 0, 1
    while s > 1:
        shift = r.bit_length() - s.bit_length()
        if shift < 0:
            r, s, u, v = s, r, v, u
            continue
        r ^= s << shift
        u ^= v << shift
        if r < s:
            r, s, u, v = s, r, v, u
    return v


def inv32(a: np.ndarray) -> np.ndarray:
    """Inverses of non-zero elements."""
    x = np.asarray(a, np.uint64)
    return np.array([_inverse32(k) for k in x.ravel().tolist()], np.uint64).reshape(x.shape)
