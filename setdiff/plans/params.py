"""Parameters of a run."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil


@dataclass(frozen=True)
class Params:
    """g groups, n = 2**m - 1 bins a group, capacity t; the rest as in the paper's evaluation unless said otherwise.

    With ``sidecar`` the signatures are written out once and every round reads those instead of working them out again.
    """

    g: int
    n: int = 127
    t: int = 13
    delta: int = 5
    w: int = 32
    ways: int = 3
    max_rounds: int | None = None
    seed: int = 0
    family: str = "fast"
    check_bin: bool = True
    check_group: bool = True
    checksum: str = "sum"
    shape: str = "auto"
    solver: str = "bm"
    sidecar: bool = True

    @property
    def m(self) -> int:
        return (self.n + 1).bit_length() - 1

    def with_(self, **changes) -> Params:
        return replace(self, **changes)


def groups_for(d: float, delta: int = 5) -> int:
    return max(1, ceil(d / delta))


def published(d: float, **more) -> Params:
    """The printed optimum for d = 1000, p0 = 0.99, three rounds: n = 127, t = 13."""
    return Params(g=groups_for(d, more.get("delta", 5)), **({"n": 127, "t": 13} | more))
