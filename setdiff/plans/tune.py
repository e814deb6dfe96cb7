"""Choice of bins and capacity: least bits a group for which the success bound holds."""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, floor

import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from setdiff.plans import model as M
from setdiff.plans.params import Params, groups_for

#: Bin counts of the practical grid, and longer codes for few rounds or very many groups.
PRACTICAL = (63, 127, 255, 511, 1023, 2047)
EXTENDED = (*PRACTICAL, 4095, 8191)

GRID_SCHEMA = "d long, delta int, r int, p0 double, g long, n int, t int, fail double, bound double, objective int, feasible boolean"


def grid(d: int, delta: int = 5, r: int = 3, p0: float = 0.99, ns: tuple[int, ...] = PRACTICAL, tail_model: str = "split_aware", bound: str = "doubled") -> list[tuple]:
    """Every (n, t) with t within 1.5 and 3.5 delta."""
    g, out = groups_for(d, delta), []
    for n in ns:
        m = (n + 1).bit_length() - 1
        for t in range(ceil(1.5 * delta), floor(3.5 * delta) + 1):
            ok = M.success_bound(d, g, n, t, r, tail_model, bound)
            out.append((d, delta, r, p0, g, n, t, M.fail_share(d, g, n, t, r, tail_model), ok, (t + delta) * m, bool(ok >= p0)))
    return out


def best(d: int, delta: int = 5, r: int = 3, p0: float = 0.99, ns: tuple[int, ...] = PRACTICAL, tail_model: str = "split_aware", bound: str = "doubled") -> tuple | None:
    """The feasible row of least bits, of these the one with the highest bound."""
    fit = [x for x in grid(d, delta, r, p0, ns, tail_model, bound) if x[10]]
    return min(fit, key=lambda x: (x[9], -x[8])) if fit else None


def tuned(d: float, delta: int = 5, r: int = 3, p0: float = 0.99, **more) -> Params:
    """Parameters for about d differences; the grid is extended where the practical one has no answer."""
    whole = max(1, ceil(d))
    row = best(whole, delta, r, p0) or best(whole, delta, r, p0, EXTENDED)
    if row is None:
        raise ValueError("no parameters reach the wanted success rate; allow more rounds")
    return Params(g=row[4], n=row[5], t=row[6], delta=delta, **({"max_rounds": r} | more))


def tuned_to_completion(d: float, delta: int = 5, r: int = 3, p0: float = 0.99, most: int = 8, **more) -> Params:
    """``tuned`` for runs that go on until all is found: where no parameters reach ``p0`` in r rounds, the fewest rounds in which some do."""
    for rounds in range(r, most):
        try:
            return tuned(d, delta, rounds, p0, **more)
        except ValueError:
            continue
    return tuned(d, delta, most, p0, **more)


def tuning_grid(spark: SparkSession, ds: list[int], delta: int = 5, r: int = 3, p0: float = 0.99, tail_model: str = "split_aware", bound: str = "doubled", ns: tuple[int, ...] = PRACTICAL) -> DataFrame:
    """The grid for many d as a Spark job, one task a few d's."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            rows = [x for d in part["d"] for x in grid(int(d), delta, r, p0, ns, tail_model, bound)]
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in GRID_SCHEMA.split(", ")])

    return spark.createDataFrame([(d,) for d in ds], "d long").repartition(max(1, len(ds))).mapInPandas(run, GRID_SCHEMA)


def round_tradeoff(d: int = 1000, delta: int = 5, p0: float = 0.99, w: int = 32, tail_model: str = "split_aware", bound: str = "doubled") -> list[tuple[int, int, int, int]]:
    """(r, n, t, bits a group) of the optimum for one to four rounds; rounds without any feasible pair are left out."""
    out = []
    for r in (1, 2, 3, 4):
        row = best(d, delta, r, p0, tuple((1 << m) - 1 for m in range(6, 21)) if r == 1 else EXTENDED, tail_model, bound)
        if row:
            out.append((r, row[5], row[6], M.bits_per_group(row[5], row[6], delta, w)))
    return out
