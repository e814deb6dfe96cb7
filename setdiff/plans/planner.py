"""Choice of a scheme and of its physical shape from what is known before the run."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setdiff.operators import cells as C
from setdiff.operators.estimate import GAMMA, estimate_d
from setdiff.operators.relational import full_exchange
from setdiff.operators.rounds import Reconciliation, choose_shape, reconcile
from setdiff.plans import model as M
from setdiff.plans import tune as T
from setdiff.plans.params import Params
from setdiff.session import written

#: Differences up to which the whole-set code may be chosen: decoding takes their square.
WHOLE_MOST = 200


@dataclass(frozen=True)
class Choice:
    scheme: str
    bits: dict[str, float]
    params: Params | None
    shape: str | None

    def explain_choice(self) -> str:
        lines = [f"{'*' if k == self.scheme else ' '} {k}: {v:.0f} bits" for k, v in sorted(self.bits.items(), key=lambda x: x[1])]
        return "\n".join([*lines, f"shape: {self.shape}", f"parameters: {self.params}"])


def predicted_bits(d: float, size_a: int, size_b: int, w: int = 32, p: Params | None = None) -> dict[str, float]:
    """Bits of each scheme for about d differences, margins included."""
    d = max(1.0, GAMMA * d)
    p = p or T.tuned_to_completion(d)
    k = C.hashes_for(d)
    out = {
        "full_exchange": float(size_b * w), "whole_syndrome": ceil(d) * w, "cell_table": C.cells_for(d, k) * 3 * w,
        "bin_parity": p.g * M.bits_per_group(p.n, p.t, 0, w) + d * (p.m + w), "grouped_syndrome": p.g * (p.t * w + w),
    }
    rate = C.best_rate(size_b, d)
    out["filter_cells"] = out["cell_table"] if rate >= 1 else C.filter_shape(size_b, rate)[0] + C.cells_for(C.passing(rate, d), 4) * 3.0 * w
    return out


def choose_scheme(d: float, size_a: int, size_b: int, w: int = 32, piecewise: bool = True) -> Choice:
    """The cheapest scheme whose decoding stays near linear; ``piecewise`` leaves out those that give all or nothing."""
    p = T.tuned_to_completion(max(1.0, GAMMA * d))
    bits = predicted_bits(d, size_a, size_b, w, p)
    fit = {k: v for k, v in bits.items() if k != "whole_syndrome" or d <= WHOLE_MOST}
    if piecewise:
        fit = {k: v for k, v in fit.items() if k in ("full_exchange", "bin_parity")}
    scheme = min(fit, key=fit.get)
    return Choice(scheme, bits, p if scheme == "bin_parity" else None, choose_shape(p, size_a + size_b) if scheme == "bin_parity" else None)


def reconcile_auto(a: DataFrame, b: DataFrame, p0: float = 0.99, r: int = 3, delta: int = 5, capped: bool = False, **more) -> tuple[DataFrame, dict]:
    """(diff (sig, side), report) for an unknown number of differences: estimate, inflate, tune, run.

    An estimate of zero is still checked by one round. Where the sets are far apart they are exchanged in full.
    """
    a, b = written(a, "side_a"), written(b, "side_b")
    d_hat = estimate_d(a, b).first()
    d_hat = d_hat["d_hat"] if d_hat else 0.0
    sizes = a.count(), b.count()
    choice = choose_scheme(d_hat, *sizes)
    report = {"d_hat": d_hat, "scheme": choice.scheme, "size_a": sizes[0], "size_b": sizes[1]}
    if choice.scheme == "full_exchange":
        return full_exchange(a, b), report
    fit = T.tuned if capped else T.tuned_to_completion
    p = fit(max(1.0, GAMMA * d_hat), delta, r, p0, max_rounds=r if capped else None, **more)
    got: Reconciliation = reconcile(a, b, p.with_(shape=choice.shape or "auto", sidecar=False))
    return got.diff.select("sig", "side"), report | {"params": p, "run": got}


def one_shot_sql(view: str, p: Params) -> dict[str, str]:
    """SQL templates: the parity bins, the per-group checksum and the bin table of a view with ``sig``, with the portable hashes."""
    from setdiff.functions import hashing as H

    root = H.portable_text("sig", H.seed_of(H.GROUP, 0, p.seed), p.g)
    bin_ = H.portable_text("sig", H.seed_of(H.BIN, 1, p.seed), p.n)
    keyed = f"(select sig, {root} as root, {bin_} as bin from {view})"
    return {
        "parity_bins": f"select root, bin from {keyed} group by root, bin having count(*) % 2 = 1",
        "checksums": f"select root, sum(sig) % {1 << p.w} as chk from {keyed} group by root",
        "bin_table": f"select root, bin, count(*) % 2 as parity, bit_xor(sig) as xs from {keyed} group by root, bin",
    }


def estimate_or(d: float | None, a: DataFrame, b: DataFrame) -> float:
    """A given d, or the inflated estimate."""
    return d if d is not None else GAMMA * estimate_d(a, b).agg(F.max("d_hat")).first()[0]
