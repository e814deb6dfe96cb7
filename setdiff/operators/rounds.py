"""Reconciliation over rounds: encode, decode, recover, verify, go on with what is open.

A is never rewritten. From the second round on, host A's sketches are taken over A together with the differences found so
far: in an XOR an element of both cancels and one of neither is added, so this is the sketch of A with the differences toggled. Only
rows of open groups are read again. Frames between rounds have as many rows as there are groups or
differences and are written to the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setdiff.functions.gf import packed_table
from setdiff.operators import binparity as S
from setdiff.operators import decode as D
from setdiff.operators import verify as V
from setdiff.operators.binparity import NODE
from setdiff.plans import ledger as L
from setdiff.plans.params import Params
from setdiff.session import written

#: Rounds after which open groups are exchanged in full, if no cap was asked for.
SAFETY_ROUNDS = 12


@dataclass
class Reconciliation:
    """What A learns. ``diff``: (inst, sig, side); ``rounds``: (inst, round, root, path, bin, sig) as recovered;
    ``status``: (inst, success, rounds); ``ledger``: messages; all lazy over written tables."""

    a: DataFrame
    b: DataFrame
    params: Params
    diff: DataFrame
    rounds: DataFrame
    open_groups: DataFrame
    ledger: DataFrame
    decoded: list[DataFrame] = field(default_factory=list)
    candidates: list[DataFrame] = field(default_factory=list)

    @property
    def a_only(self) -> DataFrame:
        return self.diff.where("side = 'A_only'").select(*self.a.columns)

    @property
    def b_only(self) -> DataFrame:
        return self.diff.where("side = 'B_only'").select(*self.a.columns)

    def union(self) -> DataFrame:
        """A together with what only B has."""
        return self.a.union(self.b_only)

    def status(self) -> DataFrame:
        """(inst, success, rounds) of every instance."""
        seen = self.a.union(self.b).select("inst").distinct()
        last = self.decoded_all().groupBy("inst").agg(F.max("round").alias("rounds"))
        left = self.open_groups.select("inst").distinct().withColumn("_open", F.lit(True))
        return seen.join(last, "inst", "left").join(left, "inst", "left").select("inst", F.col("_open").isNull().alias("success"), F.coalesce("rounds", F.lit(0)).alias("rounds"))

    def decoded_all(self) -> DataFrame:
        out = self.decoded[0]
        for x in self.decoded[1:]:
            out = out.union(x)
        return out


def choose_shape(p: Params, n_rows: int, instances: int = 1) -> str:
    """``bins``: one pass, a table of (group, bin) sums of every instance, if it is much smaller than the sets; else ``two_pass``."""
    if p.shape != "auto":
        return p.shape
    return "bins" if 3 * instances * p.g * p.n < n_rows else "two_pass"


def _sides(a: DataFrame, b: DataFrame) -> DataFrame:
    """Both hosts' rows: (side, own, inst, sig)."""
    cols = ["inst", "sig", *S.wide_columns(a)]
    return a.select(F.lit(0).alias("side"), F.lit(1).alias("own"), *cols).union(b.select(F.lit(1), F.lit(1), *cols))


def _added(found: DataFrame, cols: list[str]) -> DataFrame:
    """Differences that A adds to its sketches: rows like those of ``_sides`` with ``own`` 0."""
    return found.select(F.lit(0).alias("side"), F.lit(0).alias("own"), *cols[2:])


def _of(side: int, x: Column) -> Column:
    return F.when(F.col("side") == side, x)


def host_sketch(df: DataFrame, p: Params) -> DataFrame:
    """(NODE, cw, chk, cnt): what a host sends of its set in the first round."""
    return S.encode(S.with_node(S.with_inst(df), p, None, 0).withColumn("bin", S.bin_of(p, 1)), NODE, p.m, p.t, V.combine(p, V.value(p)).alias("chk"), F.count(F.lit(1)).alias("cnt"))


def _met(sketches: Sequence[DataFrame], p: Params) -> DataFrame:
    """(NODE, cw, chk_a, chk_b, cnt) of two hosts' sketches."""
    rows = sketches[0].select("*", F.lit(0).alias("side")).union(sketches[1].select("*", F.lit(1)))
    cw = [F.bit_xor(F.col("cw")[i]) for i in range(len(packed_table(p.m, p.t)))]
    return rows.groupBy(*NODE).agg(F.array(*cw).alias("cw"), *[V.combine(p, _of(i, F.col("chk")), summed=True).alias(f"chk_{s}") for i, s in enumerate("ab")], F.sum("cnt").alias("cnt"))


def reconcile_iter(a: DataFrame, b: DataFrame, p: Params, shape: str = "two_pass", sketches: Sequence[DataFrame] | None = None) -> Iterator[dict]:
    """Yields after each round: round, new (recovered this round), found (all so far), open, n_open, decoded, candidates.

    ``sketches``: both hosts' ``host_sketch``, where they are at hand; the shape is then two_pass.
    """
    a, b = S.with_inst(a), S.with_inst(b)
    wide = tuple(S.wide_columns(a))
    cols, whole = wide or ("sig",), ["inst", "sig", *wide]
    found: DataFrame | None = None
    open_: DataFrame | None = None
    n_open = levels = n_found = 0
    k = 0
    base = _sides(a, b)
    here = p.check_bin and p.check_group  # candidates are in the bin where they were found
    while open_ is None or n_open:
        k += 1
        if open_ is not None:  # groups only close or split: later rounds read the rows that were open before
            base = written(S.with_node(base, p, open_, levels, n_open).select(*base.columns), "open_rows")
        rows = S.with_node(base if found is None else base.union(_added(found, base.columns)), p, open_, levels, n_open).withColumn("bin", S.bin_of(p, k))
        own = lambda side: F.when((F.col("side") == side) & (F.col("own") == 1), V.value(p))
        sums = [V.combine(p, own(0)).alias("chk_a"), V.combine(p, own(1)).alias("chk_b"), F.sum("own").alias("cnt")]
        if shape == "bins":
            xor = lambda side, c: F.coalesce(F.bit_xor(_of(side, F.col(c))), F.lit(0).cast("long"))
            sides = [xor(i, c).alias(f"{s}_{c}") for i, s in enumerate("ab") for c in cols]
            odd = lambda side: F.sum(_of(side, F.lit(1))) % 2 == 1
            table = written(
                rows.groupBy(*NODE, "bin").agg(*sides, F.coalesce(odd(0), F.lit(False)).alias("pa"), F.coalesce(odd(1), F.lit(False)).alias("pb"), *sums), "bins"
            )
            looked, lanes = S.lane_columns(table, p.m, p.t)
            again = F.sum if p.checksum != "mset_xor" else F.bit_xor
            sums = [again("chk_a").alias("chk_a"), again("chk_b").alias("chk_b"), F.sum("cnt").alias("cnt")]
            cw = [F.coalesce(F.bit_xor(F.when(F.col("pa") != F.col("pb"), x)), F.lit(0).cast("long")) for x in lanes]
        else:
            looked, lanes = S.lane_columns(rows, p.m, p.t)
            cw = [F.bit_xor(x) for x in lanes]  # of both hosts' rows: the XOR of their codewords
        sketch = _met(sketches, p) if sketches and k == 1 else looked.groupBy(*NODE).agg(F.array(*cw).alias("cw"), *sums)
        keys = [*NODE, "chk_a", "chk_b", "cnt"]
        types = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in sketch.schema.fields if f.name in keys)
        order = [f.name for f in sketch.schema.fields if f.name in keys]
        decoded = written(sketch.mapInArrow(D.decode_batches(order, p.m, p.t, p.solver), f"{types}, ok boolean, bins array<bigint>").withColumn("round", F.lit(k)), "decoded")
        few = decoded.where("ok").agg(F.coalesce(F.sum(F.size("bins")), F.lit(0))).first()[0]
        n_found += few
        flagged = decoded.where("ok").select(*NODE, F.explode("bins").alias("bin"))
        if shape == "bins":
            both = table.join(flagged, [*NODE, "bin"]).select(*NODE, "bin", *[F.col(f"a_{c}").bitwiseXOR(F.col(f"b_{c}")).alias(c) for c in cols])
            recovered = S.as_candidates(both, NODE, cols)
        else:
            in_bins = written(S.among(rows, flagged, [*NODE, "bin"], few), "in_bins")
            sums_of = lambda side: in_bins.where(F.col("side") == side).groupBy(*NODE, "bin").agg(*[F.bit_xor(c).alias(c) for c in cols])  # noqa: E731, B023
            recovered = S.recover(sums_of(0), sums_of(1), NODE, cols)
        candidates = recovered.withColumn("round", F.lit(k))
        if shape != "bins":  # there it is a join of two small written tables, here another pass over the rows
            candidates = written(candidates, "candidates")
        new = S.check_candidates(candidates, p, k, levels)
        every = new.select(*whole, F.lit(None).cast("boolean").alias("in_a"))
        every = every if found is None else every.union(found.select(*whole, "in_a"))
        folded = every.groupBy(*whole).agg((F.count(F.lit(1)) % 2).alias("_odd"), F.max("in_a").alias("_was")).where("_odd = 1").select(*whole, "_was")
        of_a = in_bins.where("side = 0 and own = 1") if shape != "bins" and here else base.where("side = 0") if here else a
        in_a = S.among(of_a.select(*whole), folded, whole, n_found).withColumn("_in", F.lit(True)).distinct()
        found = written(folded.join(in_a, whole, "left").select(*whole, F.coalesce("_was", F.col("_in").isNotNull()).alias("in_a")), "found")
        mine = S.with_node(found, p, open_, levels, n_open)
        v = V.value(p)
        adjust = mine.groupBy(*NODE).agg(V.combine(p, v if p.checksum == "mset_xor" else F.when(F.col("in_a"), -v).otherwise(v)).alias("adj"))
        judged = decoded.join(adjust, NODE, "left").where(~V.agrees(p, F.col("chk_a"), F.col("adj"), F.col("chk_b")))
        digits = F.when(F.col("ok"), F.array(F.lit(""))).otherwise(F.array(*[F.lit(str(i)) for i in range(p.ways)]))
        open_ = written(judged.select("inst", "root", F.explode(digits).alias("_d"), "path", "ok").select("inst", "root", F.concat("path", "_d").alias("path"), "ok"), "open")
        n_open, levels = open_.agg(F.count(F.lit(1)), F.coalesce(F.max(F.length("path")), F.lit(0))).first()
        yield {"round": k, "new": new, "found": found, "open": open_, "n_open": n_open, "decoded": decoded, "candidates": candidates, "levels": levels}
        if p.max_rounds and k >= p.max_rounds:
            return


def reconcile(a: DataFrame, b: DataFrame, p: Params, sketches: Sequence[DataFrame] | None = None) -> Reconciliation:
    """Runs rounds until every group's checksum agrees, or ``p.max_rounds`` are over.

    ``a`` and ``b`` have sig, for 256 bits also l0 to l3 (see ``binparity.wide_set``; not null, not zero, distinct) and, for many set pairs at once, inst. With no cap the result is the exact
    difference: groups still open after SAFETY_ROUNDS are exchanged in full. ``sketches``: both hosts' ``host_sketch``, where they are at hand.
    """
    a, b = S.with_inst(a), S.with_inst(b)
    if p.sidecar:
        a, b = written(a, "side_a"), written(b, "side_b")
    sizes = [x.agg(F.count(F.lit(1)), F.approx_count_distinct("inst")).first() for x in (a, b)] if p.shape == "auto" and not sketches else [(0, 1)]
    shape = "two_pass" if sketches else choose_shape(p, sum(x[0] for x in sizes), max(1, max(x[1] for x in sizes)))
    steps = []
    for step in reconcile_iter(a, b, p, shape, sketches):
        steps.append(step)
        if p.max_rounds is None and step["round"] >= SAFETY_ROUNDS:
            break
    last = steps[-1]
    found = last["found"]
    open_ = last["open"]
    if last["n_open"] and p.max_rounds is None:
        rows = S.with_node(_sides(a, b), p, open_, last["levels"], last["n_open"])
        keys = ["inst", "sig", *S.wide_columns(a)]
        whole = rows.groupBy(*keys).agg(F.max("side").alias("hi"), F.min("side").alias("lo")).where("hi = lo").select(*keys, (F.col("hi") == 0).alias("in_a"))
        closed = found.join(S.with_node(found, p, open_, last["levels"], last["n_open"]).select("inst", "sig"), ["inst", "sig"], "left_anti")
        found, open_ = written(closed.union(whole), "found"), open_.limit(0)
    rounds = None
    for s in steps:
        part = s["new"].select("inst", "round", "root", "path", "bin", "sig")
        rounds = part if rounds is None else rounds.union(part)
    diff = found.select("inst", "sig", *S.wide_columns(a), F.when(F.col("in_a"), "A_only").otherwise("B_only").alias("side"))
    return Reconciliation(a, b, p, diff, rounds, open_, L.bin_parity_ledger(a, b, [s["decoded"] for s in steps], p), [s["decoded"] for s in steps], [s["candidates"] for s in steps])


def bin_parity_small(a: DataFrame, b: DataFrame, n: int = 255, t: int = 8, **more) -> Reconciliation:
    """The scheme for a few differences: one group."""
    return reconcile(a, b, Params(g=1, n=n, t=t, **more))


def share_by_round(r: Reconciliation) -> DataFrame:
    """(round, n): elements of the true result that were first recovered in each round."""
    first = r.rounds.join(r.diff, ["inst", "sig"], "left_semi").groupBy("inst", "sig").agg(F.min("round").alias("round"))
    return first.groupBy("round").agg(F.count(F.lit(1)).alias("n"))
