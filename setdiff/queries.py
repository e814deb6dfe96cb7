"""The registered queries: each is (run, SQL or None)."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial
from math import ceil

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setdiff import experiments as X
from setdiff.functions import hashing as H
from setdiff.functions import signature as G
from setdiff.functions.gf import packed_table
from setdiff.operators import binparity as S
from setdiff.operators import cells as C
from setdiff.operators import decode as D
from setdiff.operators import estimate as E
from setdiff.operators import relational as R
from setdiff.operators import syndromes as Y
from setdiff.operators import verify as V
from setdiff.operators.rounds import bin_parity_small, reconcile, share_by_round
from setdiff.plans import ledger as L
from setdiff.plans import model as M
from setdiff.plans import planner as P
from setdiff.plans import tune as T
from setdiff.plans.params import Params, groups_for, published
from setdiff.session import written
from setdiff.sources.workloads import DAYS_SQL, LINES_SQL, WORKLOADS, lines_an_order, orders_a_day, per_load, table
from setdiff.streaming import sketches as K

Query = Callable[[SparkSession, str], DataFrame]

#: Sketch queries lay both sets of w3 out in so many groups, whatever the scale.
GROUPS = 200
PORTABLE = Params(g=GROUPS, n=127, t=13, family="portable")
_ROOT = H.portable_text("sig", H.seed_of(H.GROUP), GROUPS, "//")
_BIN = H.portable_text("sig", H.seed_of(H.BIN, 1), 127, "//")
_W3A, _W3B = WORKLOADS["w3"].sql
_KEYED_A = f"(select sig, {_ROOT} as root, {_BIN} as bin from ({_W3A}))"
_KEYED_B = f"(select sig, {_ROOT} as root, {_BIN} as bin from (select distinct sig from ({_W3B})))"
TOW_ELL = 8
#: Keys that one side lacks in the planner's query.
PLANNED = (10, 100, 1000)


def _pair(name: str, spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return WORKLOADS[name].pair(spark, sf)


def _run_bin_parity(name: str, spark: SparkSession, sf: str, **more) -> DataFrame:
    """To completion, parameters for the estimated difference."""
    a, b = _pair(name, spark, sf)
    d = max(1.0, P.estimate_or(None, a, b) or 1.0)
    return reconcile(a, b, published(d, **more)).diff.select("sig", "side")


def _scheme(name: str, scheme: str, spark: SparkSession, sf: str) -> DataFrame:
    """The published settings: whole-set capacity the inflated estimate, two cells for each of the plain estimate; what fails is done again, so that the result is whole."""
    a, b = _pair(name, spark, sf)
    if scheme == "whole_syndrome":  # read by the estimate, the code, the sides and the checksums
        a, b = written(a, "side_a"), written(b, "side_b")
    d = max(1.0, P.estimate_or(None, a, b) or 1.0)
    if scheme == "full_exchange":
        return R.full_exchange(a, b)
    if scheme == "whole_syndrome":
        return Y.whole_syndrome(a, b, ceil(d), complete=True).select("sig", "side")
    if scheme == "grouped_syndrome":
        return Y.grouped_syndrome(a, b, published(d))[0].select("sig", "side")
    if scheme == "cell_table":
        return C.cell_digest(a, b, d / E.GAMMA, complete=True).select("sig", "side")
    return C.filter_cells(a, b, d / E.GAMMA, b.count(), complete=True)[0].select("sig", "side")


def _keyed(name: str, side: int, spark: SparkSession, sf: str, p: Params = PORTABLE) -> DataFrame:
    d = _pair(name, spark, sf)[side]
    return d.withColumn("root", S.root_of(p)).withColumn("bin", S.bin_of(p, 1))


def _decoded(spark: SparkSession, sf: str) -> DataFrame:
    both = _keyed("w3", 0, spark, sf).union(_keyed("w3", 1, spark, sf))
    return D.differing_bins(both, ["root"], 7, 13)


_PARITY = "select root, bin from {} group by root, bin having count(*) % 2 = 1"
_DIFF_BINS = f"(({_PARITY.format(_KEYED_A)}) except ({_PARITY.format(_KEYED_B)})) union all (({_PARITY.format(_KEYED_B)}) except ({_PARITY.format(_KEYED_A)}))"


def _lanes_sql() -> str:
    lists = [f"bit_xor(list_extract([{', '.join(str(int(x)) for x in lane)}], cast(bin + 1 as int)))" for lane in packed_table(7, 13)]
    return f"select root, {', '.join(f'cast({x} as bigint) as lane{i}' for i, x in enumerate(lists))} from {_KEYED_A} group by root"


def _codeword(spark: SparkSession, sf: str) -> DataFrame:
    cw = S.encode(_keyed("w3", 0, spark, sf), ["root"], 7, 13)
    return cw.select("root", *[F.col("cw")[i].alias(f"lane{i}") for i in range(2)])


def _tow(name: str, side: int, spark: SparkSession, sf: str) -> DataFrame:
    y = E.tow_sketch(_pair(name, spark, sf)[side], TOW_ELL, "portable")
    return y.select(F.posexplode("y").alias("idx", "y")).select(F.col("idx").cast("int").alias("idx"), "y")


def _tow_sql(sql: str) -> str:
    parts = [f"select {i} as idx, cast(sum({H.sign_text('sig', H.seed_of(H.SIGN, i), '//')}) as bigint) as y from (select distinct sig from ({sql}))" for i in range(TOW_ELL)]
    return " union all ".join(parts)


def _tow_estimate(spark: SparkSession, sf: str) -> DataFrame:
    a, b = (E.tow_sketch(x, TOW_ELL, "portable") for x in _pair("w3", spark, sf))
    return E.tow_estimate(a, b, TOW_ELL).select("d_hat")


def _cells_sql(cells: int, k: int) -> str:
    stripe = cells // k
    ids = [f"{H.portable_text('sig', H.seed_of(H.CELL, i), stripe, '//')} + {i * stripe}" for i in range(k)]
    rows = " union all ".join(f"select sig, {x} as cell from ({_W3A})" for x in ids)
    return f"select cell, count(*) as cnt, bit_xor(sig) as id_xor from ({rows}) group by cell"


def _filter_sql(bits: int, k: int) -> str:
    return " union ".join(f"select {H.portable_text('sig', H.seed_of(H.FILTER, i), bits, '//')} as pos from (select doc_id + 1 as sig from labels)" for i in range(k))


def _ideal(spark: SparkSession, sf: str) -> DataFrame:
    """The chance that all line items of an order fall into bins of their own."""
    return per_load(lines_an_order(spark, sf), "d int, n int, p double", lambda d: [(d, n, round(M.p_ideal(d, n), 9)) for n in T.PRACTICAL])


_IDEAL_SQL = (
    "select d::int as d, n::int as n, round((select coalesce(product(1 - k / n::double), 1) from range(d) t(k)), 9) as p "
    f"from {LINES_SQL} a, (values {', '.join(f'({n})' for n in T.PRACTICAL)}) b(n)"
)


def _matrix(spark: SparkSession, _: str) -> DataFrame:
    m = M.transition_matrix(127, 5)
    return spark.createDataFrame([(i, j, round(float(m[i, j]), 9)) for i in range(6) for j in range(6)], "i int, j int, p double")


_MATRIX_OF = """
with ij as (select i::int as i, j::int as j from range({most}) a(i), range({most}) b(j)),
terms as (
  select i, j, k, (case when (k - (i - j)) % 2 = 0 then 1 else -1 end)
    * (factorial(k::int) / (factorial((i - j)::int) * factorial((k - i + j)::int)))::double
    * (factorial(i) / (factorial(k::int) * factorial((i - k)::int)))::double
    * (select coalesce(product(1 - x / {n}.0::double), 1) from range(k) t(x)) * power(({n} - k) / {n}.0::double, i - k) as v
  from ij, range({most}) c(k) where i >= j and k >= i - j and k <= i)
select ij.i, ij.j, {round_}(coalesce((select sum(v) from terms where terms.i = ij.i and terms.j = ij.j), 0){places}) + 0.0 as p from ij
"""
_MATRIX_SQL = _MATRIX_OF.format(n=127, most=6, round_="round", places=", 9")


def _tail(spark: SparkSession, sf: str) -> DataFrame:
    return per_load(orders_a_day(spark, sf), "d int, t int, p double", lambda d: [(d, t, round(M.p_overflow(d, groups_for(d), t), 9)) for t in range(8, 18)])


#: (d, g, x, p): chance that one of g groups gets x of the differences that a missed day makes.
_PMF_SQL = (
    "(select d, g, x, case when x > d then 0 when g = 1 then (x = d)::int else "
    "exp(d * ln(1 - 1.0::double / greatest(g, 2))) * (select coalesce(product((d - j) / ((j + 1.0::double) * greatest(g - 1, 1))), 1) from range(x) q(j)) end as p "
    f"from (select d, ceil(d / 5.0::double)::bigint as g from {DAYS_SQL}), range(41) r(x))"
)
_TAIL_SQL = f"select d::int as d, t::int as t, round(1 - sum(p) filter (where x <= t), 9) + 0.0 as p from {_PMF_SQL}, range(8, 18) b(t) group by 1, 2"


def _bits_grid(spark: SparkSession, sf: str) -> DataFrame:
    """Bits of a group that differs by the line items of an order."""
    grid = lambda d: [(n, t, d, w, M.bits_per_group(n, t, d, w)) for n in T.PRACTICAL for t in range(8, 18) for w in (32, 64, 256)]
    return per_load(lines_an_order(spark, sf), "n int, t int, delta int, w int, bits int", grid)


_BITS_SQL = (
    f"select n::int as n, t::int as t, delta::int as delta, w::int as w, (t * log2(n + 1) + delta * log2(n + 1) + delta * w + w)::int as bits from (values {', '.join(f'({n})' for n in T.PRACTICAL)}) a(n), "
    f"range(8, 18) b(t), {LINES_SQL} c(delta), (values (32), (64), (256)) d(w)"
)


def _overhead(spark: SparkSession, sf: str) -> DataFrame:
    grid = lambda d: [(n, t, d, round(M.overhead_formula(n, t, d, 32, E.GAMMA) / 32, 11)) for n in T.PRACTICAL for t in range(8, 18)]
    return per_load(lines_an_order(spark, sf), "n int, t int, delta int, ratio double", grid)


_OVERHEAD_SQL = (
    f"select n::int as n, t::int as t, delta::int as delta, round((1.38::double * (t * log2(n + 1) + 32) / delta + log2(n + 1) + 32) / 32, 11) as ratio "
    f"from (values {', '.join(f'({n})' for n in T.PRACTICAL)}) a(n), range(8, 18) b(t), {LINES_SQL} c(delta)"
)

#: Golden optimum of the split-aware, doubled-bound tuner at three rounds and 0.99: differences, bits, n, t (fixed values, worked out once).
GOLDEN = ((10, 78, 63, 8), (30, 78, 63, 8), (100, 84, 63, 9), (300, 91, 127, 8), (1000, 104, 255, 8), (3000, 120, 255, 10), (10_000, 135, 511, 10), (30_000, 144, 511, 11), (100_000, 160, 1023, 11))


def _best(spark: SparkSession, _: str) -> DataFrame:
    grid = T.tuning_grid(spark, [g[0] for g in GOLDEN]).where("feasible")
    best = grid.groupBy("d").agg(F.min(F.struct("objective", (-F.col("bound")).alias("nb"), "n", "t")).alias("b"))
    return best.select("d", F.col("b.objective").alias("objective"), F.col("b.n").alias("n"), F.col("b.t").alias("t"))


def _shares(spark: SparkSession, sf: str) -> DataFrame:
    rows = lambda d: [(d, k, round(x, 6)) for k, x in enumerate(M.expected_shares(127, 13, d, groups_for(d), 4), 1)]
    return per_load(orders_a_day(spark, sf), "d long, round int, share double", rows)


def _shares_sql() -> str:
    """Of x differences in a group, those left after k rounds by powers of the transition matrix; weighted by the chance of x."""
    step = "select i, {k} as k, sum(p * left_) as left_ from m join e{b} on m.j = e{b}.x group by 1"
    powers = ", ".join(f"e{k} as (select i as x, k, left_ from ({step.format(k=k, b=k - 1)}))" for k in range(1, 5))
    every = " union all ".join(f"select x, k, left_ from e{k}" for k in range(5))
    return (
        f"with m as ({_MATRIX_OF.format(n=127, most=14, round_='', places='')}), e0 as (select x, 0 as k, x::double as left_ from range(14) r(x)), {powers}, "
        f"l as (select d, g, k, sum(p * left_) as left_ from {_PMF_SQL} join ({every}) using (x) group by 1, 2, 3) "
        "select a.d::bigint as d, b.k::int as round, round((a.left_ - b.left_) / (a.d / a.g::double), 6) + 0.0 as share from l a join l b on a.d = b.d and b.k = a.k + 1"
    )


def _full_ledger(spark: SparkSession, sf: str) -> DataFrame:
    b = _pair("w3", spark, sf)[1]
    n = b.agg(F.count(F.lit(1)).alias("n")).select(F.lit(0).cast("long").alias("inst"), F.lit(1).alias("round"), "n")
    return L.message(n, "full_exchange", "B>A", "elements", F.col("n"), 32).select("kind", "items", "model_bits", "wire_bytes")


def _rollup(spark: SparkSession, sf: str) -> DataFrame:
    return R.rollup_metrics(_bits_grid(spark, sf), ["t", "w"], ["bits"]).select(F.coalesce("t", F.lit(-1)).alias("t"), F.coalesce("w", F.lit(-1)).alias("w"), F.col("n").alias("items"), "sum_bits", "avg_bits")


def _cumulative(spark: SparkSession, sf: str) -> DataFrame:
    out = R.cumulative_share(table(spark, sf, "orders").groupBy("o_orderpriority", F.year("o_orderdate").alias("y")).agg(F.count(F.lit(1)).alias("n")), ["o_orderpriority"], "y", "n")
    return out.select("o_orderpriority", "y", "n", F.round("share", 9).alias("share"))


def _relay_batch(spark: SparkSession, sf: str) -> DataFrame:
    out = K.windowed(K.signed_events(table(spark, sf, "events"), None))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", "xs", "chk")


def _relay_stream(spark: SparkSession, sf: str) -> DataFrame:
    """The same through a stream that ends when the files do."""
    import uuid

    name = f"relay_{uuid.uuid4().hex}"
    out = K.windowed(K.signed_events(K.read_events(spark, f"{sf}/events.parque[t]"), "30 days"))
    q = out.writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", "xs", "chk")


_RELAY_SQL = "select cast(cast(ts as date) as varchar) as day, count(*) as n, bit_xor(event_id + 1) as xs, cast(sum(event_id + 1) as bigint) as chk from events group by 1"


def _sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    from setdiff.functions.sql import register

    register(spark)
    table(spark, sf, "orders").createOrReplaceTempView("sd_orders")
    return spark.sql(f"select sd_sig(o_orderkey) as sig, sd_gid(sd_sig(o_orderkey), {GROUPS}) as root, sd_bin(sd_sig(o_orderkey), 127) as bin from sd_orders")


def _one_element(spark: SparkSession, sf: str) -> DataFrame:
    return S.one_element(*_pair("w14_one", spark, sf))


def _multiset(spark: SparkSession, sf: str) -> DataFrame:
    return V.multiset_hash(_pair("w3", spark, sf)[0])


_MULTISET_SQL = (
    "select " + ", ".join(f"bit_xor(('0x' || sha256(cast(sig as varchar))[{16 * i + 1}:{16 * i + 15}])::bigint) as lane{i}" for i in range(4)) + f", count(*) as n from ({_W3A})"
)


def _exceptions(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _pair("w3", spark, sf)
    diff = S.with_bin(R.full_exchange(a, b).select("sig"), 255, H.seed_of(H.BIN, 1), "portable").withColumn("root", F.lit(0))
    return S.classify_bins(diff, ["root"]).groupBy("kind").agg(F.count(F.lit(1)).alias("bins"), F.sum("n").alias("elements"))


_EXCEPTIONS_SQL = (
    f"with d as ({WORKLOADS['w3'].difference_sql()}), b as (select {H.portable_text('sig', H.seed_of(H.BIN, 1), 255, '//')} as bin, count(*) as n from d group by 1) "
    "select case when n = 1 then 'ideal' when n % 2 = 0 then 'even' else 'odd' end as kind, count(*) as bins, cast(sum(n) as bigint) as elements from b group by 1"
)


def _bidirectional(spark: SparkSession, sf: str) -> DataFrame:
    """What each host ends up with after A has sent back what only it has: the union, twice."""
    a, b = _pair("w5", spark, sf)
    got = reconcile(a, b, published(50))
    at_a = got.union().select("sig")
    at_b = b.select("sig").union(got.a_only.select("sig"))
    return at_a.withColumn("host", F.lit("A")).union(at_b.withColumn("host", F.lit("B")))


def _small(name: str, spark: SparkSession, sf: str) -> DataFrame:
    return bin_parity_small(*_pair(name, spark, sf)).diff.select("sig", "side")


def _auto(name: str, spark: SparkSession, sf: str) -> DataFrame:
    return P.reconcile_auto(*_pair(name, spark, sf))[0].select("sig", "side")


def _plan(spark: SparkSession, sf: str) -> DataFrame:
    """The schemes for all orders against orders less d keys."""

    def rows(size: int) -> list[tuple]:
        return [(d, k, float(round(v)), P.choose_scheme(d, size, size - d).scheme) for d in PLANNED for k, v in P.predicted_bits(d, size, size - d).items()]

    return per_load(table(spark, sf, "orders").agg(F.count("o_orderkey").alias("size")), "d long, scheme string, bits double, chosen string", rows)


def _merkle(spark: SparkSession, sf: str) -> DataFrame:
    return V.merkle_leaves(_pair("w3", spark, sf)[0])


_LEAVES = f"(select greatest(1, (count(*) + {V.LEAF - 1}) // {V.LEAF}) from ({_W3A}))"
_MERKLE_SQL = f"select sig % {_LEAVES} as leaf, md5(string_agg(cast(sig as varchar), ',' order by sig)) as hash from ({_W3A}) group by 1"


def _merkle_root_sql() -> str:
    sql = _MERKLE_SQL
    for _ in range(V.LEVELS):
        sql = f"select leaf // {V.FANOUT} as leaf, md5(string_agg(hash, '' order by leaf)) as hash from ({sql}) group by 1"
    return f"select hash from ({sql})"


def _rounds(spark: SparkSession, sf: str) -> DataFrame:
    return share_by_round(reconcile(*_pair("w3", spark, sf), published(257)))


def _estimators(spark: SparkSession, sf: str) -> DataFrame:
    """d by every estimator."""
    a, b = _pair("w3", spark, sf)
    parts = {"tow": E.estimate_d(a, b).select("d_hat"), "hll": E.hll_estimate(a, b), "theta": E.theta_estimate(a, b), "minhash": E.minhash_estimate(a, b), "strata": E.strata_estimate(a, b)}
    out = None
    for k, v in parts.items():
        one = v.select(F.lit(k).alias("estimator"), F.col("d_hat").cast("double").alias("d_hat"))
        out = one if out is None else out.union(one)
    return out


def _f2(spark: SparkSession, sf: str) -> DataFrame:
    return E.f2_estimate(table(spark, sf, "events"), "user_id")


def _union(spark: SparkSession, sf: str) -> DataFrame:
    return reconcile(*_pair("w5", spark, sf), published(50)).union().select("sig")


def _intersect(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _pair("w5", spark, sf)
    return a.intersect(b)


def _asof(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events").select("user_id", "ts", "event_id")
    return R.asof_latest(e, "user_id", "ts", "2024-01-15 00:00:00").select("user_id", F.date_format("ts", "yyyyMMddHHmmss").cast("long").alias("at"))


def _interval(spark: SparkSession, sf: str) -> DataFrame:
    """Views with a purchase of the same user within an hour, over all events."""
    e = table(spark, sf, "events").select("user_id", "ts", "event_type")
    got = R.interval_match(e.where("event_type = 'view'"), e.where("event_type = 'purchase'"), "user_id", "ts", 3600)
    return got.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


_INTERVAL_SQL = (
    "select a.user_id, count(*) as n from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' "
    "and abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000 group by 1"
)


def _cells(spark: SparkSession, sf: str) -> DataFrame:
    return C.cell_table(_pair("w3", spark, sf)[0], 600, 3, "portable").select("cell", "cnt", "id_xor")


def _filter(spark: SparkSession, sf: str) -> DataFrame:
    return C.filter_rows(_pair("w4", spark, sf)[1], 8192, 4, "portable").select("pos")


def _metrics_pivot(spark: SparkSession, sf: str) -> DataFrame:
    wide = R.pivot_report(X.signature_lengths(spark).withColumn("ratio", F.round("ratio", 9)), "scheme", "w", "ratio", [32, 64, 256])
    return wide.select("scheme", *[F.col(str(w)).alias(f"w{w}") for w in (32, 64, 256)])


# SQL twins of the cost formulas; only the tuned parameters (groups, bins, capacity) come from the library.

_CELLS_SQL = "(ceil(2 * ({d}) / k) * k)"
_RATE_SQL = "({size} / (power(ln(2), 2) * 192 * ({d})))"
_FILTER_SQL = "greatest(64, ceil({size} * ln(1 / rate) / power(ln(2), 2)))"
_REST_SQL = "(ceil(2 * (rate * ({d}) + 3 * sqrt(rate * ({d})) + 8) / 4) * 4)"


def _lengths_sql(d: int = 1000) -> str:
    p = T.tuned(E.GAMMA * d, 5, 3, 0.99)
    bits = {
        "bin_parity": f"{p.g} * ({p.t} * log2({p.n + 1}) + w) + {d} * (log2({p.n + 1}) + w)", "grouped_syndrome": f"{p.g} * ({p.t} * w + w)",
        "whole_syndrome": f"ceil(1.38::double * {d}) * w", "cell_table": f"{_CELLS_SQL.format(d=d)} * 3 * w",
    }
    rows = " union all ".join(f"select w::int as w, '{s}' as scheme, round(({x}) / ({d}.0::double * w), 9) as ratio from v" for s, x in bits.items())
    return f"with v as (select w, {3 if d > 200 else 4}::double as k from (values (32), (64), (256)) t(w)) {rows}"


def _filter_use_sql(size: int = 1_000_000) -> str:
    v = f"select d, case when d > 200 then 3 else 4 end::double as k, {_RATE_SQL.format(size=f'({size} - d)', d='d')} as rate from (values (1000), (5000), (10000), (12000), (16000), (30000), (100000)) t(d)"
    bits = f"case when rate >= 1 then {_CELLS_SQL.format(d='d')} * 96 else {_FILTER_SQL.format(size=f'({size} - d)')} + {_REST_SQL.format(d='d')} * 96 end"
    return f"select d::bigint as d, rate < 1 as filter_used, ({bits}) / 8 as model_bytes from ({v})"


def _plan_sql() -> str:
    rows = []
    for d in PLANNED:
        p, size = T.tuned(max(1.0, E.GAMMA * d)), f"((select count(o_orderkey) from orders) - {d})"
        e = f"(1.38::double * {d})"
        v = f"select {3 if E.GAMMA * d > 200 else 4}::double as k, {_RATE_SQL.format(size=size, d=e)} as rate"
        cells = f"{_CELLS_SQL.format(d=e)} * 96"
        bits = {
            "full_exchange": f"{size} * 32", "whole_syndrome": f"ceil({e}) * 32", "cell_table": cells, "bin_parity": f"{p.g} * ({p.t} * log2({p.n + 1}) + 32) + {e} * (log2({p.n + 1}) + 32)",
            "grouped_syndrome": f"{p.g} * ({p.t} * 32 + 32)", "filter_cells": f"case when rate >= 1 then {cells} else {_FILTER_SQL.format(size=size)} + {_REST_SQL.format(d=e)} * 96 end",
        }
        rows += [f"select {d}::bigint as d, '{s}' as scheme, round_even(({x})::double, 0) as bits from ({v})" for s, x in bits.items()]
    every = " union all ".join(rows)
    return f"with v as ({every}) select d, scheme, bits, (select arg_min(scheme, bits) from v u where u.d = v.d and u.scheme in ('full_exchange', 'bin_parity')) as chosen from v"


def _capacity_sql() -> str:
    p = published(1)
    whole = f"(g * {p.t * p.m})::double"
    saved = f"sum(p * ({p.t} - x)) filter (where x < {p.t}) * g * {p.m}"
    cost = f"g * {E.ELL} * ceil(log2(2 * ((select count(o_orderkey) from orders) // g) + 1))"
    return f"select d::bigint as d, 'uniform' as plan, {whole} as bits from {_PMF_SQL} where x = 0 union all select d::bigint, 'per_group', round({whole} - {saved} + {cost}, 3) from {_PMF_SQL} group by d, g"


_CHAT = ["conv_id", "turn", "text"]


def _wide(spark: SparkSession, sf: str) -> DataFrame:
    """256-bit signatures of chat turns; the result has all four lanes."""
    c = table(spark, sf, "conversations")
    a, b = (S.wide_set(x, G.row_hash256(_CHAT)) for x in (c, c.where("turn < 4")))
    d = max(1.0, P.estimate_or(None, a, b) or 1.0)
    return reconcile(a, b, published(d, w=256)).diff.select(*S.WIDE, "side")


def _wide_sql() -> str:
    text = f"concat_ws('|', {', '.join(f'cast({c} as varchar)' for c in _CHAT)})"
    lane = "('0x' || sha256({t})[{i}:{j}])::ubigint::hugeint"
    cols = [lane.format(t=text, i=16 * k + 1, j=16 * k + 16) for k in range(4)]
    signed = ", ".join(f"({c} - case when {c} >= 9223372036854775808 then 18446744073709551616::hugeint else 0 end)::bigint as l{k}" for k, c in enumerate(cols))
    every, some = f"select distinct {signed} from conversations", f"select distinct {signed} from conversations where turn < 4"
    return f"select *, 'A_only' as side from (({every}) except ({some}))"


def registry() -> dict[str, tuple[Query, str | None]]:
    """Every query with its SQL, if it has one."""
    q: dict[str, tuple[Query, str | None]] = {}
    for n in ("w1_d10", "w1_d100", "w1_d1000", "w3", "w5", "w6", "w7", "w8", "w9", "w10", "w11", "w12", "w13"):
        q[f"bin_parity_{n}"] = partial(_run_bin_parity, n), WORKLOADS[n].difference_sql()
    for n in ("equal", "empty", "one", "tiny"):
        q[f"bin_parity_small_w14_{n}"] = partial(_small, f"w14_{n}"), WORKLOADS[f"w14_{n}"].difference_sql()
    for n, more in (("mset_xor", {"checksum": "mset_xor"}), ("hashed_sum", {"checksum": "hashed_sum"}), ("two_pass", {"shape": "two_pass"}), ("two_way_split", {"ways": 2, "n": 63, "t": 6}), ("toeplitz", {"solver": "toeplitz"}), ("w64", {"w": 64}), ("no_group_check", {"check_group": False})):
        q[f"bin_parity_w3_{n}"] = partial(_run_bin_parity, "w3", **more), WORKLOADS["w3"].difference_sql()
    q["bin_parity_w256_w13"] = _wide, _wide_sql()
    for n in ("w3", "w15"):
        q[f"bin_parity_auto_{n}"] = partial(_auto, n), WORKLOADS[n].difference_sql()
    for scheme, n in (("full_exchange", "w3"), ("full_exchange", "w5"), ("full_exchange", "w9"), ("whole_syndrome", "w5"), ("grouped_syndrome", "w3"), ("cell_table", "w3"), ("filter_cells", "w4")):
        q[f"{scheme}_{n}"] = partial(_scheme, n, scheme), WORKLOADS[n].difference_sql()
    w5a, w5b = WORKLOADS["w5"].sql
    q["bidirectional_w5"] = _bidirectional, f"with u as (({w5a}) union ({w5b})) select sig, 'A' as host from u union all select sig, 'B' as host from u"
    q["union_w5"] = _union, f"({w5a}) union ({w5b})"
    q["intersect_w5"] = _intersect, f"({w5a}) intersect ({w5b})"
    q["one_element_w14"] = _one_element, "select cast(7 as bigint) as sig"
    q["signatures_orders"] = (lambda s, d: table(s, d, "orders").select("o_orderkey", G.mix32("o_orderkey").alias("sig"))), f"select o_orderkey, {G.mix32_text('o_orderkey')} as sig from orders"
    cols = ["l_orderkey", "l_linenumber", "l_partkey", "l_returnflag"]
    q["portable_rowhash_lineitem"] = (lambda s, d: table(s, d, "lineitem").select("l_orderkey", G.portable_row_hash(cols).alias("sig"))), f"select l_orderkey, {G.portable_row_text(cols)} as sig from lineitem"
    q["bins_w3"] = (lambda s, d: _keyed("w3", 0, s, d)), f"select sig, root, bin from {_KEYED_A}"
    q["parity_bins_w3"] = (lambda s, d: S.parity_bins(_keyed("w3", 0, s, d), ["root"])), _PARITY.format(_KEYED_A)
    q["bitmap_diff_w3"] = (lambda s, d: S.bitmap_exchange(_keyed("w3", 0, s, d), _keyed("w3", 1, s, d), ["root"])), _DIFF_BINS
    q["decoded_bins_w3"] = _decoded, _DIFF_BINS
    q["xor_sums_w3"] = (lambda s, d: _keyed("w3", 0, s, d).groupBy("root", "bin").agg(F.bit_xor("sig").alias("xs"))), f"select root, bin, bit_xor(sig) as xs from {_KEYED_A} group by root, bin"
    q["checksums_w3"] = (lambda s, d: V.checksum(_keyed("w3", 0, s, d), ["root"]).select("root", F.col("chk").cast("long").alias("chk"))), f"select root, cast(sum(sig) % 4294967296 as bigint) as chk from {_KEYED_A} group by root"
    q["codeword_w3_m7"] = _codeword, _lanes_sql()
    q["multiset_hash_w3"] = _multiset, _MULTISET_SQL
    q["merkle_leaves_w3"] = _merkle, _MERKLE_SQL
    q["merkle_root_w3"] = (lambda s, d: V.merkle_root(_pair("w3", s, d)[0])), _merkle_root_sql()
    q["exceptions_by_type_w3"] = _exceptions, _EXCEPTIONS_SQL
    q["tow_sketch_w3"] = partial(_tow, "w3", 0), _tow_sql(_W3A)
    q["tow_estimate_w3"] = _tow_estimate, f"select sum((a.y - b.y) * (a.y - b.y)) / {float(TOW_ELL)} as d_hat from ({_tow_sql(_W3A)}) a join ({_tow_sql(_W3B)}) b using (idx)"
    q["cell_table_cells_w3"] = _cells, _cells_sql(600, 3)
    q["filter_bits_w4"] = _filter, _filter_sql(8192, 4)
    q["p_ideal"] = _ideal, _IDEAL_SQL
    q["transition_matrix_n127_t5"] = _matrix, _MATRIX_SQL
    q["binomial_tail"] = _tail, _TAIL_SQL
    q["bits_per_group_grid"] = _bits_grid, _BITS_SQL
    q["overhead_formula_grid"] = _overhead, _OVERHEAD_SQL
    q["tuning_optimum"] = _best, f"select d::bigint as d, o::int as objective, n::int as n, t::int as t from (values {', '.join(map(str, GOLDEN))}) v(d, o, n, t)"
    q["expected_share_by_round"] = _shares, _shares_sql()
    q["round_tradeoff"] = (lambda s, d: X.tuning_by_rounds(s, d)), None
    q["comm_ledger_full_exchange_w3"] = _full_ledger, f"select 'elements' as kind, count(*) as items, count(*) * 32 as model_bits, count(*) * 4 as wire_bytes from (select distinct sig from ({_W3B}))"
    q["metrics_rollup"] = _rollup, f"select coalesce(t, -1)::int as t, coalesce(w, -1)::int as w, count(*) as items, cast(sum(bits) as bigint) as sum_bits, avg(bits) as avg_bits from ({_BITS_SQL}) group by rollup (t, w)"
    q["cumulative_share"] = _cumulative, "select o_orderpriority, y::int as y, n, round(sum(n) over (partition by o_orderpriority order by y rows unbounded preceding) / (sum(n) over (partition by o_orderpriority))::double, 9) as share from (select o_orderpriority, year(o_orderdate) as y, count(*) as n from orders group by 1, 2)"
    q["topk_params"] = (lambda s, d: R.topk(_bits_grid(s, d).where("w = 32 and delta = 5"), 10, "bits", "n", "t")), f"select * from ({_BITS_SQL}) where w = 32 and delta = 5 order by bits, n, t limit 10"
    q["asof_latest_events"] = _asof, "select user_id, cast(strftime(max(ts), '%Y%m%d%H%M%S') as bigint) as at from events where ts <= timestamp '2024-01-15 00:00:00' group by 1"
    q["interval_match_events"] = _interval, _INTERVAL_SQL
    q["sql_functions"] = _sql_surface, f"select sig, root, bin from (select sig, {_ROOT} as root, {_BIN} as bin from ({_W3A}))"
    q["relay_windows_batch"] = _relay_batch, _RELAY_SQL
    q["relay_windows_stream"] = _relay_stream, _RELAY_SQL
    q["planner_bits"] = _plan, _plan_sql()
    q["estimators_w3"] = _estimators, None
    q["f2_users"] = _f2, None
    q["share_by_round_w3"] = _rounds, None
    q["x1_whole_and_cells"] = (lambda s, d: X.compare(s, d, ("bin_parity", "whole_syndrome", "cell_table"), (10, 100, 1000), count=100)), None
    q["x1_decode_growth"] = (lambda s, d: X.decode_growth(s)), None
    q["x2_filter_cells"] = (lambda s, d: X.compare(s, d, ("bin_parity", "filter_cells"), (100, 1000, 5000), count=40, p0=239 / 240)), None
    q["x3_grouped_syndrome"] = (lambda s, d: X.compare(s, d, ("bin_parity", "grouped_syndrome"), (30, 100, 1000), count=20)), None
    q["x4_signature_lengths"] = (lambda s, d: X.signature_lengths(s).withColumn("ratio", F.round("ratio", 9))), _lengths_sql()
    q["x4_pivot"] = _metrics_pivot, f"select scheme, {', '.join(f'max(ratio) filter (where w = {w}) as w{w}' for w in (32, 64, 256))} from ({_lengths_sql()}) group by scheme"
    q["x6_delta"] = (lambda s, d: X.delta_sweep(s, d)), None
    q["x7_shares"] = (lambda s, d: X.measured_shares(s, d)), None
    q["x8_estimator"] = (lambda s, d: X.estimator_accuracy(s)), None
    q["x9_split_ways"] = (lambda s, d: X.split_ways(s)), None
    q["x10_bin_kinds"] = (lambda s, d: X.bin_kinds(s)), None
    q["x11_fake_candidates"] = (lambda s, d: X.fake_candidates(s, d)), None
    q["x12_filter_use"] = (lambda s, d: X.filter_use(s)), _filter_use_sql()
    q["per_group_capacity"] = (lambda s, d: X.per_group_capacity(s, d).withColumn("bits", F.round("bits", 3))), _capacity_sql()
    return q
