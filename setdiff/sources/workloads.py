"""Set pairs on the given tables, each with the SQL that defines it.

A workload is (A, B) of DataFrames with ``sig``; ``sql`` gives the same two sets in DuckDB's dialect, for oracles.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setdiff.functions import signature as G
from setdiff.operators.relational import exclude_exact_d
from setdiff.session import written

LINE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus"]
#: Signatures of one instance that a task holds when sets are laid out.
PART_ROWS = 1 << 20
RELAY_CUT = "2024-01-30 12:00:00"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class Workload:
    name: str
    what: str
    build: Callable[[SparkSession, str], tuple[DataFrame, DataFrame]]
    sql: tuple[str, str]

    def pair(self, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
        return self.build(spark, sf_dir)

    def difference_sql(self) -> str:
        a, b = self.sql
        return (
            f"with a as (select distinct sig from ({a})), b as (select distinct sig from ({b})) "
            "select sig, 'A_only' as side from (select sig from a except select sig from b) "
            "union all select sig, 'B_only' as side from (select sig from b except select sig from a)"
        )


def _first_md5(frm: str, key: str, d: int) -> str:
    return f"(select {key} from {frm} order by md5(cast({key} as varchar)), {key} limit {d})"


def controlled(d: int) -> Workload:
    """The paper's set-up on orders: mixed 32-bit keys, B without the d keys first by md5."""

    def build(spark: SparkSession, sf: str):
        o = table(spark, sf, "orders").select("o_orderkey")
        return G.as_set(o, G.mix32("o_orderkey"), True), G.as_set(exclude_exact_d(o, "o_orderkey", d), G.mix32("o_orderkey"), True)

    sig = f"{G.mix32_text('o_orderkey')} as sig"
    return Workload(f"w1_d{d}", "orders less d keys", build, (f"select {sig} from orders", f"select {sig} from orders where o_orderkey not in {_first_md5('orders', 'o_orderkey', d)}"))


def large_controlled(d: int) -> Workload:
    """Whole line items by 64-bit hash, B without the rows of the orders first by md5; for benches, no SQL twin of the hash."""

    def build(spark: SparkSession, sf: str):
        rows = table(spark, sf, "lineitem")
        sig = G.row_hash64(rows.columns)
        a = G.as_set(rows, sig)
        gone = a.orderBy(F.xxhash64("sig", F.lit(11)), "sig").limit(d)
        return a, a.join(F.broadcast(gone) if d <= 1_000_000 else gone, "sig", "left_anti")

    return Workload(f"w2_d{d}", "line items less d rows", build, ("", ""))


def _simple(name: str, what: str, build, a: str, b: str) -> Workload:
    return Workload(name, what, build, (a, b))


def _w3(spark, sf):
    return G.as_set(table(spark, sf, "orders"), G.identity("o_orderkey"), True), G.as_set(table(spark, sf, "lineitem"), G.identity("l_orderkey"))


def _w4(spark, sf):
    return G.as_set(table(spark, sf, "documents"), G.identity("doc_id")), G.as_set(table(spark, sf, "labels"), G.identity("doc_id"))


def _w5(spark, sf):
    line, y = table(spark, sf, "lineitem"), F.year("l_shipdate")
    return G.as_set(line.where(y == 1996), G.identity("l_partkey")), G.as_set(line.where(y == 1997), G.identity("l_partkey"))


def _w6(spark, sf):
    o, cut = table(spark, sf, "orders"), F.lit("1998-01-01").cast("timestamp")
    return G.as_set(o.where(F.col("o_orderdate") < cut), G.identity("o_custkey")), G.as_set(o.where(F.col("o_orderdate") >= cut), G.identity("o_custkey"))


def _w7(spark, sf):
    e, day = table(spark, sf, "events"), F.to_date("ts")
    return tuple(G.as_set(e.where(day == F.lit(f"2024-01-0{i}").cast("date")), G.identity("user_id")) for i in (1, 2))


_CENTS = "cast(floor(l_extendedprice * 100 + 0.5) as bigint)"
_PICKED = "substring(md5(concat_ws('|', cast(l_orderkey as {t}), cast(l_linenumber as {t}), cast(l_partkey as {t}))), 1, 2) = '00'"


def _w8(spark, sf):
    line = table(spark, sf, "lineitem")
    new = f"{_CENTS} + case when {_PICKED.format(t='string')} then 1 else 0 end"
    return G.as_set(line, G.portable_row_hash([*LINE, _CENTS])), G.as_set(line, G.portable_row_hash([*LINE, f"({new})"]))


def _w9(spark, sf):
    d, sig = table(spark, sf, "documents"), G.portable_row_hash(["text"])
    return G.as_set(d.where("doc_id % 2 = 0"), sig), G.as_set(d.where("doc_id % 2 = 1"), sig)


def _w10(spark, sf):
    p, h = table(spark, sf, "pages"), F.substring(F.md5("url"), 1, 1)
    edited = p.where(h != "0").withColumn("html", F.when(h == "1", F.concat("html", F.lit("<!-- edited -->"))).otherwise(F.col("html")))
    sig = G.portable_row_hash(["url", "html"])
    return G.as_set(p, sig), G.as_set(edited, sig)


def _w11(spark, sf):
    e = table(spark, sf, "events")
    return G.as_set(e, G.identity("event_id"), True), G.as_set(e.where(F.col("ts") < F.lit(RELAY_CUT).cast("timestamp")), G.identity("event_id"), True)


def _vector(change: bool) -> str:
    lead = "case when vec_id % 50 = 0 then 1 else 0 end" if change else "0"
    return f"array_join(transform(embedding, (x, i) -> cast(cast(floor(cast(x as double) * 1000) as bigint) + case when i = 0 then {lead} else 0 end as string)), ',')"


def _vector_sql(change: bool) -> str:
    lead = "case when vec_id % 50 = 0 then 1 else 0 end" if change else "0"
    return f"array_to_string([cast(cast(floor(cast(embedding[i] as double) * 1000) as bigint) + case when i = 1 then {lead} else 0 end as varchar) for i in range(1, len(embedding) + 1)], ',')"


def _w12(spark, sf):
    e = table(spark, sf, "embeddings")
    return G.as_set(e, G.portable_row_hash(["vec_id", _vector(False)])), G.as_set(e, G.portable_row_hash(["vec_id", _vector(True)]))


def _w13(spark, sf):
    c, sig = table(spark, sf, "conversations"), G.portable_row_hash(["conv_id", "turn", "text"])
    return G.as_set(c, sig), G.as_set(c.where("turn < 4"), sig)


def _w15(spark, sf):
    line, sig = table(spark, sf, "lineitem"), G.portable_row_hash(["l_partkey", "l_suppkey"])
    return G.as_set(line.where("l_returnflag = 'A'"), sig), G.as_set(line.where("l_returnflag = 'N'"), sig)


def _degenerate(kind: str) -> Workload:
    """Equal sets, an empty B, one difference, tiny sets."""

    def build(spark, sf):
        n = G.as_set(table(spark, sf, "nation"), G.identity("n_nationkey"), True)
        r = G.as_set(table(spark, sf, "region"), G.identity("r_regionkey"), True)
        return {"equal": (n, n), "empty": (n, n.where("sig < 0")), "one": (n, n.where("sig <> 7")), "tiny": (n, r)}[kind]

    n, r = "select n_nationkey + 1 as sig from nation", "select r_regionkey + 1 as sig from region"
    b = {"equal": n, "empty": f"{n} where false", "one": f"{n} where n_nationkey <> 6", "tiny": r}[kind]
    n = f"select cast(sig as bigint) as sig from ({n})"
    return Workload(f"w14_{kind}", "degenerate pair", build, (n, f"select cast(sig as bigint) as sig from ({b})"))


_PRT = G.portable_row_text
_NEW = f"{_CENTS} + case when {_PICKED.format(t='varchar')} then 1 else 0 end"
_EDIT = "case when md5(url)[1:1] = '1' then html || '<!-- edited -->' else html end"

WORKLOADS: dict[str, Workload] = {
    w.name: w
    for w in (
        controlled(10), controlled(100), controlled(1000),
        _simple("w3", "orders against line items", _w3, "select o_orderkey + 1 as sig from orders", "select l_orderkey + 1 as sig from lineitem"),
        _simple("w4", "documents against labels", _w4, "select doc_id + 1 as sig from documents", "select doc_id + 1 as sig from labels"),
        _simple("w5", "parts shipped in two years", _w5, "select l_partkey + 1 as sig from lineitem where year(l_shipdate) = 1996", "select l_partkey + 1 as sig from lineitem where year(l_shipdate) = 1997"),
        _simple("w6", "customers before and after a date", _w6, "select o_custkey + 1 as sig from orders where o_orderdate < timestamp '1998-01-01'", "select o_custkey + 1 as sig from orders where o_orderdate >= timestamp '1998-01-01'"),
        _simple("w7", "users of two days", _w7, "select user_id + 1 as sig from events where cast(ts as date) = date '2024-01-01'", "select user_id + 1 as sig from events where cast(ts as date) = date '2024-01-02'"),
        _simple("w8", "line items, some re-priced", _w8, f"select {_PRT([*LINE, _CENTS])} as sig from lineitem", f"select {_PRT([*LINE, f'({_NEW})'])} as sig from lineitem"),
        _simple("w9", "texts of even and odd documents", _w9, f"select {_PRT(['text'])} as sig from documents where doc_id % 2 = 0", f"select {_PRT(['text'])} as sig from documents where doc_id % 2 = 1"),
        _simple("w10", "pages, some gone, some edited", _w10, f"select {_PRT(['url', 'html'])} as sig from pages", f"select {_PRT(['url', _EDIT])} as sig from pages where md5(url)[1:1] <> '0'"),
        _simple("w11", "events up to a time", _w11, "select event_id + 1 as sig from events", f"select event_id + 1 as sig from events where ts < timestamp '{RELAY_CUT}'"),
        _simple("w12", "vectors, some changed", _w12, f"select {_PRT(['vec_id', _vector_sql(False)])} as sig from embeddings", f"select {_PRT(['vec_id', _vector_sql(True)])} as sig from embeddings"),
        _simple("w13", "conversations cut short", _w13, f"select {_PRT(['conv_id', 'turn', 'text'])} as sig from conversations", f"select {_PRT(['conv_id', 'turn', 'text'])} as sig from conversations where turn < 4"),
        _simple("w15", "far apart", _w15, f"select {_PRT(['l_partkey', 'l_suppkey'])} as sig from lineitem where l_returnflag = 'A'", f"select {_PRT(['l_partkey', 'l_suppkey'])} as sig from lineitem where l_returnflag = 'N'"),
        *(_degenerate(k) for k in ("equal", "empty", "one", "tiny")),
    )
}


def instances(spark: SparkSession, sf_dir: str, count: int, d: int, size: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """(inst, sig) for ``count`` independent pairs, and the signatures of one: every instance hashes all order keys anew and drops its own d of them.

    All instances run in one job. ``size`` takes the least keys only, for small batches; without it the whole table is taken.
    """
    rows, n = hashed_anew(spark, sf_dir, count, size)
    return rows, without(rows, first_by_hash(rows, d), count * d), n


def hashed_anew(spark: SparkSession, sf_dir: str, count: int, size: int | None = None) -> tuple[DataFrame, int]:
    """(inst, sig) of ``count`` sets, each all order keys hashed anew, and how many keys one has."""
    keys = table(spark, sf_dir, "orders").select(G.mix32("o_orderkey").alias("sig"))
    keys = keys.orderBy("sig").limit(size) if size else keys
    n = size or keys.count()
    # an instance, or a range of its signatures, to a task: repeats are dropped there, and sums over an instance stay in few places
    pieces = -(-n // PART_ROWS)
    keys = keys.repartition(max(1, min(1000, n * count // PART_ROWS)))
    rows = keys.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(count - 1).cast("long"))).alias("inst"), "sig")
    rows = rows.select("inst", (F.pmod(F.xxhash64("sig", "inst"), F.lit((1 << 32) - 1)) + 1).cast("long").alias("sig"))
    key, inst, sig = F.shiftleft("inst", 32) + F.col("sig"), F.shiftright("key", 32), F.col("key").bitwiseAND(F.lit((1 << 32) - 1))
    rows = rows.select(key.alias("key")).repartitionById(max(1, count * pieces), (inst * pieces + F.shiftright(sig * pieces, 32)).cast("int"))
    return rows.mapInArrow(_distinct, "key long").select(inst.alias("inst"), sig.alias("sig")), n


def _distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The distinct keys of a task."""
    keys = np.unique(np.concatenate([np.zeros(0, np.int64), *(b.column(0).to_numpy() for b in batches)]))
    for at in range(0, len(keys), 1 << 16):
        yield pa.RecordBatch.from_arrays([pa.array(keys[at : at + (1 << 16)])], ["key"])


def first_by_hash(rows: DataFrame, d: int, size: int | None = None, count: int = 1) -> DataFrame:
    """(inst, sig, place) of the d signatures of every instance that come first by hash, places from 1: those of a smaller d are among them.

    A limit by rank, cut inside each task before the shuffle, so no task ranks a whole instance. With ``size``, of about so many signatures an instance and
    ``count`` instances, only hashes below a bound are ranked, if every instance is seen to have d of them.
    """
    from pyspark.sql import Window

    h = F.xxhash64("sig", F.lit(5))
    if size and size > 4 * d + 256:
        low = written(rows.where(h < F.lit((2 * d + 128) * (1 << 64) // size - (1 << 63))), "low")
        if low.groupBy("inst").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= d).count() == count:
            rows = low
    place = F.row_number().over(Window.partitionBy("inst").orderBy(h, "sig"))
    return rows.withColumn("place", place).where(F.col("place") <= d)


def without(rows: DataFrame, gone: DataFrame, n_gone: int) -> DataFrame:
    """Rows (inst, sig) less those of ``gone``; both numbers are below 2**31 and 2**32, so that one long is the key."""
    gone = gone.select((F.shiftleft("inst", 32) + F.col("sig")).alias("_gone"))
    return rows.join(F.broadcast(gone) if n_gone <= 1_000_000 else gone, F.shiftleft("inst", 32) + F.col("sig") == F.col("_gone"), "left_anti")


def orders_a_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d): how many orders a day has, each number once: by so many keys a replica differs that misses a day."""
    return table(spark, sf_dir, "orders").groupBy("o_orderdate").agg(F.count(F.lit(1)).alias("d")).select("d").distinct()


def lines_an_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d): how many line items an order has, each number once: by so many rows a group differs, if an order is a group and is missed."""
    return table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("d")).select("d").distinct()


DAYS_SQL = "(select distinct count(*) as d from orders group by o_orderdate)"
LINES_SQL = "(select distinct count(*) as d from lineitem group by l_orderkey)"


def per_load(loads: DataFrame, schema: str, rows: Callable[..., list[tuple]]) -> DataFrame:
    """``rows`` of every row of ``loads``, worked out in the tasks."""
    names = loads.columns

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            got = [x for load in part[names].itertuples(index=False) for x in rows(*map(int, load))]
            yield pd.DataFrame(got, columns=[c.split()[0] for c in schema.split(", ")])

    return loads.mapInPandas(run, schema)


def uniform(spark: SparkSession, size: int, d: int) -> tuple[DataFrame, DataFrame]:
    """The paper's synthetic pairs: ``size`` different 32-bit values, B without d of them. Consecutive numbers through a bijection are draws without repeats."""
    a = spark.range(size).select(G.mix32("id").alias("sig"))
    return a, spark.range(d, size).select(G.mix32("id").alias("sig"))
