"""Connected components by randomised contraction.

Every round each node picks, among itself and its neighbours, the node with the least hash under that
round's seed; edges are rewritten to the picks and repeats dropped. The number of nodes with edges
shrinks by a constant factor a round in expectation, whatever the shape (long paths included). Rounds are joins and
map-side combined minima over tables in the shared folder, so nothing but row counts reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, keep


def connected(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root), written, for every node of ``edges`` (a long, b long); nodes of one component share a root.

    Loops and repeated edges are allowed; nulls are dropped; no edges give no rows.
    """
    spark = edges.sparkSession
    picks: list[DataFrame] = []
    now = keep(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    for k in range(most_rounds):
        if now.isEmpty():
            break
        both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        order = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(k)).alias("h"), F.col(c).alias("v"))  # noqa: B023, E731
        pick = keep(both.groupBy("a").agg(F.least(F.min(order("b")), F.min(order("a"))).alias("m")).select(F.col("a").alias("node"), F.col("m.v").alias("root")), "picks")
        picks.append(pick)
        first, second = pick.toDF("a", "ra"), pick.toDF("b", "rb")
        before, now = now, keep(
            now.join(first, "a").join(second, "b").where("ra <> rb")
            .select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(),
            "edges",
        )
        discard(before)
    else:
        raise RuntimeError(f"components are not done after {most_rounds} rounds")
    discard(now)
    if not picks:
        return keep(spark.createDataFrame([], "node long, root long"), "roots")
    found = picks[0]
    for pick in picks[1:]:
        found = found.join(pick.toDF("root", "_next"), "root", "left").select("node", F.coalesce("_next", "root").alias("root"))
    found = keep(found, "roots")
    discard(*picks)
    return found
