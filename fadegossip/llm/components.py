"""Connected components by alternating large-star and small-star steps on an edge table.

Every step is a minimum per node (map-side combined) and one join, so a hub never gathers its neighbours in a
task. Each round is checkpointed; rounds stop when the edge table is a forest of stars.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadegossip.llm.frames import cut


def _star(edges: DataFrame, large: bool, together: bool = False) -> DataFrame:
    """One step. edges: distinct (a, b) with a > b. together: in one task, without a shuffle."""
    dealt = lambda x: x.coalesce(1) if together else x
    both = dealt(edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select("b", "a")) if large else edges.select(F.col("a").alias("u"), F.col("b").alias("v")))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    # the repartition-free join below is re-dealt by Spark, which can split a hub's rows
    linked = both.join(low.withColumnRenamed("u", "k"), F.col("u") == F.col("k"))
    if large:
        out = linked.where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = linked.where("v <> m").select(F.col("v").alias("a"), F.col("m").alias("b")).union(low.select("u", "m"))
    return dealt(out).where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def components(edges: DataFrame, few: int = 0) -> DataFrame:
    """(a, b) links of comparable ids -> (node, root): root is the least id reachable; only linked ids appear.

    few: a round of at most so many links runs in one task, since to deal them out costs more than the work.
    """
    now = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    mark, together = None, bool(few) and now.count() <= few
    while True:
        now = cut(_star(_star(now, True, together), False, together))
        seen = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("b").cast("decimal(38,0)")).alias("s"), F.countDistinct("a").alias("d")).first()
        state = (seen["n"], seen["s"], seen["d"])
        if state == mark or not seen["n"]:
            break
        mark, together = state, seen["n"] <= few
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select("b", "b").distinct())
