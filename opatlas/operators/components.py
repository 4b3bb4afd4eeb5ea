"""Connected components of a link table, without ever bringing links to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut


def components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """node and root (its smallest reachable node) for every node of ``edges`` (lo, hi).

    Alternates a star around each node's smallest neighbour over larger neighbours and over
    smaller ones until nothing moves: a number of rounds that grows with the logarithm of the
    longest path. Each round is cut by a checkpoint.
    """
    now = cut(edges.where("lo < hi"))
    mark = None
    for _ in range(max_rounds):
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min(F.least("u", "v")).alias("m"))
        wide = both.join(least, "u").where("v > u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("lo < hi").distinct()
        root = wide.groupBy("hi").agg(F.min("lo").alias("m"))
        tied = wide.join(root, "hi").select(F.explode(F.array(F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")), F.struct("hi", F.col("m").alias("lo")))).alias("e"))
        now = cut(tied.select("e.lo", "e.hi").where("lo < hi").distinct())
        seen = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("lo", "hi").cast("decimal(38,0)"))).first())
        if seen == mark:
            return now.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
        mark = seen
    raise RuntimeError(f"no fixpoint after {max_rounds} rounds")
