"""The three-level framework: describing clusters, expert decisions, assembly, back-off and narrowing."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planning import maybe_broadcast
from ..session import cut
from .components import components

LEVELS = ("l1", "l2", "l3")


def describe(assigned: DataFrame, weights: DataFrame, top: int = 5) -> DataFrame:
    """The heaviest terms of each cluster: cluster, rank, term, score; from assigned (stmt_id, cluster) and weights."""
    sums = weights.join(assigned.select("stmt_id", "cluster"), "stmt_id").groupBy("cluster", "term").agg(F.round(F.sum("w"), 9).alias("score"))
    rank = F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("score"), "term"))
    return sums.withColumn("rank", rank).where(F.col("rank") <= top)


def drop_source_bound(clusters: DataFrame, source_terms: DataFrame, term: str = "term") -> DataFrame:
    """Expert rule: clusters whose name is that of a data source go."""
    return clusters.join(maybe_broadcast(source_terms.select(F.col(term)).distinct()), term, "left_anti")


def merge_similar(centroids: DataFrame, min_sim: float = 0.9) -> DataFrame:
    """Expert rule: near-synonymous clusters become one: cluster, merged (smallest id it is tied to).

    centroids: cluster, term, w. Clusters are model-sized; similarities go through shared terms.
    """
    centroids = cut(centroids)  # read three times
    norm = centroids.groupBy("cluster").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("n"))
    unit = centroids.join(norm, "cluster").where("n > 0").select("cluster", "term", (F.col("w") / F.col("n")).alias("w"))
    a, b = unit.select(F.col("cluster").alias("lo"), "term", F.col("w").alias("wa")), unit.select(F.col("cluster").alias("hi"), "term", F.col("w").alias("wb"))
    alike = a.join(b, "term").where("lo < hi").groupBy("lo", "hi").agg(F.sum(F.col("wa") * F.col("wb")).alias("sim")).where(F.col("sim") >= min_sim)
    tied = components(alike.select("lo", "hi"))
    return norm.join(tied, F.col("cluster") == F.col("node"), "left").select("cluster", F.coalesce("root", "cluster").alias("merged"))


def apply_decisions(clusters: DataFrame, decisions: DataFrame) -> DataFrame:
    """What experts decided of each cluster (keep, drop or merge, with names): cluster, target, l1, l2, l3.

    A merged cluster takes the names of the one it is merged into.
    """
    d = clusters.select(F.col("cluster").alias("cluster_id")).join(F.broadcast(decisions), "cluster_id").where("action <> 'drop'")
    d = d.withColumn("target", F.when(F.col("action") == "merge", F.col("merge_into")).otherwise(F.col("cluster_id")))
    names = decisions.where("action = 'keep'").select(F.col("cluster_id").alias("target"), *LEVELS)
    return d.select(F.col("cluster_id").alias("cluster"), "target").join(F.broadcast(names), "target").select("cluster", "target", *LEVELS)


def build(functions: DataFrame) -> DataFrame:
    """Functions (l3_id, l1, l2, l3) with n (functions in their group) and m (groups in their stage).

    A group is a pair of stage and name: names repeat between stages.
    """
    groups = functions.groupBy("l1", "l2").agg(F.count("*").alias("n_l3_in_l2"))
    stages = groups.groupBy("l1").agg(F.count("*").alias("m_l2_in_l1"))
    return functions.join(F.broadcast(groups), ["l1", "l2"]).join(F.broadcast(stages), "l1").select("l3_id", *LEVELS, "n_l3_in_l2", "m_l2_in_l1")


def backoff(labels: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """The deepest level at which a label (l1, l2, l3 names) exists: ``labels`` with level (3, 2, 1 or 0) and node."""
    seen = lambda *cols: F.broadcast(taxonomy.select(*cols).distinct().withColumn(f"_{len(cols)}", F.lit(True)))
    out = labels.join(seen("l1", "l2", "l3"), list(LEVELS), "left").join(seen("l1", "l2"), ["l1", "l2"], "left").join(seen("l1"), "l1", "left")
    level = F.when(F.col("_3"), 3).when(F.col("_2"), 2).when(F.col("_1"), 1).otherwise(0)
    node = F.when(F.col("_3"), F.concat_ws("/", *LEVELS)).when(F.col("_2"), F.concat_ws("/", "l1", "l2")).when(F.col("_1"), F.col("l1"))
    return out.select(*labels.columns, level.alias("level"), node.alias("node"))


def narrow(scores: DataFrame) -> DataFrame:
    """Stage first, then a group of it, then a function of that: item_id, l1, l2, l3, from scores (item_id, l1, l2, l3, score).

    A node's score is the best of its functions' means at the levels below, ties by name.
    """
    s = scores
    for depth in (1, 2, 3):
        keys = LEVELS[:depth]
        node = s.groupBy("item_id", *keys).agg(F.round(F.avg("score"), 9).alias("s"))
        best = node.groupBy("item_id").agg(F.min_by(F.struct(*keys), F.struct(-F.col("s"), *keys)).alias("b"))
        s = s.join(best, "item_id").where(" AND ".join(f"{k} = b.{k}" for k in keys)).select("item_id", *LEVELS, "score")
    return s.select("item_id", *LEVELS).distinct()


def flat(scores: DataFrame) -> DataFrame:
    """The best function at once: item_id, l1, l2, l3."""
    best = scores.groupBy("item_id").agg(F.min_by(F.struct(*LEVELS), F.struct(-F.round("score", 9), *LEVELS)).alias("b"))
    return best.select("item_id", "b.*")
