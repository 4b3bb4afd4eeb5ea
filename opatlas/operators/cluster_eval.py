"""Measures of a clustering: distances, silhouette, Davies-Bouldin, Calinski-Harabasz, adjusted Rand."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _dims(points: DataFrame, vec: str, cluster: str) -> DataFrame:
    return points.select(F.col(cluster).alias("c"), F.posexplode(vec).alias("dim", "x")).withColumn("x", F.col("x").cast("double"))


def centroids(points: DataFrame, vec: str = "embedding", cluster: str = "label") -> DataFrame:
    """c, dim, mean, n: a row per cluster and dimension."""
    return _dims(points, vec, cluster).groupBy("c", "dim").agg(F.avg("x").alias("mean"), F.var_pop("x").alias("var"), F.count("*").alias("n"))


def distances(points: DataFrame, vec: str = "embedding", cluster: str = "label") -> DataFrame:
    """c, n, intra (root of the mean squared distance to the centroid), inter (distance to the nearest other centroid)."""
    cent = centroids(points, vec, cluster)
    intra = cent.groupBy("c").agg(F.first("n").alias("n"), F.sqrt(F.sum("var")).alias("intra"))
    other = cent.select(F.col("c").alias("c2"), "dim", F.col("mean").alias("mean2"))
    gaps = cent.join(other, "dim").where("c <> c2").groupBy("c", "c2").agg(F.sqrt(F.sum((F.col("mean") - F.col("mean2")) ** 2)).alias("d"))
    return intra.join(gaps.groupBy("c").agg(F.min("d").alias("inter")), "c", "left").select("c", "n", "intra", "inter")


def indices(points: DataFrame, vec: str = "embedding", cluster: str = "label") -> DataFrame:
    """Davies-Bouldin and Calinski-Harabasz, one row, from centroids (clusters times dimensions)."""
    cent = centroids(points, vec, cluster)
    grand = _dims(points, vec, cluster).groupBy("dim").agg(F.avg("x").alias("g"))
    per = cent.groupBy("c").agg(F.first("n").alias("n"), F.sqrt(F.sum("var")).alias("s"), F.sum("var").alias("v"))
    between = cent.join(grand, "dim").agg(F.sum(F.col("n") * (F.col("mean") - F.col("g")) ** 2).alias("b")).withColumn("k", F.lit(1))
    within = per.agg(F.sum(F.col("n") * F.col("v")).alias("w"), F.sum("n").alias("t"), F.count("*").alias("m")).withColumn("k", F.lit(1))
    other = cent.select(F.col("c").alias("c2"), "dim", F.col("mean").alias("mean2"))
    gaps = cent.join(other, "dim").where("c <> c2").groupBy("c", "c2").agg(F.sqrt(F.sum((F.col("mean") - F.col("mean2")) ** 2)).alias("d"))
    ratio = gaps.join(per.select("c", "s"), "c").join(per.select(F.col("c").alias("c2"), F.col("s").alias("s2")), "c2")
    db = ratio.groupBy("c").agg(F.max((F.col("s") + F.col("s2")) / F.col("d")).alias("r")).agg(F.avg("r").alias("davies_bouldin")).withColumn("k", F.lit(1))
    ch = (F.col("b") / (F.col("m") - 1)) / (F.col("w") / (F.col("t") - F.col("m")))
    return between.join(within, "k").join(db, "k").select("davies_bouldin", ch.alias("calinski_harabasz"))


def silhouette(points: DataFrame, vec: str = "embedding", cluster: str = "label") -> float:
    """Mean silhouette by squared distances, by MLlib, in linear time."""
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.functions import array_to_vector

    made = points.select(array_to_vector(F.col(vec).cast("array<double>")).alias("features"), F.col(cluster).cast("double").alias("prediction"))
    return ClusteringEvaluator().evaluate(made)


def adjusted_rand(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Adjusted Rand index of two labelings, one row, from their contingency table."""
    two = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2)
    cell = pairs.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").cast("double").alias("n"))
    side = lambda c, o: cell.groupBy(c).agg(F.sum("n").alias("m")).agg(two("m").alias(o)).withColumn("k", F.lit(1))
    all_ = cell.agg(two("n").alias("t"), F.sum("n").alias("n")).withColumn("k", F.lit(1))
    expected = F.col("ta") * F.col("tb") / (F.col("n") * (F.col("n") - 1) / 2)
    index = (F.col("t") - expected) / ((F.col("ta") + F.col("tb")) / 2 - expected)
    return all_.join(side("a", "ta"), "k").join(side("b", "tb"), "k").select(index.alias("ari"))
