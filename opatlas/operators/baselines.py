"""The clusterings that mixtures are compared with: k-means and density clustering."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .components import components


def kmeans(points: DataFrame, k: int, vec: str = "embedding", seed: int = 10, bisecting: bool = False) -> DataFrame:
    """``points`` with ``cluster``, by MLlib."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    made = points.withColumn("_v", array_to_vector(F.col(vec).cast("array<double>")))
    kind = BisectingKMeans if bisecting else KMeans
    return kind(k=k, seed=seed, featuresCol="_v", predictionCol="cluster").fit(made).transform(made).drop("_v")


def kmeans_step(points: DataFrame, centres: list[tuple[float, float]]) -> DataFrame:
    """One step in the plane: cluster, n, x, y of the means of the points nearest each centre. Centres are a parameter."""
    d = [(F.col("x") - x) * (F.col("x") - x) + (F.col("y") - y) * (F.col("y") - y) for x, y in centres]
    best = F.array_min(F.array(*(F.struct(v.alias("d"), F.lit(i).alias("i")) for i, v in enumerate(d))))["i"]
    return points.groupBy(best.alias("cluster")).agg(F.count("*").alias("n"), F.avg("x").alias("x"), F.avg("y").alias("y"))


def dbscan(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    """id, core, cluster (smallest core id; -1 for noise) of points (id, x, y).

    Cells have the diagonal ``eps``, so the points of one cell are all within reach: a cell with
    ``min_pts`` of them is core throughout, and only points of sparser cells are compared with
    the cells around. Core cells are linked by their closest pair. Border points go to the
    smallest core id's cluster in reach.
    """
    side = eps / math.sqrt(2)
    cell = lambda c: F.floor(F.col(c) / side).cast("long")
    placed = cut(points.select("id", "x", "y", cell("x").alias("cx"), cell("y").alias("cy")))
    sizes = placed.groupBy("cx", "cy").agg(F.count("*").alias("n"))
    around = F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in range(-2, 3) for b in range(-2, 3))))
    near = (F.col("x") - F.col("x2")) ** 2 + (F.col("y") - F.col("y2")) ** 2 <= eps * eps

    def reach(left: DataFrame, right: DataFrame) -> DataFrame:
        """Pairs of left and right points within eps, by the 25 cells that can hold one."""
        spread = left.withColumn("o", around).select("*", (F.col("cx") + F.col("o.a")).alias("gx"), (F.col("cy") + F.col("o.b")).alias("gy"))
        other = right.select(F.col("id").alias("id2"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.col("cx").alias("gx"), F.col("cy").alias("gy"))
        return spread.join(other, ["gx", "gy"]).where(near)

    sized = placed.join(sizes, ["cx", "cy"])
    dense = sized.where(F.col("n") >= min_pts).select("id")
    counted = reach(sized.where(F.col("n") < min_pts), placed).groupBy("id").agg(F.count("*").alias("m")).where(F.col("m") >= min_pts).select("id")
    core = cut(placed.join(dense.unionByName(counted).distinct(), "id"))
    head = core.groupBy("cx", "cy").agg(F.min("id").alias("head"))
    # within a cell all core points are one cluster; links between cells go from head to head
    linked = reach(core, core).where("cx <> gx OR cy <> gy").select("cx", "cy", "gx", "gy").distinct()
    other = head.select(F.col("cx").alias("gx"), F.col("cy").alias("gy"), F.col("head").alias("head2"))
    edges = linked.join(head, ["cx", "cy"]).join(other, ["gx", "gy"]).select(F.least("head", "head2").alias("lo"), F.greatest("head", "head2").alias("hi")).distinct()
    root = components(edges)
    labelled = core.join(head, ["cx", "cy"]).join(root, F.col("head") == F.col("node"), "left").select("id", "x", "y", "cx", "cy", F.coalesce("root", "head").alias("cluster"))
    border = reach(placed.join(core.select("id"), "id", "left_anti"), labelled.select("id", "x", "y", "cx", "cy")).select("id", "id2")
    by_border = border.join(labelled.select(F.col("id").alias("id2"), "cluster"), "id2").groupBy("id").agg(F.min_by("cluster", "id2").alias("border"))
    out = placed.select("id").join(labelled.select("id", "cluster"), "id", "left").join(by_border, "id", "left")
    return out.select("id", F.col("cluster").isNotNull().alias("core"), F.coalesce("cluster", "border", F.lit(-1).cast("long")).alias("cluster"))


def core_points(points: DataFrame, eps: float, min_pts: int) -> DataFrame:
    return dbscan(points, eps, min_pts).where("core").select("id")
