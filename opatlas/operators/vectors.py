"""Dense vectors: standardising, principal components, neighbours and how well an embedding keeps them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def moments(points: DataFrame, vec: str = "embedding") -> DataFrame:
    """Mean and population variance of each dimension: dim, mean, var, n. One pass, dimensions only move."""
    rows = points.select(F.posexplode(vec).alias("dim", "x"))
    return rows.groupBy("dim").agg(F.avg(F.col("x").cast("double")).alias("mean"), F.var_pop(F.col("x").cast("double")).alias("var"), F.count("*").alias("n"))


def standardize(points: DataFrame, ddof: int = 0, vec: str = "embedding") -> DataFrame:
    """``points`` with ``vec`` at mean 0 and variance 1; a constant dimension becomes 0. The moments are a row per dimension."""
    rows = sorted(moments(points, vec).collect(), key=lambda r: r.dim)
    scale = [(r["mean"], (r["var"] * r.n / max(1, r.n - ddof)) ** 0.5) for r in rows]
    means, devs = (F.array(*(F.lit(float(x)) for x in col)) for col in zip(*scale, strict=True)) if scale else (F.array(), F.array())
    centred = F.zip_with(F.col(vec).cast("array<double>"), means, lambda x, m: x - m)
    return points.withColumn(vec, F.zip_with(centred, devs, lambda x, s: F.when(s > 0, x / s).otherwise(0.0)))


def pca2(points: DataFrame, vec: str = "embedding", key: str = "vec_id") -> DataFrame:
    """First two principal components: id, x, y. Moments come from one pass per block, the axes from the driver."""
    sums = points.select(vec).mapInPandas(_gram(vec), "n long, s array<double>, g array<double>")
    parts = sums.collect()  # a row per task, dimensions squared
    if not parts:
        return points.select(F.col(key).alias("id"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))
    n = sum(p.n for p in parts)
    s, d = np.sum([p.s for p in parts], axis=0), len(parts[0].s)
    cov = np.sum([p.g for p in parts], axis=0).reshape(d, d) / n - np.outer(s, s) / n**2
    values, axes = np.linalg.eigh(cov)
    top = axes[:, np.argsort(-values)[:2]]
    top = top * np.where(top[np.abs(top).argmax(axis=0), range(top.shape[1])] < 0, -1, 1)  # a fixed sign
    mean = s / n

    def dot(axis: np.ndarray):
        terms = F.zip_with(F.zip_with(F.col(vec).cast("array<double>"), F.array(*map(F.lit, mean.tolist())), lambda x, m: x - m), F.array(*map(F.lit, axis.tolist())), lambda x, a: x * a)
        return F.aggregate(terms, F.lit(0.0), lambda a, x: a + x)

    return points.select(F.col(key).alias("id"), dot(top[:, 0]).alias("x"), dot(top[:, 1]).alias("y"))


def _gram(vec: str):
    def run(batches):
        import pandas as pd

        n, s, g = 0, None, None
        for pdf in batches:
            if len(pdf):
                x = np.stack(pdf[vec].to_numpy()).astype(float)
                n, s, g = n + len(x), x.sum(0) + (0 if s is None else s), x.T @ x + (0 if g is None else g)
        if n:
            yield pd.DataFrame({"n": [n], "s": [s.tolist()], "g": [g.ravel().tolist()]})

    return run


def neighbours(points: DataFrame, k: int, vec: str = "embedding", key: str = "vec_id", block: int = 2048, buckets: int | None = None) -> DataFrame:
    """The ``k`` nearest other points of each: i, j, d2, rank.

    Exact where ``buckets`` is None: points are dealt into blocks, every pair of blocks is one
    group's work, and only each point's ``k`` best of a block move on. That is N squared work, for
    the thousands of points of a landmark set. With ``buckets``, points meet only in a cell of a
    coarse quantiser of that many hashed centres and its nearest other cell: approximate.
    """
    from pyspark.sql import types as T  # noqa: F401

    keyed = points.select(F.col(key).cast("long").alias("i"), F.col(vec).cast("array<double>").alias("v"))
    if buckets is None:
        n = max(1, -(-keyed.count() // block))
        dealt = keyed.withColumn("b", F.pmod(F.xxhash64("i"), F.lit(n)).cast("int"))
        left = dealt.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).select("b", "c", "i", "v", F.lit(0).alias("side"))
        right = dealt.withColumn("d", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).select(F.col("d").alias("b"), F.col("b").alias("c"), "i", "v", F.lit(1).alias("side"))
        groups = left.unionByName(right).groupBy("b", "c")
    else:
        centres = np.array([r.v for r in keyed.orderBy(F.xxhash64("i")).limit(buckets).collect()])

        def place(batches):
            for pdf in batches:
                x = np.stack(pdf["v"].to_numpy()) if len(pdf) else np.zeros((0, centres.shape[1]))
                d = (x**2).sum(1)[:, None] - 2 * x @ centres.T + (centres**2).sum(1)
                near = np.argsort(d, axis=1)[:, :2]
                yield pdf.assign(b=near[:, 0], c=near[:, -1])

        placed = keyed.mapInPandas(place, "i long, v array<double>, b int, c int")
        query = placed.select("i", "v", F.col("b"), F.lit(0).alias("c"), F.lit(0).alias("side"))
        rows = placed.select("i", "v", F.explode(F.array("b", "c")).alias("b"), F.lit(0).alias("c"), F.lit(1).alias("side"))
        groups = query.unionByName(rows).groupBy("b", "c")

    def best(pdf):
        import pandas as pd

        q, r = pdf[pdf["side"] == 0], pdf[pdf["side"] == 1].drop_duplicates("i")
        if not len(q) or not len(r):
            return pd.DataFrame({"i": [], "j": [], "d2": []})
        x, y = np.stack(q["v"].to_numpy()), np.stack(r["v"].to_numpy())
        ids, out = r["i"].to_numpy(), []
        for start in range(0, len(x), 512):
            part = x[start : start + 512]
            d = np.maximum(0, (part**2).sum(1)[:, None] - 2 * part @ y.T + (y**2).sum(1))
            own = q["i"].to_numpy()[start : start + 512]
            d[own[:, None] == ids[None, :]] = np.inf
            m = min(k, len(ids))
            at = np.argpartition(d, m - 1, axis=1)[:, :m]
            rows = np.arange(len(part))[:, None]
            out.append(pd.DataFrame({"i": np.repeat(own, m), "j": ids[at].ravel(), "d2": d[rows, at].ravel()}))
        got = pd.concat(out)
        return got[np.isfinite(got["d2"])]

    found = groups.applyInPandas(best, "i long, j long, d2 double")
    w = Window.partitionBy("i").orderBy("d2", "j")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def nearest(asked: DataFrame, points: DataFrame, k: int, vec: str = "embedding", key: str = "vec_id", limit: int = 5_000) -> DataFrame:
    """The ``k`` nearest of ``points`` to each of a bounded number of ``asked`` ones, exactly: i, j, d2, rank. Those asked are broadcast after a count."""
    own = asked.select(F.col(key).cast("long").alias("i"), F.col(vec).cast("array<double>").alias("v")).limit(limit + 1).toPandas()
    if len(own) > limit:
        raise ValueError(f"more than {limit} points are asked for")
    shared = points.sparkSession.sparkContext.broadcast((own["i"].to_numpy(), np.array(own["v"].tolist(), float).reshape(len(own), -1)))

    def run(batches):
        import pandas as pd

        ids, x = shared.value
        for pdf in batches:
            if not len(pdf) or not len(ids):
                continue
            y, js = np.array(pdf["v"].tolist(), float), pdf["j"].to_numpy()
            d = np.maximum(0, (x**2).sum(1)[:, None] - 2 * x @ y.T + (y**2).sum(1))
            d[ids[:, None] == js[None, :]] = np.inf
            m = min(k, len(js))
            at = np.argpartition(d, m - 1, axis=1)[:, :m]
            got = pd.DataFrame({"i": np.repeat(ids, m), "j": js[at].ravel(), "d2": np.take_along_axis(d, at, 1).ravel()})
            yield got[np.isfinite(got["d2"])]

    rows = points.select(F.col(key).cast("long").alias("j"), F.col(vec).cast("array<double>").alias("v"))
    found = rows.mapInPandas(run, "i long, j long, d2 double")
    return found.withColumn("rank", F.row_number().over(Window.partitionBy("i").orderBy("d2", "j"))).where(F.col("rank") <= k)


def neighbour_recall(true: DataFrame, kept: DataFrame, k: int) -> DataFrame:
    """Share of each point's ``k`` true neighbours that an embedding keeps: one row."""
    hit = true.where(F.col("rank") <= k).join(kept.where(F.col("rank") <= k).select("i", "j").withColumn("hit", F.lit(1)), ["i", "j"], "left")
    return hit.agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("recall"))


def trust(true_all: DataFrame, kept: DataFrame, k: int, n: int) -> DataFrame:
    """Trustworthiness: penalises points that are near in the embedding but of a high rank before. ``true_all`` holds all ranks."""
    bad = kept.where(F.col("rank") <= k).select("i", "j").join(true_all.select("i", "j", F.col("rank").alias("r")), ["i", "j"]).where(F.col("r") > k)
    scale = 2.0 / (n * k * (2 * n - 3 * k - 1))
    return bad.agg((F.lit(1.0) - F.lit(scale) * F.coalesce(F.sum(F.col("r") - k), F.lit(0))).alias("trustworthiness"))
