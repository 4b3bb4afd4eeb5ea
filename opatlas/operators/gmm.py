"""Gaussian mixtures in two dimensions: densities as columns, and a sweep over many K in one pass per step."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planning import choose, with_each
from ..session import cut

RIDGE = 1e-6


@dataclass
class Mixture:
    weight: np.ndarray  # (K,)
    mean: np.ndarray  # (K, 2)
    cov: np.ndarray  # (K, 2, 2)
    loglik: float = -math.inf
    steps: int = 0

    def log_parts(self, x: np.ndarray) -> np.ndarray:
        """ln of weight times density, by point and component."""
        a, b, c = self.cov[:, 0, 0], self.cov[:, 0, 1], self.cov[:, 1, 1]
        det = a * c - b * b
        d = x[:, None, :] - self.mean
        q = (c * d[..., 0] ** 2 - 2 * b * d[..., 0] * d[..., 1] + a * d[..., 1] ** 2) / det
        return np.log(np.maximum(self.weight, 1e-300)) - 0.5 * (q + np.log(det)) - math.log(2 * math.pi)

    def rows(self) -> list[tuple]:
        return [(k, float(self.weight[k]), float(self.mean[k, 0]), float(self.mean[k, 1]), float(self.cov[k, 0, 0]), float(self.cov[k, 0, 1]), float(self.cov[k, 1, 1])) for k in range(len(self.weight))]


PARAMS = "k int, weight double, mx double, my double, sxx double, sxy double, syy double"


def density_of(x: Column, y: Column) -> Column:
    """The weighted density at (x, y) of the component whose parameters stand in the row."""
    det = F.col("sxx") * F.col("syy") - F.col("sxy") * F.col("sxy")
    dx, dy = x - F.col("mx"), y - F.col("my")
    q = (F.col("syy") * dx * dx - 2 * F.col("sxy") * dx * dy + F.col("sxx") * dy * dy) / det
    return F.col("weight") * F.exp(-0.5 * q) / (2 * math.pi * F.sqrt(det))


def _each(points: DataFrame, params: DataFrame) -> DataFrame:
    """Every point with every component: the parameters are an array in each row, K is model-sized."""
    listed = params.agg(F.collect_list(F.struct(*(c.split()[0] for c in PARAMS.split(", ")))).alias("_p")).withColumn("_j", F.lit(1))
    return points.withColumn("_j", F.lit(1)).join(F.broadcast(listed), "_j").select("id", "x", "y", F.inline("_p")).withColumn("part", density_of(F.col("x"), F.col("y")))


def density(points: DataFrame, params: DataFrame) -> DataFrame:
    """id, density of the whole mixture."""
    return _each(points, params).groupBy("id").agg(F.sum("part").alias("density"))


def responsibilities(points: DataFrame, params: DataFrame) -> DataFrame:
    """id, k, r: the share of each component in each point."""
    total = F.sum("part").over(Window.partitionBy("id"))
    return _each(points, params).select("id", "k", (F.col("part") / total).alias("r"))


def assign(points: DataFrame, params: DataFrame) -> DataFrame:
    """id, k of the largest share, the lower k where shares tie."""
    return _each(points, params).groupBy("id").agg(F.max_by("k", F.struct("part", -F.col("k"))).alias("k"))


def loglik(points: DataFrame, params: DataFrame) -> DataFrame:
    return density(points, params).agg(F.sum(F.log("density")).alias("loglik"))


def logliks(points: DataFrame, params: DataFrame) -> DataFrame:
    """model, loglik and n (points) of several mixtures, whose components stand in ``params`` with their ``model``, in one pass over the points."""
    names = [c.split()[0] for c in PARAMS.split(", ")]
    models = params.groupBy("model").agg(F.array_sort(F.collect_list(F.struct(*(F.col(c).alias(f"p{i}") for i, c in enumerate(names))))).alias("_p"))
    dx, dy = (lambda p: F.col("x") - p["p2"]), (lambda p: F.col("y") - p["p3"])
    det = lambda p: p["p4"] * p["p6"] - p["p5"] * p["p5"]
    q = lambda p: (p["p6"] * dx(p) * dx(p) - 2 * p["p5"] * dx(p) * dy(p) + p["p4"] * dy(p) * dy(p)) / det(p)
    part = lambda p: p["p1"] * F.exp(-0.5 * q(p)) / (2 * math.pi * F.sqrt(det(p)))
    whole = F.aggregate("_p", F.lit(0.0), lambda s, p: s + part(p))
    return with_each(points.select("x", "y"), models).withColumn("d", whole).groupBy("model").agg(F.sum(F.log("d")).alias("loglik"), F.count("*").alias("n"))


def m_step(points: DataFrame, params: DataFrame) -> DataFrame:
    """The parameters after one step: k, weight, mx, my, sxx, sxy, syy."""
    r = responsibilities(points, params).join(points, "id")
    s = lambda e: F.sum(F.col("r") * e)
    x, y = F.col("x"), F.col("y")
    sums = r.groupBy("k").agg(s(F.lit(1.0)).alias("s0"), s(x).alias("s1"), s(y).alias("s2"), s(x * x).alias("s3"), s(x * y).alias("s4"), s(y * y).alias("s5"))
    n = points.agg(F.count("*").alias("n")).withColumn("_j", F.lit(1))
    c = F.col
    mx, my = c("s1") / c("s0"), c("s2") / c("s0")
    return sums.withColumn("_j", F.lit(1)).join(F.broadcast(n), "_j").select(
        "k", (c("s0") / c("n")).alias("weight"), mx.alias("mx"), my.alias("my"), (c("s3") / c("s0") - mx * mx + RIDGE).alias("sxx"),
        (c("s4") / c("s0") - mx * my).alias("sxy"), (c("s5") / c("s0") - my * my + RIDGE).alias("syy"),
    )


def n_params(k: int | Column, cov: str = "full") -> int | Column:
    """Free parameters in two dimensions: weights, means and covariances."""
    return k - 1 + 2 * k + {"full": 3 * k, "diag": 2 * k, "spherical": k, "tied": 3}[cov]


def bic(loglik_: float | Column, k: int | Column, n: float | Column, cov: str = "full") -> float | Column:
    return -2 * loglik_ + n_params(k, cov) * (F.log(n) if isinstance(n, Column) else math.log(n))


def start(sample: np.ndarray, k: int, seed: int = 10) -> Mixture:
    """k-means++ centres on a fixed sample, spherical covariances of the sample's spread."""
    rng = np.random.default_rng([seed, k])
    centres = [sample[rng.integers(len(sample))]]
    d = ((sample - centres[0]) ** 2).sum(1)
    for _ in range(1, k):
        centres.append(sample[rng.choice(len(sample), p=d / d.sum())] if d.sum() > 0 else sample[rng.integers(len(sample))])
        d = np.minimum(d, ((sample - centres[-1]) ** 2).sum(1))
    spread = max(float(sample.var(axis=0).mean()) / k, RIDGE)
    return Mixture(np.full(k, 1 / k), np.array(centres, float), np.tile(np.eye(2) * spread, (k, 1, 1)))


def _update(sums: np.ndarray, total: float, cov: str, old: Mixture) -> Mixture:
    s0 = np.maximum(sums[:, 0], 1e-12)
    mean = sums[:, 1:3] / s0[:, None]
    second = sums[:, 3:6] / s0[:, None]
    c = np.empty((len(s0), 2, 2))
    c[:, 0, 0] = second[:, 0] - mean[:, 0] ** 2
    c[:, 0, 1] = c[:, 1, 0] = second[:, 1] - mean[:, 0] * mean[:, 1]
    c[:, 1, 1] = second[:, 2] - mean[:, 1] ** 2
    if cov in ("diag", "spherical"):
        c[:, 0, 1] = c[:, 1, 0] = 0
    if cov == "spherical":
        c[:, 0, 0] = c[:, 1, 1] = (c[:, 0, 0] + c[:, 1, 1]) / 2
    if cov == "tied":
        c[:] = (c * s0[:, None, None]).sum(0) / s0.sum()
    c[:, 0, 0] = np.maximum(c[:, 0, 0], 0) + RIDGE
    c[:, 1, 1] = np.maximum(c[:, 1, 1], 0) + RIDGE
    empty = sums[:, 0] < 1e-8 * total
    mean[empty], c[empty] = old.mean[empty], old.cov[empty]
    return Mixture(s0 / s0.sum(), mean, c, old.loglik, old.steps + 1)


def features(x: np.ndarray) -> np.ndarray:
    return np.stack([np.ones(len(x)), x[:, 0], x[:, 1], x[:, 0] ** 2, x[:, 0] * x[:, 1], x[:, 1] ** 2], axis=1)


def expect(m: Mixture, f: np.ndarray, w: np.ndarray) -> tuple[float, np.ndarray]:
    """Weighted log-likelihood of points (their features) and each component's six sums.

    ln of weight times density is linear in the features, so a block of points is two products.
    """
    a, b, c = m.cov[:, 0, 0], m.cov[:, 0, 1], m.cov[:, 1, 1]
    det = a * c - b * b
    p, q, r = c / det, -b / det, a / det  # the inverse
    x, y = m.mean[:, 0], m.mean[:, 1]
    const = np.log(np.maximum(m.weight, 1e-300)) - 0.5 * np.log(det) - math.log(2 * math.pi) - 0.5 * (p * x * x + 2 * q * x * y + r * y * y)
    coef = np.stack([const, p * x + q * y, q * x + r * y, -0.5 * p, -q, -0.5 * r])
    total, sums = 0.0, np.zeros((len(a), 6))
    for at in range(0, len(f), 4096):
        part, wt = f[at : at + 4096], w[at : at + 4096]
        e = part @ coef
        top = e.max(axis=1, keepdims=True)
        np.exp(np.subtract(e, top, out=e), out=e)
        s = e.sum(axis=1)
        total += float((wt * (top[:, 0] + np.log(s))).sum())
        sums += (e * (wt / s)[:, None]).T @ part
    return total, sums


def climb(m: Mixture, f: np.ndarray, w: np.ndarray, cov: str, tol: float, max_iter: int) -> Mixture:
    """All steps of one mixture over points held in memory, by the same rule as the shared steps of ``sweep``."""
    total = float(w.sum())
    for step in range(max_iter):
        now, sums = expect(m, f, w)
        if now - m.loglik < tol * total and step:
            m.loglik = max(now, m.loglik)
            break
        m.loglik = now
        m = _update(sums, total, cov, m)
    return m


def _by_model(base: DataFrame, ks: list[int], sample: np.ndarray, cov: str, seed: int, tol: float, max_iter: int) -> dict[int, Mixture]:
    """Every task holds the points, which are of a checked number, and fits some of the mixtures to their end."""
    spark = base.sparkSession
    held = base.orderBy("id").toPandas()
    shared = spark.sparkContext.broadcast((held[["x", "y"]].to_numpy(), held["w"].to_numpy(float), sample))

    def run(batches):
        xy, w, first = shared.value
        f = features(xy)
        for pdf in batches:
            for k in pdf["size"]:
                m = climb(start(first, int(k), seed), f, w, cov, tol, max_iter)
                flat = lambda v: [v.ravel().tolist()]
                yield pd.DataFrame({"size": [k], "ll": [m.loglik], "steps": [m.steps], "weight": flat(m.weight), "mean": flat(m.mean), "cov": flat(m.cov)})

    # large mixtures first and a task each, so that no task ends long after the others
    asked = spark.createDataFrame([(i, k) for i, k in enumerate(sorted(ks, reverse=True))], "slot int, size int").repartitionById(len(ks), F.col("slot"))
    got = asked.select("size").mapInPandas(run, "size int, ll double, steps int, weight array<double>, mean array<double>, cov array<double>").collect()
    return {r["size"]: Mixture(np.array(r["weight"]), np.array(r["mean"]).reshape(-1, 2), np.array(r["cov"]).reshape(-1, 2, 2), r["ll"], r["steps"]) for r in got}


def grid(most: int, all_to: int = 16, ratio: float = 1.125) -> list[int]:
    """Every K up to ``all_to``, then K growing by ``ratio`` up to ``most``: the coarse range of a sweep."""
    ks = list(range(1, min(most, all_to) + 1))
    while ks and ks[-1] < most:
        ks.append(min(most, max(ks[-1] + 1, int(ks[-1] * ratio))))
    return ks


def sweep(
    points: DataFrame, ks: list[int], cov: str = "full", seed: int = 10, tol: float = 1e-4, max_iter: int = 100, sample_rows: int = 20_000,
    weight: str | None = None, strategy: str | None = None,
) -> dict[int, Mixture]:
    """Fits a mixture for every K in ``ks``.

    'by_points' (any number of points): all K in each pass over the points. A task gives one row
    of sums per component, so a step moves six numbers a component and task; a K leaves when its
    likelihood settles. 'by_model' (points of a checked number): tasks hold the points, and each
    fits some K to the end. Steps and rule are the same. The driver holds the parameters: a few
    megabytes for all K up to 500.
    """
    if not ks:
        return {}
    spark = points.sparkSession
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    base = cut(points.select("id", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), w.alias("w")))
    first = base.orderBy(F.xxhash64("id"), "id").limit(sample_rows).toPandas()
    if not len(first):
        return {}
    sample = first[["x", "y"]].to_numpy()
    n, total = base.agg(F.count("*"), F.sum("w")).first()
    if (strategy or choose("mixtures", n).strategy) == "by_model":
        return _by_model(base, ks, sample, cov, seed, tol, max_iter)
    base = cut(base.repartition(spark.sparkContext.defaultParallelism, "id"))
    models = {k: start(sample, k, seed) for k in ks}
    active = dict(models)
    step = 0
    while active and step < max_iter:
        shared = spark.sparkContext.broadcast(active)

        def run(batches, shared=shared):
            sums = {k: np.zeros((k, 6)) for k in shared.value}
            ll = dict.fromkeys(shared.value, 0.0)
            for pdf in batches:
                f, wt = features(pdf[["x", "y"]].to_numpy()), pdf["w"].to_numpy()
                for k, m in shared.value.items():
                    more, part = expect(m, f, wt)
                    ll[k] += more
                    sums[k] += part
            sizes = list(sums)
            at = np.concatenate([np.arange(k) for k in sizes])
            share = np.where(at == 0, np.repeat([ll[k] for k in sizes], sizes), 0.0)  # a likelihood stands in its first row
            every = np.concatenate([sums[k] for k in sizes])
            yield pd.DataFrame({"size": np.repeat(sizes, sizes), "k": at, "ll": share} | {f"s{i}": every[:, i] for i in range(6)})

        got = base.mapInPandas(run, "size int, k int, ll double, " + ", ".join(f"s{i} double" for i in range(6)))
        rows = got.groupBy("size", "k").agg(F.sum("ll").alias("ll"), *(F.sum(f"s{i}").alias(f"s{i}") for i in range(6))).toPandas()
        for k, part in rows.groupby("size"):
            k = int(k)
            part = part.sort_values("k")
            now = float(part["ll"].sum())
            before = models[k].loglik
            if now - before < tol * total and step:
                models[k].loglik = max(now, before)
                del active[k]
                continue
            models[k].loglik = now
            models[k] = active[k] = _update(part[[f"s{i}" for i in range(6)]].to_numpy(), total, cov, models[k])
        shared.unpersist()
        step += 1
    return models


def fit(points: DataFrame, k: int, **how) -> Mixture:
    return sweep(points, [k], **how)[k]


def coarse_sweep(points: DataFrame, most: int, step: int = 8, patience: int = 3, **how) -> dict[int, Mixture]:
    """Every ``step``-th K until the criterion has risen ``patience`` times, then all K around the best."""
    n = points.count()
    found: dict[int, Mixture] = {}
    best, rises = math.inf, 0
    for low in range(1, most + 1, step):
        found |= sweep(points, [low], **how)
        b = bic(found[low].loglik, low, n)
        best, rises = (b, 0) if b < best else (best, rises + 1)
        if rises >= patience:
            break
    at = min(found, key=lambda k: bic(found[k].loglik, k, n))
    rest = [k for k in range(max(1, at - step + 1), min(most, at + step - 1) + 1) if k not in found]
    return found | sweep(points, rest, **how)


def bic_curve(spark, models: dict[int, Mixture], n: float, cov: str = "full") -> DataFrame:
    rows = [(k, float(m.loglik), n_params(k, cov), bic(m.loglik, k, n, cov)) for k, m in sorted(models.items())]
    return spark.createDataFrame(rows, "K int, loglik double, n_params int, bic double")


def select_k(curve: DataFrame, rule: str = "argmin") -> DataFrame:
    """The chosen K: the least criterion, or the point farthest below the chord of the normalised curve. K rows at most."""
    if rule == "argmin":
        return curve.agg(F.min_by("K", F.struct("bic", "K")).alias("K"))
    if rule != "elbow":
        raise ValueError(f"no rule {rule}")
    ends = curve.agg(F.min("K").alias("k0"), F.max("K").alias("k1"), F.min_by("bic", "K").alias("b0"), F.max_by("bic", "K").alias("b1"), F.min("bic").alias("lo"), F.max("bic").alias("hi")).withColumn("_j", F.lit(1))
    scaled = curve.withColumn("_j", F.lit(1)).join(ends, "_j")
    c = F.col
    at = (c("K") - c("k0")) / (c("k1") - c("k0"))
    chord = c("b0") + at * (c("b1") - c("b0"))
    return scaled.withColumn("gap", (chord - c("bic")) / (c("hi") - c("lo"))).agg(F.max_by("K", F.struct("gap", -c("K"))).alias("K"))
