"""Two-dimensional neighbour embedding: affinities as DataFrames, layouts by size.

'exact' lays out up to a few thousand points with all pairs on the driver, 'cells' up to tens
of thousands with sparse attraction in tasks and repulsion from a grid of cells, 'landmark' any
number: a hashed sample is laid out and every other point is placed at the weighted mean of its
nearest landmarks. Results do not depend on how rows are partitioned.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.planning import CELL_POINTS, EXACT_POINTS, choose, maybe_broadcast, small
from ..session import cut
from .vectors import neighbours

#: Rows of all pairs that the driver works on at once.
BLOCK = 64


def conditional_fixed(near: DataFrame, sigma: float) -> DataFrame:
    """i, j, p: similarity of j to i for one width, over the given neighbours (i, j, d2)."""
    e = near.withColumn("e", F.exp(-F.col("d2") / (2 * sigma * sigma)))
    total = e.groupBy("i").agg(F.sum("e").alias("t"))
    return e.join(maybe_broadcast(total), "i").select("i", "j", (F.col("e") / F.col("t")).alias("p"))


def _meetings(known: DataFrame, by: str, block: int) -> tuple[DataFrame, DataFrame]:
    """The points with ``b``, their block, once for each meeting (``lo``, ``hi``) of two blocks of their group, and the blocks of each group.

    A group is cut into blocks of about ``block`` points by the hash of their ids, and each two blocks meet once.
    """
    sizes = maybe_broadcast(known.groupBy(by).agg(F.ceil(F.count("*") / block).cast("int").alias("n"), F.count("*").alias("size")))
    dealt = known.join(sizes.drop("size"), by).withColumn("b", F.pmod(F.xxhash64("i"), F.col("n")).cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    return dealt.select(*known.columns, "b", F.least("b", "o").alias("lo"), F.greatest("b", "o").alias("hi")), sizes


def _kernel(x: np.ndarray, y: np.ndarray, sigma: float) -> np.ndarray:
    """The kernel between the rows of two arrays, which are moved to their middle: far from it, digits would be lost."""
    x, y = x - y.mean(0), y - y.mean(0)
    d2 = np.maximum(0, (x**2).sum(1)[:, None] - 2 * x @ y.T + (y**2).sum(1))
    return np.exp(d2 / (-2 * sigma * sigma))


def kernel_totals(points: DataFrame, sigma: float, vec: str = "embedding", key: str = "vec_id", by: str = "label", block: int = 4096) -> DataFrame:
    """i, t: the sum of the kernel of one width between each point and all others of its group; no pair is a row."""
    known = points.select(by, F.col(key).alias("i"), F.col(vec).alias("v")).where(F.col(by).isNotNull() & F.col("v").isNotNull())

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        lo, hi = int(pdf["lo"].iloc[0]), int(pdf["hi"].iloc[0])
        (ids, x), (other, y) = ((part["i"].to_numpy(), np.stack(part["v"].to_numpy()).astype(float) if len(part) else np.zeros((0, 1))) for part in (pdf[pdf["b"] == lo], pdf[pdf["b"] == hi]))
        rows, cols = np.zeros(len(x)), np.zeros(len(y))
        if len(x) and len(y):
            for start in range(0, len(x), 4 * BLOCK):
                mine = slice(start, start + 4 * BLOCK)
                e = _kernel(x[mine], y, sigma)
                if lo == hi:  # equal ids are in one block
                    e[ids[mine, None] == other] = 0
                rows[mine] = e.sum(1)
                cols += e.sum(0)
        return pd.DataFrame({"i": ids, "t": rows}) if lo == hi else pd.DataFrame({"i": np.concatenate([ids, other]), "t": np.concatenate([rows, cols])})

    met = _meetings(known, by, block)[0]
    return met.groupBy(by, "lo", "hi").applyInPandas(run, "i long, t double").groupBy("i").agg(F.sum("t").alias("t"))


def symmetric_fixed(near: DataFrame, totals: DataFrame, n: int, sigma: float) -> DataFrame:
    """i, j, p of ``symmetrize(conditional_fixed(...))`` for the pairs of ``near`` (i, j, d2), from the sums of the kernel (i, t) of all points."""
    t = maybe_broadcast(totals)
    e = near.withColumn("e", F.exp(-F.col("d2") / (2 * sigma * sigma)))
    both = e.join(t.withColumnRenamed("t", "ti"), "i").join(t.select(F.col("i").alias("j"), F.col("t").alias("tj")), "j")
    return both.groupBy("i", "j").agg((F.sum(F.col("e") / F.col("ti") + F.col("e") / F.col("tj")) / (2 * n)).alias("p"))


def symmetric_whole(points: DataFrame, sigma: float, vec: str = "embedding", key: str = "vec_id", by: str = "label", block: int = 1024) -> DataFrame:
    """i, j, p of ``symmetrize(conditional_fixed(...))`` for every two points of a group, both ways.

    The blocks of a group meet as in ``kernel_totals`` and a task gives the rows of its meetings, so no pair is exchanged.
    Points of a repeated id, or whose vector has not the usual length or lacks finite values, are few: they meet the
    others of their group as rows, by the dimensions that both have, and are summed by id; a pair without any has no p.
    """
    n, dims = points.agg(F.count("*"), F.mode(F.when(F.col(vec).isNotNull(), F.size(vec)))).first()
    known = points.select(by, F.col(key).alias("i"), F.col(vec).alias("v")).where(F.col(by).isNotNull() & F.col(key).isNotNull())
    again = known.groupBy("i").agg((F.count("*") > 1).alias("odd")).where("odd")
    lacks = F.col("v").isNull() | (F.size("v") != (dims or 0)) | F.exists("v", lambda x: x.isNull() | (F.abs(x) >= math.inf))
    known = cut(known.join(maybe_broadcast(again), "i", "left").select(by, "i", "v", (F.col("odd").isNotNull() | lacks).alias("odd")))
    plain, odd = known.where("NOT odd").drop("odd"), known.where("odd")
    totals = kernel_totals(plain, sigma, "v", "i", by)
    if odd.isEmpty():
        return _block_pairs(plain, totals, n, sigma, by, block)
    a, b = maybe_broadcast(odd).select(by, "i", F.col("v").alias("a")), known.select(by, F.col("i").alias("j"), F.col("v").alias("b"), "odd")
    terms = F.filter(F.zip_with("a", "b", lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)), lambda x: x.isNotNull())
    one = a.join(b, by).where("i <> j").select("i", "j", F.when(F.size(terms) > 0, F.aggregate(terms, F.lit(0.0), lambda s, x: s + x)).alias("d2"), "odd")
    near = one.drop("odd").unionByName(one.where("NOT odd").select(F.col("j").alias("i"), F.col("i").alias("j"), "d2"))
    more = near.groupBy("i").agg(F.sum(F.exp(-F.col("d2") / (2 * sigma * sigma))).alias("t"))
    totals = cut(totals.unionByName(more).groupBy("i").agg(F.sum("t").alias("t")))
    return _block_pairs(plain, totals, n, sigma, by, block).unionByName(symmetric_fixed(near, totals, n, sigma))


def _block_pairs(plain: DataFrame, totals: DataFrame, n: int, sigma: float, by: str, block: int) -> DataFrame:
    """i, j, p of all pairs of ``plain`` (i, v), whose ids are different, from the sums of the kernel (i, t)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(list(batches)).combine_chunks()
        ids, t, b = (rows[c].to_numpy() for c in ("i", "t", "b"))
        v = np.concatenate([c.flatten().to_numpy() for c in rows["v"].chunks]).astype(float).reshape(len(ids), -1)
        lo, hi = rows["lo"][0].as_py(), rows["hi"][0].as_py()
        first, other = np.flatnonzero(b == lo), np.flatnonzero(b == hi)
        for start in range(0, len(first) if len(other) else 0, 4 * BLOCK):
            mine = first[start : start + 4 * BLOCK]
            e = _kernel(v[mine], v[other], sigma)
            with np.errstate(divide="ignore", invalid="ignore"):
                p = ((e / t[mine, None] + e / t[other]) / (2 * n)).ravel()
            i, j = np.repeat(ids[mine], len(other)), np.tile(ids[other], len(mine))
            if lo == hi:
                i, j, p = i[i != j], j[i != j], p[i != j]
            i, j, p = map(pa.array, (i, j, p))
            yield pa.RecordBatch.from_arrays([i, j, p], ["i", "j", "p"])
            if lo != hi:
                yield pa.RecordBatch.from_arrays([j, i, p], ["i", "j", "p"])

    met, sizes = _meetings(plain.join(maybe_broadcast(totals), "i"), by, block)
    pairs = sizes.agg(F.sum(F.col("size").cast("double") ** 2)).first()[0] or 0
    tasks = int(min(max(pairs / (2 * block * block), plain.sparkSession.sparkContext.defaultParallelism), 10_000))
    return met.repartition(tasks, by, "lo", "hi").groupBy(by, "lo", "hi").applyInArrow(run, "i long, j long, p double")


def widths(d2: np.ndarray, perplexity: float, tol: float = 1e-5, steps: int = 64) -> np.ndarray:
    """Probabilities of each row's neighbours, their entropy brought to the perplexity by bisection on the precision."""
    low, high = np.zeros(len(d2)), np.full(len(d2), np.inf)
    beta = 1 / np.maximum(np.median(d2, axis=1), 1e-12)
    goal = math.log(min(perplexity, d2.shape[1]))
    p = np.zeros_like(d2)
    for _ in range(steps):
        e = np.exp(-(d2 - d2.min(axis=1, keepdims=True)) * beta[:, None])
        s = e.sum(axis=1, keepdims=True)
        p = e / s
        entropy = -(p * np.log(np.maximum(p, 1e-300))).sum(axis=1)
        wide = entropy > goal
        if np.all(np.abs(entropy - goal) < tol):
            break
        low, high = np.where(wide, beta, low), np.where(wide, high, beta)
        beta = np.where(np.isinf(high), beta * 2, (low + high) / 2)
    return p


def conditional(near: DataFrame, perplexity: float = 30.0) -> DataFrame:
    """i, j, p with a width per point such that its distribution has the perplexity; neighbours of a point are bounded by k."""
    lists = near.groupBy("i").agg(F.array_sort(F.collect_list(F.struct("d2", "j"))).alias("n"))

    def run(batches):
        for pdf in batches:
            for size, part in pdf.groupby(pdf["n"].map(len)):
                d2 = np.array([[x["d2"] for x in n] for n in part["n"]], float).reshape(len(part), int(size))
                p = widths(d2, perplexity)
                js = [x["j"] for n in part["n"] for x in n]
                yield pd.DataFrame({"i": np.repeat(part["i"].to_numpy(), int(size)), "j": js, "p": p.ravel()})

    return lists.mapInPandas(run, "i long, j long, p double")


def symmetrize(cond: DataFrame, n: int) -> DataFrame:
    """i, j, p over all pairs, both ways, summing to one."""
    both = cond.unionByName(cond.select(F.col("j").alias("i"), F.col("i").alias("j"), "p"))
    return both.groupBy("i", "j").agg((F.sum("p") / (2 * n)).alias("p"))


def _all_pairs(points: DataFrame) -> DataFrame:
    """Every ordered pair of up to ``EXACT_POINTS`` points, one side as an array in each row; more are refused."""
    if not small(points, EXACT_POINTS):
        raise ValueError(f"more than {EXACT_POINTS} points have too many pairs")
    listed = points.agg(F.collect_list(F.struct(F.col("id").alias("j"), F.col("x").alias("xj"), F.col("y").alias("yj"))).alias("_a")).withColumn("_k", F.lit(1))
    rows = points.withColumn("_k", F.lit(1)).join(F.broadcast(listed), "_k")
    return rows.select(F.col("id").alias("i"), "x", "y", F.inline("_a")).where("i <> j")


def q(points: DataFrame) -> DataFrame:
    """i, j, q of a layout (id, x, y): the Student kernel over all pairs."""
    d2 = (F.col("x") - F.col("xj")) ** 2 + (F.col("y") - F.col("yj")) ** 2
    k = _all_pairs(points).select("i", "j", (1 / (1 + d2)).alias("w"), F.lit(1).alias("_k"))
    return k.join(k.groupBy("_k").agg(F.sum("w").alias("z")), "_k").select("i", "j", (F.col("w") / F.col("z")).alias("q"))


def kl(p: DataFrame, q_: DataFrame) -> DataFrame:
    """The cost, one row."""
    return p.where("p > 0").join(q_, ["i", "j"]).agg(F.sum(F.col("p") * F.log(F.col("p") / F.col("q"))).alias("kl"))


class Descent:
    """Momentum, gains and early exaggeration, the same for all layouts."""

    def __init__(self, start: np.ndarray, n_iter: int, rate: float | None, exaggeration: float, early: int) -> None:
        n = len(start)
        self.y, self.v, self.g = start.copy(), np.zeros_like(start), np.ones_like(start)
        self.n_iter, self.early, self.exaggeration = n_iter, min(early, n_iter // 4), exaggeration
        self.rate = rate if rate is not None else max(n / exaggeration / 4, 50.0)

    def run(self, gradient: Callable[[np.ndarray, float], np.ndarray], least: float = 1e-7) -> np.ndarray:
        for t in range(self.n_iter):
            early = t < self.early
            grad = gradient(self.y, self.exaggeration if early else 1.0)
            if not early and np.linalg.norm(grad) < least:
                break
            same = np.sign(grad) == np.sign(self.v)
            self.g = np.maximum(np.where(same, self.g * 0.8, self.g + 0.2), 0.01)
            self.v = (0.5 if early else 0.8) * self.v - self.rate * self.g * grad
            self.y = self.y + self.v
            self.y -= self.y.mean(axis=0)
        return self.y


def exact_affinities(x: np.ndarray, perplexity: float) -> np.ndarray:
    """``symmetrize(conditional(...))`` of every pair of the rows of ``x``, as one dense matrix, made in blocks of rows."""
    n = len(x)
    p = np.zeros((n, n))
    if n < 2:
        return p
    s = (x**2).sum(1)
    for start in range(0, n, BLOCK):
        mine = np.arange(start, min(start + BLOCK, n))
        others = np.arange(n) != mine[:, None]
        d2 = np.maximum(0, s[mine, None] - 2 * x[mine] @ x.T + s)
        p[start : start + len(mine)][others] = widths(d2[others].reshape(len(mine), n - 1), perplexity).ravel()
    for i in range(0, n, BLOCK):
        for j in range(i, n, BLOCK):
            both = (p[i : i + BLOCK, j : j + BLOCK] + p[j : j + BLOCK, i : i + BLOCK].T) / (2 * n)
            p[i : i + BLOCK, j : j + BLOCK] = both
            p[j : j + BLOCK, i : i + BLOCK] = both.T
    return p


def exact_gradient(p: np.ndarray) -> Callable[[np.ndarray, float], np.ndarray]:
    """All pairs, a block of rows at a time: nothing but ``p`` is as large as ``p``."""

    def of(y: np.ndarray, exaggeration: float) -> np.ndarray:
        one, s, z = np.ones((len(y), 1)), (y**2).sum(1, keepdims=True), 0.0
        left, right, with_one = np.hstack([y, s + 1, one]), np.hstack([-2 * y, one, s]).T.copy(), np.hstack([one, y])
        pull, push = np.empty_like(y), np.empty_like(y)
        for start in range(0, len(y), BLOCK):
            mine = slice(start, start + BLOCK)
            w = left[mine] @ right  # one and the squared distance
            np.reciprocal(w, out=w)
            w[np.arange(len(w)), np.arange(start, start + len(w))] = 0
            m = (p[mine] * w) @ with_one
            pull[mine] = m[:, :1] * y[mine] - m[:, 1:]
            z += float(w.sum())
            w *= w
            m = w @ with_one
            push[mine] = m[:, :1] * y[mine] - m[:, 1:]
        return 4 * (exaggeration * pull - push / z) if z else pull

    return of


def repulsion(y: np.ndarray, cells: int = 48) -> tuple[np.ndarray, float]:
    """Sums over all other points of kernel squared times difference, and of the kernel: cells near each point exactly, far ones by their centre."""
    low, span = y.min(0), np.maximum(y.max(0) - y.min(0), 1e-12)
    cell = np.minimum(((y - low) / span * cells).astype(int), cells - 1)
    key = cell[:, 0] * cells + cell[:, 1]
    order = np.argsort(key, kind="stable")
    mass = np.bincount(key, minlength=cells * cells)
    first = np.cumsum(mass) - mass
    used = np.flatnonzero(mass)
    centre = np.stack([np.bincount(key, weights=y[:, a], minlength=cells * cells)[used] / mass[used] for a in (0, 1)], axis=1)
    at = np.stack([used // cells, used % cells], axis=1)
    force, z = np.zeros_like(y), 0.0
    for begin in range(0, len(y), 2048):
        mine = slice(begin, begin + 2048)
        far = np.abs(cell[mine][:, None, :] - at).max(axis=2) > 1
        dx, dy = (y[mine, a][:, None] - centre[:, a] for a in (0, 1))
        w = mass[used] * far / (1 + dx * dx + dy * dy)
        z += float(w.sum())
        w *= 1 / (1 + dx * dx + dy * dy)
        force[mine, 0] += (w * dx).sum(1)
        force[mine, 1] += (w * dy).sum(1)
    for a in (-1, 0, 1):
        for b in (-1, 0, 1):
            near = cell + (a, b)
            inside = np.flatnonzero(((near >= 0) & (near < cells)).all(axis=1))
            there = near[inside, 0] * cells + near[inside, 1]
            n = mass[there]
            for part in np.array_split(np.arange(len(inside)), 1 + int(n.sum()) // (1 << 21)):
                m = n[part]
                i = np.repeat(inside[part], m)
                j = order[np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m) + np.repeat(first[there[part]], m)]
                d = y[i] - y[j]
                w = (i != j) / (1 + (d**2).sum(1))
                z += float(w.sum())
                for axis in (0, 1):
                    force[:, axis] += np.bincount(i, weights=w * w * d[:, axis], minlength=len(y))
    return force, z


def sparse_gradient(i: np.ndarray, j: np.ndarray, p: np.ndarray) -> Callable[[np.ndarray, float], np.ndarray]:
    """Attraction along the listed pairs, repulsion by cells."""

    def of(y: np.ndarray, exaggeration: float) -> np.ndarray:
        d = y[i] - y[j]
        f = (exaggeration * p / (1 + (d**2).sum(1)))[:, None] * d
        pull = np.stack([np.bincount(i, weights=f[:, a], minlength=len(y)) for a in (0, 1)], axis=1)
        push, z = repulsion(y)
        return 4 * (pull - push / z)

    return of


def _start(ids: np.ndarray, seed: int, init: np.ndarray | None) -> np.ndarray:
    if init is not None:
        return init / max(float(init[:, 0].std()), 1e-12) * 1e-4
    return np.array([np.random.default_rng([seed, int(i) & 0xFFFFFFFF]).normal(size=2) for i in ids]) * 1e-4


def fit(
    points: DataFrame, perplexity: float = 30.0, n_iter: int = 3000, seed: int = 10, method: str | None = None, vec: str = "embedding",
    key: str = "vec_id", landmarks: int = EXACT_POINTS, rate: float | None = None, exaggeration: float = 12.0, early: int = 250,
) -> DataFrame:
    """id, x, y of every point."""
    n = points.count()
    method = method or choose("tsne", n).strategy
    if method == "landmark":
        return _landmarks(points, min(landmarks, n), perplexity, n_iter, seed, vec, key)
    if n > CELL_POINTS:
        raise ValueError(f"{n} points are too many for '{method}'; use 'landmark'")
    if method == "exact":
        kept = points.select(F.col(key).cast("long").alias("id"), F.col(vec).cast("array<double>").alias("v")).toPandas().sort_values("id")
        ids, gradient = kept["id"].to_numpy(), exact_gradient(exact_affinities(np.stack(kept["v"].to_numpy()) if n else np.zeros((0, 1)), perplexity))
    else:
        near = neighbours(points, max(1, min(n - 1, int(3 * perplexity))), vec, key)
        p = symmetrize(conditional(near, perplexity), n).toPandas()  # bounded: points times neighbours
        ids = np.sort(points.select(F.col(key).cast("long")).toPandas().iloc[:, 0].to_numpy())
        i, j = np.searchsorted(ids, p["i"]), np.searchsorted(ids, p["j"])
        order = np.lexsort((j, i))
        gradient = sparse_gradient(i[order], j[order], p["p"].to_numpy()[order])
    y = Descent(_start(ids, seed, None), n_iter, rate, exaggeration, early).run(gradient)
    return points.sparkSession.createDataFrame(pd.DataFrame({"id": ids, "x": y[:, 0], "y": y[:, 1]}))


def _landmarks(points: DataFrame, m: int, perplexity: float, n_iter: int, seed: int, vec: str, key: str, k: int = 8) -> DataFrame:
    """Lays out ``m`` hashed points and places all others; the landmarks are bounded and broadcast."""
    chosen = points.orderBy(F.xxhash64(F.lit(seed), F.col(key)), key).limit(m)
    kept = chosen.select(F.col(key).cast("long").alias("id"), F.col(vec).alias("v")).toPandas()
    laid = fit(points.sparkSession.createDataFrame(kept[["id", "v"]]), perplexity, n_iter, seed, "exact" if m <= EXACT_POINTS else "cells", "v", "id").toPandas().set_index("id")
    shared = points.sparkSession.sparkContext.broadcast((kept["id"].to_numpy(), np.stack(kept["v"].to_numpy()).astype(float), laid.loc[kept["id"]].to_numpy()))

    def place(batches):
        ids, x, y = shared.value
        at = {int(i): n for n, i in enumerate(ids)}
        for pdf in batches:
            for start in range(0, len(pdf), 1024):
                part = pdf.iloc[start : start + 1024]
                v = np.stack(part["v"].to_numpy()).astype(float)
                d2 = np.maximum(0, (v**2).sum(1)[:, None] - 2 * v @ x.T + (x**2).sum(1))
                near = np.argpartition(d2, min(k, len(ids)) - 1, axis=1)[:, :k]
                w = widths(np.take_along_axis(d2, near, 1), min(perplexity, k / 2))
                out = (w[..., None] * y[near]).sum(1)
                for row, i in enumerate(part["id"]):
                    if int(i) in at:
                        out[row] = y[at[int(i)]]
                yield pd.DataFrame({"id": part["id"], "x": out[:, 0], "y": out[:, 1]})

    return points.select(F.col(key).cast("long").alias("id"), F.col(vec).alias("v")).mapInPandas(place, "id long, x double, y double")
