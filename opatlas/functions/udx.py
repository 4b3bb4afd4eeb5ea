"""Functions that Spark has no built-in form for; ``register`` makes them known to SQL."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from itertools import combinations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udf(T.ArrayType(T.ArrayType(T.StringType())))
def k_subsets(items: list[str] | None, k: int) -> list[list[str]]:
    """All subsets of one to ``k`` items, in order."""
    return [list(s) for n in range(1, k + 1) for s in combinations(sorted(items or ()), n)]


@F.pandas_udf(T.DoubleType())
def ngram_dice(a: pd.Series, b: pd.Series) -> pd.Series:
    """Dice coefficient of the character pairs of two strings; equal strings give 1, nulls null."""

    def one(x: str | None, y: str | None) -> float | None:
        if x is None or y is None:
            return None
        if x == y:
            return 1.0
        p, q = (Counter(s[i : i + 2] for i in range(len(s) - 1)) for s in (x, y))
        total = p.total() + q.total()
        return 2.0 * (p & q).total() / total if total else 0.0

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")


@F.pandas_udf(T.DoubleType())
def jaro_winkler(a: pd.Series, b: pd.Series) -> pd.Series:
    """Jaro-Winkler similarity with the usual prefix weight of a tenth; nulls give null."""

    def one(s: str | None, t: str | None) -> float | None:
        if s is None or t is None:
            return None
        if s == t:
            return 1.0
        reach = max(0, max(len(s), len(t)) // 2 - 1)
        used, hits = [False] * len(t), []
        for i, c in enumerate(s):
            for j in range(max(0, i - reach), min(len(t), i + reach + 1)):
                if not used[j] and t[j] == c:
                    used[j] = True
                    hits.append(c)
                    break
        m = len(hits)
        if not m:
            return 0.0
        other = [t[j] for j in range(len(t)) if used[j]]
        swaps = sum(x != y for x, y in zip(hits, other, strict=True)) / 2
        jaro = (m / len(s) + m / len(t) + (m - swaps) / m) / 3
        prefix = next((i for i in range(min(4, len(s), len(t))) if s[i] != t[i]), min(4, len(s), len(t)))
        return jaro + prefix * 0.1 * (1 - jaro)

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")


@F.pandas_udf(T.DoubleType())
def weighted_gini(counts: pd.Series) -> float:
    """Gini impurity of the counts of a group: 0 if one value has them all."""
    total = float(counts.sum())
    return 1.0 - float(((counts / total) ** 2).sum()) if total else 0.0


def _node_table(lang: str):
    from ..sources import parse

    @F.udtf(returnType="node_id int, parent_id int, pos int, depth int, kind string, op string, call_path array<string>, next_call string")
    class Nodes:
        def eval(self, source: str) -> Iterator[tuple]:
            yield from parse.nodes_of(source or "", lang)

    return Nodes


@F.udtf(returnType=T.StructType([T.StructField("size", T.IntegerType()), T.StructField("items", T.ArrayType(T.StringType()))]))
class Subsets:
    """The subsets of one to k items as rows."""

    def eval(self, items: list[str], k: int) -> Iterator[tuple]:
        for n in range(1, k + 1):
            for s in combinations(sorted(items or ()), n):
                yield n, list(s)


def register(spark: SparkSession) -> None:
    """SQL names: ngram_dice, jaro_winkler, weighted_gini, k_subsets, k_subset_rows, js_nodes, py_nodes, html_nodes."""
    for name, f in (("ngram_dice", ngram_dice), ("jaro_winkler", jaro_winkler), ("weighted_gini", weighted_gini), ("k_subsets", k_subsets)):
        spark.udf.register(name, f)
    spark.udtf.register("k_subset_rows", Subsets)
    for lang in ("js", "py", "html"):
        spark.udtf.register(f"{lang}_nodes", _node_table(lang))
