"""Frequent operator sets, level by level, with their variants, baselines and measures.

Records are compressed and, after the first level, reduced to codes of frequent items; tasks
hold the candidates of a level and give back one partial count each, so what moves follows the
candidates and not the records. Candidates and frequent sets are model-sized and bounded by
``MAX_SETS``; beyond it the search stops with an error, never silently.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass, field
from decimal import Decimal
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.planning import choose
from ..session import cut
from .records import compress

MAX_SETS = 2_000_000


@dataclass
class Level:
    """What one level generated, pruned, counted and kept."""

    k: int
    generated: int
    pruned: int
    counted: int
    frequent: int


@dataclass
class Mined:
    combos: DataFrame
    levels: list[Level] = field(default_factory=list)
    n_records: int = 0
    truncated: bool = False


def least_count(min_support: float | str, n: int) -> int:
    """The smallest frequency that reaches the support; exact, as 0.05 times n may be off by one in floating point."""
    product = Decimal(str(min_support)) * n
    return max(1, int(product.to_integral_value(rounding="ROUND_CEILING")))


def count_block(records: DataFrame, candidates: list[tuple[int, ...]], n_items: int) -> dict[tuple[int, ...], int]:
    """Weighted counts: each task ands the columns of its records' item matrix along shared prefixes."""
    shared = records.sparkSession.sparkContext.broadcast((sorted(candidates), n_items))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets, width = shared.value
        counts = np.zeros(len(sets), np.int64)
        for batch in batches:
            for start in range(0, batch.num_rows, 8192):
                part = batch.slice(start, 8192)
                items = part.column("items").to_pylist()
                w = part.column("w").to_numpy(zero_copy_only=False).astype(np.int64)
                has = np.zeros((width, len(items)), bool)
                has[[c for x in items for c in x], np.repeat(np.arange(len(items)), [len(x) for x in items])] = True
                stack: list[np.ndarray] = []
                last: tuple[int, ...] = ()
                for i, s in enumerate(sets):
                    same = 0
                    while same < len(last) and same < len(s) - 1 and last[same] == s[same]:
                        same += 1
                    del stack[same:]
                    for c in s[same:]:
                        stack.append(has[c] if not stack else stack[-1] & has[c])
                    counts[i] += int(w[stack[-1]].sum())
                    last = s
        if counts.any():
            hit = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array(hit), pa.array(counts[hit])], ["i", "n"])

    partial = records.select("items", F.col("w").cast("long").alias("w")).mapInArrow(run, "i long, n long")
    ordered = sorted(candidates)
    return {ordered[r.i]: int(r.n) for r in partial.groupBy("i").agg(F.sum("n").alias("n")).collect()}


def count_join(records: DataFrame, candidates: list[tuple[int, ...]]) -> dict[tuple[int, ...], int]:
    """The same by a join of exploded items with exploded candidates; needs no candidate in a task's memory."""
    spark, k = records.sparkSession, len(candidates[0])
    rows = spark.createDataFrame([(i, c) for i, s in enumerate(candidates) for c in s], "i int, code int")
    items = records.select(F.xxhash64("items").alias("h"), "items", "w").select("h", "w", F.explode("items").alias("code"))
    held = items.join(rows, "code").groupBy("h", "w", "i").agg(F.count("*").alias("m")).where(F.col("m") == k)
    return {candidates[r.i]: int(r.n) for r in held.groupBy("i").agg(F.sum("w").alias("n")).collect()}


def _joined(frequent: set[tuple[int, ...]]) -> tuple[list[tuple[int, ...]], int]:
    """Sets that agree in all but the last item, without those that have an infrequent subset; also how many were made."""
    by_prefix: dict[tuple[int, ...], list[int]] = {}
    for s in sorted(frequent):
        by_prefix.setdefault(s[:-1], []).append(s[-1])
    made, kept = 0, []
    for head, tails in by_prefix.items():
        for a, b in combinations(tails, 2):
            made += 1
            s = (*head, a, b)
            if all(s[:i] + s[i + 1 :] in frequent for i in range(len(s) - 2)):
                kept.append(s)
        if made > MAX_SETS:
            raise ValueError(f"more than {MAX_SETS} candidates; raise the support or bound max_k")
    return kept, made


def _expanded(frequent: set[tuple[int, ...]], n_items: int) -> list[tuple[int, ...]]:
    """Every frequent set with every other item: what the join rule avoids."""
    if len(frequent) * n_items > MAX_SETS:
        raise ValueError(f"more than {MAX_SETS} candidates; expansion is for small data")
    return sorted({tuple(sorted({*s, c})) for s in frequent for c in range(n_items) if c not in s})


def apriori(
    records: DataFrame, min_support: float | str = 0.05, candidates: str = "join", support: str = "exact", max_k: int = 32,
    pairs: DataFrame | None = None, strategy: str | None = None,
) -> Mined:
    """Frequent item sets of ``records`` (items, optional weight w): combo_id, items, k, freq, support.

    candidates: 'join', 'pair_seeded' (only pairs that ``pairs`` (caller, callee) lists are grown)
    or 'expand'. support: 'exact', 'pair_min' (smallest count of a contained pair, an upper bound
    that prunes) or 'pair_sum' (sum of the counts of contained pairs over all, which does not
    prune and ends at ``max_k``). Where ``max_k`` cuts the search, ``truncated`` is set and a warning given.
    """
    spark = records.sparkSession
    base = cut(compress(records))
    total = int(base.agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0])
    least = least_count(min_support, total)
    levels: list[Level] = []
    singles = base.select(F.explode("items").alias("item"), "w").groupBy("item").agg(F.sum("w").alias("n"))
    n_items = singles.count()
    kept = singles.where(F.col("n") >= least).limit(MAX_SETS + 1).collect()
    if len(kept) > MAX_SETS:
        raise ValueError("too many frequent items")
    kept.sort(key=lambda r: (-r.n, r.item))
    names = [r.item for r in kept]
    found: dict[tuple[int, ...], int] = {(i,): int(r.n) for i, r in enumerate(kept)}
    levels.append(Level(1, n_items, 0, n_items, len(kept)))
    if not kept or max_k < 2:
        return _mined(spark, found, names, total, levels, False)

    code = F.broadcast(spark.createDataFrame([(n, i) for i, n in enumerate(names)], "item string, code int"))
    coded = base.withColumn("h", F.monotonically_increasing_id()).select("h", "w", F.explode("items").alias("item")).join(code, "item")
    reduced = coded.groupBy("h", "w").agg(F.array_sort(F.collect_list("code")).alias("items")).where(F.size("items") > 1)
    shrunk = cut(compress(reduced.select("items", "w")))

    def counted(sets: list[tuple[int, ...]]) -> dict[tuple[int, ...], int]:
        if not sets:
            return {}
        how = strategy or choose("count", len(sets)).strategy
        return count_block(shrunk, sets, len(names)) if how == "block" else count_join(shrunk, sets)

    seeds = None
    if candidates == "pair_seeded":
        if pairs is None:
            raise ValueError("pair_seeded needs the pair table")
        at = {n: i for i, n in enumerate(names)}
        listed = pairs.where(F.col("caller").isin(names) & F.col("callee").isin(names)).select("caller", "callee").distinct().collect()
        seeds = {tuple(sorted((at[r.caller], at[r.callee]))) for r in listed if r.caller != r.callee}
    pair_counts: dict[tuple[int, ...], int] = {}
    current, truncated, k = set(found), False, 2
    while current:
        if k > max_k:
            truncated = bool(_joined(current)[0])
            if truncated:
                warnings.warn(f"sets of more than {max_k} items are left out", stacklevel=2)
            break
        if candidates == "expand" or support == "pair_sum":
            sets = _expanded(current, len(names))
            made = len(sets)
        else:
            sets, made = _joined(current)
            if seeds is not None:
                sets = [s for s in sets if all(p in seeds for p in combinations(s, 2))]
        if support == "exact" or k == 2:
            n = counted(sets)
        elif support == "pair_min":
            n = {s: min(pair_counts.get(p, 0) for p in combinations(s, 2)) for s in sets}
        else:
            n = {s: sum(pair_counts.get(p, 0) for p in combinations(s, 2)) for s in sets}
        if k == 2:
            pair_counts = dict(n)
        bar = least_count(min_support, sum(pair_counts.values())) if support == "pair_sum" else least
        fresh = {s: c for s, c in n.items() if c >= bar}
        levels.append(Level(k, made, made - len(sets), len(sets), len(fresh)))
        found |= fresh
        current, k = set(fresh), k + 1
    return _mined(spark, found, names, total, levels, truncated)


def _mined(spark, found: dict, names: list[str], total: int, levels: list[Level], truncated: bool) -> Mined:
    rows = sorted((len(s), sorted(names[c] for c in s), n) for s, n in found.items())
    data = [(i, items, k, n, n / total if total else 0.0) for i, (k, items, n) in enumerate(rows)]
    return Mined(spark.createDataFrame(data, "combo_id long, items array<string>, k int, freq long, support double"), levels, total, truncated)


def support_of(records: DataFrame, sets: DataFrame) -> DataFrame:
    """Frequency of given sets (set_id, items) in ``records`` (rec_id, items): a join on items, a set counts where all are there."""
    wanted = sets.select("set_id", F.size("items").alias("size"), F.explode("items").alias("item"))
    held = records.select("rec_id", F.explode("items").alias("item")).join(wanted, "item")
    full = held.groupBy("rec_id", "set_id", "size").agg(F.count("*").alias("m")).where("m = size")
    return full.groupBy("set_id").agg(F.count("*").alias("freq"))


def subsets_of(items: Column, k: int) -> Column:
    """All subsets of one to ``k`` items, each in order, as an array; null items give null."""
    none = F.array(F.array().cast("array<string>"))
    grown = F.aggregate(F.array_sort(items), none, lambda made, x: F.concat(made, F.transform(F.filter(made, lambda s: F.size(s) < k), lambda s: F.concat(s, F.array(x)))))
    return F.filter(grown, lambda s: F.size(s) > 0)


def enumerate_all(records: DataFrame, k: int) -> DataFrame:
    """Baseline: every combination of up to ``k`` items of every record, without pruning: items, k, freq."""
    base = compress(records)
    grown = base.select("w", F.explode(subsets_of(F.col("items"), k)).alias("s"))
    return grown.groupBy(F.col("s").alias("items")).agg(F.sum("w").alias("freq")).withColumn("k", F.size("items"))


def fpgrowth(records: DataFrame, min_support: float = 0.05) -> DataFrame:
    """Cross-check by MLlib: items (sorted), k, freq."""
    from pyspark.ml.fpm import FPGrowth

    got = FPGrowth(itemsCol="items", minSupport=min_support).fit(records.select("items")).freqItemsets
    return got.select(F.array_sort("items").alias("items"), F.size("items").alias("k"), "freq")


def rules(combos: DataFrame, n_records: int, min_conf: float = 0.0, max_k: int = 3) -> DataFrame:
    """Rules with one item on the right: left, right, freq, confidence, lift, leverage."""
    sets = combos.where(F.col("k") <= max_k).select("items", "freq")
    whole = sets.where(F.size("items") > 1).select("items", "freq", F.explode("items").alias("rhs"))
    split = whole.withColumn("lhs", F.array_except("items", F.array("rhs")))
    left = sets.select(F.col("items").alias("lhs"), F.col("freq").alias("n_lhs"))
    right = sets.where(F.size("items") == 1).select(F.col("items")[0].alias("rhs"), F.col("freq").alias("n_rhs"))
    joined = split.join(left, "lhs").join(right, "rhs")
    n = F.lit(float(n_records))
    out = joined.withColumn("confidence", F.col("freq") / F.col("n_lhs"))
    out = out.withColumn("lift", F.col("confidence") * n / F.col("n_rhs")).withColumn("leverage", F.col("freq") / n - F.col("n_lhs") / n * F.col("n_rhs") / n)
    return out.where(F.col("confidence") >= min_conf).select("lhs", "rhs", "freq", "confidence", "lift", "leverage")


def size_hist(combos: DataFrame) -> DataFrame:
    """Sets by size, with whether the size is the peak."""
    return combos.groupBy("k").agg(F.count("*").alias("n_sets"), F.max("freq").alias("max_freq"))


def maximal(combos: DataFrame, closed: bool = False) -> DataFrame:
    """Sets without a frequent superset (closed: without one of equal frequency).

    Each set is looked up among the sets of one more item with one left out, so the join is on equality.
    """
    smaller = combos.where("k > 1").select(F.explode(F.transform("items", lambda x: F.array_except("items", F.array(x)))).alias("sub"), F.col("freq").alias("sup_freq"))
    on = F.col("items") == F.col("sub")
    return combos.join(smaller, on & (F.col("freq") == F.col("sup_freq")) if closed else on, "left_anti")


def sweep(mined: Mined, supports: list[str]) -> DataFrame:
    """Sets at each threshold, from one run at the lowest: support is anti-monotone, so the rest is a filter."""
    spark = mined.combos.sparkSession
    bars = spark.createDataFrame([(s, least_count(s, mined.n_records)) for s in supports], "min_support string, least long")
    return mined.combos.join(F.broadcast(bars), F.col("freq") >= F.col("least")).groupBy("min_support").agg(F.count("*").alias("n_sets"), F.max("k").cast("long").alias("max_k"))


def shadow_check(sizes: dict[int, int]) -> list[str]:
    """Which sizes of a published histogram can not come from an anti-monotone support (Kruskal-Katona bound)."""
    wrong = []
    for k in sorted(sizes):
        if k < 2 or sizes[k] == 0:
            continue
        left, bound, i = sizes[k], 0, k
        while left > 0 and i > 0:
            a = i
            while _choose(a + 1, i) <= left:
                a += 1
            left -= _choose(a, i)
            bound += _choose(a, i - 1)
            i -= 1
        if bound > sizes.get(k - 1, 0):
            wrong.append(f"{sizes[k]} sets of {k} need {bound} of {k - 1}, there are {sizes.get(k - 1, 0)}")
    return wrong


def _choose(n: int, k: int) -> int:
    from math import comb

    return comb(n, k)


def level_stats(mined: Mined) -> DataFrame:
    rows = [(x.k, x.generated, x.pruned, x.counted, x.frequent) for x in mined.levels]
    return mined.combos.sparkSession.createDataFrame(rows, "k int, generated long, pruned long, counted long, frequent long")


def sequences(ordered: DataFrame, min_support: float = 0.05, max_length: int = 4) -> DataFrame:
    """Ordered combinations by MLlib's PrefixSpan, from ``ordered`` (seq: array of operators): seq, freq."""
    from pyspark.ml.fpm import PrefixSpan

    nested = ordered.select(F.transform("seq", lambda x: F.array(x)).alias("sequence"))
    got = PrefixSpan(minSupport=min_support, maxPatternLength=max_length).findFrequentSequentialPatterns(nested)
    return got.select(F.flatten("sequence").alias("seq"), "freq")
