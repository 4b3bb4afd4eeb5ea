"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

A document's place is 48 bits of a hash of its id and text, so places permute each source the
same way on every run and in every layout. A source's documents fall into blocks by the first
bits of their place. A target is met by whole passes over the source and, for the rest, by the
documents under a threshold place, found by refining sums three times by sixteen bits. What
that leaves, less than a document, is filled with smaller documents from behind the threshold.

The blocks of all passes are quotas per source. From the root, a node's quotas are divided
between its two halves of output shards by a multivariate-hypergeometric draw, down to single
shards; each shard then takes that many of the source's permuted blocks, which no other has,
and orders its documents by a hash of place and pass. What the driver holds, and what is
broadcast, is a row per source and ``MAX_BLOCKS`` shard numbers in all; documents are never
shuffled to be drawn.

Defined results: a null text has size 0; null is a source of its own, ordered last; documents
of size 0 are taken zero words but ride with their place's block; repeated rows share a place
and are all taken or all left; a source without words has target 0.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import cut
from .common import free, packed, word_count

#: Fixed values of the contract.
WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2.0
SEED = 20_240_601
BITS, STEP = 48, 16
FILLS = 2
MAX_BLOCKS = 1 << 18
MAX_SOURCES = 20_000
#: Words of an output shard, and the most shards there are: what a task sorts follows from both.
SHARD_WORDS = 1 << 20
MAX_SHARDS = 1 << 16


@dataclass
class Plan:
    """What the mix takes of one source: ``passes`` whole ones and the places under ``threshold``."""

    source: str | None
    size: int
    target: float
    passes: int = 0
    need: float = 0.0
    threshold: int = 0
    #: (up to this size, up to this place): smaller documents behind the threshold that fill what it leaves.
    fills: tuple[tuple[int, int], ...] = ()
    shards: tuple[int, ...] = ()


def place(doc_id: Column, text: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(F.lit(SEED), doc_id, text), 64 - BITS)


def targets(sizes: list[int], weights: list[float], share: float = SHARE, most: float = MOST) -> list[float]:
    """Shares ``share`` of all sizes by weight; what exceeds ``most`` times a size is reshared by weight."""
    out, open_, left = [0.0] * len(sizes), [i for i in range(len(sizes)) if sizes[i] > 0], share * sum(sizes)
    while open_:
        unit = left / sum(weights[i] for i in open_)
        full = [i for i in open_ if unit * weights[i] > most * sizes[i]]
        if not full:
            for i in open_:
                out[i] = unit * weights[i]
            break
        for i in full:
            out[i] = most * sizes[i]
            left -= out[i]
        open_ = [i for i in open_ if out[i] == 0.0]
    return out


def split_tree(quotas: np.ndarray, shards: int, rng: np.random.Generator) -> np.ndarray:
    """Exact quotas per shard (rows) and source (columns); shards get equally many blocks, one more or less."""
    if shards == 1:
        return quotas.reshape(1, -1)
    left, total = shards // 2, int(quotas.sum())
    taken = rng.multivariate_hypergeometric(quotas, total * left // shards, method="marginals") if len(quotas) and total else np.zeros_like(quotas)
    return np.vstack([split_tree(taken, left, rng), split_tree(quotas - taken, shards - left, rng)])


def _find(coded: DataFrame, state: dict[int, tuple[int, int, float]]) -> dict[int, tuple[int, float]]:
    """For each source its threshold and the words under it: at most ``need``, of documents from place ``low`` and up to ``most`` words."""
    spark = coded.sparkSession
    prefix = {i: (0, need) for i, (_, _, need) in state.items()}
    found: dict[int, tuple[int, float]] = {}
    for level in range(BITS // STEP):
        if not prefix:
            break
        shift = BITS - STEP * (level + 1)
        rows = [(i, p, float(need), state[i][0], state[i][1]) for i, (p, need) in prefix.items()]
        at = spark.createDataFrame(rows, "j int, prefix long, need double, low long, most long")
        inside = coded.join(F.broadcast(at), F.col("i") == F.col("j")).where("place >= low AND size <= most").where(F.shiftright("place", shift + STEP) == F.col("prefix"))
        sums = inside.groupBy("i", "need", F.shiftright("place", shift).bitwiseAND(F.lit((1 << STEP) - 1)).alias("digit")).agg(F.sum("size").alias("n"))
        # one source has at most 2^16 digits
        listed = sums.groupBy("i", "need").agg(F.sort_array(F.collect_list(F.struct("digit", "n"))).alias("d"))
        walk = F.expr(
            "aggregate(d, struct(0L AS base, -1L AS digit), (a, x) -> CASE WHEN a.digit >= 0 THEN a "
            "WHEN a.base + x.n > need THEN struct(a.base AS base, x.digit AS digit) ELSE struct(a.base + x.n AS base, -1L AS digit) END)"
        )
        ends = {r.i: r.w for r in listed.select("i", walk.alias("w")).collect()}  # a row per source
        for i, (p, need) in list(prefix.items()):
            w = ends.get(i)
            base, digit = (w.base, w.digit) if w else (0, -1)
            if digit < 0:  # everything there is under this prefix
                found[i] = ((p + 1) << (shift + STEP), state[i][2] - need + base)
                del prefix[i]
            else:
                prefix[i] = ((p << STEP) | digit, need - base)
                found[i] = (prefix[i][0] << shift, state[i][2] - need + base)
    return found


def _thresholds(sized: DataFrame, plans: list[Plan]) -> None:
    """Fills in each plan's threshold place and fills, by sums over the sized rows (no texts).

    Under the threshold lies at most what is needed; what is left is filled with smaller
    documents from behind it, ``FILLS`` times or until it is under a thousandth of the target.
    """
    keys = sized.sparkSession.createDataFrame([(i, p.source) for i, p in enumerate(plans)], "i int, s string")
    coded = sized.join(F.broadcast(keys), F.col("source").eqNullSafe(F.col("s"))).select("i", "place", "size")
    left = {i: p.need for i, p in enumerate(plans) if p.need >= 1}
    for i, (threshold, words) in _find(coded, {i: (0, 1 << 62, n) for i, n in left.items()}).items():
        plans[i].threshold = threshold
        left[i] -= words
    for _ in range(FILLS):
        state = {i: (plans[i].fills[-1][1] if plans[i].fills else plans[i].threshold, int(n), n) for i, n in left.items() if n >= max(1.0, plans[i].target / 1000)}
        for i, (threshold, words) in _find(coded, state).items():
            plans[i].fills += ((state[i][1], threshold),)
            left[i] -= words


def make_plans(sized: DataFrame, shards: int | None = None, seed: int = SEED) -> tuple[list[Plan], int, int]:
    """The plan of each source, in order, the number of first bits that name a block, and the number of shards.

    Unless it is given, that number follows the words the mix takes: ``SHARD_WORDS`` to a shard,
    at most ``MAX_SHARDS``.
    """
    # nulls last, then by code point: the order of UTF-8 bytes
    rows = sized.groupBy("source").agg(F.sum("size").cast("long").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(rows) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    rows.sort(key=lambda r: (r.source is None, r.source or ""))
    aims = targets([r.n for r in rows], [WEIGHTS[i % len(WEIGHTS)] for i in range(len(rows))])
    plans = [Plan(r.source, r.n, t) for r, t in zip(rows, aims, strict=True)]
    for p in plans:
        p.passes = int(p.target // p.size) if p.size else 0
        p.need = p.target - p.passes * p.size
    _thresholds(sized, plans)
    shards = shards or max(1, min(MAX_SHARDS, -(-int(sum(aims)) // SHARD_WORDS)))
    bits = max(0, min(16, int(np.log2(MAX_BLOCKS / (3 * max(1, len(plans))))), int(np.log2(16 * shards))))
    rng = np.random.default_rng(seed)
    # the documents that fill up are one block more
    counts = [p.passes * (1 << bits) + -(-p.threshold // (1 << (BITS - bits))) + bool(p.fills) for p in plans]
    tree = split_tree(np.array(counts, np.int64), shards, rng)
    for k, p in enumerate(plans):
        owner = np.empty(counts[k], np.int64)
        owner[rng.permutation(counts[k])] = np.repeat(np.arange(shards), tree[:, k])
        p.shards = tuple(map(int, owner))
    return plans, bits, shards


def _placed(rows: DataFrame, plans: list[Plan], bits: int) -> DataFrame:
    """``rows`` (source, place, ...) with source_size, target and ``shards``: one for each time it is taken."""
    spark = rows.sparkSession
    pad = lambda p: [x for fill in [*p.fills, *[(0, 0)] * (FILLS - len(p.fills))] for x in fill]
    table = spark.createDataFrame(
        [(p.source, p.size, float(p.target), p.passes, p.threshold, *pad(p), list(p.shards)) for p in plans],
        "_s string, source_size long, target double, _passes int, _threshold long, "
        + "".join(f"_most{k} long, _place{k} long, " for k in range(FILLS)) + "_owners array<int>",
    )
    low, filled = F.col("_threshold"), F.lit(False)
    for k in range(FILLS):
        filled = filled | ((F.col("place") >= low) & (F.col("place") < F.col(f"_place{k}")) & (F.col("size") <= F.col(f"_most{k}")))
        low = F.greatest(low, F.col(f"_place{k}"))
    under = F.col("place") < F.col("_threshold")
    joined = rows.join(F.broadcast(table), F.col("source").eqNullSafe(F.col("_s"))).withColumn("_filled", filled)
    joined = joined.withColumn("_times", F.col("_passes") + (under | F.col("_filled")).cast("int"))
    # a fill's block is its source's last, any other's is named by the first bits of its place
    block = f"CASE WHEN _filled AND k = _passes THEN size(_owners) - 1 ELSE cast(k * {1 << bits} + shiftright(place, {BITS - bits}) AS int) END"
    owners = F.expr(f"CASE WHEN _times > 0 THEN transform(sequence(0, _times - 1), k -> _owners[{block}]) ELSE cast(array() AS array<int>) END")
    return joined.withColumn("shards", owners).drop(*(c for c in table.columns if c[0] == "_"), "_filled", "_times")


def sized_rows(docs: DataFrame) -> DataFrame:
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"),
        word_count(F.col("text")).alias("size"), place(F.col("doc_id").cast("long"), F.col("text").cast("string")).alias("place"),
    )


def account(docs: DataFrame, shards: int | None = None) -> DataFrame:
    """doc_id, size, source_size, target, taken and the shards that take it, for every row of ``docs``."""
    sized = cut(sized_rows(docs))
    plans, bits, _ = make_plans(sized, shards)
    placed = _placed(sized, plans, bits)
    return placed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.size("shards")).cast("long").alias("taken"), "shards")


def mix(docs: DataFrame, shards: int | None = None, shard_column: str | None = None) -> DataFrame:
    """The mixed documents: a row for each time one is taken, with its columns, and the shard's number if a column is named for it.

    Rows of a shard lie in one partition, in the shard's order. A column of ``docs`` called like
    ``shard_column`` gets an underscore before its name.
    """
    sized = cut(sized_rows(docs))
    plans, bits, shards = make_plans(sized, shards)
    rows = docs.select(
        packed(docs).alias("doc"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"),
        place(F.col("doc_id").cast("long"), F.col("text").cast("string")).alias("place"),
    )
    taken = _placed(rows, plans, bits).select("doc", "place", F.posexplode("shards").alias("pass", "shard"))
    order = F.xxhash64(F.lit(SEED + 1), "place", "pass")
    ordered = taken.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", order)
    if shard_column is None:
        return ordered.select("doc.*")
    fields = [F.col("doc").getField(c).alias(n) for c, n in zip(docs.columns, free(docs.columns, shard_column), strict=True)]
    return ordered.select(*fields, F.col("shard").alias(shard_column))
