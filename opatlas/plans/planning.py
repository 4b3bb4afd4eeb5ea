"""Size-based choice of strategies; every choice says why."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut

#: Rows of a side that is broadcast, where its rows are short.
BROADCAST_ROWS = 200_000
#: Candidates that counting tasks hold at once.
BLOCK_CANDIDATES = 200_000
EXACT_POINTS = 3_000
CELL_POINTS = 50_000
#: Points that a task holds while it fits whole mixtures.
HELD_POINTS = 200_000


@dataclass(frozen=True)
class Choice:
    strategy: str
    why: str


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """True if ``df`` has at most ``rows`` rows; counts no further than that."""
    return df.limit(rows + 1).count() <= rows


def spread(df: DataFrame) -> DataFrame:
    """``df`` of one scan, dealt anew over the cores where it has fewer files than there are cores.

    A file may be one row group and so one task; work on whole texts then needs the other cores.
    Which of the two happens depends on the layout of the files only, and rows are the same.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    # counted in the JVM: a large table has a file a task at least
    return df.repartition(cores) if len(df._jdf.inputFiles()) < cores else df


def maybe_broadcast(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` marked for broadcast if its size was checked; else as it is, for a shuffled join. It is written first, so it is made once."""
    df = cut(df)
    return F.broadcast(df) if small(df, rows) else df


def choose(method: str, n: int) -> Choice:
    """The strategy of a method for an input of ``n`` (points, candidates or pairs)."""
    ladders = {
        "tsne": ((EXACT_POINTS, "exact"), (CELL_POINTS, "cells"), (None, "landmark")),
        "count": ((BLOCK_CANDIDATES, "block"), (None, "join")),
        "mixtures": ((HELD_POINTS, "by_model"), (None, "by_points")),
        "cosine": ((None, "index"),),
        "fuzzy": ((BROADCAST_ROWS, "blocks"), (None, "refused")),
    }
    for most, name in ladders[method]:
        if most is None or n <= most:
            return Choice(name, f"{method}: {n} is " + ("beyond the smaller strategies" if most is None else f"at most {most}"))
    raise AssertionError


def with_each(rows: DataFrame, model: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Every row with every row of a model-sized table (taxonomy, labelers, mixture), which rides along as an array.

    The table is counted first; beyond ``limit`` rows this is refused.
    """
    if not small(model, limit):
        raise ValueError(f"the model side has more than {limit} rows")
    listed = model.agg(F.collect_list(F.struct(*model.columns)).alias("_each")).withColumn("_one", F.lit(1))
    return rows.withColumn("_one", F.lit(1)).join(F.broadcast(listed), "_one").select(*rows.columns, F.inline("_each"))


def with_blocks(rows: DataFrame, model: DataFrame, block: int = 5_000, limit: int = BROADCAST_ROWS) -> DataFrame:
    """As ``with_each``, with the table in arrays of about ``block`` rows, so that a row never carries all of a larger one.

    Rows and blocks are dealt over a fixed number of tasks: rows of few bytes would meet the whole table in one.
    """
    model = cut(model)
    if not small(model, limit):
        raise ValueError(f"the model side has more than {limit} rows")
    blocks = max(1, -(-model.count() // block))
    at = F.pmod(F.xxhash64(*model.columns), F.lit(blocks)).cast("int")
    listed = model.groupBy(at.alias("_block")).agg(F.collect_list(F.struct(*model.columns)).alias("_each"))
    asked = rows.withColumn("_block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    parts = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return asked.repartition(parts, *asked.columns).join(F.broadcast(listed), "_block").select(*rows.columns, F.inline("_each"))
