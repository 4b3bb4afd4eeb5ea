"""Operator pairs: nested and neighbouring calls, counted per script and merged."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planning import maybe_broadcast


def neighbour(rows: DataFrame, order: Sequence[str], rec: str = "rec_id", op: str = "op", parent: Sequence[str] = ()) -> DataFrame:
    """Each operator with the next one under the same parent."""
    w = Window.partitionBy(rec, *parent).orderBy(*order)
    paired = rows.select(F.col(rec).alias("rec_id"), F.col(op).alias("caller"), F.lead(op).over(w).alias("callee"))
    return paired.where(F.col("callee").isNotNull()).withColumn("relation", F.lit("next"))


def nest(nodes: DataFrame) -> DataFrame:
    """Each call with the nearest call around it, from parsed nodes."""
    outer = F.element_at("call_path", -1)
    found = nodes.where("kind IN ('call', 'element') AND size(call_path) > 0")
    return found.select(F.col("script_id").alias("rec_id"), outer.alias("caller"), F.col("op").alias("callee"), F.lit("nest").alias("relation"))


def next_call(nodes: DataFrame) -> DataFrame:
    """Each call with its very next sibling, if that is a call, from parsed nodes."""
    found = nodes.where("kind IN ('call', 'element') AND next_call IS NOT NULL")
    return found.select(F.col("script_id").alias("rec_id"), F.col("op").alias("caller"), F.col("next_call").alias("callee"), F.lit("next").alias("relation"))


def merge(pairs: DataFrame) -> DataFrame:
    """The pair table: occurrences and scripts of every pair, each pair once.

    Counts are reduced per script before they meet by pair, so a hot pair moves one row per
    script and task, and then one per task.
    """
    per_script = pairs.groupBy("rec_id", "relation", "caller", "callee").agg(F.count("*").alias("n"))
    return per_script.groupBy("relation", "caller", "callee").agg(F.sum("n").alias("n_occ"), F.count("*").alias("n_scripts"))


def in_catalogue(pairs: DataFrame, operators: DataFrame, op: str = "op") -> DataFrame:
    """Pairs whose two operators are both known; applied before anything is counted."""
    known = maybe_broadcast(operators.select(F.col(op).alias("_op")).distinct())
    return pairs.join(known, F.col("caller") == F.col("_op"), "left_semi").join(known, F.col("callee") == F.col("_op"), "left_semi")


def summary(table: DataFrame, operators: DataFrame | None = None, op: str = "op") -> DataFrame:
    """Distinct pairs, operators, callers and callees, and the catalogue they cover; of a merged table, so small."""
    pairs = table.select("caller", "callee").distinct()
    both = pairs.select(F.explode(F.array("caller", "callee")).alias("o")).distinct()
    counts = pairs.agg(F.count("*").alias("n_pairs"), F.count_distinct("caller").alias("n_callers"), F.count_distinct("callee").alias("n_callees"))
    out = counts.withColumn("one", F.lit(1)).join(both.agg(F.count("*").alias("n_operators")).withColumn("one", F.lit(1)), "one")
    if operators is not None:
        size = operators.select(op).distinct().agg(F.count("*").alias("n_catalogue")).withColumn("one", F.lit(1))
        out = out.join(size, "one")
    return out.drop("one")


def top(table: DataFrame, n: int = 20) -> DataFrame:
    return table.orderBy(F.desc("n_occ"), "caller", "callee", "relation").limit(n)
