"""Records (transactions): sorted sets of items, compressed to distinct ones with a weight."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def make(rows: DataFrame, unit: str = "script", rec: str = "rec_id", item: str = "item") -> DataFrame:
    """rec_id and sorted distinct items.

    ``unit``: 'script' for rows (rec, item); 'caller' for pairs, one record per calling operator
    of a script's pairs holding its callees; 'pair' for pairs, one record each.
    """
    if unit == "script":
        # distinct first: a map-side combine, so repeated items of a hot record never meet in one list
        return rows.select(F.col(rec).alias("rec_id"), F.col(item).alias("item")).distinct().groupBy("rec_id").agg(F.array_sort(F.collect_set("item")).alias("items"))
    if unit == "caller":
        return rows.select("caller", "callee").distinct().groupBy(F.col("caller").alias("rec_id")).agg(F.array_sort(F.collect_set("callee")).alias("items"))
    if unit == "pair":
        return rows.select(F.col(rec).alias("rec_id"), F.array_sort(F.array_distinct(F.array("caller", "callee"))).alias("items"))
    raise ValueError(f"no record unit {unit}")


def compress(records: DataFrame) -> DataFrame:
    """Distinct item sets with the number of records that have them."""
    weight = F.sum("w") if "w" in records.columns else F.count("*")
    return records.groupBy("items").agg(weight.cast("long").alias("w"))
