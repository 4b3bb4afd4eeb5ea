"""The call graph: degrees, frequency slices, correlation of operators, and the graph form of a knowledge base."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def degrees(table: DataFrame) -> DataFrame:
    """op, out_degree, in_degree, weight_out, weight_in, degree of a merged pair table."""
    out = table.groupBy(F.col("caller").alias("op")).agg(F.count_distinct("callee").alias("out_degree"), F.sum("n_occ").alias("weight_out"))
    into = table.groupBy(F.col("callee").alias("op")).agg(F.count_distinct("caller").alias("in_degree"), F.sum("n_occ").alias("weight_in"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    both = out.join(into, "op", "full_outer").select("op", *map(zero, ("out_degree", "in_degree", "weight_out", "weight_in")))
    return both.withColumn("degree", F.col("out_degree") + F.col("in_degree"))


def slices(table: DataFrame, n: int = 4) -> DataFrame:
    """Pairs in ``n`` slices by falling frequency. The table is bounded by operators squared."""
    w = Window.orderBy(F.desc("n_occ"), "caller", "callee")
    return table.withColumn("slice", F.ntile(n).over(w).cast("long"))


def correlation(rows: DataFrame, rec: str = "rec_id", op: str = "op") -> DataFrame:
    """Pearson, phi, Jaccard and lift of operators' counts over records, for all pairs a < b.

    Records meet once per operator that they hold; moments of zero counts follow from totals.
    """
    counts = rows.groupBy(F.col(rec).alias("r"), F.col(op).alias("o")).agg(F.count("*").cast("double").alias("x"))
    # over all records and per operator: bounded by the catalogue
    n = rows.agg(F.count_distinct(rec).cast("double").alias("n"))
    one = counts.groupBy("o").agg(F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("q"), F.count("*").cast("double").alias("d"))
    a, b = counts.select("r", F.col("o").alias("a"), F.col("x").alias("xa")), counts.select("r", F.col("o").alias("b"), F.col("x").alias("xb"))
    both = a.join(b, "r").where("a < b").groupBy("a", "b").agg(F.sum(F.col("xa") * F.col("xb")).alias("p"), F.count("*").cast("double").alias("c"))
    side = lambda x: one.select(F.col("o").alias(x), F.col("s").alias(f"s{x}"), F.col("q").alias(f"q{x}"), F.col("d").alias(f"d{x}"))
    grid = side("a").join(side("b"), F.col("a") < F.col("b")).join(both, ["a", "b"], "left").withColumn("k", F.lit(1)).join(n.withColumn("k", F.lit(1)), "k")
    zero = lambda x: F.coalesce(F.col(x), F.lit(0.0))
    N = F.col("n")
    var = lambda x: N * F.col(f"q{x}") - F.col(f"s{x}") * F.col(f"s{x}")
    spread = lambda x: F.col(f"d{x}") * (N - F.col(f"d{x}"))
    safe = lambda num, den: F.when(den > 0, num / F.sqrt(den))
    return grid.select(
        "a", "b", safe(N * zero("p") - F.col("sa") * F.col("sb"), var("a") * var("b")).alias("pearson"),
        safe(N * zero("c") - F.col("da") * F.col("db"), spread("a") * spread("b")).alias("phi"),
        (zero("c") / (F.col("da") + F.col("db") - zero("c"))).alias("jaccard"), (N * zero("c") / (F.col("da") * F.col("db"))).alias("lift"),
    )


def kb_edges(kb: DataFrame) -> DataFrame:
    """Edges of the knowledge base as a graph: operator - combination - function - group - stage: src, dst, kind."""
    op = kb.select(F.explode("combo.items").alias("i"), "kb_id").select(F.concat(F.lit("op:"), "i").alias("src"), F.concat(F.lit("combo:"), "kb_id").alias("dst"), F.lit("in").alias("kind"))
    does = kb.where("l3_id IS NOT NULL").select(F.concat(F.lit("combo:"), "kb_id").alias("src"), F.concat(F.lit("l3:"), "l3_id").alias("dst"), F.lit("does").alias("kind"))
    up = lambda a, b: kb.where(f"{a}_id IS NOT NULL").select(F.concat(F.lit(f"{a}:"), f"{a}_id").alias("src"), F.concat(F.lit(f"{b}:"), f"{b}_id").alias("dst"), F.lit("part of").alias("kind"))
    return op.unionByName(does).unionByName(up("l3", "l2")).unionByName(up("l2", "l1")).distinct()
