"""The knowledge base and its uses: assembly, lookups, retrieval-augmented prompts, tuning sets and their cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..plans.planning import maybe_broadcast


def build(combos: DataFrame, votes: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """kb_id, level ids and names, the combination, its votes and confidence.

    votes: item_id (= combo_id), l3_id, votes, total. Level ids are hashes of their path.
    """
    tax = maybe_broadcast(taxonomy.select("l3_id", "l1", "l2", "l3"))
    key = F.sha2(F.array_join("items", "|"), 256)
    joined = combos.join(votes.withColumnRenamed("item_id", "combo_id"), "combo_id").join(tax, "l3_id")
    path = lambda *c: F.substring(F.md5(F.concat_ws("/", *c)), 1, 8)
    return joined.select(
        F.substring(key, 1, 16).alias("kb_id"), path("l1").alias("l1_id"), path("l1", "l2").alias("l2_id"), F.col("l3_id").cast("string").alias("l3_id"), "l1", "l2", "l3",
        F.struct("items", "support", "freq").alias("combo"), F.create_map(F.col("l3"), F.col("votes").cast("long")).alias("votes"), (F.col("votes") / F.col("total")).alias("confidence"),
    )


def to_json(kb: DataFrame) -> DataFrame:
    """kb_id and the entry as JSON with its index."""
    return kb.select("kb_id", F.to_json(F.struct(*kb.columns)).alias("json"))


def functions_for(demands: DataFrame, functions: DataFrame, k: int = 3) -> DataFrame:
    """Question 1: the ``k`` functions whose text is most like a demand: item_id, l3_id, sim, rank.

    Demands and functions meet by shared words only; idf is that of the functions.
    """
    words = lambda c: F.array_distinct(tokens(c))
    side = functions.select("l3_id", F.explode(words(F.col("text"))).alias("t"))
    n = functions.count()
    idf = side.groupBy("t").agg(F.log(F.lit(n + 1.0) / F.count("*")).alias("w"))
    weighed = side.join(idf, "t")
    norm = weighed.groupBy("l3_id").agg(F.sqrt(F.sum(F.col("w") ** 2)).alias("nf"))
    ask = demands.select("item_id", F.explode(words(F.col("text"))).alias("t")).join(maybe_broadcast(idf), "t")
    norm_d = ask.groupBy("item_id").agg(F.sqrt(F.sum(F.col("w") ** 2)).alias("nd"))
    dot = ask.join(side, "t").groupBy("item_id", "l3_id").agg(F.sum(F.col("w") ** 2).alias("dot"))
    sims = dot.join(norm, "l3_id").join(norm_d, "item_id").select("item_id", "l3_id", F.round(F.col("dot") / (F.col("nf") * F.col("nd")), 9).alias("sim"))
    rank = F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("sim"), "l3_id"))
    return sims.withColumn("rank", rank).where(F.col("rank") <= k)


def precedence(ordered_pairs: DataFrame) -> DataFrame:
    """Question 2: how much oftener a comes right before b than after: a, b, net, for net > 0; from pairs caller, callee, n_occ."""
    back = ordered_pairs.select(F.col("callee").alias("caller"), F.col("caller").alias("callee"), F.col("n_occ").alias("m"))
    both = ordered_pairs.join(back, ["caller", "callee"], "left").withColumn("net", F.col("n_occ") - F.coalesce("m", F.lit(0)))
    return both.where("net > 0 AND caller <> callee").select(F.col("caller").alias("a"), F.col("callee").alias("b"), "net")


def order_functions(functions: DataFrame, stages: list[str]) -> DataFrame:
    """Functions in the order of their stage, then by name: ``functions`` with ``step`` per item."""
    rank = F.coalesce(*(F.when(F.col("l1") == s, F.lit(i)) for i, s in enumerate(stages)), F.lit(len(stages)))
    return functions.withColumn("step", F.row_number().over(Window.partitionBy("item_id").orderBy(rank, "l3")))


def combos_for(kb: DataFrame, l1: str | None = None, l3: str | None = None, top: int = 5) -> DataFrame:
    """Question 3: the most frequent combinations of each function: l3, rank, items, freq. Filters reach partitioned files."""
    kept = kb
    if l1 is not None:
        kept = kept.where(F.col("l1") == l1)
    if l3 is not None:
        kept = kept.where(F.col("l3") == l3)
    rank = F.row_number().over(Window.partitionBy("l1", "l2", "l3").orderBy(F.desc("combo.freq"), "kb_id"))
    return kept.withColumn("rank", rank).where(F.col("rank") <= top).select("l1", "l2", "l3", "rank", "combo.items", "combo.freq")


def by_id(kb: DataFrame, kb_id: str) -> DataFrame:
    return kb.where(F.col("kb_id") == kb_id)


def rag_prompt(demands: DataFrame, answers: DataFrame, combos: DataFrame) -> DataFrame:
    """item_id, prompt: the demand with its functions in rank order and their combinations."""
    listed = combos.groupBy("l3_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rank", "items"))), lambda x: F.array_join(x["items"], "+")), "; ").alias("c"))
    lines = answers.join(listed, "l3_id", "left").groupBy("item_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rank", "l3", F.coalesce("c", F.lit("-")).alias("c")))), lambda x: F.concat(x["rank"].cast("string"), F.lit(". "), x["l3"], F.lit(": "), x["c"])), "\n").alias("lines")
    )
    known = F.coalesce("lines", F.lit("nothing known"))
    return demands.join(lines, "item_id", "left").select("item_id", F.concat(F.lit("Demand: "), "text", F.lit("\nKnown functions:\n"), known, F.lit("\nWrite the script.")).alias("prompt"))


def bare_prompt(demands: DataFrame) -> DataFrame:
    """Baseline: the demand alone."""
    return demands.select("item_id", F.concat(F.lit("Demand: "), "text", F.lit("\nWrite the script.")).alias("prompt"))


def finetune(kb: DataFrame, style: str = "chat", valid: float = 0.1) -> DataFrame:
    """kb_id, split and record (JSON) in the style 'instruction', 'completion' or 'chat'; the split is a hash of the id."""
    ask = F.concat(F.lit("Which function do these operators perform together: "), F.array_join("combo.items", ", "), F.lit("?"))
    tell = F.concat_ws(" > ", "l1", "l2", "l3")
    record: Column = {
        "instruction": F.to_json(F.struct(F.lit("Name the function.").alias("instruction"), F.array_join("combo.items", ", ").alias("input"), tell.alias("output"))),
        "completion": F.to_json(F.struct(ask.alias("prompt"), tell.alias("completion"))),
        "chat": F.to_json(F.struct(F.array(F.struct(F.lit("user").alias("role"), ask.alias("content")), F.struct(F.lit("assistant").alias("role"), tell.alias("content"))).alias("messages"))),
    }[style]
    bucket = F.conv(F.substring(F.md5("kb_id"), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
    return kb.select("kb_id", F.when(bucket < valid, "valid").otherwise("train").alias("split"), record.alias("record"))


def tuning_cost(layers: DataFrame, rank: int = 8, bottleneck: int = 64, prefix: int = 20) -> DataFrame:
    """Trainable parameters of the four tuning families, from layers (d_in, d_out, d, n): family, n_params."""
    c = F.col
    sums = layers.agg(
        F.sum(c("n") * c("d_in") * c("d_out")).alias("full"), F.sum(c("n") * rank * (c("d_in") + c("d_out"))).alias("low_rank"),
        F.sum(c("n") * (2 * c("d") * bottleneck + bottleneck + c("d"))).alias("adapter"), F.sum(c("n") * 2 * prefix * c("d")).alias("prefix"),
    )
    return sums.unpivot([], ["full", "low_rank", "adapter", "prefix"], "family", "n_params")
