"""Sampling, expert consensus, and the measures: semantic, structural and overall score."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import edit_ratio, jaccard
from ..session import cut

W_SEMANTIC = 0.6


# --- sample and truth -----------------------------------------------------------------------


def strata(combos: DataFrame, n: int = 150) -> DataFrame:
    """k, size, quota: proportional by length, the largest remainders rounded up. A row per length."""
    sizes = combos.groupBy("k").agg(F.count("*").alias("size"))
    total = F.sum("size").over(Window.partitionBy(F.lit(1)))
    share = F.col("size") * n / total
    floored = sizes.withColumn("share", share).withColumn("base", F.floor("share")).withColumn("rest", F.round(F.col("share") - F.col("base"), 9))
    left = F.lit(n) - F.sum("base").over(Window.partitionBy(F.lit(1)))
    rank = F.row_number().over(Window.partitionBy(F.lit(1)).orderBy(F.desc("rest"), "k"))
    return floored.withColumn("left", left).withColumn("rank", rank).select("k", "size", F.least(F.col("size"), F.col("base") + (F.col("rank") <= F.col("left")).cast("int")).cast("long").alias("quota"))


def sample(combos: DataFrame, n: int = 150) -> DataFrame:
    """The quota of each length, by a hash of the items."""
    order = Window.partitionBy("k").orderBy(F.md5(F.array_join("items", "|")), "combo_id")
    ranked = combos.withColumn("_r", F.row_number().over(order))
    return ranked.join(F.broadcast(strata(combos, n).select("k", "quota")), "k").where("_r <= quota").drop("_r", "quota")


def evaluation_sample(combos: DataFrame, by_length: int = 100, similar: int = 25, rare: int = 25) -> DataFrame:
    """The sample that experts label: ``combos`` with ``draw``, each combination once.

    First in proportion to lengths ('length'), then of those that differ from one of them by
    one operator ('similar'), then of those that hold a rare operator ('rare'); each draw goes
    by a hash of the items. Combinations are mined sets, draws are bounded parameters.
    """
    order = [F.md5(F.array_join("items", "|")), "combo_id"]
    first = cut(sample(combos, by_length).withColumn("draw", F.lit("length")))
    pairs = near_pairs(combos)
    near = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).join(first.select(F.col("combo_id").alias("a")), "a", "left_semi").select(F.col("b").alias("combo_id")).distinct()
    left = combos.join(first.select("combo_id"), "combo_id", "left_anti")
    second = cut(left.join(near, "combo_id", "left_semi").orderBy(*order).limit(similar).withColumn("draw", F.lit("similar")))
    left = left.join(second.select("combo_id"), "combo_id", "left_anti")
    third = left.join(low_frequency(combos).select("combo_id").distinct(), "combo_id", "left_semi").orderBy(*order).limit(rare).withColumn("draw", F.lit("rare"))
    return first.unionByName(second).unionByName(third)


def near_pairs(combos: DataFrame, insertion: bool = False) -> DataFrame:
    """Pairs a, b that differ by one operator: substituted at equal length, or (insertion) one more in b.

    Sets meet by what is left when one item is taken out, so nothing is compared with everything.
    """
    left = combos.select(F.col("combo_id").alias("a"), F.col("items").alias("ia"), F.explode("items").alias("out"))
    key = left.select("a", F.array_join(F.array_except("ia", F.array("out")), "|").alias("rest"))
    if insertion:
        whole = combos.select(F.col("combo_id").alias("s"), F.array_join("items", "|").alias("rest"))
        return whole.join(key, "rest").select(F.col("s").alias("a"), F.col("a").alias("b"))
    return key.join(key.withColumnRenamed("a", "b"), "rest").where("a < b").select("a", "b").distinct()


def low_frequency(combos: DataFrame, share: float = 0.25) -> DataFrame:
    """Combinations that hold an operator of the rarest ``share``: combo_id, op."""
    ops = combos.where("k = 1").select(F.col("items")[0].alias("op"), "freq")
    rare = ops.withColumn("r", F.percent_rank().over(Window.partitionBy(F.lit(1)).orderBy("freq", "op"))).where(F.col("r") <= share).select("op")
    return combos.select("combo_id", F.explode("items").alias("op")).join(F.broadcast(rare), "op").select("combo_id", "op")


def consensus(votes: DataFrame, item: str = "item_id", label: str = "label", unanimous: bool = False) -> DataFrame:
    """item, label on which most experts agree (all, if unanimous); items without are left out as ambiguous."""
    n = votes.groupBy(item, label).agg(F.count("*").alias("n"))
    top = n.groupBy(item).agg(F.sum("n").alias("t"), F.max_by(label, "n").alias(label), F.max("n").alias("m"))
    return top.where(F.col("m") == F.col("t") if unanimous else 2 * F.col("m") > F.col("t")).select(item, label)


def fleiss(votes: DataFrame, item: str = "item_id", label: str = "label") -> DataFrame:
    """Fleiss' kappa, one row, where every item has equally many votes."""
    n = votes.groupBy(item, label).agg(F.count("*").cast("double").alias("n"))
    per = n.groupBy(item).agg(F.sum("n").alias("r"), F.sum(F.col("n") * F.col("n")).alias("q"))
    agree = per.agg(F.avg((F.col("q") - F.col("r")) / (F.col("r") * (F.col("r") - 1))).alias("p"), F.sum("r").alias("t")).withColumn("_k", F.lit(1))
    chance = n.groupBy(label).agg(F.sum("n").alias("c")).agg(F.sum(F.col("c") * F.col("c")).alias("c2")).withColumn("_k", F.lit(1))
    pe = F.col("c2") / (F.col("t") * F.col("t"))
    return agree.join(chance, "_k").select(((F.col("p") - pe) / (1 - pe)).alias("kappa"))


def cohen(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Cohen's kappa of two raters, one row."""
    n = pairs.agg(F.count("*").cast("double").alias("n"), F.sum((F.col(a) == F.col(b)).cast("double")).alias("same")).withColumn("_k", F.lit(1))
    ca, cb = (pairs.groupBy(F.col(c).alias("v")).agg(F.count("*").cast("double").alias(f"c{i}")) for i, c in enumerate((a, b)))
    both = ca.join(cb, "v").agg(F.sum(F.col("c0") * F.col("c1")).alias("e")).withColumn("_k", F.lit(1))
    pe = F.col("e") / (F.col("n") * F.col("n"))
    return n.join(both, "_k").select(((F.col("same") / F.col("n") - pe) / (1 - pe)).alias("kappa"))


# --- scores ---------------------------------------------------------------------------------


def levels(pred: DataFrame, truth: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """``pred`` (item_id, l3_id, ...) with t1, t2, t3: right stage, group (by path) and function, and the truth's n and m."""
    tax = taxonomy.select("l3_id", "l1", "l2", "l3", "n_l3_in_l2", "m_l2_in_l1")
    p = F.broadcast(tax.select("l3_id", F.col("l1").alias("p1"), F.col("l2").alias("p2"), F.col("l3").alias("p3")))
    t = F.broadcast(tax.withColumnsRenamed({"l3_id": "truth", "l1": "q1", "l2": "q2", "l3": "q3", "n_l3_in_l2": "n", "m_l2_in_l1": "m"}))
    joined = pred.join(truth.select("item_id", "truth"), "item_id").join(p, "l3_id", "left").join(t, "truth")
    same = lambda *k: F.coalesce(*([F.expr(" AND ".join(f"p{i} = q{i}" for i in k))]), F.lit(False))
    return joined.select(*pred.columns, "truth", same(1).alias("t1"), same(1, 2).alias("t2"), F.coalesce(F.col("l3_id") == F.col("truth"), F.lit(False)).alias("t3"), "n", "m", "p3", "q3")


def text_similarity(how: str = "jaccard") -> Column:
    """S in [0, 1] between the predicted and the true function's name."""
    return {"jaccard": jaccard, "edit": edit_ratio}[how](F.coalesce("p3", F.lit("")), F.col("q3"))


def semantic(s: Column) -> Column:
    """100 for the right function, else 100 S."""
    return F.when(F.col("t3"), 100.0).otherwise(100.0 * s)


def structure() -> Column:
    """100 for the right function, 80 over the group's functions for the right group, 20 over the stage's groups for the right stage."""
    return F.when(F.col("t3"), 100.0).when(F.col("t2"), 80.0 / F.col("n")).when(F.col("t1"), 20.0 / F.col("m")).otherwise(0.0)


def overall(semantic_: Column, structure_: Column, w_sem: float = W_SEMANTIC) -> Column:
    return w_sem * semantic_ + (1 - w_sem) * structure_


def scored(pred: DataFrame, truth: DataFrame, taxonomy: DataFrame, how: str = "jaccard", w_sem: float = W_SEMANTIC) -> DataFrame:
    """Predictions with their levels and three scores."""
    out = levels(pred, truth, taxonomy).withColumn("semantic", semantic(text_similarity(how))).withColumn("structure", structure())
    return out.withColumn("overall", overall(F.col("semantic"), F.col("structure"), w_sem))


def means(scores: DataFrame) -> DataFrame:
    """Mean scores of each subset. Fifteen rows."""
    return scores.groupBy("subset").agg(*(F.avg(c).alias(c) for c in ("structure", "semantic", "overall")))


def report(scores: DataFrame) -> DataFrame:
    """Mean scores of each subset, its models, rank in its size, and gain over the best single model. Fifteen rows."""
    mean = means(scores).withColumn("n_models", F.size(F.split("subset", r"\+")))
    rank = F.rank().over(Window.partitionBy("n_models").orderBy(F.desc(F.round("overall", 9))))
    best = F.max(F.when(F.col("n_models") == 1, F.col("overall"))).over(Window.partitionBy(F.lit(1)))
    return mean.withColumn("rank", rank).withColumn("gain", F.col("overall") - best)


def accuracy(lv: DataFrame) -> DataFrame:
    """Share right at each level, one row per subset."""
    return lv.groupBy("subset").agg(*(F.avg(F.col(f"t{i}").cast("double")).alias(f"acc_l{i}") for i in (1, 2, 3)))


def macro_f1(lv: DataFrame, pred: str = "p3", true: str = "q3") -> DataFrame:
    """Mean of the classes' F1 per subset, over all classes predicted or true."""
    hit = lv.where(F.col(pred) == F.col(true)).groupBy("subset", F.col(true).alias("c")).agg(F.count("*").alias("tp"))
    p = lv.groupBy("subset", F.col(pred).alias("c")).agg(F.count("*").alias("np"))
    t = lv.groupBy("subset", F.col(true).alias("c")).agg(F.count("*").alias("nt"))
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    both = t.join(p, ["subset", "c"], "full_outer").join(hit, ["subset", "c"], "left").where("c IS NOT NULL")
    return both.groupBy("subset").agg(F.avg(2.0 * z("tp") / (z("np") + z("nt"))).alias("macro_f1"))


def confusion(lv: DataFrame, values: list[str], pred: str = "p1", true: str = "q1") -> DataFrame:
    """True class by predicted class."""
    return lv.groupBy(F.col(true).alias("truth")).pivot(pred, values).agg(F.count(F.lit(1))).na.fill(0)


def invented_rate(calls: DataFrame, operators: DataFrame, op: str = "op") -> DataFrame:
    """Share of calls of operators that the catalogue does not have, one row."""
    known = F.broadcast(operators.select(F.col(op)).distinct().withColumn("_known", F.lit(1)))
    out = calls.groupBy(op).agg(F.count("*").alias("n")).join(known, op, "left")
    return out.agg(F.sum("n").alias("n_calls"), F.sum(F.when(F.col("_known").isNull(), F.col("n")).otherwise(0)).alias("n_invented"))


def hit_at_k(answers: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of items whose true function is among the first ``k`` answers (item_id, l3_id, rank), one row."""
    hit = answers.where(F.col("rank") <= k).join(truth, ["item_id", "l3_id"], "left_semi").select("item_id").distinct().withColumn("_h", F.lit(1.0))
    return truth.select("item_id").distinct().join(hit, "item_id", "left").agg(F.avg(F.coalesce("_h", F.lit(0.0))).alias("hit_rate"))
