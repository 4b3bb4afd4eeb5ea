"""Queueing, labelers, verification, fuzzy matching and voting."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from itertools import combinations

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.edits import Names
from ..functions.noise import noise
from ..functions.text import edit_ratio, set_jaccard, token_set, tokens
from ..functions.udx import ngram_dice
from ..plans.planning import BROADCAST_ROWS, maybe_broadcast, with_blocks, with_each
from ..session import cut
from .taxonomy import narrow

#: Models in the order that breaks ties, with the error rates of their simulated annotators.
MODELS = ("M1", "M3", "M2", "M4")
ERROR = {"M1": 0.40, "M2": 0.44, "M3": 0.42, "M4": 0.48}
RUNS = 5
#: Places that fit beside a similarity in one whole number; far more than names may be compared.
_PLACES = 1 << 20


# --- queue ----------------------------------------------------------------------------------


def order(combos: DataFrame, by: str = "len_freq", batch: int = 50) -> DataFrame:
    """``combos`` (combo_id, items, k, freq) with place and batch: short and frequent first.

    'len_freq_sim' puts alike combinations of one length and frequency side by side by their
    items. Combinations are mined sets; places come from a range sort and each partition's
    offset, so no single task sees them all.
    """
    keys = [F.col("k"), F.desc("freq"), *([F.array_join("items", "|")] if by == "len_freq_sim" else []), F.col("combo_id")]
    return places(combos, keys).withColumn("batch", F.floor((F.col("place") - 1) / batch).cast("long"))


def places(rows: DataFrame, keys: Sequence[Column]) -> DataFrame:
    """``rows`` with place, from 1 in the order of ``keys``: a range sort and each partition's offset, in no single task."""
    parts = max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranged = cut(rows.repartitionByRange(parts, *keys).withColumn("_p", F.spark_partition_id()))
    sizes = ranged.groupBy("_p").agg(F.count("*").alias("_n"))  # a row per partition
    offsets = sizes.select("_p", (F.sum("_n").over(Window.orderBy("_p")) - F.col("_n")).alias("_o"))
    inside = F.row_number().over(Window.partitionBy("_p").orderBy(*keys))
    placed = ranged.withColumn("_r", inside).join(F.broadcast(offsets), "_p")
    return placed.withColumn("place", (F.col("_o") + F.col("_r")).cast("long")).drop("_p", "_r", "_o")


def chain(combos: DataFrame) -> DataFrame:
    """combo_id, k, pos: inside each length, each next combination is the one most like the last, by Jaccard.

    A length's mined sets are one group; they are model-sized.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = pdf.sort_values(["freq", "combo_id"], ascending=[False, True])
        sets = [(int(i), frozenset(x)) for i, x in zip(rows["combo_id"], rows["items"], strict=True)]
        out, left = [], sets[:]
        at = left.pop(0) if left else None
        while at is not None:
            out.append(at[0])
            if not left:
                break
            best = max(range(len(left)), key=lambda n: (len(at[1] & left[n][1]) / len(at[1] | left[n][1]), -n))
            at = left.pop(best)
        return pd.DataFrame({"combo_id": out, "k": int(pdf["k"].iloc[0]), "pos": range(len(out))})

    return combos.select("combo_id", "items", "k", "freq").groupBy("k").applyInPandas(run, "combo_id long, k int, pos int")


# --- labelers -------------------------------------------------------------------------------


def subsets(models: Sequence[str] = MODELS) -> list[tuple[str, tuple[str, ...]]]:
    """All non-empty subsets of the models: name and members."""
    return [("+".join(sorted(s)), s) for n in range(1, len(models) + 1) for s in combinations(models, n)]


def seeded(items: DataFrame, taxonomy: DataFrame, models: Sequence[str] = MODELS, runs: int = RUNS) -> DataFrame:
    """Ballots of SIMULATED annotators: item_id, model, run, raw_label.

    items: item_id, truth (l3_id). An annotator errs where noise shared by all models, by all
    runs of one, and its own add up to less than the model's error rate; a wrong label is drawn
    from the same group, the same stage or anywhere. One label in ten is spelt wrongly.
    """
    spark = items.sparkSession
    team = spark.createDataFrame([(m, ERROR[m], r) for m in models for r in range(1, runs + 1)], "model string, err double, run int")
    ballots = with_each(items, team)
    i, m, r = F.col("item_id"), F.col("model"), F.col("run")
    wrong = 0.4 * noise(i, "d") + 0.3 * noise(i, m) + 0.3 * noise(i, m, r) < F.col("err")
    tax = cut(taxonomy.select("l3_id", "l1", "l2", "l3"))
    where, pick = noise(i, m, r, "where"), noise(i, m, r, "pick")
    scope = F.when(where < 0.5, 2).when(where < 0.8, 1).otherwise(0)
    drawn = ballots.join(maybe_broadcast(_surroundings(tax)), "truth").withColumn("scope", F.when(wrong, scope))
    of = lambda *c: F.when(F.col("scope") >= len(c), F.col(c[-1])).otherwise("")
    size = F.when(F.col("scope") == 2, F.col("in_l2")).when(F.col("scope") == 1, F.col("in_l1")).otherwise(F.col("in_all"))
    asked = drawn.select("item_id", "model", "run", F.col("l3").alias("own"), "scope", of("l1").alias("l1"), of("l1", "l2").alias("l2"), (F.floor(pick * size) + 1).cast("long").alias("place"))
    named = asked.join(maybe_broadcast(_pools(tax)), ["scope", "l1", "l2", "place"], "left")  # a right label has no scope, so no match
    label = F.when(F.col("scope").isNull(), F.col("own")).otherwise(F.col("l3"))
    damaged = F.concat(F.lower(F.substring(label, 1, 3)), F.substring(label, F.lit(5), F.lit(99)))
    return named.select("item_id", "model", "run", F.when(noise(i, m, r, "spell") < 0.1, damaged).otherwise(label).alias("raw_label"))


def _surroundings(tax: DataFrame) -> DataFrame:
    """Each function (truth) with its path and how many functions there are in its group, in its stage and at all."""
    group = tax.groupBy("l1", "l2").agg(F.count("*").alias("in_l2"))
    stage = group.groupBy("l1").agg(F.sum("in_l2").alias("in_l1"))
    whole = tax.agg(F.count("*").alias("in_all")).withColumn("_k", F.lit(1))
    around = tax.join(group, ["l1", "l2"]).join(stage, "l1").withColumn("_k", F.lit(1)).join(F.broadcast(whole), "_k")
    return around.select(F.col("l3_id").alias("truth"), "l1", "l2", "l3", "in_l2", "in_l1", "in_all")


def _pools(tax: DataFrame) -> DataFrame:
    """Functions by their place in each pool: scope (2 group, 1 stage, 0 all), l1, l2 (empty beyond the scope), place, l3.

    Three rows a function, in place of a list of the pool in each row.
    """
    at = lambda *c: F.row_number().over(Window.partitionBy(*c).orderBy("l3_id")).cast("long").alias("place")
    none = F.lit("")
    group = tax.select(F.lit(2).alias("scope"), "l1", "l2", at("l1", "l2"), "l3")
    stage = tax.select(F.lit(1).alias("scope"), "l1", none.alias("l2"), at("l1"), "l3")
    whole = places(tax, [F.col("l3_id")]).select(F.lit(0).alias("scope"), none.alias("l1"), none.alias("l2"), "place", "l3")
    return group.unionByName(stage).unionByName(whole)


def word_scores(items: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """item_id, l3_id, l1, l2, l3, score: cosine of the words of an item's ``text`` and a function's path, where they share any."""
    names = taxonomy.select("l3_id", "l1", "l2", "l3", F.array_distinct(tokens(F.concat_ws(" ", "l1", "l2", "l3"))).alias("ws"))
    words = names.select("l3_id", "l1", "l2", "l3", F.size("ws").alias("n"), F.explode("ws").alias("word"))
    asked = items.select("item_id", F.array_distinct(tokens(F.col("text"))).alias("ws"))
    mine = asked.select("item_id", F.size("ws").alias("m"), F.explode("ws").alias("word"))
    shared = mine.join(maybe_broadcast(words), "word").groupBy("item_id", "l3_id", "l1", "l2", "l3", "n", "m").agg(F.count("*").alias("c"))
    return shared.select("item_id", "l3_id", "l1", "l2", "l3", (F.col("c") / F.sqrt(F.col("n") * F.col("m"))).alias("score"))


def lexical(items: DataFrame, taxonomy: DataFrame, model: str = "lexical") -> DataFrame:
    """Ballots by shared words: item_id, model, run, raw_label. Functions without any shared word are no candidates."""
    best = word_scores(items, taxonomy).groupBy("item_id").agg(F.min_by("l3", F.struct(-F.round("score", 9), F.col("l3_id"))).alias("raw_label"))
    return best.select("item_id", F.lit(model).alias("model"), F.lit(1).alias("run"), "raw_label")


def narrowing(items: DataFrame, taxonomy: DataFrame, model: str = "narrowing") -> DataFrame:
    """The same scores, but a stage is chosen first, then a group of it, then a function."""
    chosen = narrow(word_scores(items, taxonomy).select("item_id", "l1", "l2", "l3", "score"))
    return chosen.select("item_id", F.lit(model).alias("model"), F.lit(1).alias("run"), F.col("l3").alias("raw_label"))


def recorded(items: DataFrame, replies: DataFrame) -> DataFrame:
    """Ballots from recorded replies (item_id, model, run, raw_label), for known items only; a ballot is kept once."""
    return replies.join(items.select("item_id").distinct(), "item_id", "left_semi").dropDuplicates(["item_id", "model", "run"])


def run(items: DataFrame, provider: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Ballots of any provider, checked for their columns and written once: a provider is never asked twice."""
    out = provider(items)
    missing = {"item_id", "model", "run", "raw_label"} - set(out.columns)
    if missing:
        raise ValueError(f"a provider must give {sorted(missing)}")
    return cut(out)


# --- matching -------------------------------------------------------------------------------


def exists(labels: DataFrame, taxonomy: DataFrame, label: str = "raw_label") -> DataFrame:
    """Distinct labels that are functions of the taxonomy."""
    return labels.select(label).distinct().join(maybe_broadcast(taxonomy.select(F.col("l3").alias(label)).distinct()), label, "left_semi")


def missing(labels: DataFrame, taxonomy: DataFrame, label: str = "raw_label") -> DataFrame:
    """Distinct labels that are not."""
    return labels.select(label).distinct().join(maybe_broadcast(taxonomy.select(F.col("l3").alias(label)).distinct()), label, "left_anti")


def prepared(how: str, col: Column) -> Column:
    """What ``similarity`` compares of a name; made once a name, not once a pair."""
    return token_set(col) if how == "jaccard" else col


def similarity(how: str, a: Column, b: Column) -> Column:
    return {"edit": edit_ratio, "jaccard": set_jaccard, "dice": ngram_dice}[how](a, b)


def fuzzy(labels: DataFrame, taxonomy: DataFrame, how: str = "edit", label: str = "raw_label") -> DataFrame:
    """Nearest function of each distinct label: label, l3_id, sim; ties go to the lower id.

    how: 'edit', 'jaccard', 'dice', or 'cosine' (TF-IDF of character pairs). By cosine, labels and
    functions meet by shared pairs of characters, and a label that shares none has no row. Else
    every label is compared with every function, in blocks of the taxonomy; one of more than
    ``BROADCAST_ROWS`` functions is refused.
    """
    wanted = labels.select(F.col(label)).distinct()
    tax = taxonomy.select("l3_id", "l3")
    if how != "cosine":
        # of functions of one name the lowest id wins, so a name is compared once
        names = tax.groupBy("l3").agg(F.min("l3_id").alias("l3_id"))
        return _nearest_by_edits(wanted, names, label) if how == "edit" else _nearest(wanted, names, how, label)
    scored = _by_grams(wanted, tax, label).withColumnRenamed("cosine", "sim")
    best = scored.groupBy(label).agg(F.min_by(F.struct("l3_id", "sim"), F.struct(-F.round("sim", 9), F.col("l3_id"))).alias("b"))
    return best.select(label, "b.l3_id", "b.sim")


def _nearest(labels: DataFrame, names: DataFrame, how: str, label: str) -> DataFrame:
    """The nearest of ``names`` (l3, l3_id) for each label, over all pairs.

    A pair becomes one whole number, its similarity in billionths before the name's place by id,
    whose maximum is taken by hash: a smallest struct would sort all pairs first.
    """
    names = cut(places(names, [F.col("l3_id")]).select("l3", "l3_id", "place", prepared(how, F.col("l3")).alias("_b")))
    pairs = with_blocks(labels.withColumn("_a", prepared(how, F.col(label))), names.select("place", "_b"))
    near = F.coalesce(F.round(F.round(similarity(how, F.col("_a"), F.col("_b")), 9) * 1e9).cast("long"), F.lit(-1).cast("long"))
    best = pairs.select(label, (near * _PLACES - F.col("place")).alias("_code")).groupBy(label).agg(F.max("_code").alias("_code"))
    found = best.withColumn("place", F.pmod(-F.col("_code"), F.lit(_PLACES))).join(maybe_broadcast(names), "place")
    return found.select(label, "l3_id", similarity(how, prepared(how, F.col(label)), F.col("_b")).alias("sim"))


def _nearest_by_edits(labels: DataFrame, names: DataFrame, label: str) -> DataFrame:
    """The same by edit distance: each task holds all names, model-sized and counted, and takes a label against all of them in array steps."""
    context = labels.sparkSession.sparkContext
    kept = sorted((r.l3_id, r.l3) for r in names.where("l3 IS NOT NULL").limit(BROADCAST_ROWS + 1).collect())
    if len(kept) > BROADCAST_ROWS:
        raise ValueError(f"the model side has more than {BROADCAST_ROWS} rows")
    shared = context.broadcast(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, texts = zip(*shared.value, strict=True) if shared.value else ((), ())
        index = Names(texts) if texts else None
        for batch in batches:
            asked = batch.column(0).to_pylist() if index else []
            found = [(0, None) if x is None else index.nearest(x) for x in asked]
            yield pa.RecordBatch.from_arrays([pa.array(asked, pa.string()), pa.array([ids[i] for i, _ in found], pa.int64()), pa.array([s for _, s in found], pa.float64())], ["label", "l3_id", "sim"])

    parts = max(1, int(labels.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    # by a hash of its own: dealt by the label as ``distinct`` deals it, Spark drops this exchange and few bytes become one task
    dealt = labels.select(F.col(label).cast("string").alias("label")).repartition(parts, F.xxhash64("label"))
    return dealt.mapInArrow(run, "label string, l3_id long, sim double").withColumnRenamed("label", label)


def grams(col: Column) -> Column:
    """Character pairs of a lower-case text, each once."""
    t = F.lower(col)
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(t) - 1)), lambda i: F.substring(t, i, F.lit(2))))


def _by_grams(labels: DataFrame, tax: DataFrame, label: str) -> DataFrame:
    """Labels and functions that share a character pair, with the cosine of their weighted pairs."""
    side = tax.select("l3_id", "l3", F.explode(grams(F.col("l3"))).alias("g"))
    seen = side.groupBy("g").agg(F.count("*").alias("d"))
    n = tax.count()
    idf = seen.select("g", F.log(F.lit(n + 1.0) / (F.col("d") + 1) + 1).alias("idf"))
    norm_t = side.join(idf, "g").groupBy("l3_id").agg(F.sqrt(F.sum(F.col("idf") ** 2)).alias("nt"))
    mine = labels.select(label, F.explode(grams(F.col(label))).alias("g")).join(idf, "g", "left").withColumn("idf", F.coalesce("idf", F.log(F.lit(n + 2.0))))
    norm_l = mine.groupBy(label).agg(F.sqrt(F.sum(F.col("idf") ** 2)).alias("nl"))
    dot = mine.join(side, "g").groupBy(label, "l3_id", "l3").agg(F.sum(F.col("idf") ** 2).alias("dot"))
    return dot.join(norm_t, "l3_id").join(norm_l, label).select(label, "l3_id", "l3", (F.col("dot") / (F.col("nt") * F.col("nl"))).alias("cosine"))


def resolve(ballots: DataFrame, taxonomy: DataFrame, how: str = "edit", least: float = 0.5) -> DataFrame:
    """``ballots`` with l3_id and matched_by ('exact', 'fuzzy' or 'none').

    Distinct labels are verified first, and only the missing ones are compared.
    """
    tax = taxonomy.select("l3_id", "l3")
    exact = tax.groupBy("l3").agg(F.min("l3_id").alias("_exact"))
    lost = fuzzy(missing(ballots, taxonomy), taxonomy, how).where(F.col("sim") >= least).select("raw_label", F.col("l3_id").alias("_near"))
    out = ballots.join(maybe_broadcast(exact), F.col("raw_label") == F.col("l3"), "left").join(maybe_broadcast(lost), "raw_label", "left")
    by = F.when(F.col("_exact").isNotNull(), "exact").when(F.col("_near").isNotNull(), "fuzzy").otherwise("none")
    return out.select("item_id", "model", "run", "raw_label", F.coalesce("_exact", "_near").alias("l3_id"), by.alias("matched_by"))


# --- voting ---------------------------------------------------------------------------------


def _priority(models: Sequence[str]) -> Column:
    return F.coalesce(*(F.when(F.col("model") == m, F.lit(i)) for i, m in enumerate(models)), F.lit(len(models)))


def tallies(resolved: DataFrame, models: Sequence[str] = MODELS) -> DataFrame:
    """item_id, model, l3_id, n, prio: what all votes are made from, one exchange for all subsets."""
    return cut(resolved.where("l3_id IS NOT NULL").groupBy("item_id", "model", "l3_id").agg(F.count("*").alias("n")).withColumn("prio", _priority(models)))


def single(tally: DataFrame) -> DataFrame:
    """Each model's own vote: item_id, model, l3_id, n; ties go to the lower id."""
    best = tally.groupBy("item_id", "model").agg(F.min_by(F.struct("l3_id", "n"), F.struct(-F.col("n"), F.col("l3_id"))).alias("b"))
    return best.select("item_id", "model", "b.l3_id", "b.n")


def _in_subsets(tally: DataFrame, models: Sequence[str]) -> DataFrame:
    table = tally.sparkSession.createDataFrame([(name, m) for name, members in subsets(models) for m in members], "subset string, model string")
    return tally.join(F.broadcast(table), "model")


def pooled(tally: DataFrame, models: Sequence[str] = MODELS, weight: Column | None = None) -> DataFrame:
    """Votes of every subset over all its ballots: subset, item_id, l3_id, votes. Ties go to the first model that cast it, then the lower id."""
    w = F.sum(F.col("n") * (weight if weight is not None else F.lit(1)))
    sums = _in_subsets(tally, models).groupBy("subset", "item_id", "l3_id").agg(w.alias("votes"), F.min("prio").alias("prio"))
    best = sums.groupBy("subset", "item_id").agg(F.min_by(F.struct("l3_id", "votes"), F.struct(-F.col("votes"), F.col("prio"), F.col("l3_id"))).alias("b"))
    return best.select("subset", "item_id", "b.l3_id", "b.votes")


def two_stage(tally: DataFrame, models: Sequence[str] = MODELS) -> DataFrame:
    """Each model votes alone first, then the subset's models with one voice each."""
    voices = single(tally).withColumn("n", F.lit(1)).withColumn("prio", _priority(models))
    return pooled(voices, models)


def weighted(tally: DataFrame, models: Sequence[str] = MODELS) -> DataFrame:
    """Ballots count by their model's accuracy."""
    w = F.coalesce(*(F.when(F.col("model") == m, F.lit(1 - ERROR[m])) for m in models), F.lit(0.5))
    return pooled(tally, models, w)


def agreement(resolved: DataFrame) -> DataFrame:
    """Over each item's ballots: number, labels, margin of the first over the second, entropy, and share of stable models."""
    per = resolved.where("l3_id IS NOT NULL").groupBy("item_id", "l3_id").agg(F.count("*").alias("n"))
    tops = per.groupBy("item_id").agg(F.sum("n").alias("ballots"), F.count("*").alias("n_labels"), F.slice(F.reverse(F.array_sort(F.collect_list("n"))), 1, 2).alias("t"), F.collect_list("n").alias("ns"))
    p = F.transform("ns", lambda x: x / F.col("ballots"))
    entropy = F.aggregate(F.array_sort(p), F.lit(0.0), lambda a, x: a - x * F.log(x))
    steady = resolved.where("l3_id IS NOT NULL").groupBy("item_id", "model").agg((F.count_distinct("l3_id") == 1).cast("double").alias("s")).groupBy("item_id").agg(F.avg("s").alias("stable"))
    margin = (F.col("t")[0] - F.coalesce(F.get("t", F.lit(1)), F.lit(0))) / F.col("ballots")
    return tops.select("item_id", "ballots", "n_labels", margin.alias("margin"), entropy.alias("entropy")).join(steady, "item_id")
