"""The whole of stage A: from statements to a three-level framework of functions.

Distinct statements, weighted by how often they occur, become TF-IDF rows; a signed hash folds
those into ``dims`` dimensions, which keeps inner products up to a small error and makes them
dense and bounded; standardised, they are laid out in the plane; mixtures are fitted for a
range of K, one is chosen, and its clusters are described, dropped, merged and assembled. Every
step is written before the next one reads it.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut
from . import gmm, taxonomy, tfidf, tsne, vectors


@dataclass
class Framework:
    """What the chain makes on its way."""

    phrases: DataFrame  # stmt_id, text, w, source_share and source (where it mostly stands)
    vectors: DataFrame  # stmt_id, ids, terms, w: normalised TF-IDF rows
    points: DataFrame  # vec_id, embedding: folded and standardised
    layout: DataFrame  # id, x, y, w
    curve: DataFrame  # K, loglik, n_params, bic
    chosen: dict[str, int]  # K by each rule
    assigned: DataFrame  # stmt_id, cluster, w
    terms: DataFrame  # cluster, term, score, rank
    decisions: DataFrame  # cluster, action, target
    functions: DataFrame  # l3_id, l1, l2, l3, n_l3_in_l2, m_l2_in_l1


def distinct(statements: DataFrame, text: str = "text", source: str = "source") -> DataFrame:
    """stmt_id (a hash of the text), text, w (its frequency), the source it occurs in most and that source's share of it."""
    per = statements.groupBy(F.col(text).alias("text"), F.col(source).alias("source")).agg(F.count("*").alias("n"))
    out = per.groupBy("text").agg(F.sum("n").alias("w"), F.max("n").alias("m"), F.max_by("source", F.struct("n", "source")).alias("source"))
    return out.select(F.xxhash64("text").alias("stmt_id"), "text", "w", "source", (F.col("m") / F.col("w")).alias("source_share"))


def fold(sparse: DataFrame, dims: int = 64, key: str = "stmt_id") -> DataFrame:
    """vec_id, embedding: each term is added to one of ``dims`` places with a sign, both by its hash."""
    h = lambda t: F.xxhash64(t)
    place = F.transform("terms", lambda t: F.pmod(h(t), F.lit(dims)).cast("int"))
    sign = F.transform("terms", lambda t: F.when(F.shiftright(h(t), 40).bitwiseAND(F.lit(1)) == 1, 1.0).otherwise(-1.0))
    hit = F.arrays_zip(place.alias("p"), F.zip_with("w", sign, lambda w, s: w * s).alias("v"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda d: F.aggregate(F.filter(F.col("_hit"), lambda x: x["p"] == d), F.lit(0.0), lambda a, x: a + x["v"]))
    return sparse.select(F.col(key).alias("vec_id"), hit.alias("_hit")).select("vec_id", dense.alias("embedding"))


def decide(assigned: DataFrame, phrases: DataFrame, terms_of: DataFrame, source_share: float = 0.5, min_sim: float = 0.9) -> DataFrame:
    """cluster, action ('drop', 'merge' or 'keep') and target: the expert rules, as far as data can tell.

    A cluster of which one source has more than ``source_share`` of the statements is bound to
    that source and dropped; clusters whose term sums are at least ``min_sim`` alike become one.
    """
    by = assigned.join(phrases.select("stmt_id", "source"), "stmt_id").groupBy("cluster", "source").agg(F.sum("w").alias("n"))
    bound = by.groupBy("cluster").agg((F.max("n") / F.sum("n") > source_share).alias("bound"))
    kept = bound.where(~F.col("bound")).select("cluster")
    merged = taxonomy.merge_similar(terms_of.join(kept, "cluster", "left_semi"), min_sim)
    out = bound.join(merged, "cluster", "left")
    action = F.when(F.col("bound"), "drop").when(F.col("merged") != F.col("cluster"), "merge").otherwise("keep")
    return out.select("cluster", action.alias("action"), F.when(~F.col("bound"), F.coalesce("merged", "cluster")).alias("target"))


def assemble(terms_of: DataFrame, decisions: DataFrame, l2_sim: float = 0.5, l1_sim: float = 0.2) -> DataFrame:
    """The kept clusters as functions in groups and stages: l3_id, l1, l2, l3, n_l3_in_l2, m_l2_in_l1.

    A group holds functions tied by similarities of ``l2_sim`` or more, a stage by ``l1_sim`` or
    more, so groups nest in stages. Each is named by its heaviest terms.
    """
    now = cut(terms_of.join(decisions.where("target IS NOT NULL").select("cluster", "target"), "cluster").groupBy(F.col("target").alias("cluster"), "term").agg(F.sum("w").alias("w")))
    groups = taxonomy.merge_similar(now, l2_sim).select("cluster", F.col("merged").alias("g"))
    stages = taxonomy.merge_similar(now, l1_sim).select("cluster", F.col("merged").alias("s"))
    placed = cut(now.join(groups, "cluster").join(stages, "cluster"))

    def name(key: str, n: int) -> DataFrame:
        """The ``n`` heaviest terms of each node, and its number, so that names of nodes differ."""
        sums = placed.groupBy(key, "term").agg(F.round(F.sum("w"), 9).alias("score"))
        top = sums.withColumn("r", F.row_number().over(Window.partitionBy(key).orderBy(F.desc("score"), "term"))).where(F.col("r") <= n)
        listed = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "term"))), lambda x: x["term"]), " ")
        return top.groupBy(key).agg(listed.alias("name")).select(key, F.concat("name", F.lit(" #"), F.col(key).cast("string")).alias(f"{key}_name"))

    nodes = placed.select("cluster", "g", "s").distinct().join(name("cluster", 3), "cluster").join(name("g", 2), "g").join(name("s", 1), "s")
    named = nodes.select(F.col("cluster").alias("l3_id"), F.col("s_name").alias("l1"), F.col("g_name").alias("l2"), F.col("cluster_name").alias("l3"))
    return taxonomy.build(named)


def build(
    statements: DataFrame, min_df: int = 2, most_terms: int = 20_000, dims: int = 64, most_k: int = 500, rule: str = "argmin", method: str | None = None,
    landmarks: int = 1_000, n_iter: int = 3000, perplexity: float = 30.0, seed: int = 10, top: int = 5,
) -> Framework:
    """The chain over statements (text, source). K runs over ``gmm.grid(most_k)`` and then over every K around the best one."""
    phrases = cut(distinct(statements))
    tok = tfidf.tokens(phrases, weight="w")
    known = cut(tfidf.vocab(tfidf.idf(tok), min_df=min_df, top=most_terms))
    sparse = cut(tfidf.rows(tok, known))
    points = cut(vectors.standardize(fold(sparse, dims)))
    laid = tsne.fit(points, perplexity, n_iter, seed, method or "landmark", landmarks=landmarks)
    layout = cut(laid.join(phrases.select(F.col("stmt_id").alias("id"), "w"), "id"))
    n, total = layout.agg(F.count("*"), F.sum("w")).first()
    spark, total = statements.sparkSession, float(total or 0)
    ks = gmm.grid(min(most_k, n))
    models = gmm.sweep(layout, ks, seed=seed, weight="w")
    value = lambda k: gmm.bic(models[k].loglik, k, total)
    if models:
        at = ks.index(min(models, key=lambda k: (value(k), k)))
        models |= gmm.sweep(layout, [k for k in range(ks[max(0, at - 1)], ks[min(len(ks) - 1, at + 1)] + 1) if k not in models], seed=seed, weight="w")
    curve = gmm.bic_curve(spark, models, total) if models else spark.createDataFrame([], "K int, loglik double, n_params int, bic double")
    chosen = {r: gmm.select_k(curve, r).first()["K"] for r in ("argmin", "elbow")} if models else {}
    params = models[chosen[rule]].rows() if models else []
    assigned = gmm.assign(layout, spark.createDataFrame(params, gmm.PARAMS)).select(F.col("id").alias("stmt_id"), F.col("k").cast("long").alias("cluster"))
    assigned = cut(assigned.join(phrases.select("stmt_id", "w"), "stmt_id"))
    long = sparse.select("stmt_id", F.inline(F.arrays_zip("terms", "w")).alias("term", "v"))
    sums = cut(long.join(assigned, "stmt_id").groupBy("cluster", "term").agg(F.sum(F.col("v") * F.col("w")).alias("w")))
    # idf may be negative: a term speaks for a cluster by the size of its sum
    rank = F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("score"), "term"))
    terms = sums.select("cluster", "term", F.round("w", 9).alias("score")).withColumn("rank", rank).where(F.col("rank") <= top)
    decisions = cut(decide(assigned, phrases, sums))
    return Framework(phrases, sparse, points, layout, curve, chosen, assigned, terms, decisions, cut(assemble(sums, decisions)))


def quality(f: Framework, k: int = 10, sampled: int = 200) -> DataFrame:
    """How the layout and the clusters do: measure, value. Neighbours are those of every ``sampled``-th statement by hash, among all."""
    n = f.points.count()
    asked = F.pmod(F.xxhash64("vec_id"), F.lit(max(1, n // sampled))) == 0
    flat = f.layout.select(F.col("id").alias("vec_id"), F.array("x", "y").alias("embedding"))
    true = cut(vectors.nearest(f.points.where(asked), f.points, max(k, min(n - 1, 10 * k))))
    kept = cut(vectors.nearest(flat.where(asked), flat, k))
    ari = cluster_agreement(f)
    recall = vectors.neighbour_recall(true, kept, k).select(F.lit("neighbour_recall").alias("measure"), F.col("recall").alias("value"))
    return recall.unionByName(ari)


def cluster_agreement(f: Framework) -> DataFrame:
    from .cluster_eval import adjusted_rand

    pairs = f.assigned.join(f.phrases.select("stmt_id", "source"), "stmt_id")
    return adjusted_rand(pairs, "cluster", "source").select(F.lit("ari_with_source").alias("measure"), F.col("ari").alias("value"))
