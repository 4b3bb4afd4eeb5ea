"""TF-IDF with the published variants, as sparse rows and in long form (stmt_id, term, w).

With a vocabulary of a checked size, term counts, weights and the norm stay in the row of their
statement (``rows``, ``normed``): the vocabulary is broadcast, and its own aggregation is the only exchange.
A larger vocabulary is joined in long form. ``weight`` (a phrase's multiplicity) counts a phrase
as so many statements.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.planning import BROADCAST_ROWS, maybe_broadcast
from ..session import cut


def tokens(statements: DataFrame, text: str = "text", weight: str | None = None) -> DataFrame:
    """stmt_id, tok (array) and w, from normalised statements."""
    w = F.col(weight) if weight else F.lit(1)
    return statements.select("stmt_id", F.filter(F.split(text, " "), lambda x: x != "").alias("tok"), w.cast("long").alias("w"))


def counts(tok: DataFrame) -> DataFrame:
    """stmt_id, term, f (occurrences in the statement), n_tok, w."""
    rows = tok.select("stmt_id", "w", F.size("tok").alias("n_tok"), F.explode("tok").alias("term"))
    return rows.groupBy("stmt_id", "term").agg(F.count("*").alias("f"), F.first("n_tok").alias("n_tok"), F.first("w").alias("w"))


def tf(tok: DataFrame, scope: str = "statement") -> DataFrame:
    """Term frequency per statement, or of the whole corpus on every statement that has the term."""
    c = counts(tok)
    if scope == "statement":
        return c.select("stmt_id", "term", (F.col("f") / F.col("n_tok")).alias("tf"), "w")
    if scope != "corpus":
        raise ValueError(f"no scope {scope}")
    total = tok.agg(F.sum(F.col("w") * F.size("tok")).alias("n")).withColumn("k", F.lit(1))
    share = c.groupBy("term").agg(F.sum(F.col("w") * F.col("f")).alias("s")).withColumn("k", F.lit(1)).join(total, "k").select("term", (F.col("s") / F.col("n")).alias("tf"))
    return c.select("stmt_id", "term", "w").join(maybe_broadcast(share), "term").select("stmt_id", "term", "tf", "w")


def idf(tok: DataFrame, form: str = "paper") -> DataFrame:
    """term, n_t (statements with it) and idf: ln(N / (1 + n)), which may be 0 or negative, or the smooth form, which may not."""
    seen = tok.select("w", F.explode(F.array_distinct("tok")).alias("term")).groupBy("term").agg(F.sum("w").alias("n_t")).withColumn("k", F.lit(1))
    n = tok.agg(F.sum("w").alias("n")).withColumn("k", F.lit(1))
    ratio = {"paper": F.col("n") / (1 + F.col("n_t")), "smooth": (F.col("n") + 1) / (1 + F.col("n_t"))}[form]
    return seen.join(n, "k").select("term", "n_t", F.log(ratio).alias("idf"))


def vocab(terms: DataFrame, min_df: int = 1, max_df: int | None = None, top: int | None = None) -> DataFrame:
    """Terms within document-frequency bounds, the ``top`` most frequent of them, with a rank from 1."""
    kept = terms.where((F.col("n_t") >= min_df) & (F.lit(True) if max_df is None else F.col("n_t") <= max_df))
    if top is None:
        return kept
    first = kept.orderBy(F.desc("n_t"), "term").limit(top)
    return first.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n_t"), "term")))


def _schema(tok: DataFrame) -> str:
    return f"stmt_id {tok.schema['stmt_id'].dataType.simpleString()}, ids array<int>, terms array<string>, w array<double>"


def rows(tok: DataFrame, terms: DataFrame, normed: bool = True, scope: str = "statement", most: int = BROADCAST_ROWS) -> DataFrame | None:
    """stmt_id, ids (ranks in the ordered vocabulary), terms and weights of each statement in one row; over their length if ``normed``.

    ``terms`` is a vocabulary (term, idf); words outside it count for the statement's length only.
    None if it has more than ``most`` rows: it is counted no further, and not collected.
    """
    known = cut(terms.select("term", "idf"))
    if known.limit(most + 1).count() > most:
        return None
    if scope == "corpus":
        share = tok.select("w", F.explode("tok").alias("term")).groupBy("term").agg(F.sum("w").alias("s"))
        total = float(tok.agg(F.sum(F.col("w") * F.size("tok"))).first()[0] or 1)
        known = known.join(share, "term").select("term", (F.col("idf") * F.col("s") / total).alias("idf"))
    listed = known.toArrow().sort_by("term")
    shared = tok.sparkSession.sparkContext.broadcast((listed["term"].combine_chunks(), listed["idf"].to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, idf = shared.value
        for batch in batches:
            tokens_ = batch.column("tok")
            sizes = pc.fill_null(pc.list_value_length(tokens_), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            code = pc.fill_null(pc.index_in(pc.list_flatten(tokens_), value_set=words), -1).to_numpy(zero_copy_only=False).astype(np.int64)
            row = np.repeat(np.arange(len(sizes)), sizes)[code >= 0]
            # a term of a row once, with how often it stands there
            key, n = np.unique(row * (len(words) + 1) + code[code >= 0], return_counts=True)
            row, code = key // (len(words) + 1), key % (len(words) + 1)
            w = idf[code] if scope == "corpus" else n / sizes[row] * idf[code]
            if normed:
                length = np.sqrt(np.bincount(row, weights=w * w, minlength=len(sizes)))[row]
                w = np.divide(w, length, out=np.zeros_like(w), where=length > 0)
            ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(sizes)))]), pa.int32())
            cols = (pa.array(code, pa.int32()), words.take(pa.array(code)), pa.array(w))
            yield pa.RecordBatch.from_arrays([batch.column("stmt_id"), *(pa.ListArray.from_arrays(ends, c) for c in cols)], ["stmt_id", "ids", "terms", "w"])

    return tok.select("stmt_id", "tok").mapInArrow(run, _schema(tok))


def _long(sparse: DataFrame) -> DataFrame:
    return sparse.select("stmt_id", F.inline(F.arrays_zip("terms", "w")).alias("term", "w"))


def weights(tok: DataFrame, scope: str = "statement", form: str = "paper", terms: DataFrame | None = None) -> DataFrame:
    """stmt_id, term, w = tf * idf, in long form and in the JVM; ``rows`` gives the same in the statement's row."""
    v = (idf(tok, form) if terms is None else terms).select("term", "idf")
    return tf(tok, scope).select("stmt_id", "term", "tf").join(maybe_broadcast(v), "term").select("stmt_id", "term", (F.col("tf") * F.col("idf")).alias("w"))


def summed(tok: DataFrame, by: str, form: str = "paper") -> DataFrame:
    """by, term, w: ``weights`` summed over the statements of each value of ``by``, a column of ``tok``.

    Statements are read once, and what moves is a partial sum of each term: its shares, the
    statements that have it, and the statements in all.
    """
    ordered = tok.select(by, "w", F.array_sort("tok").alias("o"))
    # in order, a term's first place is where the one before differs
    marked = F.transform("o", lambda x, i: F.struct(x.alias("term"), (i == 0).alias("head"), ((i == 0) | (F.get("o", i - 1) != x)).alias("once")))
    rows = ordered.select(by, "w", F.size("o").alias("n"), F.inline_outer(marked))
    head = F.coalesce("head", F.lit(True))  # a statement without a token counts too
    part = cut(rows.groupBy(by, "term").agg(F.sum(F.try_divide(F.lit(1.0), "n")).alias("s"), F.sum(F.when(F.col("once"), F.col("w"))).alias("d"), F.sum(F.when(head, F.col("w"))).alias("h")))
    total = part.agg(F.coalesce(F.sum("h"), F.lit(0))).first()[0]
    seen = part.where("term IS NOT NULL").groupBy("term").agg(F.sum("d").alias("n_t"))
    ratio = {"paper": F.lit(total) / (1 + F.col("n_t")), "smooth": F.lit(total + 1) / (1 + F.col("n_t"))}[form]
    return part.join(maybe_broadcast(seen.select("term", F.log(ratio).alias("idf"))), "term").select(by, "term", (F.col("s") * F.col("idf")).alias("w"))


def normed(tok: DataFrame, form: str = "paper", terms: DataFrame | None = None) -> DataFrame:
    """stmt_id, term, w over the statement's length: ``l2`` of ``weights``, in the row where the vocabulary allows it."""
    v = cut((idf(tok, form) if terms is None else terms).select("term", "idf"))
    sparse = rows(tok, v)
    return _long(sparse) if sparse is not None else l2(weights(tok, terms=v))


def l2(long: DataFrame) -> DataFrame:
    """Each statement's weights over their length; a vector of zeros stays one."""
    norm = long.groupBy("stmt_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("_n"))
    return long.join(norm, "stmt_id").select("stmt_id", "term", F.when(F.col("_n") > 0, F.col("w") / F.col("_n")).otherwise(0.0).alias("w"))


def cosine_pairs(normed: DataFrame, min_sim: float = 0.8) -> DataFrame:
    """Pairs a < b of statements at least ``min_sim`` alike, through an inverted index with prefix pruning.

    Of unit vectors only entries before the point where the rest cannot reach ``min_sim`` are
    indexed against: terms are taken from the rarest, so common terms rarely make pairs.
    """
    df = normed.where("w <> 0").groupBy("term").agg(F.count("*").alias("d"))
    placed = normed.where("w <> 0").join(maybe_broadcast(df), "term")
    order = Window.partitionBy("stmt_id").orderBy("d", "term")
    rest = placed.withColumn("before", F.coalesce(F.sum(F.col("w") * F.col("w")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
    # the part from here on has length sqrt(1 - before): below min_sim, no pair starts here
    prefix = rest.where(F.col("before") <= 1 - min_sim * min_sim + 1e-9).select("stmt_id", "term")
    a, b = prefix.withColumnRenamed("stmt_id", "a"), prefix.withColumnRenamed("stmt_id", "b")
    pairs = a.join(b, "term").where("a < b").select("a", "b").distinct()
    vec = normed.where("w <> 0").groupBy("stmt_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "w"))).alias("v"))
    both = pairs.join(vec.select(F.col("stmt_id").alias("a"), F.col("v").alias("va")), "a").join(vec.select(F.col("stmt_id").alias("b"), F.col("v").alias("vb")), "b")
    dot = F.expr("aggregate(map_keys(va), 0D, (s, t) -> s + va[t] * coalesce(vb[t], 0D))")
    return both.select("a", "b", dot.alias("sim")).where(F.col("sim") >= min_sim)


def mllib_pipeline(statements: DataFrame, text: str = "text", vocab_size: int = 1 << 18):
    """The MLlib equivalent (counts, smooth idf, L2), fitted: a cross-check of the smooth form."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import IDF, CountVectorizer, Normalizer, RegexTokenizer

    stages = [
        RegexTokenizer(inputCol=text, outputCol="tok", pattern=" +", toLowercase=False),
        CountVectorizer(inputCol="tok", outputCol="tf", vocabSize=vocab_size),
        IDF(inputCol="tf", outputCol="tfidf"),
        Normalizer(inputCol="tfidf", outputCol="features", p=2.0),
    ]
    return Pipeline(stages=stages).fit(statements)
