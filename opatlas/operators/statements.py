"""Functional statements: extraction, normalisation, distinct phrases, granularity and term statistics."""

from __future__ import annotations

from collections.abc import Callable, Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.corpus import NOT_LETTER, NOT_TOKEN, STATEMENT_END


def normalize(col: Column) -> Column:
    """Lower case, only letters and digits, single blanks."""
    return F.trim(F.regexp_replace(F.lower(col), NOT_TOKEN, " "))


def extract(scripts: DataFrame, provider: str | Callable[[str], Iterable[str]] = "rules", text: str = "text", keep: tuple[str, ...] = ("script_id",)) -> DataFrame:
    """Rows of ``keep``, pos and text (normalised), in order, without empty statements.

    provider: 'rules' cuts at sentence ends; a function from a text to statements stands for a
    language model or for recorded replies and runs on Arrow batches.
    """
    cols = [F.col(c) for c in keep]
    if callable(provider):

        def run(batches):
            for pdf in batches:
                out = pdf.assign(parts=[list(provider(t)) if t is not None else [] for t in pdf["_text"]])
                yield out.drop(columns="_text")

        picked = scripts.select(*cols, F.col(text).alias("_text"))
        ddl = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in picked.schema.fields if f.name != "_text")
        split = picked.mapInPandas(run, f"{ddl}, parts array<string>")
    else:
        split = scripts.select(*cols, F.split(text, STATEMENT_END).alias("parts"))
    clean = F.filter(F.transform("parts", normalize), lambda s: s != "")
    rows = split.select(*keep, clean.alias("_clean"))
    return rows.select(*keep, F.posexplode("_clean").alias("pos", "text"))


def recorded(replies: pd.DataFrame, script: str = "script", steps: str = "steps") -> Callable[[str], Iterable[str]]:
    """A provider that plays back recorded replies."""
    table = dict(zip(replies[script], replies[steps], strict=True))
    return lambda text: table.get(text, ())


def phrases(statements: DataFrame, text: str = "text") -> DataFrame:
    """Distinct statements with their multiplicity and a stable id."""
    return statements.groupBy(F.col(text).alias("text")).agg(F.count("*").alias("freq")).withColumn("phrase_id", F.xxhash64("text"))


def n_words(col: Column) -> Column:
    return F.size(F.split(col, " "))


def granularity(statements: DataFrame, script: str = "script_id") -> DataFrame:
    """Statements a script: shares with 1 to 5 and up to 10, quartiles and maximum."""
    per = statements.groupBy(script).agg(F.count("*").alias("n"))
    share = lambda most: F.avg((F.col("n") <= most).cast("double"))
    q = F.percentile("n", [0.25, 0.5, 0.75])
    out = per.agg(F.count("*").alias("n_scripts"), F.sum("n").alias("n_statements"), share(5).alias("share_1_5"), share(10).alias("share_1_10"), q.alias("q"), F.max("n").alias("max_n"))
    return out.select("n_scripts", "n_statements", "share_1_5", "share_1_10", *(F.col("q")[i].alias(f"q{i + 1}") for i in range(3)), "max_n")


def word_buckets(statements: DataFrame, text: str = "text") -> DataFrame:
    """Statements of 1-5, 6-9 and 10 or more words, their share and longest."""
    n = statements.select(n_words(F.col(text)).alias("n"))
    bucket = F.when(F.col("n") <= 5, "1-5").when(F.col("n") <= 9, "6-9").otherwise("10+")
    counts = n.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n_statements"), F.max("n").cast("long").alias("max_words"))
    total = counts.agg(F.sum("n_statements").alias("t")).withColumn("k", F.lit(1))  # three rows at most
    return counts.withColumn("k", F.lit(1)).join(total, "k").select("bucket", "n_statements", "max_words", (F.col("n_statements") / F.col("t")).alias("share"))


def term_freq(texts: DataFrame, text: str = "text", by: tuple[str, ...] = (), over: str = "occurrences", keywords: DataFrame | None = None, pattern: str = NOT_LETTER) -> DataFrame:
    """Frequency of words by the columns ``by``; ``over`` 'distinct' counts each text once a word.

    keywords (term, category) restricts to a dictionary and adds its categories.
    """
    found = F.filter(F.split(F.lower(text), pattern), lambda x: x != "")
    term = F.array_distinct(found) if over == "distinct" else found
    rows = texts.select(*by, F.explode(term).alias("term"))
    if keywords is not None:
        rows = rows.join(F.broadcast(keywords), "term")
        by = ("category", *by)
    return rows.groupBy(*by, "term").agg(F.count("*").alias("freq"))


def term_rollup(freq: DataFrame, *levels: str) -> DataFrame:
    """Totals of every level and above, with the share of all: word-cloud proportions."""
    rolled = freq.rollup(*levels).agg(F.sum("freq").alias("freq"), F.grouping_id().cast("long").alias("level"))
    total = freq.agg(F.sum("freq").alias("t")).withColumn("k", F.lit(1))
    return rolled.withColumn("k", F.lit(1)).join(total, "k").select(*levels, "level", "freq", (F.col("freq") / F.col("t")).alias("share"))
