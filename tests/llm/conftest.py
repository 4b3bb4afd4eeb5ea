import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, extra string"


@pytest.fixture()
def odd(spark):
    """Nulls in every column, empty and blank texts, ties, repeated rows, a very long text, and an extra column."""
    words = " ".join(f"w{i % 997}x{i % 13}" for i in range(30_000))
    rows = [
        (1, "one two three four five six seven eight nine ten eleven", "en", "a", 10, "x"),
        (1, "one two three four five six seven eight nine ten eleven", "en", "a", 10, "x"),
        (2, None, None, None, None, None), (3, "", "en", "b", 0, "y"), (4, " \t\n\x0b\f\r ", "en", "b", 7, "y"),
        (5, "中文 ▁ é\U0001f600 <|endoftext|> ## $$ || ☃ end", "zh", "ä", 3, "z"), (6, words, "en", "a", len(words), None),
        (None, "a row without an id but with some words in it, a dozen or so of them", "en", None, 1, None), (7, "x" * 50_000, "en", "b", 50_000, ""),
        (8, "same line\nsame line\nsame line\n\n", "en", "c", 1, ""),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture()
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture()
def clashing(odd):
    """The same rows with columns called like those that operators make, in other cases, or with dots and blanks."""
    from pyspark.sql import functions as F

    names = ("ids", "N_Pieces", "lossless", "_text", "_key", "n_words", "rule_bits", "_qr_t", "_shard", "shard", "doc", "place", "node", "fp", "keys", "root", "score", "label", "x", "image", "argb", "a.b", "two words", "struct<z>", "_doc", "_n")
    return odd.select("*", *(F.lit(n).alias(n) for n in names), F.struct(F.lit(1).alias("c.d"), F.array(F.lit(2)).alias("e f")).alias("nested.one"))
