"""The given tables as script corpora.

Each function gives rows in the form the methods take: operators in order (``rec_id``, order
columns, ``op``), records (``rec_id``, ``item``) or statements. ``*_SQL`` is the same in SQL.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.planning import spread
from .io import read

#: Order of an order's lines; the line number alone has ties.
LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's events of a day, in order."""
    e = read(spark, sf_dir, "events", ("event_id", "ts", "user_id", "event_type"))
    return e.select(F.concat_ws("_", "user_id", F.to_date("ts").cast("string")).alias("rec_id"), "ts", "event_id", F.col("event_type").alias("op"))


SESSIONS_SQL = "SELECT concat_ws('_', user_id::VARCHAR, ts::DATE::VARCHAR) AS rec_id, ts, event_id, event_type AS op FROM events"


def order_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of orders with their part's name and type, and the words of the name as enclosing and enclosed operator."""
    lines = read(spark, sf_dir, "lineitem", ("l_orderkey", *LINE_ORDER, "l_returnflag", "l_linestatus"))
    parts = read(spark, sf_dir, "part", ("p_partkey", "p_name", "p_type"))
    joined = lines.join(parts, lines["l_partkey"] == parts["p_partkey"])
    word = F.split("p_name", " ")
    return joined.select(F.col("l_orderkey").alias("rec_id"), *LINE_ORDER, "l_returnflag", "l_linestatus", "p_type", word[0].alias("outer_op"), word[1].alias("inner_op"))


ORDER_PARTS_SQL = (
    "SELECT l_orderkey AS rec_id, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_returnflag, l_linestatus, p_type, "
    "split_part(p_name, ' ', 1) AS outer_op, split_part(p_name, ' ', 2) AS inner_op FROM lineitem JOIN part ON l_partkey = p_partkey"
)


def type_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return order_parts(spark, sf_dir).select("rec_id", F.col("p_type").alias("item"))


TYPE_ITEMS_SQL = f"SELECT DISTINCT rec_id, p_type AS item FROM ({ORDER_PARTS_SQL})"


def word_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = order_parts(spark, sf_dir)
    return lines.select("rec_id", F.explode(F.array("outer_op", "inner_op")).alias("item"))


WORD_ITEMS_SQL = f"SELECT DISTINCT rec_id, unnest([outer_op, inner_op]) AS item FROM ({ORDER_PARTS_SQL})"


def event_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sessions(spark, sf_dir).select("rec_id", F.col("op").alias("item"))


EVENT_ITEMS_SQL = f"SELECT DISTINCT rec_id, op AS item FROM ({SESSIONS_SQL})"


def mixed_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Types, flags and states of an order's lines and its priority: sixteen items of uneven frequency."""
    lines = order_parts(spark, sf_dir)
    orders = read(spark, sf_dir, "orders", ("o_orderkey", "o_orderpriority"))
    joined = lines.join(orders, lines["rec_id"] == orders["o_orderkey"])
    items = F.array(*(F.concat(F.lit(f"{c}:"), F.col(c)) for c in ("p_type", "l_returnflag", "l_linestatus", "o_orderpriority")))
    return joined.select("rec_id", F.explode(items).alias("item"))


MIXED_ITEMS_SQL = (
    "SELECT DISTINCT rec_id, unnest(['p_type:' || p_type, 'l_returnflag:' || l_returnflag, 'l_linestatus:' || l_linestatus, "
    f"'o_orderpriority:' || o_orderpriority]) AS item FROM ({ORDER_PARTS_SQL}) JOIN orders ON rec_id = o_orderkey"
)

#: Where statements end and what parts tokens, in classes that both engines read alike.
STATEMENT_END = r"[.!?\n]+"
NOT_LETTER = r"[^\p{L}]+"
NOT_TOKEN = r"[^\p{L}\p{N}]+"


def statements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sentences of documents as functional statements: script_id, lang, source, pos, text (normalised)."""
    from ..operators.statements import extract

    docs = spread(read(spark, sf_dir, "documents", ("doc_id", "lang", "source", "text")))
    return extract(docs.withColumnRenamed("doc_id", "script_id"), keep=("script_id", "lang", "source"))


STATEMENTS_SQL = r"""
SELECT script_id, lang, source, (row_number() OVER (PARTITION BY script_id ORDER BY i) - 1)::BIGINT AS pos, text FROM (
  SELECT doc_id AS script_id, lang, source, i, trim(regexp_replace(lower(parts[i]), '[^\p{L}\p{N}]+', ' ', 'g')) AS text
  FROM (SELECT doc_id, lang, source, regexp_split_to_array(text, '[.!?\n]+') AS parts FROM documents), unnest(range(1, len(parts) + 1)) AS u(i)
) WHERE text <> ''
"""


def sentence_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of English sentences."""
    docs = spread(read(spark, sf_dir, "documents", ("doc_id", "lang", "text"))).where("lang = 'en'")
    sentence = docs.select("doc_id", F.posexplode(F.split("text", STATEMENT_END)).alias("i", "s"))
    token = F.explode(F.split(F.lower("s"), NOT_LETTER))
    return sentence.select(F.concat_ws("_", "doc_id", "i").alias("rec_id"), token.alias("item")).where("item <> ''")


SENTENCE_ITEMS_SQL = r"""
SELECT DISTINCT rec_id, item FROM (
  SELECT concat_ws('_', doc_id::VARCHAR, (i - 1)::VARCHAR) AS rec_id, unnest(regexp_split_to_array(lower(parts[i]), '[^\p{L}]+')) AS item
  FROM (SELECT doc_id, regexp_split_to_array(text, '[.!?\n]+') AS parts FROM documents WHERE lang = 'en'), unnest(range(1, len(parts) + 1)) AS u(i)
) WHERE item <> ''
"""


def rendered_orders(spark: SparkSession, sf_dir: str, lang: str = "js") -> DataFrame:
    """Orders as source text: each line a call of its first word around one of the second, comments here and there."""
    lines = order_parts(spark, sf_dir)
    mark = "//" if lang == "js" else "#"
    end = ";" if lang == "js" else ""
    call = F.concat(F.lit("op."), "outer_op", F.lit("(op."), "inner_op", F.lit(f"(x, 'a {mark} b')){end}"))
    noisy = F.when(F.col("l_partkey") % 3 == 0, F.concat(call, F.lit(f" {mark} not(called(here))"))).otherwise(call)
    keyed = F.struct(*LINE_ORDER, noisy.alias("code"))
    return lines.groupBy("rec_id").agg(F.array_sort(F.collect_list(keyed)).alias("l")).select(
        F.col("rec_id").cast("string").alias("script_id"), F.lit(lang).alias("lang"), F.concat_ws("\n", "l.code").alias("source")
    )


def rendered_sessions(spark: SparkSession, sf_dir: str, lang: str = "js") -> DataFrame:
    """Sessions as source text: one call a line."""
    end = ";" if lang == "js" else ""
    keyed = F.struct("ts", "event_id", F.concat("op", F.lit(f"(1){end}")).alias("code"))
    return sessions(spark, sf_dir).groupBy("rec_id").agg(F.array_sort(F.collect_list(keyed)).alias("l")).select(
        F.col("rec_id").alias("script_id"), F.lit(lang).alias("lang"), F.concat_ws("\n", "l.code").alias("source")
    )
