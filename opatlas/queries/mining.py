"""Stage B: pair statistics and frequent operator sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import graph, itemsets, pairs, records
from ..sources import corpus, io, parse
from . import Catalog

CATALOG = Catalog()
query = CATALOG.query
SUPPORT = "0.05"

_NEXT_SQL = f"SELECT rec_id, 'next' AS relation, op AS caller, lead(op) OVER (PARTITION BY rec_id ORDER BY ts, event_id) AS callee FROM ({corpus.SESSIONS_SQL})"
_NEST_SQL = f"SELECT rec_id, 'nest' AS relation, outer_op AS caller, inner_op AS callee FROM ({corpus.ORDER_PARTS_SQL})"
_TABLE_SQL = (
    "SELECT relation, caller, callee, count(*)::BIGINT AS n_occ, count(DISTINCT rec_id)::BIGINT AS n_scripts "
    f"FROM (SELECT * FROM ({_NEXT_SQL}) WHERE callee IS NOT NULL UNION ALL {_NEST_SQL}) GROUP BY ALL"
)
_EVENT_TABLE_SQL = f"SELECT caller, callee, count(*)::BIGINT AS n_occ, count(DISTINCT rec_id)::BIGINT AS n_scripts FROM ({_NEXT_SQL}) WHERE callee IS NOT NULL GROUP BY ALL"


def session_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.neighbour(corpus.sessions(spark, sf_dir), ("ts", "event_id"))


def order_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = corpus.order_parts(spark, sf_dir)
    return lines.select(F.col("rec_id").cast("string").alias("rec_id"), F.col("outer_op").alias("caller"), F.col("inner_op").alias("callee"), F.lit("nest").alias("relation"))


@query(
    "SELECT 'documents' AS corpus, count(*)::BIGINT AS n_scripts, min(length(text))::BIGINT AS min_chars, max(length(text))::BIGINT AS max_chars, "
    "sum(length(text))::BIGINT AS total_chars, count(DISTINCT lang)::BIGINT AS n_langs FROM documents UNION ALL "
    "SELECT 'pages', count(*), min(length(html)), max(length(html)), sum(length(html))::BIGINT, NULL FROM pages"
)
def b_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Count and sizes of scripts."""

    def profile(df: DataFrame, name: str, text: str, langs) -> DataFrame:
        n = F.length(text)
        return df.agg(
            F.lit(name).alias("corpus"), F.count("*").alias("n_scripts"), F.min(n).cast("long").alias("min_chars"), F.max(n).cast("long").alias("max_chars"),
            F.sum(n).alias("total_chars"), langs.alias("n_langs"),
        )

    docs = profile(io.read(spark, sf_dir, "documents", ("lang", "text")), "documents", "text", F.count_distinct("lang"))
    return docs.unionByName(profile(io.read(spark, sf_dir, "pages", ("html",)), "pages", "html", F.lit(None).cast("long")))


@query()
def b_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scripts that parse, and why others do not."""
    good = corpus.rendered_orders(spark, sf_dir)
    bad = good.where("crc32(script_id) % 50 = 0").withColumn("source", F.concat("source", F.lit("\nf((")))
    return parse.check(good.unionByName(bad), "js").groupBy("parses", "parse_error").agg(F.count("*").alias("n"))


@query(
    r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', '', 'g'), "
    r"'(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g'))) AS text_md5 FROM pages"
)
def b_clean_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return io.read(spark, sf_dir, "pages", ("page_id", "html")).select("page_id", F.md5(parse.clean_html(F.col("html"))).alias("text_md5"))


def _rendered(spark: SparkSession, sf_dir: str, lang: str) -> DataFrame:
    nodes = parse.to_nodes(corpus.rendered_orders(spark, sf_dir, lang), lang)
    events = parse.to_nodes(corpus.rendered_sessions(spark, sf_dir, lang), lang)
    return pairs.merge(pairs.nest(nodes).unionByName(pairs.next_call(events))).select("relation", "caller", "callee", "n_occ", "n_scripts")


@query(_TABLE_SQL)
def b_pair_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The merged pair table of sessions (neighbours) and orders (nesting)."""
    both = session_pairs(spark, sf_dir).unionByName(order_pairs(spark, sf_dir))
    return pairs.merge(both).select("relation", "caller", "callee", "n_occ", "n_scripts")


@query(_TABLE_SQL)
def b_parsed_js(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same from JavaScript source with comments: rendered, parsed, walked and counted."""
    return _rendered(spark, sf_dir, "js")


@query(_TABLE_SQL)
def b_parsed_py(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same from Python source."""
    return _rendered(spark, sf_dir, "py")


@query()
def b_pairs_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nesting and neighbourhood of tags."""
    nodes = parse.to_nodes(io.read(spark, sf_dir, "pages", ("page_id", "html")), "html", key="page_id", source="html")
    return pairs.merge(pairs.nest(nodes).unionByName(pairs.next_call(nodes)))


@query(f"SELECT caller, callee, count(*)::BIGINT AS n_occ FROM ({_NEST_SQL}) GROUP BY ALL")
def b_pairs_nest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.merge(order_pairs(spark, sf_dir)).select("caller", "callee", "n_occ")


@query(_EVENT_TABLE_SQL)
def b_pairs_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.merge(session_pairs(spark, sf_dir)).select("caller", "callee", "n_occ", "n_scripts")


@query(f"SELECT caller, callee, count(*)::BIGINT AS n_occ FROM ({_NEXT_SQL}) WHERE caller IN ('click', 'view', 'purchase') AND callee IN ('click', 'view', 'purchase') GROUP BY ALL")
def b_catalogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = spark.createDataFrame([("click",), ("view",), ("purchase",)], "op string")
    return pairs.merge(pairs.in_catalogue(session_pairs(spark, sf_dir), known)).select("caller", "callee", "n_occ")


@query(
    f"WITH t AS ({_EVENT_TABLE_SQL}) SELECT count(*)::BIGINT AS n_pairs, count(DISTINCT caller)::BIGINT AS n_callers, count(DISTINCT callee)::BIGINT AS n_callees, "
    "(SELECT count(DISTINCT o) FROM (SELECT caller AS o FROM t UNION ALL SELECT callee FROM t))::BIGINT AS n_operators, "
    "(SELECT count(DISTINCT event_type) FROM events)::BIGINT AS n_catalogue FROM t"
)
def b_pair_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = pairs.merge(session_pairs(spark, sf_dir))
    return pairs.summary(table, io.read(spark, sf_dir, "events", ("event_type",)), "event_type")


@query(f"SELECT caller, callee, n_occ FROM ({_EVENT_TABLE_SQL}) ORDER BY n_occ DESC, caller, callee LIMIT 20")
def b_top_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pairs.top(pairs.merge(session_pairs(spark, sf_dir)), 20).select("caller", "callee", "n_occ")


@query(
    f"WITH t AS (SELECT caller, callee, count(*) AS n FROM ({_NEST_SQL}) GROUP BY ALL), "
    "o AS (SELECT caller AS op, count(*) AS od, sum(n) AS wo FROM t GROUP BY 1), i AS (SELECT callee AS op, count(*) AS id, sum(n) AS wi FROM t GROUP BY 1) "
    "SELECT op, coalesce(od, 0)::BIGINT AS out_degree, coalesce(id, 0)::BIGINT AS in_degree, coalesce(wo, 0)::BIGINT AS weight_out, coalesce(wi, 0)::BIGINT AS weight_in, "
    "(coalesce(od, 0) + coalesce(id, 0))::BIGINT AS degree FROM o FULL JOIN i USING (op)"
)
def b_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.degrees(pairs.merge(order_pairs(spark, sf_dir)))


@query(f"SELECT caller, callee, ntile(4) OVER (ORDER BY n_occ DESC, caller, callee)::BIGINT AS slice FROM ({_EVENT_TABLE_SQL})")
def b_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.slices(pairs.merge(session_pairs(spark, sf_dir))).select("caller", "callee", "slice")


@query(
    f"WITH c AS (SELECT rec_id, op, count(*)::DOUBLE AS x FROM ({corpus.SESSIONS_SQL}) GROUP BY ALL), r AS (SELECT DISTINCT rec_id FROM c), o AS (SELECT DISTINCT op FROM c), "
    "g AS (SELECT r.rec_id, o.op, coalesce(x, 0) AS x FROM r CROSS JOIN o LEFT JOIN c ON c.rec_id = r.rec_id AND c.op = o.op) "
    "SELECT p.op AS a, q.op AS b, round(corr(p.x, q.x), 6) AS pearson, round(corr((p.x > 0)::INT, (q.x > 0)::INT), 6) AS phi, "
    "round(sum((p.x > 0 AND q.x > 0)::INT)::DOUBLE / sum((p.x > 0 OR q.x > 0)::INT), 6) AS jaccard, "
    "round(count(*)::DOUBLE * sum((p.x > 0 AND q.x > 0)::INT) / (sum((p.x > 0)::INT)::DOUBLE * sum((q.x > 0)::INT)), 6) AS lift "
    "FROM g p JOIN g q ON p.rec_id = q.rec_id AND p.op < q.op GROUP BY 1, 2"
)
def b_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = graph.correlation(corpus.sessions(spark, sf_dir))
    return got.select("a", "b", *(F.round(c, 6).alias(c) for c in ("pearson", "phi", "jaccard", "lift")))


def joined(df: DataFrame) -> DataFrame:
    """Item arrays as text, as both engines compare it."""
    return df.withColumn("items", F.array_join("items", "|"))


@query(f"SELECT rec_id, string_agg(item, '|' ORDER BY item) AS items FROM ({corpus.EVENT_ITEMS_SQL}) GROUP BY 1")
def b_records_script(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(records.make(corpus.event_items(spark, sf_dir)))


@query(f"SELECT caller AS rec_id, string_agg(callee, '|' ORDER BY callee) AS items FROM (SELECT DISTINCT caller, callee FROM ({_NEST_SQL})) GROUP BY 1")
def b_records_caller(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(records.make(order_pairs(spark, sf_dir), "caller"))


@query(f"SELECT CASE WHEN caller = callee THEN caller ELSE least(caller, callee) || '|' || greatest(caller, callee) END AS items, count(*)::BIGINT AS w FROM ({_NEXT_SQL}) WHERE callee IS NOT NULL GROUP BY 1")
def b_records_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(records.compress(records.make(session_pairs(spark, sf_dir), "pair")))


@query(f"SELECT items, count(*)::BIGINT AS w FROM (SELECT rec_id, string_agg(item, '|' ORDER BY item) AS items FROM ({corpus.EVENT_ITEMS_SQL}) GROUP BY 1) GROUP BY 1")
def b_records_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joined(records.compress(records.make(corpus.event_items(spark, sf_dir))))


#: Levels that the SQL of mixed sets unrolls: one more than any set has, which a test checks.
DEEPEST = 11


def apriori_sql(items: str, max_k: int, support: str = SUPPORT, every: bool = False) -> str:
    """Frequent sets, level by level: records holding a frequent set meet their later frequent items. items, k, freq."""
    cents = int(round(float(support) * 1000))
    bar = "1" if every else "(SELECT b FROM bar)"
    steps = [
        f"r AS MATERIALIZED ({items})", f"bar AS (SELECT (count(DISTINCT rec_id) * {cents} + 999) // 1000 AS b FROM r)",
        f"f1 AS MATERIALIZED (SELECT item AS items, count(*) AS freq FROM r GROUP BY 1 HAVING count(*) >= {bar})",
        "t AS MATERIALIZED (SELECT r.* FROM r SEMI JOIN f1 ON r.item = f1.items)", "l1 AS (SELECT rec_id, item AS items, item AS last FROM t)",
    ]
    for k in range(2, max_k + 1):
        steps += [
            f"g{k} AS MATERIALIZED (SELECT l{k - 1}.rec_id, l{k - 1}.items || '|' || t.item AS items, t.item AS last FROM l{k - 1} JOIN t ON l{k - 1}.rec_id = t.rec_id AND t.item > l{k - 1}.last)",
            f"f{k} AS MATERIALIZED (SELECT items, count(*) AS freq FROM g{k} GROUP BY 1 HAVING count(*) >= {bar})", f"l{k} AS (SELECT g{k}.* FROM g{k} SEMI JOIN f{k} USING (items))",
        ]
    return "WITH " + ", ".join(steps) + " " + " UNION ALL ".join(f"SELECT items, {k}::BIGINT AS k, freq FROM f{k}" for k in range(1, max_k + 1))


MIXED_SQL = apriori_sql(corpus.MIXED_ITEMS_SQL, DEEPEST)


def found(mined: itemsets.Mined) -> DataFrame:
    return joined(mined.combos).select("items", F.col("k").cast("long").alias("k"), "freq")


@query(apriori_sql(corpus.TYPE_ITEMS_SQL, 6))
def b_apriori_ptype(spark: SparkSession, sf_dir: str) -> DataFrame:
    return found(itemsets.apriori(records.make(corpus.type_items(spark, sf_dir)), SUPPORT))


@query(apriori_sql(corpus.WORD_ITEMS_SQL, 7))
def b_apriori_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return found(itemsets.apriori(records.make(corpus.word_items(spark, sf_dir)), SUPPORT))


@query(apriori_sql(corpus.EVENT_ITEMS_SQL, 5))
def b_apriori_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return found(itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT))


def mined(spark: SparkSession, sf_dir: str) -> itemsets.Mined:
    """All frequent mixed sets: the combinations that stages C to E label and serve."""
    return itemsets.apriori(records.make(corpus.mixed_items(spark, sf_dir)), SUPPORT)


@query(MIXED_SQL)
def b_apriori_mixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of every size."""
    return found(mined(spark, sf_dir))


@query(apriori_sql(corpus.SENTENCE_ITEMS_SQL, 6))
def b_apriori_sent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return found(itemsets.apriori(records.make(corpus.sentence_items(spark, sf_dir)), SUPPORT))


@query(apriori_sql(corpus.TYPE_ITEMS_SQL, 6))
def b_apriori_expand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates by expansion: the same sets, many more candidates."""
    return found(itemsets.apriori(records.make(corpus.type_items(spark, sf_dir)), SUPPORT, candidates="expand"))


@query(apriori_sql(corpus.TYPE_ITEMS_SQL, 6))
def b_apriori_join_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counting by a join instead of in tasks' memory: the same sets."""
    return found(itemsets.apriori(records.make(corpus.type_items(spark, sf_dir)), SUPPORT, strategy="join"))


@query(apriori_sql(corpus.EVENT_ITEMS_SQL, 5))
def b_apriori_seeded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only sets whose pairs all occur as calls are grown; every pair of event types does."""
    table = pairs.merge(session_pairs(spark, sf_dir))
    both = table.unionByName(table.select("relation", F.col("callee").alias("caller"), F.col("caller").alias("callee"), "n_occ", "n_scripts"))
    return found(itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT, candidates="pair_seeded", pairs=both))


_SUBSETS = (
    f"WITH RECURSIVE r AS MATERIALIZED ({corpus.EVENT_ITEMS_SQL}), bar AS (SELECT (count(DISTINCT rec_id) * 50 + 999) // 1000 AS b FROM r), "
    "f1 AS (SELECT item, count(*) AS n FROM r GROUP BY 1 HAVING count(*) >= (SELECT b FROM bar)), "
    "p AS (SELECT x.item AS a, y.item AS b, count(*) AS n FROM r x JOIN r y ON x.rec_id = y.rec_id AND x.item < y.item WHERE x.item IN (SELECT item FROM f1) AND y.item IN (SELECT item FROM f1) GROUP BY ALL), "
    "sub AS (SELECT [item] AS s FROM f1 UNION ALL SELECT list_append(s, item) FROM sub JOIN f1 ON item > s[len(s)]), "
    "held AS (SELECT s, a, b, n FROM sub JOIN p ON list_contains(s, a) AND list_contains(s, b)), "
    "m AS (SELECT s, CASE WHEN count(*) = len(s) * (len(s) - 1) // 2 THEN min(n) ELSE 0 END AS least, sum(n) AS total, max(n) AS most FROM held GROUP BY s), "
    "bar2 AS (SELECT (sum(n)::BIGINT * 50 + 999) // 1000 AS b FROM p) SELECT item AS items, 1::BIGINT AS k, n::BIGINT AS freq FROM f1 UNION ALL "
)


@query(_SUBSETS + "SELECT array_to_string(s, '|'), len(s)::BIGINT, least::BIGINT FROM m WHERE least >= (SELECT b FROM bar)")
def b_apriori_pair_min(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Support bounded by the rarest contained pair."""
    return found(itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT, support="pair_min"))


@query(_SUBSETS + "SELECT array_to_string(s, '|'), len(s)::BIGINT, total::BIGINT FROM m WHERE most >= (SELECT b FROM bar2)")
def b_apriori_pair_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Support as the share of contained pairs' occurrences, which does not prune."""
    return found(itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT, support="pair_sum"))


@query()
def b_level_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates generated, pruned, counted and frequent at each level."""
    return itemsets.level_stats(mined(spark, sf_dir))


@query(
    "WITH w(set_id, a, b) AS (VALUES (1, 'click', 'view'), (2, 'error', 'purchase'), (3, 'signup', 'signup')) "
    f"SELECT set_id::BIGINT AS set_id, count(*)::BIGINT AS freq FROM w JOIN ({corpus.EVENT_ITEMS_SQL}) x ON x.item = a JOIN ({corpus.EVENT_ITEMS_SQL}) y ON y.item = b AND x.rec_id = y.rec_id GROUP BY 1"
)
def b_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    sets = spark.createDataFrame([(1, ["click", "view"]), (2, ["error", "purchase"]), (3, ["signup"])], "set_id long, items array<string>")
    return itemsets.support_of(records.make(corpus.event_items(spark, sf_dir)), sets)


@query(apriori_sql(corpus.TYPE_ITEMS_SQL, 3, every=True))
def b_enumerate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: all combinations of up to three, unpruned."""
    got = itemsets.enumerate_all(records.make(corpus.type_items(spark, sf_dir)), 3)
    return joined(got).select("items", F.col("k").cast("long").alias("k"), "freq")


@query(
    f"SELECT caller, callee, n_occ FROM ({_EVENT_TABLE_SQL}) WHERE n_occ * 20 >= (SELECT sum(n_occ) FROM ({_EVENT_TABLE_SQL}))"
)
def b_pairs_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: pairs over the threshold by occurrences, without growth."""
    table = pairs.merge(session_pairs(spark, sf_dir))
    total = int(table.agg(F.sum("n_occ")).first()[0] or 0)
    return table.where(F.col("n_occ") >= itemsets.least_count(SUPPORT, total)).select("caller", "callee", "n_occ")


@query(apriori_sql(corpus.TYPE_ITEMS_SQL, 6))
def b_fpgrowth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cross-check by FP-growth."""
    got = itemsets.fpgrowth(records.make(corpus.type_items(spark, sf_dir)), float(SUPPORT))
    return joined(got).select("items", F.col("k").cast("long").alias("k"), "freq")


@query(
    f"WITH s AS MATERIALIZED ({apriori_sql(corpus.EVENT_ITEMS_SQL, 5)}), n AS (SELECT count(DISTINCT rec_id)::DOUBLE AS n FROM ({corpus.EVENT_ITEMS_SQL})), "
    "w AS (SELECT string_split(items, '|') AS x, freq, unnest(string_split(items, '|')) AS rhs FROM s WHERE k > 1), "
    "d AS (SELECT array_to_string(list_filter(x, lambda i: i <> rhs), '|') AS lhs, rhs, freq FROM w) "
    "SELECT lhs, rhs, d.freq, round(d.freq / l.freq::DOUBLE, 6) AS confidence, round(d.freq / l.freq::DOUBLE * n / r.freq, 6) AS lift, "
    "round(d.freq / n - l.freq / n * r.freq / n, 6) AS leverage FROM d JOIN s l ON l.items = lhs JOIN s r ON r.items = rhs, n"
)
def b_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules from all frequent sets."""
    m = itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT)
    got = itemsets.rules(m.combos, m.n_records, max_k=len(m.levels))
    return got.select(F.array_join("lhs", "|").alias("lhs"), "rhs", "freq", *(F.round(c, 6).alias(c) for c in ("confidence", "lift", "leverage")))


@query(f"SELECT k, count(*)::BIGINT AS n_sets, max(freq)::BIGINT AS max_freq FROM ({apriori_sql(corpus.EVENT_ITEMS_SQL, 5)}) GROUP BY 1")
def b_size_hist(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Flagship: neighbour records to frequent sets to their sizes."""
    m = itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT)
    return itemsets.size_hist(m.combos).select(F.col("k").cast("long").alias("k"), "n_sets", "max_freq")


_MAXIMAL = "list_has_all(string_split(b.items, '|'), string_split(a.items, '|'))"


@query(f"WITH s AS ({apriori_sql(corpus.EVENT_ITEMS_SQL, 5)}) SELECT items, k, freq FROM s a WHERE NOT EXISTS (SELECT 1 FROM s b WHERE b.k = a.k + 1 AND {_MAXIMAL})")
def b_maximal(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), SUPPORT)
    return joined(itemsets.maximal(m.combos)).select("items", F.col("k").cast("long").alias("k"), "freq")


@query(
    f"WITH s AS MATERIALIZED ({MIXED_SQL}), w AS (SELECT string_split(items, '|') AS x, freq, unnest(string_split(items, '|')) AS o FROM s WHERE k > 1), "
    "u AS (SELECT DISTINCT array_to_string(list_filter(x, lambda i: i <> o), '|') AS items, freq FROM w) SELECT items, k, freq FROM s ANTI JOIN u USING (items, freq)"
)
def b_closed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of every size without a superset of equal frequency."""
    return joined(itemsets.maximal(mined(spark, sf_dir).combos, closed=True)).select("items", F.col("k").cast("long").alias("k"), "freq")


_SWEEP = ("0.05", "0.1", "0.2", "0.4")


@query(" UNION ALL ".join(f"SELECT '{s}' AS min_support, count(*)::BIGINT AS n_sets, max(k)::BIGINT AS max_k FROM ({apriori_sql(corpus.EVENT_ITEMS_SQL, 5, s)}) HAVING count(*) > 0" for s in _SWEEP))
def b_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = itemsets.apriori(records.make(corpus.event_items(spark, sf_dir)), min(_SWEEP))
    return itemsets.sweep(m, list(_SWEEP))


@query()
def b_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ordered combinations of events."""
    keyed = F.array_sort(F.collect_list(F.struct("ts", "event_id", "op")))
    ordered = corpus.sessions(spark, sf_dir).groupBy("rec_id").agg(keyed.alias("s")).select(F.col("s.op").alias("seq"))
    return joined(itemsets.sequences(ordered).withColumnRenamed("seq", "items")).withColumnRenamed("items", "seq")
