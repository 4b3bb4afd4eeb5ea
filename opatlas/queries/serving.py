"""Stage E: the knowledge base and its uses."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import graph, pairs, score, serve
from ..plans.planning import with_each
from ..session import cut
from ..sources import corpus, io
from . import Catalog
from .labels import _ITEMS, _POOLED, combos, items, joined, labelling, tally
from .mining import _EVENT_TABLE_SQL, MIXED_SQL, session_pairs
from .taxonomy import r6, tax

CATALOG = Catalog()
query = CATALOG.query

_ALL = "'M1+M2+M3+M4'"
_KB = (
    f"{_POOLED}, tot AS (SELECT item_id, sum(n) AS total FROM tally GROUP BY 1), mn AS MATERIALIZED (SELECT items, freq, freq / (SELECT count(DISTINCT rec_id) FROM ({corpus.MIXED_ITEMS_SQL}))::DOUBLE AS support FROM ({MIXED_SQL})), "
    "kb AS MATERIALIZED (SELECT substr(sha256(items), 1, 16) AS kb_id, substr(md5(l1), 1, 8) AS l1_id, substr(md5(l1 || '/' || l2), 1, 8) AS l2_id, v.l3_id::VARCHAR AS l3_id, l1, l2, l3, "
    f"items, support, freq::BIGINT AS freq, v.votes::BIGINT AS n_votes, round(v.votes::DOUBLE / total, 6) AS confidence FROM votes v JOIN mn ON mn.items = v.item_id JOIN tot USING (item_id) JOIN tax ON tax.l3_id = v.l3_id WHERE subset = {_ALL})"
)


def kb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The mined combinations, with their support and the function that all models together voted for."""
    t = tally(spark, sf_dir)
    votes = labelling.pooled(t).where("subset = 'M1+M2+M3+M4'").join(t.groupBy("item_id").agg(F.sum("n").alias("total")), "item_id")
    c = combos(spark, sf_dir).select(F.array_join("items", "|").alias("combo_id"), "items", "support", "freq")
    return serve.build(c, votes.select("item_id", "l3_id", "votes", "total"), tax(spark, sf_dir))


@query(f"{_KB} SELECT kb_id, l1_id, l2_id, l3_id, l1, l2, l3, items, freq, round(support, 6) AS support, n_votes, confidence FROM kb")
def c_kb(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = kb(spark, sf_dir)
    return k.select("kb_id", "l1_id", "l2_id", "l3_id", "l1", "l2", "l3", F.array_join("combo.items", "|").alias("items"), "combo.freq", F.round("combo.support", 6).alias("support"), F.element_at("votes", F.col("l3")).alias("n_votes"), *r6("confidence"))


_TOK = r"list_distinct(list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> ''))"
_FUNCS = (
    f"WITH f AS (SELECT doc_id AS l3_id, unnest({_TOK}) AS t FROM documents), i AS (SELECT t, ln(((SELECT count(*) FROM documents) + 1.0)::DOUBLE / count(*)) AS w FROM f GROUP BY 1), "
    f"nf AS (SELECT l3_id, sqrt(sum(w * w)) AS nf FROM f JOIN i USING (t) GROUP BY 1), d AS (SELECT item_id, t, w FROM (SELECT item_id, unnest({_TOK}) AS t FROM benchmark) JOIN i USING (t)), nd AS (SELECT item_id, sqrt(sum(w * w)) AS nd FROM d GROUP BY 1), "
    "s AS (SELECT item_id, l3_id, round(sum(w * w) / any_value(nf) / any_value(nd), 9) AS sim FROM d JOIN f USING (t) JOIN nf USING (l3_id) JOIN nd USING (item_id) GROUP BY 1, 2), "
    "r AS (SELECT item_id, l3_id, sim, row_number() OVER (PARTITION BY item_id ORDER BY sim DESC, l3_id)::BIGINT AS rank FROM s)"
)


def answers(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """Documents as functions, benchmark texts as demands."""
    docs = io.read(spark, sf_dir, "documents", ("doc_id", "text")).withColumnRenamed("doc_id", "l3_id")
    return serve.functions_for(io.read(spark, sf_dir, "benchmark"), docs, k)


@query(f"{_FUNCS} SELECT item_id, rank, round(sim, 6) AS sim FROM r WHERE rank <= 3")
def e_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Question 1; ids are left out of the comparison, as copies of a document tie."""
    return answers(spark, sf_dir).select("item_id", F.col("rank").cast("long").alias("rank"), *r6("sim"))


@query(f"WITH t AS ({_EVENT_TABLE_SQL}) SELECT a.caller AS a, a.callee AS b, (a.n_occ - coalesce(b.n_occ, 0))::BIGINT AS net FROM t a LEFT JOIN t b ON a.caller = b.callee AND a.callee = b.caller WHERE a.caller <> a.callee AND a.n_occ > coalesce(b.n_occ, 0)")
def e_precedence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Question 2: learnt order."""
    return serve.precedence(pairs.merge(session_pairs(spark, sf_dir)).select("caller", "callee", "n_occ"))


@query(f"{_KB} SELECT item_id, l1, l3, row_number() OVER (PARTITION BY item_id ORDER BY l1, l3)::BIGINT AS step FROM (SELECT DISTINCT split_part(items, '|', 1) AS item_id, l1, l3 FROM kb)")
def e_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Question 2: order of stages."""
    f = kb(spark, sf_dir).select(F.col("combo.items")[0].alias("item_id"), "l1", "l3").distinct()
    return serve.order_functions(f, ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]).withColumn("step", F.col("step").cast("long"))


@query(f"{_KB} SELECT l1, l2, l3, rank, items, freq FROM (SELECT *, row_number() OVER (PARTITION BY l1, l2, l3 ORDER BY freq DESC, kb_id)::BIGINT AS rank FROM kb WHERE l1 = 'ASIA') WHERE rank <= 2")
def e_combos(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Question 3."""
    got = serve.combos_for(kb(spark, sf_dir), l1="ASIA", top=2)
    return joined(got).withColumn("rank", F.col("rank").cast("long"))


@query(f"{_KB} SELECT kb_id, l3, items FROM kb WHERE kb_id = (SELECT min(kb_id) FROM kb)")
def e_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = kb(spark, sf_dir)
    return serve.by_id(k, k.agg(F.min("kb_id")).first()[0]).select("kb_id", "l3", F.array_join("combo.items", "|").alias("items"))


@query()
def e_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return serve.to_json(kb(spark, sf_dir))


@query()
def e_rag_prompt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as demands, with the functions whose combinations share words with them."""
    k = kb(spark, sf_dir)
    funcs = k.groupBy("l3_id", "l3").agg(F.array_join(F.array_sort(F.array_distinct(F.flatten(F.collect_list("combo.items")))), " ").alias("text"))
    demands = io.read(spark, sf_dir, "part", ("p_partkey", "p_type", "p_name")).select(F.col("p_partkey").alias("item_id"), F.concat_ws(" ", "p_type", "p_name").alias("text"))
    found = serve.functions_for(demands, funcs.select("l3_id", "text"), 3).join(funcs.select("l3_id", "l3"), "l3_id")
    best = serve.combos_for(k, top=2).join(k.select("l3_id", "l3").distinct(), "l3")
    return serve.rag_prompt(demands, found, best)


@query("SELECT item_id, md5('Demand: ' || text || chr(10) || 'Write the script.') AS prompt_md5 FROM benchmark")
def e_bare_prompt(spark: SparkSession, sf_dir: str) -> DataFrame:
    return serve.bare_prompt(io.read(spark, sf_dir, "benchmark")).select("item_id", F.md5("prompt").alias("prompt_md5"))


_WORDS = r"list_distinct(list_filter(regexp_split_to_array(lower({}), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> ''))"
_HITS = (
    f"{_KB}, fn AS (SELECT l3_id, unnest({_WORDS.format("string_agg(items, ' ')")}) AS t FROM kb GROUP BY 1), fi AS (SELECT t, ln(((SELECT count(DISTINCT l3_id) FROM kb) + 1.0)::DOUBLE / count(*)) AS w FROM fn GROUP BY 1), "
    "nf AS (SELECT l3_id, sqrt(sum(w * w)) AS nf FROM fn JOIN fi USING (t) GROUP BY 1), "
    f"ask AS (SELECT item_id, t, w FROM (SELECT item_id, unnest({_WORDS.format('item_id')}) AS t FROM {_ITEMS}) JOIN fi USING (t)), nd AS (SELECT item_id, sqrt(sum(w * w)) AS nd FROM ask GROUP BY 1), "
    "sims AS (SELECT item_id, l3_id, round(sum(w * w) / any_value(nf) / any_value(nd), 9) AS sim FROM ask JOIN fn USING (t) JOIN nf USING (l3_id) JOIN nd USING (item_id) WHERE nf > 0 AND nd > 0 GROUP BY 1, 2), "
    "found AS MATERIALIZED (SELECT item_id, l3_id, row_number() OVER (PARTITION BY item_id ORDER BY sim DESC, l3_id) AS rank FROM sims), "
    f"bare AS MATERIALIZED (SELECT l3_id, row_number() OVER (ORDER BY n DESC, l3_id) AS rank FROM (SELECT l3_id, count(*) AS n FROM kb GROUP BY 1)), tr AS MATERIALIZED (SELECT item_id, truth::VARCHAR AS truth FROM {_ITEMS})"
)


@query(
    f"{_HITS} "
    + " UNION ALL ".join(
        f"SELECT 'retrieval' AS how, {k}::BIGINT AS k, round(avg((EXISTS (SELECT 1 FROM found f WHERE f.item_id = tr.item_id AND f.l3_id = tr.truth AND rank <= {k}))::INT), 6) AS hit_rate FROM tr "
        f"UNION ALL SELECT 'bare', {k}, round(avg((truth IN (SELECT l3_id FROM bare WHERE rank <= {k}))::INT), 6) FROM tr"
        for k in (1, 3, 10)
    )
)
def e_hit_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hit rate of the true function of each mined combination: retrieved by its words from the knowledge base, and without retrieval, where the same most frequent functions answer every demand."""
    k = kb(spark, sf_dir)
    truth = cut(items(spark, sf_dir).select("item_id", F.col("truth").cast("string").alias("l3_id")))
    texts = cut(k.groupBy("l3_id").agg(F.array_join(F.flatten(F.collect_list("combo.items")), " ").alias("text"), F.count("*").alias("n")))
    demands = truth.select("item_id", F.col("item_id").alias("text"))
    retrieved = cut(serve.functions_for(demands, texts.select("l3_id", "text"), 10))
    prior = texts.orderBy(F.desc("n"), "l3_id").limit(10).withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "l3_id"))).select("l3_id", "rank")
    bare = with_each(truth.select("item_id"), prior)
    out = [score.hit_at_k(ranked, truth, n).select(F.lit(how).alias("how"), F.lit(n).cast("long").alias("k"), *r6("hit_rate")) for how, ranked in (("retrieval", retrieved), ("bare", bare)) for n in (1, 3, 10)]
    return reduce(DataFrame.unionByName, out)


@query(
    f"{_KB} SELECT kb_id, CASE WHEN ('0x' || substr(md5(kb_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE < 0.1 THEN 'valid' ELSE 'train' END AS split, "
    "md5('{\"prompt\":\"Which function do these operators perform together: ' || replace(items, '|', ', ') || '?\",\"completion\":\"' || concat_ws(' > ', l1, l2, l3) || '\"}') AS record_md5 FROM kb"
)
def e_finetune(spark: SparkSession, sf_dir: str) -> DataFrame:
    return serve.finetune(kb(spark, sf_dir), "completion").select("kb_id", "split", F.md5("record").alias("record_md5"))


@query(
    f"{_KB}, x AS (SELECT kb_id, CASE WHEN ('0x' || substr(md5(kb_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE < 0.1 THEN 'valid' ELSE 'train' END AS split, replace(items, '|', ', ') AS ops, concat_ws(' > ', l1, l2, l3) AS tell FROM kb) "
    "SELECT kb_id, split, '{\"messages\":[{\"role\":\"user\",\"content\":\"Which function do these operators perform together: ' || ops || '?\"},{\"role\":\"assistant\",\"content\":\"' || tell || '\"}]}' AS record FROM x UNION ALL "
    "SELECT kb_id, split, '{\"instruction\":\"Name the function.\",\"input\":\"' || ops || '\",\"output\":\"' || tell || '\"}' FROM x"
)
def e_finetune_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chat and instruction styles."""
    k = kb(spark, sf_dir)
    return serve.finetune(k, "chat").unionByName(serve.finetune(k, "instruction"))


@query(
    "WITH l AS (SELECT 64 * p_size::BIGINT AS a, 64 * length(p_name)::BIGINT AS b, 64 * p_size::BIGINT AS d, count(*) AS n FROM part GROUP BY ALL) SELECT unnest(['full', 'low_rank', 'adapter', 'prefix']) AS family, "
    "unnest([sum(n * a * b)::BIGINT, sum(n * 8 * (a + b))::BIGINT, sum(n * (2 * d * 64 + 64 + d))::BIGINT, sum(n * 2 * 20 * d)::BIGINT]) AS n_params FROM l"
)
def e_tuning_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as layers: 64 inputs a unit of size, 64 outputs a letter of the name."""
    wide = lambda c: 64 * c.cast("long")
    p = io.read(spark, sf_dir, "part", ("p_size", "p_name"))
    layers = p.groupBy(wide(F.col("p_size")).alias("d_in"), wide(F.length("p_name")).alias("d_out")).agg(F.count("*").alias("n"))
    return serve.tuning_cost(layers.withColumn("d", F.col("d_in")))


@query(
    f"{_KB} SELECT kind, count(*)::BIGINT AS n FROM (SELECT DISTINCT 'op:' || unnest(string_split(items, '|')) AS src, 'combo:' || kb_id AS dst, 'in' AS kind FROM kb UNION SELECT 'combo:' || kb_id, 'l3:' || l3_id, 'does' FROM kb "
    "UNION SELECT 'l3:' || l3_id, 'l2:' || l2_id, 'part of' FROM kb UNION SELECT 'l2:' || l2_id, 'l1:' || l1_id, 'part of' FROM kb) GROUP BY 1"
)
def e_kb_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.kb_edges(kb(spark, sf_dir)).groupBy("kind").agg(F.count("*").alias("n"))
