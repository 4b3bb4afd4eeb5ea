"""Stages C and D: mapping combinations to functions by simulated annotators, and scoring the result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import noise, noise_sql
from ..operators import labelling, prompts, score
from ..operators.labelling import ERROR, MODELS, RUNS
from ..sources import io
from . import Catalog
from .mining import MIXED_SQL, joined, mined
from .taxonomy import TAX_SQL, r6, tax

CATALOG = Catalog()
query = CATALOG.query

# --- the mined combinations as input ----------------------------------------------------------

_COMBOS = f"(SELECT items, k, freq FROM ({MIXED_SQL}))"


#: Stage results that later stages of a session read: by application, tables and name. Each is written (or held by the driver) once.
_WRITTEN: dict[tuple[str, str, str], DataFrame] = {}


def once(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _WRITTEN:
        _WRITTEN[key] = make()
    return _WRITTEN[key]


def combos(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All frequent mixed sets, numbered by length and items."""
    return once(spark, sf_dir, "combos", lambda: mined(spark, sf_dir).combos)


def named(df: DataFrame, *cols: str) -> DataFrame:
    """Combination ids as their items, since ids number arrays and SQL numbers strings."""
    return joined(df).select("items", *cols)


@query(f"SELECT items, row_number() OVER (ORDER BY k, freq DESC, items)::BIGINT AS place, ((row_number() OVER (ORDER BY k, freq DESC, items) - 1) // 50)::BIGINT AS batch FROM {_COMBOS}")
def c_queue(spark: SparkSession, sf_dir: str) -> DataFrame:
    return named(labelling.order(combos(spark, sf_dir), "len_freq_sim"), "place", "batch")


@query(f"SELECT k::BIGINT AS k, sum(place)::BIGINT AS places, count(*)::BIGINT AS n FROM (SELECT k, row_number() OVER (ORDER BY k, freq DESC)::BIGINT AS place FROM {_COMBOS}) GROUP BY 1")
def c_queue_plain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The default order: length, then frequency."""
    got = labelling.order(combos(spark, sf_dir))
    return got.groupBy(F.col("k").cast("long").alias("k")).agg(F.sum("place").alias("places"), F.count("*").alias("n"))


@query()
def c_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.chain(combos(spark, sf_dir))


_INDEX = (
    "SELECT string_agg(l1 || ': ' || g, chr(10) ORDER BY l1) AS index_text FROM (SELECT l1, string_agg(l2 || ' (' || f || ')', '; ' ORDER BY l2) AS g FROM "
    f"(SELECT l1, l2, string_agg(l3_id::VARCHAR || ':' || l3, ', ' ORDER BY l3_id) AS f FROM ({TAX_SQL}) GROUP BY ALL) GROUP BY 1)"
)


@query(_INDEX)
def c_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts.index_taxonomy(tax(spark, sf_dir))


_WORDS = r"len(list_filter(regexp_split_to_array({}, '[ \n]+'), lambda x: x <> ''))"


@query(f"SELECT (SELECT {_WORDS.format('index_text')} FROM ({_INDEX}))::BIGINT AS index_words, sum({_WORDS.format("concat_ws(' ', l1, l2, l3)")})::BIGINT AS full_words FROM ({TAX_SQL})")
def c_token_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts.token_volume(tax(spark, sf_dir))


@query(
    f"WITH q AS (SELECT items, row_number() OVER (ORDER BY k, freq DESC, items) AS place FROM {_COMBOS}), b AS (SELECT ((place - 1) // 50)::BIGINT AS batch, string_agg(place::VARCHAR || '. ' || replace(items, '|', ' + '), chr(10) ORDER BY place) AS combos FROM q GROUP BY 1) "
    f"SELECT batch, md5('Functions:' || chr(10) || index_text || chr(10) || 'Combinations:' || chr(10) || combos || chr(10) || 'Answer with one function index a line.') AS prompt_md5 FROM b, ({_INDEX})"
)
def c_prompt(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = prompts.build_map_prompt(labelling.order(combos(spark, sf_dir), "len_freq_sim"), tax(spark, sf_dir))
    return got.select("batch", F.md5("prompt").alias("prompt_md5"))


# --- ballots and votes ------------------------------------------------------------------------

#: The mined combinations, each with its true function: one drawn by a hash of its items.
_ITEMS = f"(SELECT items AS item_id, (SELECT min(s_suppkey) FROM supplier) + floor({noise_sql("items", "'truth'")} * (SELECT count(*) FROM supplier))::BIGINT AS truth FROM {_COMBOS})"
_TEAM = "(SELECT * FROM (VALUES " + ", ".join(f"('{m}', {ERROR[m]}::DOUBLE, {i})" for i, m in enumerate(MODELS)) + f") AS m(model, err, prio), (SELECT unnest(range(1, {RUNS + 1})) AS run))"
_N = lambda *p: noise_sql("item_id", *p)
_BALLOTS = (
    f"WITH tax AS MATERIALIZED ({TAX_SQL}), al AS (SELECT list(l3_id ORDER BY l3_id) AS any_l FROM tax), s2 AS (SELECT l1, l2, list(l3_id ORDER BY l3_id) AS in_l2 FROM tax GROUP BY 1, 2), s1 AS (SELECT l1, list(l3_id ORDER BY l3_id) AS in_l1 FROM tax GROUP BY 1), "
    f"e AS (SELECT item_id, model, run, truth, 0.4 * {_N("'d'")} + 0.3 * {_N('model')} + 0.3 * {_N('model', 'run')} < err AS wrong, {_N('model', 'run', "'where'")} AS wh, {_N('model', 'run', "'pick'")} AS pk, {_N('model', 'run', "'spell'")} AS sp FROM {_ITEMS}, {_TEAM}), "
    "p AS (SELECT e.*, CASE WHEN wh < 0.5 THEN in_l2 WHEN wh < 0.8 THEN in_l1 ELSE any_l END AS pool FROM e JOIN tax ON tax.l3_id = truth JOIN s2 USING (l1, l2) JOIN s1 USING (l1), al), "
    "c AS (SELECT item_id, model, run, sp, CASE WHEN wrong THEN pool[(floor(pk * len(pool)) + 1)::INT] ELSE truth END AS l3_id FROM p), "
    "ballots AS MATERIALIZED (SELECT item_id, model, run::BIGINT AS run, CASE WHEN sp < 0.1 THEN lower(substr(l3, 1, 3)) || substr(l3, 5, 99) ELSE l3 END AS raw_label FROM c JOIN tax USING (l3_id))"
)
_EDIT = "(CASE WHEN greatest(length(raw_label), length(l3)) = 0 THEN 1.0 ELSE 1 - levenshtein(raw_label, l3)::DOUBLE / greatest(length(raw_label), length(l3)) END)"
_FUZZY = (
    f"{_BALLOTS}, lost AS (SELECT DISTINCT raw_label FROM ballots WHERE raw_label NOT IN (SELECT l3 FROM tax)), "
    f"near AS (SELECT raw_label, l3_id, {_EDIT} AS sim FROM lost, tax QUALIFY row_number() OVER (PARTITION BY raw_label ORDER BY round({_EDIT}, 9) DESC, l3_id) = 1)"
)
_RESOLVED = (
    f"{_FUZZY}, resolved AS MATERIALIZED (SELECT item_id, model, run, ballots.raw_label, coalesce(x.l3_id, near.l3_id) AS l3_id, CASE WHEN x.l3_id IS NOT NULL THEN 'exact' WHEN near.l3_id IS NOT NULL THEN 'fuzzy' ELSE 'none' END AS matched_by "
    "FROM ballots LEFT JOIN (SELECT l3, min(l3_id) AS l3_id FROM tax GROUP BY 1) x ON x.l3 = ballots.raw_label LEFT JOIN (SELECT * FROM near WHERE sim >= 0.5) near ON near.raw_label = ballots.raw_label), "
    "prio(model, prio) AS (VALUES " + ", ".join(f"('{m}', {i})" for i, m in enumerate(MODELS)) + "), "
    "tally AS MATERIALIZED (SELECT item_id, model, l3_id, count(*) AS n, any_value(prio) AS prio FROM resolved JOIN prio USING (model) WHERE l3_id IS NOT NULL GROUP BY 1, 2, 3), "
    "subs(subset, model) AS (VALUES " + ", ".join(f"('{name}', '{m}')" for name, members in labelling.subsets() for m in members) + ")"
)


def _vote_sql(tally: str, weight: str = "n") -> str:
    return (
        f"SELECT subset, item_id, l3_id, votes FROM (SELECT subset, item_id, l3_id, sum({weight}) AS votes, min(prio) AS prio FROM {tally} t JOIN subs USING (model) GROUP BY 1, 2, 3) "
        "QUALIFY row_number() OVER (PARTITION BY subset, item_id ORDER BY votes DESC, prio, l3_id) = 1"
    )


_SINGLE = "SELECT item_id, model, l3_id, n FROM tally QUALIFY row_number() OVER (PARTITION BY item_id, model ORDER BY n DESC, l3_id) = 1"
_POOLED = f"{_RESOLVED}, votes AS MATERIALIZED ({_vote_sql('tally')})"


def functions_range(spark: SparkSession, sf_dir: str) -> tuple[int, int]:
    """The first function's id and the number of functions, whose ids run on."""
    return io.read(spark, sf_dir, "supplier", ("s_suppkey",)).agg(F.min("s_suppkey"), F.count("*")).first()


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every mined combination, by its items, and its true function."""
    low, n = functions_range(spark, sf_dir)
    key = combos(spark, sf_dir).select(F.array_join("items", "|").alias("item_id"))
    return key.select("item_id", (F.lit(low) + F.floor(noise(F.col("item_id"), "truth") * n)).alias("truth"))


def ballots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return once(spark, sf_dir, "ballots", lambda: labelling.run(items(spark, sf_dir), lambda i: labelling.seeded(i, tax(spark, sf_dir))))


def resolved(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.resolve(ballots(spark, sf_dir), tax(spark, sf_dir))


def tally(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.tallies(resolved(spark, sf_dir))


@query(f"{_BALLOTS} SELECT * FROM ballots")
def c_ballots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Simulated annotators' ballots."""
    return ballots(spark, sf_dir).select("item_id", "model", F.col("run").cast("long").alias("run"), "raw_label")


def _named_parts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Parts as items, with their type, brand and name as text, and the same names as a taxonomy."""
    p = io.read(spark, sf_dir, "part")
    t = p.select(F.col("p_type").alias("l1"), F.col("p_brand").alias("l2"), F.col("p_name").alias("l3")).distinct()
    t = t.withColumn("l3_id", F.conv(F.substring(F.md5(F.concat_ws("/", "l1", "l2", "l3")), 1, 15), 16, 10).cast("long"))
    return p.select(F.col("p_partkey").alias("item_id"), F.concat_ws(" ", "p_type", "p_brand", "p_name").alias("text")), t


_WORDS_OF = r"list_distinct(list_filter(regexp_split_to_array(lower({}), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> ''))"
_WORD_SCORES = (
    "WITH nt AS (SELECT DISTINCT p_type AS l1, p_brand AS l2, p_name AS l3 FROM part), nw AS (SELECT *, len(ws) AS n, unnest(ws) AS w FROM (SELECT *, "
    + _WORDS_OF.format("concat_ws(' ', l1, l2, l3)") + " AS ws FROM nt)), it AS (SELECT p_partkey AS item_id, len(ws) AS m, unnest(ws) AS w FROM (SELECT p_partkey, "
    + _WORDS_OF.format("concat_ws(' ', p_type, p_brand, p_name)") + " AS ws FROM part)), "
    "sc AS MATERIALIZED (SELECT item_id, l1, l2, l3, round(count(*) / sqrt(any_value(n) * any_value(m)), 9) AS score FROM it JOIN nw USING (w) GROUP BY ALL)"
)


@query(
    f"{_WORD_SCORES}, top AS (SELECT item_id, l1, l2, l3, score, max(score) OVER (PARTITION BY item_id) AS best FROM sc) SELECT item_id, 'lexical' AS model, 1::BIGINT AS run, arg_min(l3, ('0x' || substr(md5(l1 || '/' || l2 || '/' || l3), 1, 15))::BIGINT) AS raw_label FROM top WHERE score = best GROUP BY item_id"
)
def c_lexical(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels by shared words."""
    parts, t = _named_parts(spark, sf_dir)
    return labelling.run(parts, lambda i: labelling.lexical(i, t)).withColumn("run", F.col("run").cast("long"))


@query()
def c_narrowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels by shared words, level by level."""
    parts, t = _named_parts(spark, sf_dir)
    return labelling.run(parts, lambda i: labelling.narrowing(i, t))


@query(f"{_BALLOTS} SELECT DISTINCT raw_label FROM ballots WHERE raw_label IN (SELECT l3 FROM tax)")
def c_exists(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.exists(ballots(spark, sf_dir), tax(spark, sf_dir))


@query(f"{_BALLOTS} SELECT DISTINCT raw_label FROM ballots WHERE raw_label NOT IN (SELECT l3 FROM tax)")
def c_missing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.missing(ballots(spark, sf_dir), tax(spark, sf_dir))


@query(f"{_FUZZY} SELECT raw_label, l3_id, round(sim, 6) AS sim FROM near")
def c_fuzzy_lev(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = tax(spark, sf_dir)
    return labelling.fuzzy(labelling.missing(ballots(spark, sf_dir), t), t).select("raw_label", "l3_id", *r6("sim"))


_TOKENS = r"list_distinct(list_filter(regexp_split_to_array(lower({}), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> ''))"
_JACCARD = f"(len(list_intersect({_TOKENS.format('raw_label')}, {_TOKENS.format('l3')}))::DOUBLE / len(list_distinct(list_concat({_TOKENS.format('raw_label')}, {_TOKENS.format('l3')}))))"


@query(f"{_BALLOTS}, lost AS (SELECT DISTINCT raw_label FROM ballots WHERE raw_label NOT IN (SELECT l3 FROM tax)) SELECT raw_label, l3_id, round({_JACCARD}, 6) AS sim FROM lost, tax QUALIFY row_number() OVER (PARTITION BY raw_label ORDER BY round({_JACCARD}, 9) DESC, l3_id) = 1")
def c_fuzzy_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = tax(spark, sf_dir)
    return labelling.fuzzy(labelling.missing(ballots(spark, sf_dir), t), t, "jaccard").select("raw_label", "l3_id", *r6("sim"))


@query()
def c_fuzzy_others(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Character-pair cosine and Dice: how often each finds the function that was misspelt."""
    t = tax(spark, sf_dir)
    lost = labelling.missing(ballots(spark, sf_dir), t)
    out = [labelling.fuzzy(lost, t, how).select(F.lit(how).alias("how"), "raw_label", "l3_id", "sim") for how in ("cosine", "dice")]
    return out[0].unionByName(out[1])


@query(f"{_RESOLVED} SELECT item_id, model, run, raw_label, l3_id, matched_by FROM resolved")
def c_resolve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return resolved(spark, sf_dir).withColumn("run", F.col("run").cast("long"))


@query(f"{_RESOLVED} SELECT item_id, model, l3_id, n::BIGINT AS n FROM ({_SINGLE})")
def c_vote_single(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.single(tally(spark, sf_dir))


@query(f"{_POOLED} SELECT subset, item_id, l3_id, votes::BIGINT AS votes FROM votes")
def c_vote_pooled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.pooled(tally(spark, sf_dir))


@query(f"{_RESOLVED}, voices AS (SELECT item_id, model, l3_id, 1 AS n, prio FROM ({_SINGLE}) JOIN prio USING (model)) SELECT subset, item_id, l3_id, votes::BIGINT AS votes FROM ({_vote_sql('voices')})")
def c_vote_two_stage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.two_stage(tally(spark, sf_dir))


_ACC = "CASE model " + " ".join(f"WHEN '{m}' THEN {1 - ERROR[m]!r}::DOUBLE" for m in MODELS) + " END"


@query(f"{_RESOLVED} SELECT subset, item_id, round(votes, 6) AS votes FROM ({_vote_sql('tally', f'n * {_ACC}')})")
def c_vote_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.weighted(tally(spark, sf_dir)).select("subset", "item_id", *r6("votes"))


@query(
    f"{_RESOLVED}, cnt AS (SELECT item_id, l3_id, sum(n) AS n FROM tally GROUP BY 1, 2), t AS (SELECT item_id, sum(n) AS b, count(*) AS m, list(n ORDER BY n DESC) AS l FROM cnt GROUP BY 1), "
    "s AS (SELECT item_id, avg(d) AS stable FROM (SELECT item_id, model, (count(*) = 1)::INT::DOUBLE AS d FROM tally GROUP BY 1, 2) GROUP BY 1) "
    "SELECT item_id, b::BIGINT AS ballots, m::BIGINT AS n_labels, round((l[1] - coalesce(l[2], 0))::DOUBLE / b, 6) AS margin, round(list_sum(list_transform(l, lambda x: -(x::DOUBLE / b) * ln(x::DOUBLE / b))), 6) + 0.0 AS entropy, round(stable, 6) AS stable FROM t JOIN s USING (item_id)"
)
def c_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return labelling.agreement(resolved(spark, sf_dir)).select("item_id", "ballots", "n_labels", *r6("margin", "entropy", "stable"))


# --- measures ---------------------------------------------------------------------------------


@query(
    f"WITH s AS (SELECT k, count(*) AS size FROM {_COMBOS} GROUP BY 1), f AS (SELECT k, size, floor(size * 150 / sum(size) OVER ()::DOUBLE) AS base, round(size * 150 / sum(size) OVER ()::DOUBLE - floor(size * 150 / sum(size) OVER ()::DOUBLE), 9) AS rest FROM s) "
    "SELECT k::BIGINT AS k, size::BIGINT AS size, least(size, base + (row_number() OVER (ORDER BY rest DESC, k) <= 150 - sum(base) OVER ())::INT)::BIGINT AS quota FROM f"
)
def d_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score.strata(combos(spark, sf_dir)).withColumn("k", F.col("k").cast("long"))


_SAMPLE = (
    f"cs AS MATERIALIZED (SELECT * FROM {_COMBOS}), "
    "qs AS (SELECT k, floor(size * 100 / sum(size) OVER ()::DOUBLE) AS base, round(size * 100 / sum(size) OVER ()::DOUBLE - floor(size * 100 / sum(size) OVER ()::DOUBLE), 9) AS rest, size FROM (SELECT k, count(*) AS size FROM cs GROUP BY 1)), "
    "qt AS (SELECT k, least(size, base + (row_number() OVER (ORDER BY rest DESC, k) <= 100 - sum(base) OVER ())::INT)::BIGINT AS quota FROM qs), "
    "draw1 AS MATERIALIZED (SELECT items, cs.k FROM cs JOIN qt USING (k) QUALIFY row_number() OVER (PARTITION BY cs.k ORDER BY md5(items)) <= any_value(quota) OVER (PARTITION BY cs.k)), "
    "less AS (SELECT items, k, x, array_to_string(list_filter(string_split(items, '|'), lambda i: i <> x), '|') AS rest FROM (SELECT items, k, unnest(string_split(items, '|')) AS x FROM cs)), "
    "draw2 AS MATERIALIZED (SELECT items, k FROM (SELECT DISTINCT b.items, b.k FROM less a SEMI JOIN draw1 USING (items) JOIN less b ON a.rest = b.rest AND a.k = b.k AND a.items <> b.items) ANTI JOIN draw1 USING (items) ORDER BY md5(items) LIMIT 25), "
    "ra AS (SELECT items AS op FROM (SELECT items, percent_rank() OVER (ORDER BY freq, items) AS p FROM cs WHERE k = 1) WHERE p <= 0.25), "
    "draw3 AS (SELECT items, k FROM (SELECT DISTINCT items, k FROM less WHERE x IN (SELECT op FROM ra)) ANTI JOIN draw1 USING (items) ANTI JOIN draw2 USING (items) ORDER BY md5(items) LIMIT 25), "
    "sample AS MATERIALIZED (SELECT items, k, 'length' AS draw FROM draw1 UNION ALL SELECT items, k, 'similar' FROM draw2 UNION ALL SELECT items, k, 'rare' FROM draw3)"
)
_EXPERT = ", ".join(f"CASE WHEN {noise_sql('item_id', "'expert'", str(e))} < 0.1 THEN low + floor({noise_sql('item_id', "'expert'", str(e), "'pick'")} * n)::BIGINT ELSE truth END" for e in (1, 2, 3))
_TRUTH = (
    f"{_SAMPLE}, opinions AS (SELECT item_id, unnest([{_EXPERT}]) AS label FROM {_ITEMS} JOIN sample ON items = item_id, (SELECT min(s_suppkey) AS low, count(*) AS n FROM supplier)), "
    "agreed AS MATERIALIZED (SELECT item_id, label AS truth FROM opinions GROUP BY 1, 2 HAVING 2 * count(*) > 3)"
)


def evaluated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The evaluation sample of 150: by length, similar to those, and of rare operators."""
    return score.evaluation_sample(combos(spark, sf_dir))


@query(f"WITH {_SAMPLE} SELECT items, k, draw FROM sample")
def d_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return named(evaluated(spark, sf_dir), F.col("k").cast("long").alias("k"), "draw")


def opinions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three SIMULATED experts' labels of each sampled combination; each errs one time in ten."""
    low, n = functions_range(spark, sf_dir)
    chosen = named(evaluated(spark, sf_dir)).withColumnRenamed("items", "item_id")
    known = items(spark, sf_dir).join(chosen, "item_id", "left_semi")
    i = F.col("item_id")
    each = (F.when(noise(i, "expert", str(e)) < 0.1, F.lit(low) + F.floor(noise(i, "expert", str(e), "pick") * n)).otherwise(F.col("truth")) for e in (1, 2, 3))
    return known.select("item_id", F.explode(F.array(*each)).alias("label"))


@query(f"WITH {_TRUTH} SELECT item_id, truth FROM agreed")
def d_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The experts' majority on the sample; combinations without one are left out as ambiguous."""
    return score.consensus(opinions(spark, sf_dir)).withColumnRenamed("label", "truth")


def _pairs_by_name(spark: SparkSession, sf_dir: str, insertion: bool) -> DataFrame:
    c = combos(spark, sf_dir)
    p = score.near_pairs(c, insertion)
    name = lambda k: joined(c).select(F.col("combo_id").alias(k), F.col("items").alias(f"items_{k}"))
    got = p.join(name("a"), "a").join(name("b"), "b")
    return got.select(F.least("items_a", "items_b").alias("x"), F.greatest("items_a", "items_b").alias("y"))


_BOTH = "len(list_intersect(string_split(a.items, '|'), string_split(b.items, '|')))"


@query(f"WITH c AS MATERIALIZED (SELECT * FROM {_COMBOS}) SELECT a.items AS x, b.items AS y FROM c a JOIN c b ON a.k = b.k AND a.items < b.items AND {_BOTH} = a.k - 1")
def d_near_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Combinations that differ by one operator."""
    return _pairs_by_name(spark, sf_dir, False)


@query(f"WITH c AS MATERIALIZED (SELECT * FROM {_COMBOS}) SELECT least(a.items, b.items) AS x, greatest(a.items, b.items) AS y FROM c a JOIN c b ON b.k = a.k + 1 AND {_BOTH} = a.k")
def d_near_inserted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Combinations with one operator more."""
    return _pairs_by_name(spark, sf_dir, True)


@query(f"WITH c AS MATERIALIZED (SELECT * FROM {_COMBOS}), r AS (SELECT items AS op FROM (SELECT items, percent_rank() OVER (ORDER BY freq, items) AS p FROM c WHERE k = 1) WHERE p <= 0.25) SELECT c.items, op FROM c JOIN r ON list_contains(string_split(c.items, '|'), op)")
def d_lowfreq(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = combos(spark, sf_dir)
    return score.low_frequency(c).join(joined(c).select("combo_id", "items"), "combo_id").select("items", "op")


_EXPERTS = "(SELECT doc_id AS item_id, unnest([quality, toxic, (length(text) > 800)::INT]) AS label FROM labels JOIN documents USING (doc_id))"


def experts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three 0/1 opinions on each labelled document."""
    d = io.read(spark, sf_dir, "documents", ("doc_id", "text"))
    third = (F.length("text") > 800).cast("long")
    votes = F.explode(F.array(F.col("quality").cast("long"), F.col("toxic").cast("long"), third))
    return io.read(spark, sf_dir, "labels").join(d, "doc_id").select(F.col("doc_id").alias("item_id"), votes.alias("label"))


@query(f"SELECT item_id, mode(label)::BIGINT AS label FROM {_EXPERTS} GROUP BY 1")
def d_consensus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score.consensus(experts(spark, sf_dir))


@query(f"SELECT item_id, any_value(label)::BIGINT AS label FROM {_EXPERTS} GROUP BY 1 HAVING count(DISTINCT label) = 1")
def d_unanimous(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score.consensus(experts(spark, sf_dir), unanimous=True)


@query(
    "WITH n AS (SELECT count(*)::DOUBLE AS n, sum((quality = toxic)::INT)::DOUBLE AS s, sum(quality)::DOUBLE AS a, sum(toxic)::DOUBLE AS b FROM labels), p AS (SELECT s / n AS po, (a * b + (n - a) * (n - b)) / (n * n) AS pe FROM n), "
    f"v AS (SELECT item_id, sum(label)::DOUBLE AS o FROM {_EXPERTS} GROUP BY 1), g AS (SELECT avg((o * o + (3 - o) * (3 - o) - 3) / 6) AS p, sum(o) / (3 * count(*)) AS q FROM v) "
    "SELECT round((po - pe) / (1 - pe), 6) AS cohen, (SELECT round((p - (q * q + (1 - q) * (1 - q))) / (1 - (q * q + (1 - q) * (1 - q))), 6) FROM g) AS fleiss FROM p"
)
def d_kappa(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = score.cohen(io.read(spark, sf_dir, "labels"), "quality", "toxic").select(F.col("kappa").alias("cohen"), F.lit(1).alias("_k"))
    f = score.fleiss(experts(spark, sf_dir)).select(F.col("kappa").alias("fleiss"), F.lit(1).alias("_k"))
    return c.join(f, "_k").select(*r6("cohen", "fleiss"))


_SCORED = (
    f"{_POOLED}, {_TRUTH}, lv AS MATERIALIZED (SELECT v.subset, v.item_id, v.l3_id, i.truth, p.l1 = t.l1 AS t1, p.l1 = t.l1 AND p.l2 = t.l2 AS t2, v.l3_id = i.truth AS t3, t.n_l3_in_l2 AS n, t.m_l2_in_l1 AS m, p.l3 AS p3, t.l3 AS q3, p.l1 AS p1, t.l1 AS q1 "
    f"FROM votes v JOIN agreed i USING (item_id) JOIN tax p ON p.l3_id = v.l3_id JOIN tax t ON t.l3_id = i.truth), "
    f"sc AS MATERIALIZED (SELECT *, CASE WHEN t3 THEN 100 ELSE 100 * {_JACCARD.replace('raw_label', 'p3').replace('lower(l3)', 'lower(q3)')} END AS semantic, CASE WHEN t3 THEN 100 WHEN t2 THEN 80.0::DOUBLE / n WHEN t1 THEN 20.0::DOUBLE / m ELSE 0 END AS structure FROM lv)"
)


def scored(spark: SparkSession, sf_dir: str) -> DataFrame:
    truth = score.consensus(opinions(spark, sf_dir)).withColumnRenamed("label", "truth")
    return score.scored(labelling.pooled(tally(spark, sf_dir)), truth, tax(spark, sf_dir))


@query(f"{_SCORED} SELECT subset, item_id, t1, t2, t3 FROM lv")
def d_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, sf_dir).select("subset", "item_id", "t1", "t2", "t3")


@query(f"{_SCORED} SELECT subset, item_id, round(semantic, 6) AS semantic FROM sc")
def d_semantic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, sf_dir).select("subset", "item_id", *r6("semantic"))


@query(f"{_SCORED} SELECT subset, item_id, round(structure, 6) AS structure FROM sc")
def d_structure(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, sf_dir).select("subset", "item_id", *r6("structure"))


@query(f"{_SCORED} SELECT subset, item_id, round(0.6 * semantic + 0.4 * structure, 6) AS overall FROM sc")
def d_overall(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scored(spark, sf_dir).select("subset", "item_id", *r6("overall"))


@query(
    f"{_SCORED}, a AS (SELECT subset, len(string_split(subset, '+')) AS n_models, avg(structure) AS structure, avg(semantic) AS semantic, avg(0.6 * semantic + 0.4 * structure) AS overall FROM sc GROUP BY 1) "
    "SELECT subset, n_models::BIGINT AS n_models, round(structure, 6) AS structure, round(semantic, 6) AS semantic, round(overall, 6) AS overall, rank() OVER (PARTITION BY n_models ORDER BY round(overall, 9) DESC)::BIGINT AS rank, round(overall - (SELECT max(overall) FROM a WHERE n_models = 1), 6) + 0.0 AS gain FROM a"
)
def d_table9(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of the fifteen subsets of SIMULATED annotators."""
    got = score.report(scored(spark, sf_dir))
    return got.select("subset", F.col("n_models").cast("long").alias("n_models"), *r6("structure", "semantic", "overall"), F.col("rank").cast("long").alias("rank"), *r6("gain"))


@query(f"{_SCORED} SELECT subset, round(avg(t1::INT), 6) AS acc_l1, round(avg(t2::INT), 6) AS acc_l2, round(avg(t3::INT), 6) AS acc_l3 FROM lv GROUP BY 1")
def d_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score.accuracy(scored(spark, sf_dir)).select("subset", *r6("acc_l1", "acc_l2", "acc_l3"))


@query(
    f"{_SCORED}, h AS (SELECT subset, q3 AS c, count(*) AS tp FROM lv WHERE p3 = q3 GROUP BY 1, 2), np AS (SELECT subset, p3 AS c, count(*) AS n FROM lv GROUP BY 1, 2), nt AS (SELECT subset, q3 AS c, count(*) AS n FROM lv GROUP BY 1, 2) "
    "SELECT subset, round(avg(2.0::DOUBLE * coalesce(tp, 0) / (coalesce(np.n, 0) + coalesce(nt.n, 0))), 6) AS macro_f1 FROM nt FULL JOIN np USING (subset, c) LEFT JOIN h USING (subset, c) GROUP BY 1"
)
def d_macro_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score.macro_f1(scored(spark, sf_dir)).select("subset", *r6("macro_f1"))


_REGIONS = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]


@query(f"{_SCORED} SELECT q1 AS truth, " + ", ".join(f"count(*) FILTER (p1 = '{r}')::BIGINT AS \"{r}\"" for r in _REGIONS) + " FROM lv GROUP BY 1")
def d_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = tax(spark, sf_dir).select("l3_id", "l1")
    lv = scored(spark, sf_dir).drop("p1", "q1").join(F.broadcast(t.withColumnRenamed("l1", "p1")), "l3_id").join(F.broadcast(t.select(F.col("l3_id").alias("truth"), F.col("l1").alias("q1"))), "truth")
    return score.confusion(lv, _REGIONS)


@query("SELECT count(*)::BIGINT AS n_calls, sum((event_type NOT IN ('click', 'view', 'purchase'))::INT)::BIGINT AS n_invented FROM events")
def d_invented(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = spark.createDataFrame([("click",), ("view",), ("purchase",)], "event_type string")
    return score.invented_rate(io.read(spark, sf_dir, "events", ("event_type",)), known, "event_type")


@query(
    f"{_SCORED}, a AS (SELECT subset, 0.6 * avg(semantic) + 0.4 * avg(structure) AS parts, avg(0.6 * semantic + 0.4 * structure) AS overall FROM sc GROUP BY 1) "
    "SELECT subset, round(parts, 3) AS overall, abs(round(parts, 3) - overall) <= 0.0011 AS agrees FROM a"
)
def d_paper_t9(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Overall scores of the fifteen subsets, recomputed from the means of their two parts, and whether the mean of the overall scores agrees."""
    mean = score.means(scored(spark, sf_dir))
    value = F.round(score.overall(F.col("semantic"), F.col("structure")), 3)
    return mean.select("subset", value.alias("overall"), (F.abs(value - F.col("overall")) <= 0.0011).alias("agrees"))
