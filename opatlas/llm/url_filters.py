"""URL filters: explicit rules, and a per-host path-template tree where no rule speaks (DataFrame functions only).

A path is cut into ``DEPTH`` segments and a last slot that holds whatever follows them, so no
path is cut short. Urls on which a rule speaks are the labelled ones.

1. Vocabulary. Per host and depth a segment stays literal if it occurs at least twice and in
   at least one of ``VOCABULARY`` of the host's urls; any other one is ``<*>``. Counts come
   from one aggregation by (host, depth, segment); what is kept of a host is bounded.
2. Tree. Urls are counted by host and remaining segments, and nodes are made level by level
   from the host down. Below each node a child that occurs once, or in under one of
   ``VARIABLE`` of the node's urls, is generalised to ``<*>``, so a variable middle segment
   does not part what follows it.
3. Merging. The labelled children of a node lie on two sides: those with at least the node's
   share of allowed urls and those with less. Children that a two-by-two test cannot tell from
   the rest of their side are similar; two or more of them become the branch ``<+>`` or
   ``<->`` and are one node from there on.
4. Purity. A node's share of allowed urls is smoothed towards its parent's, from the host down
   to the leaf, with ``PRIOR`` pseudo-urls; the root's own prior is the neutral ``BASE``. Only a
   host's own labels speak for it, so a host without any is left alone. A template whose
   purity is under ``THRESHOLD`` is rejected.

Work per host after the vocabulary is on its distinct templates, not on its urls: windows by
host and node, all on one exchange by host.

Defined results: a null url or one without ``://`` has empty host and path and is judged as
the template of the empty path on the empty host; repeated urls and repeated rows count as
often as they occur; very long paths and segments are read whole; an empty table gives no
rows; without any label every purity is ``BASE``; columns of the input other than page_id and
url are not read, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut
from .common import lower_ascii


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    rule: str

    @property
    def host(self) -> str:
        return self.rule.split("/", 1)[0]

    @property
    def path(self) -> str:
        return "/" + self.rule.split("/", 1)[1]


#: Fixed values of the contract.
RULES = (
    UrlRule("allow", "com/"),
    UrlRule("block", "example.com/en/"),
    UrlRule("allow", "www.example.com/en/"),
    UrlRule("block", "net/es/"),
    UrlRule("block", "net/fr/"),
)
#: Segments that are nodes of their own; what follows them is one more.
DEPTH = 4
LEVELS = range(1, DEPTH + 2)
#: A literal segment holds at least one part in this many of its host's urls.
VOCABULARY = 200
#: A child with under one part in this many of its parent's urls is variable.
VARIABLE = 50
PRIOR = 4.0
#: The 5 % point of a chi-squared test with one degree of freedom.
Z2 = 3.8416
BASE = 0.5
THRESHOLD = 0.5
ANY, HIGH, LOW = "/<*>", "/<+>", "/<->"


def host_of(url: Column) -> Column:
    return lower_ascii(F.coalesce(F.regexp_extract(url, "://([^/?#]*)", 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: tuple[UrlRule, ...] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict, both null if none does. Rules are a bounded parameter."""
    fits = [(r, ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)) for r in sorted(rules, key=lambda r: -len(r.rule))]

    def pick(value) -> Column:
        out = F.lit(None).cast("string")
        for r, when in reversed(fits):
            out = F.when(when, F.lit(value(r))).otherwise(out)
        return out

    return pick(lambda r: r.rule), pick(lambda r: r.verdict)


def judged(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES) -> DataFrame:
    """page_id, host, path, rule, said (the rule's verdict) and the path's slots s1, s2 ...: each with its slash, empty where the path has ended."""
    split = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rule, said = rule_of(F.col("host"), F.col("path"), rules)
    parts = F.split("path", "/")
    slot = lambda d: F.when(F.size(parts) > d, F.concat(F.lit("/"), F.get(parts, F.lit(d)))).otherwise("")
    rest = F.when(F.size(parts) > DEPTH + 1, F.concat(F.lit("/"), F.array_join(F.slice(parts, DEPTH + 2, F.size(parts)), "/"))).otherwise("")
    return split.select("*", rule.alias("rule"), said.alias("said"), *(slot(d).alias(f"s{d}") for d in range(1, DEPTH + 1)), rest.alias(f"s{DEPTH + 1}"))


def vocabulary(urls: DataFrame) -> DataFrame:
    """host and ``words``: its literal segments with their depth before them, at most ``VOCABULARY`` a depth."""
    # depth 0 counts the host's urls
    each = F.explode(F.array(F.struct(F.lit(0).alias("d"), F.lit("").alias("seg")), *(F.struct(F.lit(d).alias("d"), F.col(f"s{d}").alias("seg")) for d in LEVELS)))
    seen = urls.select("host", each.alias("x")).where("x.d = 0 OR x.seg <> ''").groupBy("host", "x.d", "x.seg").agg(F.count("*").alias("n"))
    totals = seen.where("d = 0").select("host", F.col("n").alias("hn"))
    kept = seen.where("d > 0 AND n >= 2").join(totals, "host").where(F.col("n") * VOCABULARY >= F.col("hn"))
    return kept.groupBy("host").agg(F.collect_list(F.concat(F.col("d").cast("string"), "seg")).alias("words"))


def typed(urls: DataFrame) -> DataFrame:
    """``urls`` with l1, l2 ... in place of the slots: literal segments of the host's vocabulary, ``<*>`` for others."""
    known = vocabulary(urls)
    label = lambda d: F.when(F.col(f"s{d}") == "", "").when(F.array_contains("words", F.concat(F.lit(str(d)), f"s{d}")), F.col(f"s{d}")).otherwise(ANY)
    return urls.join(known, "host", "left").select("page_id", "host", "path", "rule", "said", *(label(d).alias(f"l{d}") for d in LEVELS))


def _smooth(a: Column, b: Column, prior: Column) -> Column:
    return (a + F.lit(PRIOR) * prior) / (a + b + F.lit(PRIOR))


def _similar(a: Column, b: Column, pa: Column, pb: Column) -> Column:
    """True if a child's share of allowed urls cannot be told from that of the rest of its side, which has ``pa`` and ``pb`` in all."""
    c, d = pa - a, pb - b
    gap = a * d - b * c
    return gap * gap * (pa + pb) <= F.lit(Z2) * (a + b) * (c + d) * pa * pb


def template_verdicts(urls: DataFrame) -> DataFrame:
    """host, l1, l2 ..., template, purity and verdict of each remaining path, from ``typed`` rows."""
    labels = [f"l{d}" for d in LEVELS]
    one = lambda v: F.sum(F.col("said").eqNullSafe(v).cast("double"))
    leaves = urls.groupBy("host", *labels).agg(F.count("*").alias("n"), one("allow").alias("a"), one("block").alias("b"))
    over = lambda what, *by: F.sum(what).over(Window.partitionBy("host", *by))

    rows = leaves.select("*", over("a").alias("na"), over("b").alias("nb"), F.lit("").alias("node"))
    rows = rows.withColumn("purity", _smooth(F.col("na"), F.col("nb"), F.lit(BASE)))
    for label in labels:
        rare = (over("n", "node", label) * VARIABLE < over("n", "node")) | (over("n", "node", label) < 2)
        rows = rows.withColumn("child", F.when(F.col(label) == "", "").when(rare, ANY).otherwise(F.col(label)))
        rows = rows.withColumn("ca", over("a", "node", "child")).withColumn("cb", over("b", "node", "child"))
        high = F.col("ca") * F.col("nb") >= F.col("cb") * F.col("na")
        rows = rows.withColumn("side", F.when((F.col("child") != "") & (F.col("ca") + F.col("cb") > 0), F.when(high, HIGH).otherwise(LOW)))
        rows = rows.withColumn("like", F.col("side").isNotNull() & _similar(F.col("ca"), F.col("cb"), over("a", "node", "side"), over("b", "node", "side")))
        by = Window.partitionBy("host", "node", "side", "like")
        several = F.col("like") & (F.min("child").over(by) != F.max("child").over(by))
        rows = rows.withColumn("merged", several).withColumn("ma", F.sum("a").over(by)).withColumn("mb", F.sum("b").over(by))
        rows = rows.select(
            "host", *labels, "n", "a", "b", F.when(F.col("merged"), F.col("ma")).otherwise(F.col("ca")).alias("na"), F.when(F.col("merged"), F.col("mb")).otherwise(F.col("cb")).alias("nb"),
            F.concat("node", F.when(F.col("merged"), F.col("side")).otherwise(F.col("child"))).alias("node"), "purity", "child",
        )
        rows = rows.withColumn("purity", F.when(F.col("child") == "", F.col("purity")).otherwise(_smooth(F.col("na"), F.col("nb"), F.col("purity")))).drop("child")
    return rows.select("host", *labels, F.col("node").alias("template"), "purity", F.when(F.col("purity") < THRESHOLD, "block").otherwise("allow").alias("verdict"))


def filter_urls(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, template and purity of every row of ``pages``, which is scanned once."""
    urls = cut(typed(cut(judged(pages, rules))))
    keys = ["host", *(f"l{d}" for d in LEVELS)]
    joined = urls.join(template_verdicts(urls).withColumnRenamed("verdict", "_v"), keys)
    return joined.select("page_id", "host", "path", "rule", F.coalesce("said", "_v").alias("verdict"), "template", F.round("purity", 6).alias("purity"))


def _oracle() -> str:
    """The same in SQL, by groups and joins instead of windows."""
    names = ", ".join(f"l{d}" for d in LEVELS)
    ctes = [
        "s AS (SELECT page_id, translate(coalesce(regexp_extract(url, '://([^/?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, "
        "coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') AS path FROM pages)",
        "rules(verdict, rule) AS (VALUES " + ", ".join(f"('{r.verdict}', '{r.rule}')" for r in RULES) + ")",
        "m AS (SELECT page_id, max_by(rule, length(rule)) AS rule, max_by(verdict, length(rule)) AS said FROM s JOIN rules "
        "ON (host = split_part(rule, '/', 1) OR host LIKE '%.' || split_part(rule, '/', 1)) AND starts_with(path, substr(rule, strpos(rule, '/'))) GROUP BY page_id)",
        "u AS (SELECT s.*, rule, said, string_split(path, '/') AS x FROM s LEFT JOIN m USING (page_id))",
        "g AS (SELECT page_id, host, path, rule, said, [" + ", ".join(f"CASE WHEN len(x) > {d} THEN '/' || x[{d + 1}] ELSE '' END" for d in range(1, DEPTH + 1))
        + f", CASE WHEN len(x) > {DEPTH + 1} THEN '/' || array_to_string(x[{DEPTH + 2}:], '/') ELSE '' END] AS seg FROM u)",
        f"v AS (SELECT host, d, seg FROM (SELECT host, unnest(range(1, {DEPTH + 2})) AS d, unnest(seg) AS seg FROM g) JOIN (SELECT host, count(*) AS hn FROM g GROUP BY 1) USING (host) "
        f"GROUP BY host, d, seg, hn HAVING count(*) >= 2 AND count(*) * {VOCABULARY} >= hn)",
        "y AS MATERIALIZED (SELECT page_id, g.host AS host, path, rule, said, " + ", ".join(f"CASE WHEN g.seg[{d}] = '' THEN '' WHEN v{d}.seg IS NULL THEN '{ANY}' ELSE g.seg[{d}] END AS l{d}" for d in LEVELS)
        + " FROM g " + " ".join(f"LEFT JOIN v AS v{d} ON v{d}.host = g.host AND v{d}.d = {d} AND v{d}.seg = g.seg[{d}]" for d in LEVELS) + ")",
        f"t AS (SELECT host, {names}, count(*) AS n, (count(*) FILTER (said = 'allow'))::DOUBLE AS a, (count(*) FILTER (said = 'block'))::DOUBLE AS b FROM y GROUP BY ALL)",
        f"r0 AS (SELECT t.*, '' AS node, na, nb, (na + {PRIOR}::DOUBLE * {BASE}::DOUBLE) / (na + nb + {PRIOR}) AS purity "
        "FROM t JOIN (SELECT host, sum(a) AS na, sum(b) AS nb FROM t GROUP BY 1) USING (host))",
    ]
    for d in LEVELS:
        r = f"r{d - 1}"
        ctes += [
            f"c{d} AS (SELECT {r}.*, CASE WHEN l{d} = '' THEN '' WHEN x.n * {VARIABLE} < p.n OR x.n < 2 THEN '{ANY}' ELSE l{d} END AS child FROM {r} "
            f"JOIN (SELECT host, node, l{d}, sum(n) AS n FROM {r} GROUP BY ALL) x USING (host, node, l{d}) JOIN (SELECT host, node, sum(n) AS n FROM {r} GROUP BY ALL) p USING (host, node))",
            f"e{d} AS (SELECT *, CASE WHEN child <> '' AND ca + cb > 0 THEN CASE WHEN ca * nb >= cb * na THEN '{HIGH}' ELSE '{LOW}' END END AS side FROM "
            f"(SELECT host, node, child, any_value(na) AS na, any_value(nb) AS nb, sum(a) AS ca, sum(b) AS cb FROM c{d} GROUP BY ALL))",
            f"f{d} AS (SELECT host, node, child, side, ca, cb FROM e{d} JOIN (SELECT host, node, side, sum(ca) AS sa, sum(cb) AS sb FROM e{d} WHERE side IS NOT NULL GROUP BY ALL) USING (host, node, side) "
            f"WHERE (ca * (sb - cb) - cb * (sa - ca)) ** 2 * (sa + sb) <= {Z2}::DOUBLE * (ca + cb) * (sa - ca + (sb - cb)) * sa * sb)",
            f"m{d} AS (SELECT host, node, side, sum(ca) AS ma, sum(cb) AS mb FROM f{d} GROUP BY ALL HAVING count(*) > 1)",
            f"k{d} AS (SELECT e.host, e.node, e.child, coalesce(m.side, e.child) AS label, coalesce(ma, e.ca) AS na, coalesce(mb, e.cb) AS nb FROM e{d} e "
            f"LEFT JOIN f{d} f ON f.host = e.host AND f.node = e.node AND f.child = e.child LEFT JOIN m{d} m ON m.host = f.host AND m.node = f.node AND m.side = f.side)",
            f"r{d} AS MATERIALIZED (SELECT c.host, {names}, n, a, b, c.node || label AS node, k.na, k.nb, CASE WHEN c.child = '' THEN purity ELSE (k.na + {PRIOR} * purity) / (k.na + k.nb + {PRIOR}) END AS purity "
            f"FROM c{d} c JOIN k{d} k USING (host, node, child))",
        ]
    return (
        "WITH " + ", ".join(ctes) + f" SELECT page_id, host, path, rule, coalesce(said, CASE WHEN purity < {THRESHOLD} THEN 'block' ELSE 'allow' END) AS verdict, "
        f"node AS template, round(purity, 6) AS purity FROM y JOIN r{DEPTH + 1} USING (host, {names})"
    )


ORACLE = _oracle()
