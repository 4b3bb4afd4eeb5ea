"""Sources, relational operators, scalar functions and the batch twins of the streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import udx
from ..functions.text import edit_ratio, jaccard
from ..plans.planning import maybe_broadcast, with_each
from ..sources import io
from ..streaming import pairs as streams
from . import Catalog

CATALOG = Catalog()
query = CATALOG.query


def _t(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return io.read(spark, sf_dir, name, columns or None)


# --- sources ----------------------------------------------------------------------------------


@query("SELECT l_returnflag, sum(l_quantity)::BIGINT AS qty FROM lineitem WHERE l_shipdate < TIMESTAMP '1995-01-01' GROUP BY 1")
def f_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns read, the filter pushed to the scan."""
    kept = _t(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity", "l_shipdate").where("l_shipdate < TIMESTAMP '1995-01-01'")
    return kept.groupBy("l_returnflag").agg(F.sum("l_quantity").cast("long").alias("qty"))


@query("SELECT n_name, count(*)::BIGINT AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def f_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The SQL surface."""
    views = {"c": _t(spark, sf_dir, "customer"), "n": _t(spark, sf_dir, "nation")}
    return spark.sql("SELECT n_name, count(*) AS n FROM {c} JOIN {n} ON c_nationkey = n_nationkey GROUP BY 1", **views)


# --- relational -------------------------------------------------------------------------------


@query("SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 100 AND 500 AND lang IN ('en', 'fr') AND source LIKE 'src1%' AND regexp_matches(source, '[0-4]$') AND text IS NOT NULL")
def g_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _t(spark, sf_dir, "documents")
    kept = d.where(F.col("n_chars").between(100, 500) & F.col("lang").isin("en", "fr") & F.col("source").like("src1%") & F.col("source").rlike("[0-4]$") & F.col("text").isNotNull())
    return kept.select("doc_id", "n_chars")


@query("SELECT r_name, count(*)::BIGINT AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def g_bcast_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = maybe_broadcast(_t(spark, sf_dir, "nation").join(F.broadcast(_t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey")))
    return _t(spark, sf_dir, "supplier").join(n, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


_LO = "SELECT o_orderpriority, count(*)::BIGINT AS n, sum(l_quantity)::BIGINT AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _lines_orders(spark: SparkSession, sf_dir: str, hint: str) -> DataFrame:
    o = _t(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").hint(hint)
    joined = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


@query(_LO)
def g_smj(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lines_orders(spark, sf_dir, "merge")


@query(_LO)
def g_shj(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lines_orders(spark, sf_dir, "shuffle_hash")


@query("SELECT coalesce(a.k, b.k) AS k, n_sup, n_cust FROM (SELECT s_nationkey AS k, count(*)::BIGINT AS n_sup FROM supplier GROUP BY 1) a FULL JOIN (SELECT c_nationkey AS k, count(*)::BIGINT AS n_cust FROM customer WHERE c_acctbal > 5000 GROUP BY 1) b ON a.k = b.k")
def g_full_outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = _t(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("n_sup"))
    b = _t(spark, sf_dir, "customer").where("c_acctbal > 5000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("n_cust"))
    return a.join(b, "k", "full_outer")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def g_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _t(spark, sf_dir, "orders", "o_custkey", "o_orderpriority").where("o_orderpriority = '1-URGENT'")
    return _t(spark, sf_dir, "customer", "c_custkey").join(o, F.col("o_custkey") == F.col("c_custkey"), "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def g_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "documents", "doc_id").join(_t(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey <= b.n_regionkey AND levenshtein(a.n_name, b.n_name) <= 4 AND a.n_nationkey <> b.n_nationkey")
def g_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A join without equality, of a side whose size is checked."""
    n = _t(spark, sf_dir, "nation")
    b = maybe_broadcast(n.toDF(*(f"b_{c}" for c in n.columns)), 1_000)
    on = (F.col("n_regionkey") <= F.col("b_n_regionkey")) & (F.levenshtein("n_name", "b_n_name") <= 4) & (F.col("n_nationkey") != F.col("b_n_nationkey"))
    return n.join(b, on).select(F.col("n_name").alias("a"), F.col("b_n_name").alias("b"))


_NEAR = "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND v.ts BETWEEN p.ts - INTERVAL 10 HOUR AND p.ts"


@query(_NEAR)
def g_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Views within ten hours before a purchase: an equality join on the user and a time bucket, both neighbouring buckets of one side."""
    e = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    span = 10 * 3600
    bucket = F.floor(F.unix_timestamp("ts") / span)
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("vt"), F.explode(F.array(bucket, bucket + 1)).alias("b"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("pt"), bucket.alias("b"))
    return v.join(p, ["user_id", "b"]).where("vt BETWEEN pt - INTERVAL 10 HOURS AND pt").select("view_id", "purchase_id")


@query("SELECT event_id, view_id FROM (SELECT event_id, event_type, max_by(CASE WHEN event_type = 'view' THEN event_id END, CASE WHEN event_type = 'view' THEN epoch_us(ts) END) OVER w AS view_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)) WHERE event_type = 'purchase'")
def g_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last view before each purchase: one exchange and sort, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    e = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("view_id", last).where("event_type = 'purchase'").select("event_id", "view_id")


@query("SELECT n_name, r_name, (n_regionkey = r_regionkey) AS mine FROM nation, region")
def g_cross(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every row with every row of a model-sized table."""
    got = with_each(_t(spark, sf_dir, "nation", "n_name", "n_regionkey"), _t(spark, sf_dir, "region", "r_regionkey", "r_name"), 1_000)
    return got.select("n_name", "r_name", (F.col("n_regionkey") == F.col("r_regionkey")).alias("mine"))


@query("SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(l_quantity)::BIGINT AS qty, round(avg(l_discount), 6) AS disc, round(stddev_pop(l_tax), 6) AS sd, arg_min(l_orderkey, l_extendedprice * 1000000 + l_orderkey / 1000000) IS NOT NULL AS some, bool_and(l_quantity > 0) AS pos FROM lineitem GROUP BY 1, 2")
def g_agg(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = _t(spark, sf_dir, "lineitem")
    return li.groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.round(F.stddev_pop("l_tax"), 6).alias("sd"),
        F.min_by("l_orderkey", "l_extendedprice").isNotNull().alias("some"), F.bool_and(F.col("l_quantity") > 0).alias("pos"),
    )


@query("SELECT o_orderpriority, count(DISTINCT o_custkey)::BIGINT AS n_cust, string_agg(DISTINCT o_orderstatus, '|' ORDER BY o_orderstatus) AS states FROM orders GROUP BY 1")
def g_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _t(spark, sf_dir, "orders")
    return o.groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("n_cust"), F.array_join(F.array_sort(F.collect_set("o_orderstatus")), "|").alias("states"))


@query()
def g_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sketches: distinct count and percentile."""
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


@query("SELECT p_type, round(quantile_cont(p_retailprice, 0.5), 6) AS q2, round(quantile_cont(p_retailprice, 0.9), 6) AS q9 FROM part GROUP BY 1")
def g_pctl(spark: SparkSession, sf_dir: str) -> DataFrame:
    q = F.percentile("p_retailprice", [0.5, 0.9])
    return _t(spark, sf_dir, "part").groupBy("p_type").agg(q.alias("q")).select("p_type", F.round(F.col("q")[0], 6).alias("q2"), F.round(F.col("q")[1], 6).alias("q9"))


@query("SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY 1")
def g_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"))


_NS = "FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _located(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _t(spark, sf_dir, "nation").join(F.broadcast(_t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return _t(spark, sf_dir, "supplier").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))


@query(f"SELECT r_name, n_name, count(*)::BIGINT AS n {_NS} GROUP BY ROLLUP (r_name, n_name)")
def g_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _located(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, grouping(l_returnflag, l_linestatus)::BIGINT AS g, count(*)::BIGINT AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def g_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("g"), F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def g_gsets(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _t(spark, sf_dir, "orders", "o_orderstatus", "o_orderpriority")
    return o.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'view')::BIGINT AS view FROM events GROUP BY 1")
def g_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT p_partkey, 'p_size' AS what, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'p_retailprice', p_retailprice FROM part")
def g_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _t(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return p.unpivot("p_partkey", ["p_size", "p_retailprice"], "what", "value")


@query("SELECT s_suppkey, row_number() OVER w::BIGINT AS rn, rank() OVER w2::BIGINT AS rk, dense_rank() OVER w2::BIGINT AS dr, ntile(4) OVER w::BIGINT AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey), w2 AS (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000))")
def g_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, w2 = Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey"), Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_acctbal") / 1000))
    n = lambda c, a: c.cast("long").alias(a)
    return _t(spark, sf_dir, "supplier").select(
        "s_suppkey", n(F.row_number().over(w), "rn"), n(F.rank().over(w2), "rk"), n(F.dense_rank().over(w2), "dr"), n(F.ntile(4).over(w), "nt"),
        F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"),
    )


@query("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def g_lead(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    return e.select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


@query("SELECT o_orderkey, sum(1) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS n, max(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS m FROM orders")
def g_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    n = F.sum(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0))
    return _t(spark, sf_dir, "orders").select("o_orderkey", n.cast("long").alias("n"), F.max("o_orderkey").over(w.rowsBetween(-2, 0)).alias("m"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def g_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-86400, 0)
    return _t(spark, sf_dir, "events", "event_id", "ts", "user_id").select("event_id", F.count("*").over(w).alias("n"))


@query("SELECT * FROM (SELECT l_orderkey, max(l_extendedprice) AS p FROM lineitem GROUP BY 1) ORDER BY p DESC, l_orderkey LIMIT 10 OFFSET 5")
def g_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _t(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice").groupBy("l_orderkey").agg(F.max("l_extendedprice").alias("p"))
    return p.orderBy(F.desc("p"), "l_orderkey").offset(5).limit(10)


@query("SELECT s_nationkey AS k FROM supplier INTERSECT SELECT c_nationkey FROM customer WHERE c_acctbal > 9000")
def g_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")).intersect(_t(spark, sf_dir, "customer").where("c_acctbal > 9000").select("c_nationkey"))


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def g_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(_t(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region")
def g_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "nation").select(F.col("n_name").alias("name")).unionByName(_t(spark, sf_dir, "region").select(F.col("r_name").alias("name")))


@query("SELECT s_suppkey FROM supplier s WHERE s_acctbal > (SELECT avg(s_acctbal) FROM supplier x WHERE x.s_nationkey = s.s_nationkey) AND EXISTS (SELECT 1 FROM customer WHERE c_nationkey = s_nationkey)")
def g_subquery(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlated scalar and existence subqueries."""
    v = {"s": _t(spark, sf_dir, "supplier"), "c": _t(spark, sf_dir, "customer")}
    return spark.sql("SELECT s_suppkey FROM {s} AS s WHERE s_acctbal > (SELECT avg(x.s_acctbal) FROM {s} AS x WHERE x.s_nationkey = s.s_nationkey) AND EXISTS (SELECT 1 FROM {c} AS c WHERE c.c_nationkey = s.s_nationkey)", **v)


_WALK = "WITH RECURSIVE up(id, parent, depth) AS (SELECT 's' || s_suppkey, 'n' || s_nationkey, 0 FROM {s} UNION ALL SELECT CASE WHEN up.depth = 0 THEN 'n' || n_nationkey ELSE up.id END, 'r' || n_regionkey, up.depth + 1 FROM up JOIN {n} AS n ON up.parent = 'n' || n_nationkey WHERE up.depth < 1) SELECT id, parent, CAST(depth AS BIGINT) AS depth FROM up"


@query(_WALK.replace("{s}", "supplier").replace("{n}", "nation"))
def g_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A walk up the taxonomy."""
    return spark.sql(_WALK, s=_t(spark, sf_dir, "supplier"), n=_t(spark, sf_dir, "nation"))


@query("SELECT doc_id, lang FROM documents WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT % 100 < CASE lang WHEN 'en' THEN 10 ELSE 30 END")
def g_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stratified sample by hash."""
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 100
    return _t(spark, sf_dir, "documents", "doc_id", "lang").where(h < F.when(F.col("lang") == "en", 10).otherwise(30))


@query("SELECT user_id, event_type, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts DESC, event_id DESC) = 1")
def g_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The latest row of each key, by an aggregate instead of a window."""
    e = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    return e.groupBy("user_id", "event_type").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


# --- scalar functions -------------------------------------------------------------------------


@query(r"SELECT p_partkey, upper(p_name) AS u, regexp_extract(p_name, '(\w+) (\w+)', 2) AS w2, replace(p_name, ' ', '_') AS r, substr(p_name, 2, 3) AS s, length(p_name)::BIGINT AS n, levenshtein(p_name, p_brand)::BIGINT AS lev, md5(p_name) AS m, sha256(p_name) AS h, instr(p_name, 'a')::BIGINT AS i, translate(p_name, 'ae', '43') AS t, round(1 - levenshtein(p_name, p_brand)::DOUBLE / greatest(length(p_name), length(p_brand)), 6) AS er FROM part")
def h_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("p_name")
    return _t(spark, sf_dir, "part").select(
        "p_partkey", F.upper(n).alias("u"), F.regexp_extract(n, r"(\w+) (\w+)", 2).alias("w2"), F.concat_ws("_", F.split(n, " ")).alias("r"), F.substring(n, 2, 3).alias("s"),
        F.length(n).cast("long").alias("n"), F.levenshtein(n, F.col("p_brand")).cast("long").alias("lev"), F.md5(n).alias("m"), F.sha2(n, 256).alias("h"), F.instr(n, "a").cast("long").alias("i"),
        F.translate(n, "ae", "43").alias("t"), F.round(edit_ratio(n, F.col("p_brand")), 6).alias("er"),
    )


@query("SELECT o_orderkey, strftime(o_orderdate, '%Y-%m-%d') AS d, year(o_orderdate)::BIGINT AS y, quarter(o_orderdate)::BIGINT AS q, hour(o_orderdate)::BIGINT AS h, date_diff('day', DATE '1990-01-01', o_orderdate::DATE)::BIGINT AS n, epoch_us(date_trunc('month', o_orderdate)) AS m, epoch_us(o_orderdate + INTERVAL 36 HOUR) AS later FROM orders")
def h_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return _t(spark, sf_dir, "orders").select(
        "o_orderkey", F.date_format(d, "yyyy-MM-dd").alias("d"), F.year(d).cast("long").alias("y"), F.quarter(d).cast("long").alias("q"), F.hour(d).cast("long").alias("h"),
        F.datediff(F.to_date(d), F.lit("1990-01-01").cast("date")).cast("long").alias("n"), F.unix_micros(F.date_trunc("month", d).cast("timestamp")).alias("m"),
        F.unix_micros((d + F.expr("INTERVAL 36 HOURS")).cast("timestamp")).alias("later"),
    )


@query("SELECT s_suppkey, round(ln(abs(s_acctbal) + 1), 6) AS l, round(sqrt(abs(s_acctbal)), 6) AS s, round(pow(1.01::DOUBLE, s_suppkey % 50), 6) AS p, floor(s_acctbal)::BIGINT AS f, s_suppkey % 7 AS m, greatest(s_acctbal, 0) AS g, round(ln(exp(s_acctbal / 10000) + exp(-s_acctbal / 10000)), 6) AS lse FROM supplier")
def h_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = F.col("s_acctbal")
    return _t(spark, sf_dir, "supplier").select(
        "s_suppkey", F.round(F.log(F.abs(b) + 1), 6).alias("l"), F.round(F.sqrt(F.abs(b)), 6).alias("s"), F.round(F.pow(F.lit(1.01), F.col("s_suppkey") % 50), 6).alias("p"),
        F.floor(b).alias("f"), F.pmod("s_suppkey", F.lit(7)).alias("m"), F.greatest(b, F.lit(0.0)).alias("g"), F.round(F.log(F.exp(b / 10000) + F.exp(-b / 10000)), 6).alias("lse"),
    )


@query("SELECT rec, array_to_string(list_sort(list_distinct(a)), '|') AS d, len(list_intersect(list_distinct(a), ['click', 'view']))::BIGINT AS i, list_contains(a, 'error') AS e, a[1] AS f, array_to_string(a[2:3], '|') AS s, list_has_any(a, ['signup']) AS o FROM (SELECT user_id AS rec, list(event_type ORDER BY ts, event_id) AS a FROM events GROUP BY 1)")
def h_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    a = e.groupBy(F.col("user_id").alias("rec")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("s")).select("rec", F.col("s.event_type").alias("a"))
    both = F.array(F.lit("click"), F.lit("view"))
    return a.select(
        "rec", F.array_join(F.array_sort(F.array_distinct("a")), "|").alias("d"), F.size(F.array_intersect("a", both)).cast("long").alias("i"), F.array_contains("a", "error").alias("e"),
        F.element_at("a", 1).alias("f"), F.array_join(F.slice("a", 2, 2), "|").alias("s"), F.arrays_overlap("a", F.array(F.lit("signup"))).alias("o"),
    )


@query("SELECT user_id, event_type AS k, count(*)::BIGINT * 10 AS v FROM events GROUP BY 1, 2 HAVING count(*) > 1")
def h_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _t(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    kept = F.transform_values(F.map_filter("m", lambda k, v: v > 1), lambda k, v: v * 10)
    return m.select("user_id", F.explode(kept).alias("k", "v"))


@query("SELECT event_id, json_extract_string(props, '$.k') AS k, (json_extract_string(props, '$.k')::BIGINT + 1)::BIGINT AS k1 FROM events")
def h_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _t(spark, sf_dir, "events", "event_id", "props")
    return e.select("event_id", F.get_json_object("props", "$.k").alias("k"), (F.from_json("props", "k bigint")["k"] + 1).alias("k1"))


@query("SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def h_variant(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _t(spark, sf_dir, "events", "event_id", "props").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 5) AS n2, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS pos, list_max(embedding) > 1 AS big FROM embeddings")
def h_hof(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("embedding")
    return _t(spark, sf_dir, "embeddings").select(
        "vec_id", F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + x.cast("double") * x), 5).alias("n2"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("pos"),
        F.exists(v, lambda x: x > 1).alias("big"),
    )


@query(r"SELECT a.n_name AS a, b.n_name AS b, round(len(list_intersect(regexp_split_to_array(lower(a.n_name), '[^\p{L}\p{N}]+'), regexp_split_to_array(lower(b.n_name), '[^\p{L}\p{N}]+')))::DOUBLE / len(list_distinct(list_concat(regexp_split_to_array(lower(a.n_name), '[^\p{L}\p{N}]+'), regexp_split_to_array(lower(b.n_name), '[^\p{L}\p{N}]+')))), 6) AS j FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def h_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = _t(spark, sf_dir, "nation")
    b = n.select(F.col("n_name").alias("b"), "n_regionkey", F.col("n_nationkey").alias("kb"))
    return n.join(b, "n_regionkey").where("n_nationkey < kb").select(F.col("n_name").alias("a"), "b", F.round(jaccard(F.col("n_name"), F.col("b")), 6).alias("j"))


@query()
def i_udx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Registered functions from SQL: similarities, an aggregate and a table function."""
    udx.register(spark)
    v = {"p": _t(spark, sf_dir, "part"), "e": _t(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))}
    a = spark.sql("SELECT 'dice' AS f, avg(ngram_dice(p_name, p_type)) AS v FROM {p} UNION ALL SELECT 'jaro', avg(jaro_winkler(p_name, p_type)) FROM {p}", **v)
    g = spark.sql("SELECT 'gini' AS f, avg(g) AS v FROM (SELECT user_id, weighted_gini(n) AS g FROM {e} GROUP BY user_id)", **v)
    s = spark.sql("SELECT 'subsets' AS f, CAST(count(*) AS DOUBLE) AS v FROM k_subset_rows(array('a', 'b', 'c'), 2)")
    j = spark.sql("SELECT 'calls' AS f, CAST(count(*) AS DOUBLE) AS v FROM js_nodes('f(g(x), h(k(y)));') WHERE kind = 'call'")
    return a.unionByName(g).unionByName(s).unionByName(j)


# --- batch twins of the streams ---------------------------------------------------------------


@query("SELECT epoch_us(date_trunc('day', ts)) AS start_us, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def j_tumble(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.tumble(_t(spark, sf_dir, "events")).select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "event_type", "n")


@query("SELECT (epoch_us(ts) // 21600000000 - i) * 21600000000 AS start_us, event_type, count(*)::BIGINT AS n FROM events, range(4) r(i) GROUP BY 1, 2")
def j_slide(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.slide(_t(spark, sf_dir, "events")).select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "event_type", "n")


@query("SELECT user_id, min(t) AS start_us, count(*)::BIGINT AS n FROM (SELECT user_id, t, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id) AS s FROM (SELECT user_id, event_id, epoch_us(ts) AS t, (coalesce(epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id), 1e18) >= 43200000000)::INT AS fresh FROM events)) GROUP BY user_id, s")
def j_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.session(_t(spark, sf_dir, "events")).select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n")
