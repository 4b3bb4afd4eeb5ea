"""Round trips of formats, and plans."""

from pyspark.sql import functions as F

from opatlas.operators import serve
from opatlas.queries.relational import f_scan, g_semi
from opatlas.queries.serving import kb
from opatlas.queries.taxonomy import a_tfidf
from opatlas.sources import io, parse

SF = "/root/testdata/sf0.001"


def plan(df) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_formats(spark, tmp_path):
    df = io.read(spark, SF, "nation")
    for fmt in ("parquet", "orc", "json", "csv"):
        path = str(tmp_path / fmt)
        io.write(df, path, fmt)
        back = {
            "json": lambda: io.read_json(spark, path, df.schema), "csv": lambda: io.read_csv(spark, path, df.schema),
        }.get(fmt, lambda: spark.read.format(fmt).load(path))()
        assert sorted(map(tuple, back.collect())) == sorted(map(tuple, df.collect()))


def test_broken_json_is_kept(spark, tmp_path):
    (tmp_path / "r.json").write_text('{"overall": "x", "steps": []}\n{"overall": \n')
    got = io.read_json(spark, str(tmp_path / "r.json"), io.REPLY).collect()
    assert [r._corrupt_record is None for r in got] == [True, False]


def test_whole_files(spark, tmp_path):
    (tmp_path / "a.js").write_text("f(g(x));\nm(z);")
    assert io.read_files(spark, str(tmp_path), "*.js").count() == 1
    text = io.read_text(spark, str(tmp_path / "a.js"), whole=True).select(F.lit("a").alias("script_id"), F.col("value").alias("source"))
    assert parse.to_nodes(text, "js").where("kind = 'call'").count() == 3


def test_partitioned_kb_is_pruned(spark, tmp_path):
    io.write(kb(spark, SF), str(tmp_path / "kb"), partition_by=["l1"])
    back = spark.read.parquet(str(tmp_path / "kb"))
    got = serve.combos_for(back, l1="ASIA")
    assert "PartitionFilters: [isnotnull(l1" in plan(got)
    assert got.count() == serve.combos_for(kb(spark, SF), l1="ASIA").count()


def test_bucketed_join_needs_no_exchange(spark):
    for t, k in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        io.write_bucketed(io.read(spark, SF, t), f"b_{t}", 4, [k])
    a, b = spark.table("b_orders").hint("merge"), spark.table("b_lineitem")
    assert "Exchange" not in plan(a.join(b, a["o_orderkey"] == b["l_orderkey"]))
    for t in ("orders", "lineitem"):
        spark.sql(f"DROP TABLE b_{t}")


def test_plans(spark):
    p = plan(f_scan(spark, SF))
    assert "PushedFilters: [IsNotNull(l_shipdate), LessThan(l_shipdate" in p and "l_extendedprice" not in p
    assert "LeftSemi" in plan(g_semi(spark, SF))
    assert not any(x in plan(a_tfidf(spark, SF)) for x in ("Python", "Pandas", "Arrow"))
