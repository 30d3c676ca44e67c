"""Catalogue queries against DuckDB on the smallest tables, plans, sources, streams."""

import re

import pytest
from pyspark.sql import functions as F

from shapeplan.functions.register import register
from shapeplan.sources import io
from shapeplan.sources.graph import ClassTableSource
from shapeplan.sources.mapping import ClassMap, Edge, Mapping
from shapeplan.streaming import events as ev
from shapeplan.workload import catalogue
from shapeplan.workload.testbeds import graph_of
from tests.conftest import SMALL

NAMES = [n for n in catalogue.oracle_sql() if n.startswith((
    "push", "split", "union", "join", "asof", "fn_", "win_", "report", "x", "retrieved", "checks", "capped_misses_naive", "plan_orders_B", "min_R",
    "max_A_Nation", "graph_size", "explain", "work", "cascade", "strata", "fragments", "shape_skew", "demand",
))]


def plain(v):
    return round(v, 6) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, duck, name):
    df = catalogue.queries()[name](spark, SMALL)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    sql = duck.sql(catalogue.oracle_sql()[name])
    assert sorted(sql.columns) == cols
    at = [sql.columns.index(c) for c in cols]
    assert got == sorted(tuple(plain(r[i]) for i in at) for r in sql.fetchall())


@pytest.mark.parametrize("name", [f"{kind}_{s}" for kind in ("degrees", "deps") for s in "RABC"])
def test_references_with_their_links(spark, duck, name):
    df = catalogue.queries()[name](spark, SMALL)
    assert any(f.endswith(".parquet") for f in df.inputFiles())
    test_query(spark, duck, name)


def test_value_tests_reach_the_scan(spark):
    plan = catalogue.queries()["filter_value_test"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "GreaterThanOrEqual(p_size,1)" in plan and "p_name" not in plan.split("ReadSchema")[1]


def test_anti_joins_are_no_nested_loops(spark):
    plan = catalogue.queries()["join_anti_invalid"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "LeftAnti" in plan and "NestedLoop" not in plan


def test_ntriples_escapes(spark):
    none = F.lit(None).cast("string")
    text = 'a "b"\n\\n\r c\\'
    t = spark.createDataFrame([("s", text)], "s string, x string").select(
        "s", F.lit("p").alias("p"),
        F.struct(F.lit("literal").alias("kind"), none.alias("iri"), F.col("x").alias("lex"), F.lit("string").alias("dt")).alias("o"),
    )
    assert io.from_ntriples(io.to_ntriples(t)).first()["o"]["lex"] == text
    long = (text + "\u2028\x85 <x> .") * 30_000
    assert io.from_ntriples(io.to_ntriples(t.withColumn("o", F.col("o").withField("lex", F.lit(long))))).first()["o"]["lex"] == long


def test_lines_are_read_as_the_pattern_reads_them(spark):
    pattern = re.compile(r'<([^>]*)> <([^>]*)> (?:<([^>]*)>|"(.*)"(?:\^\^<([^>]*)>)?) \.\s*\Z', re.S)
    ends = ["<o>", "<>", "< o >", "<o>x>", "<o", '"l"', '""', '"', '"l"^^<t>', '""^^<t>', '"^^<t>', '"l"^^<>', '"l"^^<t>>', '"a"^^<t>"^^<u>', '"a> <b> "c"^^<t>', '"a"@en', '"\u00e9> \u2028"^^<t>', "x", ""]
    heads = ["<s> <p> ", "<s>  <p> ", "<> <> ", "<s>> <p> ", "<s> <p>> ", "<s> p ", " <s> <p> ", "<s> ", "# <s> <p> ", "<\u00e9 x> <p> ", ""]
    lines = [h + o + e for h in heads for o in ends for e in (" .", ".", " . ", " .\t\r", " . .", "")] + [None, "", "# c", "<"]
    hits = [pattern.match(x) for x in lines if x is not None]
    want = [(m[1], m[2], ("literal", None, m[4], m[5] or None) if m[4] is not None else ("iri", m[3], None, None)) for m in hits if m]
    got = [(r.s, r.p, tuple(r.o)) for r in io.from_ntriples(spark.createDataFrame([(x,) for x in lines], "value string")).collect()]
    assert len(want) > 50 and sorted(got, key=str) == sorted(want, key=str)


def test_triples_written_by_predicate(spark, tmp_path):
    t = graph_of(spark, SMALL, "B")[0].triples(["Nation"])
    io.write_triples(t, str(tmp_path / "t"))
    back = io.read_triples(spark, str(tmp_path / "t"))
    plan = back.where("p = 'n_name'")._jdf.queryExecution().executedPlan().toString()
    assert back.count() == t.count() and "PartitionFilters: [isnotnull(p" in plan


def test_edge_lists_and_sinks(spark, tmp_path):
    (tmp_path / "e.csv").write_text("s,p,o\na,p,x\na,p,x\nb,q,y\n")
    assert sorted((r.s, r.p, r.o.iri) for r in io.read_edges_csv(spark, str(tmp_path / "e.csv")).collect()) == [("a", "p", "x"), ("b", "q", "y")]
    verdicts = spark.createDataFrame([("S", "a", True), ("T", "b", False)], "shape string, entity string, valid boolean")
    io.write_verdicts(verdicts, str(tmp_path / "v"))
    io.write_verdicts(verdicts.where("shape = 'T'").withColumn("valid", F.lit(True)), str(tmp_path / "v"))
    assert {(r.shape, r.valid) for r in spark.read.parquet(str(tmp_path / "v")).collect()} == {("S", True), ("T", True)}
    io.write_report(verdicts, str(tmp_path / "r"))
    assert spark.read.json(str(tmp_path / "r")).count() == 2


def test_dief_in_sql(spark):
    register(spark)
    out = spark.sql("SELECT dief(t, 5.0D) AS d FROM VALUES (1.0D), (3.0D), (3.0D) AS x(t)")
    assert out.first()["d"] == 10.0


def test_published_batches(spark, tmp_path):
    spark.read.parquet(f"{SMALL}/events.parquet").repartition(2).write.parquet(str(tmp_path / "in"))
    seen = []
    q = ev.publish(
        ev.read_events(spark, str(tmp_path / "in")).withColumn("ok", ev.conforms()), str(tmp_path / "out"), str(tmp_path / "at"),
        lambda batch, n: seen.append(n),
    ).start()
    q.processAllAvailable()
    q.stop()
    assert spark.read.parquet(str(tmp_path / "out")).count() == spark.read.parquet(str(tmp_path / "in")).count() and seen == [0, 1]


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SMALL}/events.parquet")
    events.withColumn("ts", F.col("ts").cast("timestamp")).repartition(3).write.parquet(str(tmp_path / "in"))
    q = ev.tumbling(ev.read_events(spark, str(tmp_path / "in"))).writeStream.format("memory").queryName("windows").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    batch = ev.tumbling(spark.read.parquet(str(tmp_path / "in")))
    assert sorted(map(tuple, spark.table("windows").collect())) == sorted(map(tuple, batch.collect()))


def test_stateful_alerts(spark, tmp_path):
    spark.read.parquet(f"{SMALL}/events.parquet").repartition(3).write.parquet(str(tmp_path / "in"))
    q = ev.max_count_alerts(ev.read_events(spark, str(tmp_path / "in")), "error", 12).writeStream.format("memory").queryName("alerts").outputMode("append").start()
    q.processAllAvailable()
    q.stop()
    per = spark.read.parquet(str(tmp_path / "in")).where("event_type = 'error'").groupBy("user_id").count().where("count > 12")
    assert {r[0] for r in spark.table("alerts").collect()} == {r[0] for r in per.collect()}


def test_triples_are_a_set_and_no_triple_is_shuffled(spark):
    g = graph_of(spark, SMALL, "B")[0]
    twice = type(g)(lambda name: g.read(name).unionByName(g.read(name)), g.mapping)
    for classes in (["Nation", "OrderLine"], ["Customer", "Part", "Customer"]):
        once, both = g.triples(classes), twice.triples(classes)
        assert once.count() == once.distinct().count() == both.count() and both.exceptAll(once).isEmpty()
    plan = g.triples(["OrderLine"])._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_repeats_go_before_rows_become_triples(spark):
    plan = graph_of(spark, SMALL, "B")[0].triples(["OrderLine"])._jdf.queryExecution().executedPlan().toString()
    assert plan.rindex("Generate") < plan.index("Aggregate")


def test_triples_of_values_that_differ_or_miss(spark):
    rows = spark.createDataFrame([(1, 2, 0.0, "a"), (1, 2, -0.0, None), (1, 3, 0.0, "a"), (2, None, None, None), (None, 4, 1.0, "b")], "k int, link int, x double, y string")
    edge = lambda v: Edge("t", "k", v)
    for single, multi in (({"link": "link", "x": "x", "y": "y"}, {}), ({}, {"link": edge("link"), "x": edge("x"), "y": edge("y")}), ({"link": "link"}, {"x": Edge("t", "k", "x", "k > 0"), "y": Edge("t", "k", "y", "k < 9")})):
        g = ClassTableSource(lambda name: rows, Mapping({"C": ClassMap("t", "k", single, multi, True)}, {"link": "D"}))
        got = sorted((r.s, r.p, r.o.kind, r.o.iri or r.o.lex, r.o.dt or "") for r in g.triples().collect())
        assert got == [
            ("C/1", "link", "iri", "D/2", ""), ("C/1", "link", "iri", "D/3", ""), ("C/1", "type", "iri", "C", ""), ("C/1", "x", "literal", "-0.0", "double"),
            ("C/1", "x", "literal", "0.0", "double"), ("C/1", "y", "literal", "a", "string"), ("C/2", "type", "iri", "C", ""),
        ]
