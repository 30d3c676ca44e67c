"""Engines agree with each other, with DuckDB and with the published-style golden numbers; micro fixtures."""

import pytest
from pyspark.sql import functions as F

from shapeplan.execute import validate
from shapeplan.execute.engines import cascade, decision_order, equivalent, interleave
from shapeplan.execute.grounding import n_rules
from shapeplan.measure import trace as tr
from shapeplan.measure import work
from shapeplan.model import UnsupportedFragment, load_schema, schema_from_dict
from shapeplan.operators.compile import max_query, min_query
from shapeplan.operators.rewrite import Limits, RewriteConfig, choose_list, filter_edges, sliced, slices, split_filter
from shapeplan.plans.depgraph import dependency_graph
from shapeplan.plans.order import CONFIGS, PlanConfig, traverse
from shapeplan.sources import TripleSource, class_tables
from shapeplan.sources.stats import graph_stats
from shapeplan.workload import catalogue
from shapeplan.workload import reference_sql as ref
from shapeplan.workload.testbeds import Testbed, graph_of, run_matrix, testbeds, times_table
from tests.conftest import SMALL

GOLD = {("A", "L0"): 1534, ("A", "L2"): 650, ("A", "L3"): 162, ("B", "L1"): 3782, ("B", "L3"): 638, ("C", "L0"): 2685, ("C", "L2"): 1458}


@pytest.mark.parametrize(("schema", "level"), GOLD)
def test_golden(spark, duck, schema, level):
    g, s = graph_of(spark, SMALL, schema, level)
    out = sorted(map(tuple, validate(g, s, "fused").summary().collect()))
    assert sum(r[2] for r in out) == GOLD[schema, level]
    assert out == sorted(duck.sql(ref.summary(g.mapping, s)).fetchall())


@pytest.mark.parametrize("engine", ["naive", "naive_py", "planned"])
def test_engines_agree(spark, engine):
    g, s = graph_of(spark, SMALL, "A", "L2")
    assert equivalent(validate(g, s, engine).verdicts, validate(g, s, "fused").verdicts).isEmpty()


@pytest.mark.parametrize("config", [PlanConfig("random", seed=2), PlanConfig("links", start="OrderLine"), 7])
def test_order_does_not_matter(spark, config):
    g, s = graph_of(spark, SMALL, "R", "L3")
    expected = sorted(map(tuple, validate(g, s, "fused").summary().collect()))
    for rewrite in (RewriteConfig(), RewriteConfig(push=False, skip=False, reorder=False)):
        assert sorted(map(tuple, validate(g, s, "planned", config, rewrite).summary().collect())) == expected


def test_interleaved_delivery(spark):
    g, s = graph_of(spark, SMALL, "A", "L1")
    parts = [p.select("shape").distinct().collect()[0][0] for p in interleave(g, s)]
    assert sorted(parts) == ["Customer", "Nation", "Order"]


def test_rule_counts(spark):
    g, s = graph_of(spark, SMALL, "A", "L3")
    v = validate(g, s, "fused").valid
    assert work.count_rules(g, s).first()[0] == 4089
    assert work.count_rules(g, s, ["Nation", "Customer", "Order"], v).first()[0] == 809


def test_27_beds():
    assert len(testbeds()) == 27


def triples(spark, rows):
    none = F.lit(None).cast("string")
    return TripleSource(spark.createDataFrame(rows, "s string, p string, v string").select(
        "s", "p", F.struct(F.lit("iri").alias("kind"), F.col("v").alias("iri"), none.alias("lex"), none.alias("dt")).alias("o"),
    ))


def shape(constraints, target="T", name="S"):
    return {"name": name, "target": target, "constraints": constraints}


def run(g, *shapes, engine="fused", **how):
    s = schema_from_dict({"name": "t", "shapes": list(shapes)})
    return {(r.shape, r.entity): r.valid for r in validate(g, s, engine, **how).verdicts.collect()}


#: b links to y, which doesn't conform, and c to a node of no class; x and z conform, so the list of the others is the shorter one.
DANGLING = [(e, "type", "T") for e in "abc"] + [(e, "type", "U") for e in "xyz"] + [
    ("x", "q", "1"), ("z", "q", "1"), ("a", "r", "x"), ("a", "r", "y"), ("b", "r", "y"), ("c", "r", "lost"),
]
REFER = shape([{"path": "r", "min": 1, "ref": "V"}, {"path": "r", "max": 3, "ref": "V"}]), shape([{"path": "q", "min": 1}], "U", "V")
DANGLING_WAYS = [("fused", {}), ("naive", {}), ("naive_py", {}), ("grounded", {})] + [("planned", {"config": k}) for k in CONFIGS]
DANGLING_WAYS += [("planned", {"config": 1, "rewrite": RewriteConfig(lists=x, split=y), "limits": Limits(max_filter_items=1, literal_items=z)}) for x in ("smaller", "invalid", "valid") for y, z in ((False, 10), (True, 10), (False, 0))]


@pytest.mark.parametrize(("engine", "how"), DANGLING_WAYS)
def test_links_that_leave_the_domain(spark, engine, how):
    out = run(triples(spark, DANGLING), *REFER, engine=engine, **how)
    assert {e for (s, e), ok in out.items() if ok} == {"a", "x", "z"}


def test_dangling_links_in_class_tables(spark, duck):
    m, s = catalogue._dangling_mapping(), load_schema("R")
    g = class_tables(spark, SMALL, m)
    want = sorted(duck.sql(ref.summary(m, s)).fetchall())
    stats = graph_stats(g, s)
    assert not stats.closed("OrderLine", "l_suppkey") and stats.closed("Supplier", "s_nationkey")
    for engine, how in (("fused", {}), ("planned", {"stats": stats}), ("planned", {"rewrite": RewriteConfig(lists="invalid")})):
        assert sorted(map(tuple, validate(g, s, engine, **how).summary().collect())) == want


SWITCHES = [{"push": False}, {"reorder": False}, {"skip": False}, {"slice": True}, {"split": True}, {"lists": "invalid"}, {"lists": "valid"}]


@pytest.mark.parametrize("switch", SWITCHES)
def test_a_switch_changes_the_plan_and_never_the_verdict(spark, switch):
    g, s = graph_of(spark, SMALL, "A", "L2")
    limits, stats = Limits(slice_rows=700, max_filter_items=30), graph_stats(g, s)
    base = validate(g, s, "planned", 2, RewriteConfig(), limits, stats=stats)
    other = validate(g, s, "planned", 2, RewriteConfig(**switch), limits, stats=stats)
    assert equivalent(base.verdicts, other.verdicts).isEmpty()
    if "reorder" not in switch and switch != {"lists": "valid"}:
        assert other.measures != base.measures
    if "slice" in switch:
        assert len(other.trace) > len(base.trace) and sum(n for *_, n in other.trace) == sum(n for *_, n in base.trace)


def test_adaptive_order_and_sorted_verdicts(spark):
    g, s = graph_of(spark, SMALL, "R", "L3")
    r = validate(g, s, "planned", adaptive=True, ordered=True)
    assert equivalent(r.verdicts, validate(g, s, "fused").verdicts).isEmpty() and sorted(r.order) == sorted(s.names)
    rows = [(v.shape, v.entity) for v in r.verdicts.collect()]
    assert rows == sorted(rows)


def test_naive_reports_the_order_that_it_ran(spark):
    g, s = graph_of(spark, SMALL, "A", "L2")
    for k, c in CONFIGS.items():
        want = [n for p in decision_order(dependency_graph(s), traverse(dependency_graph(s), c)) for n in p]
        assert validate(g, s, "naive", k).order == want == ["Nation", "Customer", "Order"]
    traced = validate(g, s, "naive", 9, traced=True)
    assert [n for n, *_ in traced.trace] == traced.order and sum(n for *_, n in traced.trace) == 25 + 150 + 1500
    dep = dependency_graph(load_schema("B"))
    assert [p[0] for p in decision_order(dep, ["OrderLine", "Part", "Order", "Supplier", "Customer", "Nation", "Region"])] == ["Part", "Region", "Nation", "Supplier", "Customer", "Order", "OrderLine"]


@pytest.mark.parametrize("engine", ["naive", "naive_py", "grounded"])
def test_baselines_refuse_what_they_lack(spark, engine):
    with pytest.raises(UnsupportedFragment):
        validate(*graph_of(spark, SMALL, "X3"), engine)


def test_rules_counted_while_running(spark):
    g, s = graph_of(spark, SMALL, "A", "L3")
    valid = validate(g, s, "fused").valid
    for engine, config in (("planned", 5), ("planned", 2), ("grounded", 5)):
        r = validate(g, s, engine, config, count=True)
        assert n_rules(r) == work.count_rules(g, s, traverse(dependency_graph(s), CONFIGS[config]), valid).first()[0]
    assert n_rules(validate(g, s, "grounded", 5, RewriteConfig(push=False))) == work.count_rules(g, s, ["Customer", "Nation", "Order"], valid, push=False).first()[0]
    assert r.measures["Order"]["prefiltered"] > 0


def test_capped_endpoint(spark, duck):
    g, s = graph_of(spark, SMALL, "A", "L1")
    exact = validate(g, s, "fused").verdicts
    naive = validate(g, s, "naive", limits=Limits(answer_cap=300)).verdicts
    assert sorted(map(tuple, naive.collect())) == sorted(duck.sql(ref.capped(g.mapping, s, 300)).fetchall())
    assert not equivalent(exact, naive).isEmpty()
    planned = validate(g, s, "planned", rewrite=RewriteConfig(slice=True), limits=Limits(answer_cap=300))
    assert equivalent(exact, planned.verdicts).isEmpty() and planned.measures["Order"]["slices"] >= 5
    assert not equivalent(exact, validate(g, s, "planned", limits=Limits(answer_cap=300)).verdicts).isEmpty()


def test_slices_are_delivered_one_by_one(spark):
    g, s = graph_of(spark, SMALL, "A", "L1")
    parts = list(interleave(g, s, rewrite=RewriteConfig(slice=True), limits=Limits(slice_rows=600)))
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    assert len(parts) >= 5 and equivalent(whole, validate(g, s, "fused").verdicts).isEmpty()


def test_many_slices_share_a_job(spark):
    g, s = graph_of(spark, SMALL, "A", "L1")
    how = {"rewrite": RewriteConfig(slice=True), "limits": Limits(answer_cap=40)}
    result = validate(g, s, "planned", **how)
    assert equivalent(validate(g, s, "fused").verdicts, result.verdicts).isEmpty()
    assert result.measures["Order"]["slices"] >= 38 and len(result.trace) <= 20


def test_depth_of_a_cascade(spark):
    rows = [(e, "type", t) for t, es in (("T", "abc"), ("U", "xy"), ("W", "w")) for e in es] + [
        ("x", "r", "w"), ("a", "r", "x"), ("b", "r", "y"), ("a", "p", "1"), ("b", "p", "1"), ("x", "p", "1"), ("y", "p", "1"),
    ]
    shapes = shape([{"path": "p", "min": 1}, {"path": "r", "min": 1, "ref": "V"}]), shape(
        [{"path": "p", "min": 1}, {"path": "r", "min": 1, "ref": "X"}], "U", "V",
    ), shape([{"path": "q", "min": 1}], "W", "X")
    s = schema_from_dict({"name": "t", "shapes": list(shapes)})
    g = triples(spark, rows)
    got = {(r.shape, r.entity): r.depth for r in cascade(g, s, validate(g, s, "fused")).collect()}
    assert got == {("X", "w"): 0, ("V", "x"): 1, ("V", "y"): 0, ("S", "a"): 2, ("S", "b"): 1, ("S", "c"): 0}


def test_matrix_and_times(spark):
    rows = list(run_matrix(spark, [Testbed("A", SMALL, "L1")], [("naive", "naive", 5), ("planned_5", "planned", 5)], runs=2))
    assert [(r[0], r[1], r[2]) for r in rows] == [("A-sf0.001-L1", e, k) for e in ("naive", "planned_5") for k in (0, 1)]
    out = {r.engine: r for r in tr.times(times_table(spark, rows), ["testbed", "engine"]).collect()}
    mean = sum(r[3] for r in rows[:2]) / 2
    assert out["naive"].n_runs == 2 and out["naive"].mean_s == pytest.approx(mean) and out["naive"].sd_s == pytest.approx(abs(rows[0][3] - rows[1][3]) / 2**0.5)


@pytest.mark.parametrize("engine", ["fused", "planned", "naive", "grounded"])
def test_thresholds_and_set_semantics(spark, engine):
    rows = [(e, "type", "T") for e in ("a", "b", "c")] + [("a", "p", "1"), ("a", "p", "1"), ("b", "p", "1"), ("b", "p", "2"), ("c", "p", "1"), ("c", "p", "2"), ("c", "p", "3")]
    out = run(triples(spark, rows), shape([{"path": "p", "min": 2, "max": 2}]), engine=engine)
    assert out == {("S", "a"): False, ("S", "b"): True, ("S", "c"): False}


@pytest.mark.parametrize("engine", ["fused", "planned", "naive", "grounded"])
def test_one_good_link_is_enough(spark, engine):
    rows = [
        ("a", "type", "T"), ("b", "type", "T"), ("x", "type", "U"), ("y", "type", "U"), ("x", "q", "1"), ("a", "r", "x"), ("a", "r", "y"), ("b", "r", "y"),
        ("b", "r", "nowhere"),
    ]
    out = run(triples(spark, rows), shape([{"path": "r", "min": 1, "ref": "V"}]), shape([{"path": "q", "min": 1}], "U", "V"), engine=engine)
    assert out["S", "a"] and not out["S", "b"]


@pytest.mark.parametrize("engine", ["fused", "planned"])
def test_shape_without_target_and_bare_nodes(spark, engine):
    rows = [("a", "type", "T"), ("a", "r", "lone")]
    hub = {"name": "Hub", "target": None, "class": "U", "constraints": [{"path": "q", "max": 0}]}
    assert run(triples(spark, rows), shape([{"path": "r", "min": 1, "ref": "Hub"}]), hub, engine=engine)["S", "a"]


@pytest.mark.parametrize("engine", ["fused", "planned"])
def test_positive_cycle_is_unfounded(spark, engine):
    rows = [("a", "type", "T"), ("b", "type", "T"), ("c", "type", "T"), ("a", "n", "b"), ("b", "n", "a"), ("c", "stop", "1")]
    one = shape([{"or": [{"path": "stop", "min": 1}, {"path": "n", "min": 1, "ref": "S"}]}])
    assert run(triples(spark, rows), one, engine=engine) == {("S", "a"): False, ("S", "b"): False, ("S", "c"): True}


@pytest.mark.parametrize("links", [[], [("c7", "n", "b")]])
def test_chains_and_branches(spark, links):
    """A chain of ten, one broken in the middle, a cycle and a dangling end; with a second link the rounds go link by link."""
    rows = [(f"{x}{i}", "type", "T") for x in "cd" for i in range(10)] + [(e, "type", "T") for e in ("u", "v", "w", "b")]
    rows += [(f"{x}{i}", "n", f"{x}{i + 1}") for x in "cd" for i in range(9)] + [(f"{x}{i}", "ok", "1") for x in "cd" for i in range(10) if (x, i) != ("d", 4)]
    rows += [("c9", "stop", "1"), ("d9", "stop", "1"), ("u", "n", "v"), ("v", "n", "u"), ("w", "n", "lost")] + [(e, "ok", "1") for e in "uvwb"] + links
    one = shape([{"path": "ok", "min": 1}, {"or": [{"path": "stop", "min": 1}, {"path": "n", "min": 1, "ref": "S"}]}])
    good = {*(f"c{i}" for i in range(10)), *(f"d{i}" for i in range(5, 10))}
    for engine in ("fused", "planned"):
        assert {e for (_, e), ok in run(triples(spark, rows), one, engine=engine).items() if ok} == good
        assert {e for (_, e), ok in run(triples(spark, rows), one, engine=engine, unfounded="valid").items() if ok} == good | {"u", "v"}


@pytest.mark.parametrize("engine", ["fused", "planned"])
def test_unfounded_entities_may_conform(spark, engine):
    rows = [(e, "type", "T") for e in "abcd"] + [("a", "n", "b"), ("b", "n", "a"), ("c", "stop", "1"), ("d", "n", "e")]
    one = shape([{"or": [{"path": "stop", "min": 1}, {"path": "n", "min": 1, "ref": "S"}]}])
    assert run(triples(spark, rows), one, engine=engine, unfounded="valid") == {("S", "a"): True, ("S", "b"): True, ("S", "c"): True, ("S", "d"): False}


def test_empty_graph_and_shape_without_constraints(spark):
    assert run(triples(spark, []), shape([{"path": "p", "min": 1}])) == {}
    assert run(triples(spark, [("a", "type", "T")]), shape([])) == {("S", "a"): True}


def test_combinations(spark):
    g = triples(spark, [("a", "type", "T")] + [("a", "p", str(i)) for i in range(4)])
    s = schema_from_dict({"name": "t", "shapes": [shape([{"path": "p", "min": 2, "max": 2}])]})["S"]
    assert min_query(g, s).count() == 6
    assert max_query(g, s, s.counts("max")[0]).count() == 4


def test_choose_list():
    assert choose_list(3, 3) == "valid" and choose_list(4, 3) == "invalid"


@pytest.mark.parametrize("mode", ["valid", "invalid"])
def test_split_lists(spark, mode):
    pairs = spark.createDataFrame([("a", "1"), ("a", "2"), ("b", "2"), ("c", "9")], "entity string, value string")
    nodes = spark.createDataFrame([(str(i),) for i in range(4)], "entity string")
    whole = {r[0] for r in filter_edges(pairs, nodes, mode).select("entity").collect()}
    assert {r[0] for r in split_filter(pairs, nodes, 4, mode, Limits(max_filter_items=1, max_rewritten=8)).collect()} == whole


@pytest.mark.parametrize("strategy", ["offset", "hash", "range"])
def test_slices_cover(spark, strategy):
    rows = spark.range(100).withColumnRenamed("id", "entity")
    got = [r[0] for p in slices(rows, 30, 100, strategy) for r in p.collect()]
    assert sorted(got) == list(range(100))


@pytest.mark.parametrize("strategy", ["hash", "range"])
def test_many_slices_are_one_pass(spark, strategy):
    rows = spark.range(10_000).select(F.when(F.col("id") != 7, F.col("id")).alias("entity"))
    dealt = sliced(rows, 250, strategy)
    assert dealt.count() == 10_000 and dealt.groupBy("slice").count().agg(F.max("count")).first()[0] <= 90
    assert dealt._jdf.queryExecution().optimizedPlan().toString().count("Range (") == 1


@pytest.mark.parametrize("n", [None, 30, 60, 100])
def test_offset_slices_go_on_beyond_the_size_given(spark, n):
    rows = spark.range(100).withColumnRenamed("id", "entity")
    parts = [[r[0] for r in p.collect()] for p in slices(rows, 30, n, "offset")]
    assert [len(p) for p in parts] == [30, 30, 30, 10] and sorted(sum(parts, [])) == list(range(100))


@pytest.mark.parametrize("strategy", ["offset", "hash", "range"])
def test_sliced_queries_return_all_customers(spark, strategy):
    large = "/root/testdata/sf0.1"
    ids = [r.entity for r in catalogue.queries()[f"slices_{strategy}"](spark, large).collect()]
    assert sorted(ids) == sorted(r[0] for r in spark.read.parquet(f"{large}/customer.parquet").select("c_custkey").collect())


def test_dief(spark):
    t = spark.createDataFrame([("e", 1.0, 1), ("e", 3.0, 2), ("e", 3.0, 3)], "engine string, t double, answer_no long")
    assert tr.dief_at_t(t, 5.0, ["engine"]).first()["dief"] == 4.0 + 6.0
    assert tr.dief_at_t(t, 0.5, ["engine"]).isEmpty()
    assert tr.dief_at_t(t, 1.0, ["engine"]).first()["dief"] == 0.0


def test_large_tables_are_not_broadcast_by_the_size_of_their_files(spark):
    g, s = graph_of(spark, "/root/testdata/sf0.1", "R")
    rows = min_query(g, s["OrderLine"])._jdf.queryExecution().executedPlan().toString()
    assert rows.count("SortMergeJoin") >= 5 and rows.count("BroadcastExchange") <= 2


def test_what_baselines_refer_to_is_written(spark):
    g, s = graph_of(spark, SMALL, "B", "L2")
    files = validate(g, s, "naive").valid["OrderLine"].inputFiles()
    assert any("/valid-Order-" in f for f in files) and not any("customer.parquet" in f for f in files)


@pytest.mark.parametrize(("schema", "engine"), [("X2", "planned"), ("R", "naive"), ("B", "naive"), ("B", "fused"), ("B", "planned")])
def test_large_sides_are_not_broadcast_by_their_shuffled_bytes(spark, monkeypatch, schema, engine):
    from shapeplan import runtime
    from shapeplan.execute import engines

    monkeypatch.setattr(runtime, "SMALL_FILES", -1)  # every side counts as large
    monkeypatch.setattr(runtime, "SMALL_ROWS", -1)
    monkeypatch.setattr(engines, "SMALL_ROWS", -1)
    held = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", str(1 << 30))
    made = spark._jsparkSession.sharedState().statusStore()
    before = made.executionsCount()
    try:
        g, s = graph_of(spark, SMALL, schema, "L2")
        result = validate(g, s, engine, limits=Limits(broadcast_bytes=0, literal_items=0))
        result.verdicts.collect()
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        plans = [made.executionsList().apply(i).physicalPlanDescription() for i in range(before, made.executionsCount())]
        assert plans and not [p for p in plans if "BroadcastExchange" in p]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)


def test_naive_decides_each_shape_in_a_job_of_its_own(spark):
    g, s = graph_of(spark, SMALL, "B", "L2")
    plan = validate(g, s, "naive").summary()._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan
