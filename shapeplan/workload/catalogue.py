"""All queries over the given tables by name, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

import json
from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from shapeplan.execute import validate
from shapeplan.execute.endpoint import misclassified
from shapeplan.execute.engines import cascade, equivalent, explain
from shapeplan.execute.grounding import n_rules
from shapeplan.functions.register import register
from shapeplan.measure import trace as tr
from shapeplan.measure import work
from shapeplan.model import Count, ShapeSchema, UnsupportedFragment, load_schema
from shapeplan.operators import compile as q
from shapeplan.operators import relational as rel
from shapeplan.operators.rewrite import OFF, Limits, RewriteConfig, filter_edges, push_filter, sliced, slices, split_filter
from shapeplan.plans.depgraph import classify, degrees, dependencies, strata
from shapeplan.plans.order import CONFIGS, PlanConfig, plan_orders, plan_validation
from shapeplan.runtime import scratch_path, table, written
from shapeplan.sources import TripleSource, class_tables
from shapeplan.sources import io as graph_io
from shapeplan.sources.mapping import corrupted, default_mapping
from shapeplan.sources.stats import class_stats, graph_size, graph_stats, predicate_stats, schema_classes
from shapeplan.streaming import events as ev
from shapeplan.workload import evidence
from shapeplan.workload import reference_sql as ref
from shapeplan.workload.testbeds import graph_of, measured

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def _add(name: str, run: Query, sql: str | None = None) -> None:
    _queries[name] = run
    if sql is not None:
        _sql[name] = sql


def _mapping(schema: str, level: str):
    s = load_schema(schema)
    return corrupted(default_mapping(s.options.get("line_key", "line")), level, schema == "C"), s


def _values(rows: list[tuple], cols: str) -> str:
    lit = lambda x: "TRUE" if x is True else "FALSE" if x is False else str(x) if isinstance(x, (int, float)) else f"'{x}'"
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) t({cols})"


# Verdicts and summaries of the workloads by every engine.


def _verdicts(schema: str, level: str, engine: str, config, spark: SparkSession, sf_dir: str) -> DataFrame:
    return validate(*graph_of(spark, sf_dir, schema, level), engine, config).verdicts


def _summary(schema: str, level: str, engine: str, config, spark: SparkSession, sf_dir: str) -> DataFrame:
    return validate(*graph_of(spark, sf_dir, schema, level), engine, config).summary()


def _needed(schema: ShapeSchema, shape: str) -> ShapeSchema:
    """The schema of a shape and all that it refers to, directly or not."""
    need, todo = set(), [shape]
    while todo:
        name = todo.pop()
        if name not in need:
            need.add(name)
            todo += schema[name].refs
    return ShapeSchema(schema.name, tuple(s for s in schema.shapes if s.name in need), schema.options)


def _valid(schema: str, shape: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts of the fused engine, and once more each one in which another engine differs from it.

    The naive one is left out of C: the combinations of an order line's values grow with the product of its seventeen constraints.
    """
    g, s = graph_of(spark, sf_dir, schema)
    s = _needed(s, shape)
    # Traced, so that each shape has a job of its own and the driver's plans stay small.
    fused = out = written(validate(g, s, "fused", traced=True).of(shape), "fused")
    for engine in ("planned",) if schema == "C" else ("naive", "planned"):
        # Written, as a comparison looks at both sides twice.
        other = written(validate(g, s, engine).of(shape), engine)
        out = out.unionByName(equivalent(fused, other).drop("side"))
    return out


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _verdicts("A", "L0", "planned", 5, spark, sf_dir)


for _s, _l in [("A", "L0"), ("A", "L1"), ("A", "L2"), ("A", "L3"), ("B", "L0"), ("B", "L2"), ("C", "L0"), ("C", "L2"), ("R", "L3")]:
    _add(f"verdicts_{_s}_{_l}", partial(_verdicts, _s, _l, "fused", 5), ref.verdicts(*_mapping(_s, _l)))
for _s, _l, _engines in [("A", "L2", ("naive", "naive_py", "fused", "planned")), ("B", "L2", ("naive", "fused", "planned")), ("C", "L2", ("fused", "planned")), ("R", "L3", ("naive", "fused", "planned")), ("B_low", "L0", ("fused", "planned")), ("star", "L2", ("naive", "planned"))]:
    for _e in _engines:
        _add(f"summary_{_s}_{_l}_{_e}", partial(_summary, _s, _l, _e, 5), ref.summary(*_mapping(_s, _l)))
for _k in CONFIGS:
    _add(f"summary_A_L3_planned_{_k}", partial(_summary, "A", "L3", "planned", _k), ref.summary(*_mapping("A", "L3")))
for _name, _c in (("links", PlanConfig("links", start="OrderLine")), ("random", PlanConfig("random", seed=1)), ("referenced_first", PlanConfig("referenced_first"))):
    _add(f"summary_R_L3_{_name}", partial(_summary, "R", "L3", "planned", _c), ref.summary(*_mapping("R", "L3")))
for _s in "RABC":
    for _shape in load_schema(_s).names:
        _add(f"valid_{_s}_{_shape}", partial(_valid, _s, _shape), ref.verdicts(*_mapping(_s, "L0"), _shape))


def _rewrite_off(spark, sf_dir):
    return validate(*graph_of(spark, sf_dir, "R", "L3"), "planned", 5, OFF).summary()


_add("summary_R_L3_order_only", _rewrite_off, ref.summary(*_mapping("R", "L3")))


def _triple_engine(spark, sf_dir):
    """Schema R over triples instead of class tables; entities lose their class prefix in the end."""
    g, schema = graph_of(spark, sf_dir, "R", "L3")
    triples = written(g.triples(["Nation", "Supplier", "Part", "Customer", "Order", "OrderLine"]), "triples")
    out = validate(TripleSource(triples, g.mapping.links), schema, "fused").verdicts
    return out.withColumn("entity", F.substring_index("entity", "/", -1))


_r_map, _r_schema = _mapping("R", "L3")
_add("verdicts_R_triples", _triple_engine, ref.verdicts(_r_map, _r_schema))


def _variant(schema: str, level: str, how: dict, spark, sf_dir):
    g, s = graph_of(spark, sf_dir, schema, level)
    stats = graph_stats(g, s) if how.get("stats") else None
    return validate(g, s, "planned", **how | {"stats": stats}).summary()


for _name, _s, _l, _how in [
    ("stats", "A", "L2", {"stats": True}), ("stats", "R", "L3", {"stats": True}), ("adaptive", "R", "L3", {"adaptive": True}), ("invalid_lists", "R", "L3", {"rewrite": RewriteConfig(lists="invalid")}),
    ("split", "A", "L2", {"rewrite": RewriteConfig(split=True), "limits": Limits(max_filter_items=100)}), ("split_invalid", "A", "L2", {"rewrite": RewriteConfig(split=True, lists="invalid"), "limits": Limits(max_filter_items=200)}),
    ("unsplit", "A", "L2", {"rewrite": RewriteConfig(split=True), "limits": Limits(max_filter_items=5, max_rewritten=2)}), ("sliced", "A", "L2", {"rewrite": RewriteConfig(slice=True), "limits": Limits(slice_rows=4000)}),
    ("no_push", "A", "L2", {"rewrite": RewriteConfig(push=False)}), ("no_reorder", "A", "L2", {"rewrite": RewriteConfig(reorder=False)}), ("no_skip", "A", "L2", {"rewrite": RewriteConfig(skip=False)}),
]:
    _add(f"summary_{_s}_{_l}_planned_{_name}", partial(_variant, _s, _l, _how), ref.summary(*_mapping(_s, _l)))
_add("summary_A_L2_grounded", partial(_summary, "A", "L2", "grounded", 5), ref.summary(*_mapping("A", "L2")))
_add("summary_B_low_L0_naive", partial(_summary, "B_low", "L0", "naive", 5), ref.summary(*_mapping("B_low", "L0")))
_add("verdicts_ordered_A", lambda spark, d: validate(*graph_of(spark, d, "A", "L2"), "planned", ordered=True).verdicts, ref.verdicts(*_mapping("A", "L2")))

# Links that lead nowhere: suppliers and parts are missing, order lines that name them are not.


def _dangling_mapping():
    return default_mapping().without("Supplier", "s_suppkey % 7 = 3").without("Part", "p_partkey % 5 = 1")


def _dangling(how: dict, spark, sf_dir):
    g, s = class_tables(spark, sf_dir, corrupted(_dangling_mapping(), "L2")), load_schema("R")
    stats = graph_stats(g, s) if how.get("stats") else None
    return validate(g, s, how["engine"], rewrite=how.get("rewrite", RewriteConfig()), stats=stats).verdicts


for _name, _how in {"fused": {"engine": "fused"}, "naive": {"engine": "naive"}, "planned": {"engine": "planned"}, "planned_stats": {"engine": "planned", "stats": True}, "planned_invalid_lists": {"engine": "planned", "rewrite": RewriteConfig(lists="invalid")}}.items():
    _add(f"verdicts_dangling_{_name}", partial(_dangling, _how), ref.verdicts(corrupted(_dangling_mapping(), "L2"), load_schema("R")))


def _agree(spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "A", "L2")
    return equivalent(validate(g, s, "fused").verdicts, validate(g, s, "naive").verdicts)


_add("verdict_diff", _agree, "SELECT 'A' AS shape, '' AS entity, TRUE AS valid, 'a' AS side WHERE FALSE")


def _explained(spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "A", "L2")
    return explain(g, s, validate(g, s, "fused"), "Customer").groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


_add("explain_A_Customer", _explained, """
WITH n AS (SELECT n_nationkey AS k FROM nation WHERE n_name IS NOT NULL AND n_nationkey % 25 >= 6),
c AS (SELECT *, CASE WHEN c_custkey % 100 < 25 THEN NULL ELSE c_acctbal END AS bal FROM customer)
SELECT CASE WHEN bal IS NULL OR bal < 0 THEN 'c_acctbal min 1 [value >= 0]' ELSE 'c_nationkey min 1 -> Nation' END AS reason, count(*) AS n
FROM c WHERE bal IS NULL OR bal < 0 OR c_nationkey NOT IN (SELECT k FROM n) GROUP BY 1
""")

_add("cascade_A", lambda spark, d: cascade(*graph_of(spark, d, "A", "L2"), validate(*graph_of(spark, d, "A", "L2"), "fused")), f"""
{ref.valid_ctes(*_mapping("A", "L2"))},
n AS (SELECT n_nationkey AS e, 0 AS depth FROM nation WHERE n_nationkey NOT IN (SELECT entity FROM valid_Nation)),
c AS (SELECT c_custkey AS e, CASE WHEN c_custkey % 100 < 25 OR c_acctbal < 0 THEN 0 ELSE n.depth + 1 END AS depth FROM customer LEFT JOIN n ON n.e = c_nationkey WHERE c_custkey NOT IN (SELECT entity FROM valid_Customer)),
l AS (SELECT l_orderkey AS k, count(DISTINCT l_linenumber) AS n FROM lineitem GROUP BY 1),
o AS (SELECT o_orderkey AS e, CASE WHEN o_orderkey % 100 < 25 OR l.n IS NULL OR l.n > 7 THEN 0 ELSE c.depth + 1 END AS depth
  FROM orders LEFT JOIN c ON c.e = o_custkey LEFT JOIN l ON l.k = o_orderkey WHERE o_orderkey NOT IN (SELECT entity FROM valid_Order))
SELECT 'Nation' AS shape, CAST(e AS VARCHAR) AS entity, depth FROM n UNION ALL SELECT 'Customer', CAST(e AS VARCHAR), depth FROM c UNION ALL SELECT 'Order', CAST(e AS VARCHAR), depth FROM o
""")

# Planning; the expected rows were worked out by hand. Links and entities are those of the given tables.


def _links(name: str, spark, sf_dir) -> DataFrame:
    """``src``, ``dst``, ``path`` of the references of a schema, and how many links of the graph go along each."""
    g, s = graph_of(spark, sf_dir, name)
    ways = {(a.name, leaf.ref, leaf.path): a.entity_class for a in s.shapes for c in a.body for leaf, _ in q.leaves(c) if leaf.ref}
    return reduce(DataFrame.unionByName, [
        g.edges(cls, path).distinct().agg(F.count(F.lit(1)).alias("n_links")).select(F.lit(a).alias("src"), F.lit(b).alias("dst"), F.lit(path).alias("path"), "n_links")
        for (a, b, path), cls in ways.items()
    ])


def _dependencies(name: str, spark, sf_dir) -> DataFrame:
    return dependencies(spark, load_schema(name)).join(_links(name, spark, sf_dir), ["src", "dst", "path"])


def _degrees(name: str, spark, sf_dir) -> DataFrame:
    links = _links(name, spark, sf_dir)
    ends = links.select(F.col("dst").alias("shape"), F.col("n_links").alias("in_links"), F.lit(0).cast("long").alias("out_links")).unionByName(
        links.select(F.col("src").alias("shape"), F.lit(0).cast("long").alias("in_links"), F.col("n_links").alias("out_links")),
    ).groupBy("shape").agg(F.sum("in_links").alias("in_links"), F.sum("out_links").alias("out_links"))
    return degrees(spark, load_schema(name)).join(ends, "shape", "left").fillna(0, ["in_links", "out_links"])


def _links_sql(name: str) -> str:
    m, s = _mapping(name, "L0")
    count = lambda a, path: f"(SELECT count(*) FROM (SELECT DISTINCT entity, value FROM {ref.edges(m, s[a].entity_class, path)} WHERE entity IS NOT NULL AND value IS NOT NULL))"
    ways = dict.fromkeys(x[:3] for x in evidence.DEPENDENCIES[name])
    return " UNION ALL ".join(f"SELECT '{a}' AS src, '{b}' AS dst, '{path}' AS path, {count(a, path)} AS n_links" for a, b, path in ways)


for _s in "RABC":
    _schema = load_schema(_s)
    _add(f"plan_orders_{_s}", lambda spark, d, s=_schema: plan_orders(spark, s), _values(evidence.orders(_s), "config, pos, shape"))
    _degrees_sql = _values([(n, *x, True) for n, x in evidence.DEGREES[_s].items()], "shape, in_deg, out_deg, n_constraints, has_target")
    _add(
        f"degrees_{_s}", partial(_degrees, _s),
        f"WITH l AS MATERIALIZED ({_links_sql(_s)}) SELECT *, (SELECT coalesce(sum(n_links), 0)::BIGINT FROM l WHERE dst = shape) AS in_links, (SELECT coalesce(sum(n_links), 0)::BIGINT FROM l WHERE src = shape) AS out_links FROM ({_degrees_sql})",
    )
    _add(f"deps_{_s}", partial(_dependencies, _s), f"SELECT * FROM ({_values(evidence.DEPENDENCIES[_s], 'src, dst, path, kind, n')}) JOIN ({_links_sql(_s)}) USING (src, dst, path)")


def _fragment(name: str) -> str:
    try:
        return classify(load_schema(name))
    except UnsupportedFragment:
        return "rejected"


def _fragments(spark, sf_dir) -> DataFrame:
    """The fragment of each schema, and how many entities of the given tables it is about."""
    sizes = [class_stats(graph_of(spark, sf_dir, n)[0], schema_classes(load_schema(n))).select(F.lit(n).alias("schema"), "n_entities") for n, _ in evidence.FRAGMENTS]
    found = spark.createDataFrame([(n, _fragment(n)) for n, _ in evidence.FRAGMENTS], "schema string, fragment string")
    return found.join(reduce(DataFrame.unionByName, sizes).groupBy("schema").agg(F.sum("n_entities").alias("n_entities")), "schema")


_add(
    "fragments", _fragments,
    " UNION ALL ".join(
        f"SELECT '{n}' AS schema, '{f}' AS fragment, " + " + ".join(f"(SELECT count(*) FROM {ref.entities(_mapping(n, 'L0')[0], c)})" for c in schema_classes(load_schema(n))) + " AS n_entities"
        for n, f in evidence.FRAGMENTS
    ),
)
_add(
    "strata",
    lambda spark, d: spark.createDataFrame([(s, n, k) for s in ("X4", "A", "R") for n, k in strata(load_schema(s)).items()], "schema string, shape string, level long"),
    _values(evidence.STRATA, "schema, shape, level"),
)


def _udtf(spark, sf_dir):
    register(spark)
    from shapeplan.model.parse import FOLDER

    text = json.dumps(json.loads((FOLDER / "B.json").read_text())).replace("'", "''")
    return spark.sql(f"SELECT * FROM shape_plan('{text}', 5)")


_add("udtf_plan", _udtf, _values(evidence.PLAN_B, "pos, shape, deferred"))

# Target, minimum, maximum and counting queries.

_base = default_mapping()
for _shape in load_schema("C").shapes:
    _add(f"target_{_shape.name}", lambda spark, d, s=_shape: q.target(graph_of(spark, d, "C")[0], s), f"SELECT entity FROM {ref.entities(_base, _shape.target)}")
for _s, _names in (("A", ("Nation", "Customer", "Order")), ("R", ("Supplier", "OrderLine"))):
    for _n in _names:
        _shape = load_schema(_s)[_n]
        _add(f"counts_{_s}_{_n}", lambda spark, d, s=_shape, x=_s: q.counts(graph_of(spark, d, x)[0], s), ref.counts(_base, _shape))
        _add(
            f"min_{_s}_{_n}", lambda spark, d, s=_shape, x=_s: q.min_query(graph_of(spark, d, x)[0], s).select("entity"),
            "SELECT t.entity FROM " + ref.entities(_base, _shape.target) + " t" + "".join(f" JOIN {ref.witnesses(_base, _shape, c, False)} w{k} ON w{k}.entity = t.entity" for k, c in enumerate(_shape.counts("min"))),
        )
        for _k, _c in enumerate(_shape.counts("max"), 1):
            # The given tables break few maxima; one less than the schema's bound has rows to compare.
            _c = Count(_c.path, "max", 3 if _c.n > 3 else _c.n - 1, _c.test, _c.ref)
            _w = ref.witnesses(_base, _shape, _c, False)
            _add(
                f"max_{_s}_{_n}_{_k}", lambda spark, d, s=_shape, x=_s, c=_c: q.max_query(graph_of(spark, d, x)[0], s, c).select("entity").distinct(),
                f"SELECT entity FROM {_w} GROUP BY entity HAVING count(*) > {_c.n}",
            )

_add(
    "demand_R_Nation", lambda spark, d: q.demanded(*graph_of(spark, d, "R"), "Nation"),
    "SELECT s_nationkey AS entity FROM supplier UNION SELECT c_nationkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
)
_add(
    "path_alternative", lambda spark, d: graph_of(spark, d, "B")[0].edges("Nation", "^c_nationkey|^s_nationkey").distinct(),
    "SELECT c_nationkey AS entity, c_custkey AS value FROM customer UNION SELECT s_nationkey, s_suppkey FROM supplier",
)
_add(
    "path_inverse_sequence", lambda spark, d: graph_of(spark, d, "B")[0].edges("Order", "o_custkey/c_nationkey/n_regionkey").distinct(),
    "SELECT DISTINCT o_orderkey AS entity, n_regionkey AS value FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
)

# Rewrites.


def _pushed(mode: str, spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "R", "L3")
    c = next(c for c in s["OrderLine"].counts() if c.ref == "Nation")
    valid = validate(g, s, "fused").valid["Nation"]
    domain = g.entities("Nation")
    known = q.NodeList(mode, valid) if mode == "valid" else q.NodeList(mode, domain.join(valid, "entity", "left_anti"), domain)
    return push_filter(g, s["OrderLine"], g.entities("OrderLine"), c, known).select("entity")


_hub = "SELECT DISTINCT l_orderkey * 16 + l_linenumber AS entity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE c_nationkey % 25 >= 12"
_add("push_valid_list", partial(_pushed, "valid"), _hub)
_add("push_invalid_list", partial(_pushed, "invalid"), _hub)


def _split(mode: str, spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "A", "L2")
    valid = validate(g, s, "fused").valid["Customer"]
    nodes = valid if mode == "valid" else g.entities("Customer").join(valid, "entity", "left_anti")
    n = nodes.count()
    return split_filter(g.edges("Order", "o_custkey"), nodes, n, mode, Limits(max_filter_items=-(-n // 4), max_rewritten=8))


_a_map, _a_schema = _mapping("A", "L2")
_linked = ref.valid_ctes(_a_map, _a_schema, "Customer") + " SELECT o_orderkey AS entity FROM orders WHERE o_custkey IN (SELECT entity FROM valid_Customer)"
_add("union_split_filter", partial(_split, "valid"), _linked)
_add("split_exclusion", partial(_split, "invalid"), _linked)


def _slice(spark, sf_dir):
    rows = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("entity"))
    return rows.orderBy("entity").offset(100).limit(50)


_add("slice_offset", _slice, "SELECT o_orderkey AS entity FROM orders ORDER BY 1 LIMIT 50 OFFSET 100")


def _sliced(strategy: str, spark, sf_dir):
    rows = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("entity"))
    if strategy != "offset":
        return sliced(rows, max(1, -(-rows.count() // 400)), strategy).repartition("slice").select("entity")
    parts = list(slices(rows, 400, strategy=strategy))
    out = parts[0].withColumn("slice", F.lit(0))
    for i, p in enumerate(parts[1:], 1):
        out = out.unionByName(p.withColumn("slice", F.lit(i)))
    return out.select("entity")


for _strategy in ("offset", "hash", "range"):
    _add(f"slices_{_strategy}", partial(_sliced, _strategy), "SELECT c_custkey AS entity FROM customer")


def _edge_join(mode: str, spark, sf_dir):
    g, _ = graph_of(spark, sf_dir, "R", "L3")
    good = table(spark, sf_dir, "supplier").where("s_acctbal >= 0").select(F.col("s_suppkey").alias("entity"))
    bad = table(spark, sf_dir, "supplier").where("s_acctbal < 0").select(F.col("s_suppkey").alias("entity"))
    pairs = g.edges("OrderLine", "l_suppkey")
    return filter_edges(pairs, good if mode == "valid" else bad, mode).select("entity").distinct()


_edge_sql = "SELECT DISTINCT l_orderkey * 16 + l_linenumber AS entity FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_acctbal >= 0"
_add("join_semi_valid", partial(_edge_join, "valid"), _edge_sql)
_add("join_anti_invalid", partial(_edge_join, "invalid"), _edge_sql)

# Measures.


def _rules(schema: str, level: str, order: bool, spark, sf_dir):
    g, s = graph_of(spark, sf_dir, schema, level)
    if not order:
        return work.count_rules(g, s)
    return work.count_rules(g, s, ["Nation", "Customer", "Order"] if schema == "A" else list(plan_validation(s, 5).order), validate(g, s, "fused").valid)


for _s, _l, _o in (("A", "L2", ["Nation", "Customer", "Order"]), ("R", "L3", list(plan_validation(load_schema("R"), 5).order))):
    _add(f"rules_naive_{_s}", partial(_rules, _s, _l, False), ref.rules(*_mapping(_s, _l)))
    _add(f"rules_planned_{_s}", partial(_rules, _s, _l, True), ref.rules(*_mapping(_s, _l), _o))


def _running(schema: str, level: str, engine: str, spark, sf_dir):
    """Rules as an engine counts them while it runs; they are those of the closed form for the order in which shapes were visited."""
    g, s = graph_of(spark, sf_dir, schema, level)
    return spark.createDataFrame([(float(n_rules(validate(g, s, engine, 5, count=True))),)], "n_rules double")


for _e, _s, _l in (("planned", "A", "L2"), ("planned", "R", "L3"), ("grounded", "A", "L2"), ("grounded", "R", "L3")):
    _add(f"rules_running_{_s}_{_e}", partial(_running, _s, _l, _e), ref.rules(*_mapping(_s, _l), list(plan_validation(load_schema(_s), 5).order)))


def _order_only(order: list[str], spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "R", "L3")
    return work.count_rules(g, s, order, validate(g, s, "fused").valid, push=False)


for _name, _order in (("exploiting", "Nation Supplier OrderLine Part"), ("linked", "OrderLine Nation Supplier Part")):
    _add(f"rules_order_only_R_{_name}", partial(_order_only, _order.split()), ref.rules(*_mapping("R", "L3"), _order.split(), push=False))


def _ratio(spark, sf_dir):
    a, b = _rules("A", "L3", False, spark, sf_dir), _rules("A", "L3", True, spark, sf_dir)
    return a.select(F.col("n_rules").alias("naive")).crossJoin(F.broadcast(b.select(F.col("n_rules").alias("planned")))).withColumn(
        "ratio", F.round(F.col("naive") / F.col("planned"), 2),
    )


def _ratio_r(spark, sf_dir):
    a, b = _rules("R", "L3", False, spark, sf_dir), _rules("R", "L3", True, spark, sf_dir)
    return a.select(F.col("n_rules").alias("naive")).crossJoin(F.broadcast(b.select(F.col("n_rules").alias("planned")))).withColumn(
        "ratio", F.round(F.col("naive") / F.col("planned"), 2),
    )


_add(
    "rules_ratio_R", _ratio_r,
    f"SELECT a.n_rules AS naive, b.n_rules AS planned, round(a.n_rules / b.n_rules, 2) AS ratio FROM ({ref.rules(*_mapping('R', 'L3'))}) a, ({ref.rules(*_mapping('R', 'L3'), 'Nation Supplier OrderLine Part'.split())}) b",
)
_add(
    "rules_ratio_A", _ratio,
    f"SELECT a.n_rules AS naive, b.n_rules AS planned, round(a.n_rules / b.n_rules, 2) AS ratio FROM ({ref.rules(*_mapping('A', 'L3'))}) a, ({ref.rules(*_mapping('A', 'L3'), ['Nation', 'Customer', 'Order'])}) b",
)


def _prefiltered(spark, sf_dir):
    g, s = graph_of(spark, sf_dir, "R", "L3")
    return work.prefiltered(g, s, "OrderLine", "l_orderkey/o_custkey/c_nationkey", validate(g, s, "fused").valid["Nation"])


_add("prefiltered_running_example", _prefiltered, f"SELECT (SELECT count(*) FROM {ref.entities(_base, 'OrderLine')}) - (SELECT count(*) FROM ({_hub})) AS n_prefiltered")
def _counters(spark, sf_dir):
    """What a planned run counted: targets that lists dropped, rows left, lists pushed."""
    r = validate(*graph_of(spark, sf_dir, "A", "L3"), "planned", 2)
    rows = [(n, m["prefiltered"], m["rows"], len(m["pushed"]), sum(p[2] for p in m["pushed"])) for n, m in r.measures.items()]
    return spark.createDataFrame(rows, "shape string, prefiltered long, fetched long, lists long, items long")


_add("work_counters_A", _counters, f"""
{ref.valid_ctes(*_mapping("A", "L3"))}
SELECT 'Nation' AS shape, 0::BIGINT AS prefiltered, (SELECT count(*) FROM nation) AS fetched, 0::BIGINT AS lists, 0::BIGINT AS items
UNION ALL SELECT 'Customer', count(*) FILTER (WHERE NOT ok), count(*) FILTER (WHERE ok), 1, (SELECT count(*) FROM valid_Nation) FROM (SELECT c_nationkey IN (SELECT entity FROM valid_Nation) AS ok FROM customer)
UNION ALL SELECT 'Order', count(*) FILTER (WHERE NOT ok), count(*) FILTER (WHERE ok), 1, (SELECT count(*) FROM valid_Customer) FROM (SELECT o_custkey IN (SELECT entity FROM valid_Customer) AS ok FROM orders)
""")
_add("retrieved_A", lambda spark, d: work.retrieved(*graph_of(spark, d, "A")), """
SELECT 'Nation' AS shape, count(*) AS n_retrieved FROM nation
UNION ALL SELECT 'Customer', (SELECT count(*) FROM customer) + (SELECT count(DISTINCT c_nationkey) FROM customer)
UNION ALL SELECT 'Order', (SELECT count(*) FROM orders) + (SELECT count(DISTINCT o_custkey) FROM orders)
""")
for _s in "ABC":
    _add(
        f"invalid_pct_{_s}", lambda spark, d, s=_s: work.invalid_pct(_verdicts(s, "L2", "fused", 5, spark, d)),
        f"SELECT count(*) AS n_entities, count(*) FILTER (WHERE valid) AS n_valid, round(100.0 * count(*) FILTER (WHERE NOT valid) / count(*), 2)::DOUBLE AS invalid_pct FROM ({ref.verdicts(*_mapping(_s, 'L2'))})",
    )
_add("checks_A", lambda spark, d: work.checks(*graph_of(spark, d, "A")), f"""
WITH c(kind, n) AS ({" UNION ALL ".join(f"SELECT '{'inter' if c.ref else 'intra'}', (SELECT sum(greatest(coalesce(k, 0), 1)) FROM {ref.entities(_base, s.target)} t LEFT JOIN (SELECT entity, count(*) AS k FROM {ref.witnesses(_base, s, c, False)} GROUP BY entity) w ON w.entity = t.entity)" for s in load_schema("A").shapes for c in s.counts())})
SELECT kind, count(*) AS n_constraints, avg(n)::DOUBLE AS avg_checks FROM c GROUP BY kind
""")
_add(
    "shape_cardinality", lambda spark, d: class_stats(graph_of(spark, d, "C")[0], schema_classes(load_schema("C"))),
    " UNION ALL ".join(f"SELECT '{c}' AS cls, count(*) AS n_entities FROM {ref.entities(_base, c)}" for c in schema_classes(load_schema("C"))),
)
_add(
    "predicate_stats_Order", lambda spark, d: predicate_stats(graph_of(spark, d, "B")[0], "Order", ["o_custkey", "^l_orderkey"]),
    " UNION ALL ".join(f"SELECT '{p}' AS path, (SELECT count(*) FROM (SELECT DISTINCT entity, value FROM {x})) AS n, (SELECT count(DISTINCT entity) FROM {x}) AS n_subjects, (SELECT count(DISTINCT value) FROM {x}) AS n_objects, (SELECT max(k) FROM (SELECT count(DISTINCT value) AS k FROM {x} GROUP BY entity)) AS max_per_subject" for p in ("o_custkey", "^l_orderkey") for x in [f"(SELECT * FROM {ref.edges(_base, 'Order', p)} WHERE value IS NOT NULL)"]),
)
_add(
    "graph_size", lambda spark, d: graph_size(graph_of(spark, d, "B")[0].triples()),
    f"SELECT sum(n)::BIGINT AS n_triples, (SELECT count(*) FROM ({' UNION ALL '.join(f'SELECT CAST(entity AS VARCHAR) FROM {ref.entities(_base, c)}' for c in _base.classes)})) AS n_subjects FROM ({ref.by_predicate(_base)})",
)
_biggest = " UNION ALL ".join(f"SELECT count(*) AS n FROM {ref.entities(_base, c)}" for c in schema_classes(load_schema("C")))


def _skew(spark, sf_dir):
    """The share of all entities that the two largest shapes have."""
    per = class_stats(graph_of(spark, sf_dir, "C")[0], schema_classes(load_schema("C")))
    top = per.orderBy(F.desc("n_entities"), "cls").limit(2).agg(F.sum("n_entities").alias("n_two"))
    return per.agg(F.sum("n_entities").alias("n_entities")).crossJoin(F.broadcast(top)).withColumn("share", F.round(F.col("n_two") / F.col("n_entities"), 6))


_add(
    "shape_skew_C", _skew,
    f"WITH b AS ({_biggest}), x AS (SELECT (SELECT sum(n) FROM b)::BIGINT AS n_entities, (SELECT sum(n) FROM (SELECT n FROM b ORDER BY n DESC LIMIT 2))::BIGINT AS n_two) SELECT *, round(n_two / n_entities, 6) AS share FROM x",
)

#: Rows that an answer of the capped endpoint may have.
CAP = 2000


def _capped(engine: str, spark, sf_dir):
    """How verdicts under the cap differ from the exact ones: the baseline's answers are cut, the planned engine fetches slices."""
    g, s = graph_of(spark, sf_dir, "A", "L1")
    exact = validate(g, s, "fused").verdicts
    return misclassified(exact, validate(g, s, engine, rewrite=RewriteConfig(slice=True), limits=Limits(answer_cap=CAP)).verdicts)


_exact = ref.verdicts(*_mapping("A", "L1"))
_add("capped_misses_naive", partial(_capped, "naive"), ref.misclassified(_exact, ref.capped(*_mapping("A", "L1"), CAP)))
_add("capped_misses_planned", partial(_capped, "planned"), ref.misclassified(_exact, _exact))


def _engine_measures(spark, sf_dir):
    """Continuous measures of three engines over their own traces, as far as they don't depend on the clock: answers, steps, whether the
    area under the curve lies within its bounds and the first answer comes before the last."""
    return measured(spark, sf_dir, "A", "L2", ("naive", "naive_py", "planned"))


_add(
    "engine_measures_A", _engine_measures,
    "SELECT e AS engine, (SELECT count(*) FROM nation) + (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) AS comp, 3::BIGINT AS n_steps, TRUE AS area_within, TRUE AS first_before_last FROM (VALUES ('naive'), ('naive_py'), ('planned')) t(e)",
)


def _answers(spark, sf_dir):
    t = F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)") / 1e6
    return table(spark, sf_dir, "events").select(F.col("event_type").alias("engine"), "event_id", t.cast("double").alias("t"))


def _trace(spark, sf_dir):
    return tr.answer_trace(_answers(spark, sf_dir), ["engine"], ["t", "event_id"])


_trace_sql = "SELECT event_type AS engine, event_id, t, row_number() OVER (PARTITION BY event_type ORDER BY t, event_id) AS answer_no FROM (SELECT *, epoch_us(ts) / 1e6 - epoch(TIMESTAMP '2024-01-01') AS t FROM events)"
_add("answer_trace", _trace, _trace_sql)
_add("dief_at_t", lambda spark, d: tr.dief_at_t(_trace(spark, d), 1_000_000.0, ["engine"]).withColumn("dief", F.round("dief", 2)), f"""
WITH s AS (SELECT engine, t, max(answer_no)::DOUBLE AS k FROM ({_trace_sql}) WHERE t <= 1000000 GROUP BY engine, t),
x AS (SELECT *, lead(t) OVER w AS t2, lead(k) OVER w AS k2 FROM s WINDOW w AS (PARTITION BY engine ORDER BY t))
SELECT engine, round(sum(CASE WHEN t2 IS NULL THEN (1000000 - t) * k ELSE (t2 - t) * (k + k2) / 2 END), 2) AS dief FROM x GROUP BY engine
""")
_add(
    "trace_summary", lambda spark, d: tr.trace_summary(_trace(spark, d), ["engine"], steps=False),
    f"SELECT engine, 1.0 / nullif(min(t), 0) AS inv_tfff, 1.0 / nullif(max(t), 0) AS inv_et, count(*) AS comp, count(*)::DOUBLE / nullif(max(t), 0) AS throughput FROM ({_trace_sql}) GROUP BY engine",
)

# Recursion, disjunction, negation.


def _recursive(schema: str, shape: str, level: str, wide: bool, spark, sf_dir):
    g, s = graph_of(spark, sf_dir, schema)
    from shapeplan.sources import corrupt

    return validate(corrupt(g, level, wide), s, "planned").of(shape)


_add("x1_turn_chain", partial(_recursive, "X1", "Turn", "L1", True), """
WITH t AS (SELECT *, CASE WHEN (conv_id * 8 + turn) % 100 < 10 THEN NULL ELSE text END AS x FROM conversations)
SELECT 'Turn' AS shape, CAST(conv_id * 64 + turn AS VARCHAR) AS entity, bool_and(x IS NOT NULL) OVER (PARTITION BY conv_id ORDER BY turn) AND min(turn) OVER (PARTITION BY conv_id) = 0 AS valid FROM t
""")
_add("x2_order_chain", partial(_recursive, "X2", "Order", "L1", False), """
SELECT 'Order' AS shape, CAST(o_orderkey AS VARCHAR) AS entity, bool_and(o_totalprice IS NOT NULL AND o_orderkey % 100 >= 10) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS valid FROM orders
""")
for _s in ("X3", "X4"):
    _add(f"{_s.lower()}_documents", lambda spark, d, s=_s: validate(*graph_of(spark, d, s), "fused").of("Document"), ref.verdicts(*_mapping(_s, "L0"), "Document"))

# Surrounding operators.

_add(
    "filter_value_test",
    lambda spark, d: table(spark, d, "part").where("p_size BETWEEN 1 AND 10 AND p_type LIKE '%MO%' AND p_brand IS NOT NULL").select("p_partkey", "p_size"),
    "SELECT p_partkey, p_size FROM part WHERE p_size BETWEEN 1 AND 10 AND p_type LIKE '%MO%' AND p_brand IS NOT NULL",
)
_add(
    "join_inner_path", lambda spark, d: graph_of(spark, d, "R")[0].edges("OrderLine", "l_orderkey/o_custkey/c_nationkey").distinct(),
    "SELECT DISTINCT l_orderkey * 16 + l_linenumber AS entity, c_nationkey AS value FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
)


def _range(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_orderdate")
    return rel.range_join(
        lines, orders, ["k"], F.col("l_shipdate"), F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"),
    ).groupBy("l_linenumber").agg(F.count(F.lit(1)).alias("n"))


_add(
    "join_range_ship", _range,
    "SELECT l_linenumber, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAYS GROUP BY 1",
)


def _asof(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    buys = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    clicks = e.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("click_id"))
    return rel.asof_join(buys, clicks, ["user_id"], "ts", ["click_id"])


_add("asof_event", _asof, """
SELECT b.user_id, b.ts, b.event_id, c.click_id FROM (SELECT * FROM events WHERE event_type = 'purchase') b
ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS click_id FROM events WHERE event_type = 'click' GROUP BY 1, 2) c ON b.user_id = c.user_id AND b.ts >= c.ts
""")
_rep = f"SELECT 'A' AS workload, shape, valid FROM ({ref.verdicts(*_mapping('A', 'L2'))}) UNION ALL SELECT 'R', shape, valid FROM ({ref.verdicts(*_mapping('R', 'L3'))})"


def _report(kind: str, spark, sf_dir):
    v = _verdicts("A", "L2", "fused", 5, spark, sf_dir).withColumn("workload", F.lit("A")).unionByName(_verdicts(
        "R", "L3", "fused", 5, spark, sf_dir,
    ).withColumn("workload", F.lit("R")))
    return rel.quality_report(v, ["workload", "shape"], kind)


for _k in ("rollup", "cube"):
    _add(
        f"report_{_k}", partial(_report, _k),
        f"SELECT workload, shape, count(*) AS n, count(*) FILTER (WHERE valid) AS n_valid FROM ({_rep}) GROUP BY {_k.upper()}(workload, shape)",
    )
_add(
    "topk_invalid_shapes", lambda spark, d: rel.top_invalid(_summary("B", "L2", "fused", 5, spark, d), 3),
    f"SELECT * FROM ({ref.summary(*_mapping('B', 'L2'))}) ORDER BY n_invalid DESC, shape LIMIT 3",
)
_add(
    "counts_distinct",
    lambda spark, d: table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.min("l_shipdate").alias("first"), F.bool_or(F.col("l_tax") > 0.07).alias("high"), F.count_if(F.col("l_discount") > 0.05).alias("n_discount")),
    "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, min(l_shipdate) AS first, bool_or(l_tax > 0.07) AS high, count(*) FILTER (WHERE l_discount > 0.05) AS n_discount FROM lineitem GROUP BY 1",
)
_add(
    "prev_order_chain",
    lambda spark, d: table(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("prev"), F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).cast("long").alias("depth")),
    "SELECT o_orderkey, lag(o_orderkey) OVER w AS prev, row_number() OVER w AS depth FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)",
)
_add(
    "triples_by_predicate",
    lambda spark, d: graph_of(spark, d, "B")[0].triples().groupBy("p").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("s").alias("n_subjects")),
    ref.by_predicate(_base),
)


#: Triples that a task makes distinct at a time: some 50 MB of them fit its memory, so none go to disk.
_NT_TASK = 250_000


def _ntriples(spark, sf_dir):
    t = graph_of(spark, sf_dir, "B")[0].triples()
    path, seen = scratch_path(spark, "nt"), Observation()
    graph_io.to_ntriples(t.observe(seen, F.count(F.lit(1)).alias("n"))).write.text(path, compression="snappy")
    # Dealt out by subject, which both the set and its subjects can be counted by; a subject's triples next to each other also compress well.
    tasks = seen.get["n"] // _NT_TASK
    back = graph_io.from_ntriples(spark.read.text(path))
    back = back.repartition(tasks, "s") if tasks > int(spark.conf.get("spark.sql.shuffle.partitions")) else back.repartition("s")
    return back.distinct().groupBy("p").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("s").alias("n_subjects"))


_add("ntriples_roundtrip", _ntriples, ref.by_predicate(_base))
_add(
    "fn_string",
    lambda spark, d: table(spark, d, "customer").select("c_custkey", F.concat(F.lit("Customer/"), F.col("c_custkey").cast("string")).alias("iri"), F.length("c_name").cast("long").alias("len"), F.col("c_name").rlike("[0-9]+5$").alias("five"), F.upper(F.substring("c_mktsegment", 1, 3)).alias("seg")),
    "SELECT c_custkey, 'Customer/' || c_custkey AS iri, length(c_name) AS len, regexp_matches(c_name, '[0-9]+5$') AS five, upper(substring(c_mktsegment, 1, 3)) AS seg FROM customer",
)
_add(
    "fn_date",
    lambda spark, d: table(spark, d, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lit("1992-01-01")).cast("long").alias("days"), F.year("o_orderdate").cast("long").alias("y"), F.date_format(F.trunc("o_orderdate", "month"), "yyyy-MM-dd").alias("m")),
    "SELECT o_orderkey, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days, year(o_orderdate) AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m FROM orders",
)
_add(
    "fn_json",
    lambda spark, d: table(spark, d, "events").select("event_id", F.from_json("props", "k INT")["k"].cast("long").alias("k"), F.get_json_object("props", "$.k").alias("raw")),
    "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, json_extract_string(props, '$.k') AS raw FROM events",
)
_add(
    "fn_array",
    lambda spark, d: table(spark, d, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.forall("embedding", lambda x: x < 10).alias("small"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")), 4).alias("total")),
    "SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x >= 10)) = 0 AS small, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 4) AS total FROM embeddings",
)


def _binom(spark, sf_dir):
    register(spark)
    per = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("k"))
    return per.selectExpr("l_orderkey", "binom(k, 2) AS pairs")


_add("fn_math_binomial", _binom, "SELECT l_orderkey, (count(*) * (count(*) - 1) / 2)::DOUBLE AS pairs FROM lineitem GROUP BY 1")
_win = "count(*) AS n, count(*) FILTER (WHERE NOT (event_type IN ('click', 'error', 'purchase', 'signup', 'view') AND value >= 0)) AS n_invalid, count(*) FILTER (WHERE event_type = 'error') AS n_errors"
_add(
    "win_tumbling", lambda spark, d: ev.tumbling(table(spark, d, "events")),
    f"SELECT time_bucket(INTERVAL 1 HOUR, ts) AS w_start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS w_end, {_win} FROM events GROUP BY 1, 2",
)
_add(
    "win_sliding", lambda spark, d: ev.sliding(table(spark, d, "events")),
    f"SELECT w_start, w_start + INTERVAL 1 HOUR AS w_end, {_win} FROM (SELECT *, unnest([time_bucket(INTERVAL 30 MINUTES, ts), time_bucket(INTERVAL 30 MINUTES, ts) - INTERVAL 30 MINUTES]) AS w_start FROM events) GROUP BY 1, 2",
)
_add("win_session", lambda spark, d: ev.sessions(table(spark, d, "events")), """
WITH a AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events),
b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a)
SELECT user_id, min(ts) AS w_start, max(ts) + INTERVAL 30 MINUTES AS w_end, count(*) AS n, count(*) FILTER (WHERE NOT (event_type IN ('click', 'error', 'purchase', 'signup', 'view') AND value >= 0)) AS n_invalid FROM b GROUP BY user_id, s
""")


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)
