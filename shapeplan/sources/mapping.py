"""How the given tables are a graph: classes, keys, predicates, links.

Expressions are SQL that Spark and DuckDB both read, so one mapping serves the engines and the oracles.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

#: Keys of composite entities: line numbers stay below 16, turns below 64.
LINE = "l_orderkey * 16 + l_linenumber"
ROW = "CAST(l_orderkey AS VARCHAR(20)) || '/' || CAST(l_linenumber AS VARCHAR(20)) || '/' || CAST(l_partkey AS VARCHAR(20)) || '/' || CAST(l_suppkey AS VARCHAR(20))"
TURN = "conv_id * 64 + turn"


@dataclass(frozen=True)
class Edge:
    """A multi-valued predicate: rows of a table give (entity, value) pairs."""

    table: str
    entity: str
    value: str
    where: str | None = None


@dataclass(frozen=True)
class ClassMap:
    """A class: one entity for each distinct key; ``single`` predicates are columns of its row."""

    table: str
    key: str
    single: dict[str, str] = field(default_factory=dict, hash=False)
    multi: dict[str, Edge] = field(default_factory=dict, hash=False)
    distinct: bool = False


@dataclass(frozen=True)
class Mapping:
    classes: dict[str, ClassMap]
    #: Class of the objects of a predicate that links entities.
    links: dict[str, str]

    def with_single(self, cls: str, predicate: str, expression: str) -> Mapping:
        c = self.classes[cls]
        return replace(self, classes=self.classes | {cls: replace(c, single=c.single | {predicate: expression})})


    def without(self, cls: str, condition: str) -> Mapping:
        """The mapping without the entities of a class that meet a condition; links to them stay, and dangle."""
        c = self.classes[cls]
        return replace(self, classes=self.classes | {cls: replace(c, key=f"CASE WHEN {condition} THEN NULL ELSE {c.key} END")})


def _same(*names: str) -> dict[str, str]:
    return {n: n for n in names}


def default_mapping(line_key: str = "line") -> Mapping:
    """The classes of all workloads; ``line_key="row"`` tells order lines apart by all their keys."""
    line = ROW if line_key == "row" else LINE
    lines = {p: Edge("lineitem", line, p) for p in ("l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")}
    turns = lambda where: Edge("conversations", "conv_id", TURN, where)
    did = lambda kind: Edge("events", "user_id", "event_id", f"event_type = '{kind}'")
    classes = {
        "Region": ClassMap("region", "r_regionkey", _same("r_name"), {"^n_regionkey": Edge("nation", "n_regionkey", "n_nationkey")}),
        "Nation": ClassMap("nation", "n_nationkey", _same("n_name", "n_regionkey"), {"^c_nationkey": Edge("customer", "c_nationkey", "c_custkey"), "^s_nationkey": Edge("supplier", "s_nationkey", "s_suppkey")}),
        "Supplier": ClassMap("supplier", "s_suppkey", _same("s_name", "s_acctbal", "s_nationkey"), {"^l_suppkey": Edge("lineitem", "l_suppkey", line)}),
        "Customer": ClassMap("customer", "c_custkey", _same("c_name", "c_acctbal", "c_mktsegment", "c_nationkey"), {"^o_custkey": Edge("orders", "o_custkey", "o_orderkey")}),
        "Part": ClassMap("part", "p_partkey", _same("p_name", "p_brand", "p_type", "p_size", "p_retailprice"), {"^l_partkey": Edge("lineitem", "l_partkey", line)}),
        "Order": ClassMap("orders", "o_orderkey", _same("o_orderstatus", "o_orderpriority", "o_totalprice", "o_orderdate", "o_custkey"), {"^l_orderkey": Edge("lineitem", "l_orderkey", line), "prev_order": Edge("orders", "o_orderkey", "lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey)")}),
        "OrderLine": ClassMap("lineitem", line, {} if line_key == "line" else _same(*lines) | {"l_orderkey": "l_orderkey"}, {"l_orderkey": Edge("lineitem", line, "l_orderkey")} | lines if line_key == "line" else {}, True),
        "Event": ClassMap("events", "event_id", _same("ts", "event_type", "value", "props", "user_id")),
        "User": ClassMap("events", "user_id", {"account": "user_id"}, {"^user_id": Edge("events", "user_id", "event_id"), "u_purchase": did("purchase"), "u_error": did("error"), "u_signup": did("signup")}, True),
        "Document": ClassMap("documents", "doc_id", _same("text", "lang", "source", "n_chars"), {"^label_doc": Edge("labels", "doc_id", "doc_id")}),
        "Label": ClassMap("labels", "doc_id", {"label_doc": "doc_id"} | _same("quality", "toxic")),
        "Conversation": ClassMap("conversations", "conv_id", {}, {"^turn_conv": turns(None), "^user_turn_conv": turns("role = 'user'"), "^assistant_turn_conv": turns("role = 'assistant'")}, True),
        "Turn": ClassMap("conversations", TURN, {"turn_conv": "conv_id"} | _same("role", "text", "turn"), {"prev_turn": Edge("conversations", TURN, f"lag({TURN}) OVER (PARTITION BY conv_id ORDER BY turn)")}),
        "Page": ClassMap("pages", "page_id", _same("url", "html")),
    }
    links = {"n_regionkey": "Region", "s_nationkey": "Nation", "c_nationkey": "Nation", "o_custkey": "Customer", "l_orderkey": "Order", "l_partkey": "Part", "l_suppkey": "Supplier", "user_id": "User", "account": "Customer", "label_doc": "Document", "turn_conv": "Conversation", "prev_turn": "Turn", "prev_order": "Order"}
    return Mapping(classes, links)


#: Corruption levels: nations without a name of 25, share of other triples dropped of 100.
LEVELS = {"L0": (0, 0), "L1": (2, 10), "L2": (6, 25), "L3": (12, 50)}


def corrupted(mapping: Mapping, level: str, wide: bool = False) -> Mapping:
    """The mapping without the triples that a level removes; ``wide`` also those of events, documents and turns."""
    k, p = LEVELS[level]
    if not p:
        return mapping
    drops = [("Nation", "n_name", f"n_nationkey % 25 < {k}"), ("Customer", "c_acctbal", f"c_custkey % 100 < {p}"), ("Order", "o_totalprice", f"o_orderkey % 100 < {p}")]
    if wide:
        drops += [("Event", "value", f"event_id % 100 < {p}"), ("Document", "lang", f"doc_id % 100 < {p}"), ("Turn", "text", f"(conv_id * 8 + turn) % 100 < {p}")]
    for cls, predicate, where in drops:
        mapping = mapping.with_single(cls, predicate, f"CASE WHEN {where} THEN NULL ELSE {mapping.classes[cls].single[predicate]} END")
    return mapping
