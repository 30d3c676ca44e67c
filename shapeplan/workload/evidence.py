"""Expected rows worked out by hand from the schemas: orders, degrees, references, fragments, strata."""

from __future__ import annotations

#: By schema, the order that each group of configurations takes. Neighbours come by name, in R as declared.
ORDERS = {
    "R": {(1, 2, 5, 6): "Nation Supplier OrderLine Part", (3, 4, 7, 8): "OrderLine Nation Supplier Part"},
    "A": {(1, 3, 4, 5, 7, 8): "Customer Nation Order", (2, 6): "Nation Customer Order"},
    "B": {
        (1, 2): "Nation Customer Region Supplier Order OrderLine Part",
        (3, 4): "OrderLine Order Part Supplier Customer Nation Region",
        (5, 6): "Nation Customer Order OrderLine Part Supplier Region",
        (7, 8): "OrderLine Order Customer Nation Region Supplier Part",
    },
    "C": {
        (1,): "Customer Nation Order User Region Supplier OrderLine Event Part Conversation Turn Document Label Page",
        (2,): "Nation Customer Region Supplier Order User OrderLine Event Part Conversation Turn Document Label Page",
        (3, 4): "OrderLine Order Part Supplier Customer Nation User Region Event Conversation Turn Document Label Page",
        (5,): "Customer Nation Region Supplier OrderLine Order Part User Event Conversation Turn Document Label Page",
        (6,): "Nation Customer Order OrderLine Part Supplier User Event Region Conversation Turn Document Label Page",
        (7, 8): "OrderLine Order Customer Nation Region Supplier User Event Part Conversation Turn Document Label Page",
    },
}

#: Shapes that refer to it, shapes that it refers to, constraints.
DEGREES = {
    "R": {"Nation": (2, 0, 2), "Supplier": (1, 1, 4), "OrderLine": (0, 3, 6), "Part": (1, 0, 2)},
    "A": {"Nation": (1, 0, 4), "Customer": (1, 1, 6), "Order": (0, 1, 6)},
    "B": {"Region": (1, 0, 3), "Nation": (2, 1, 4), "Supplier": (1, 1, 5), "Customer": (1, 1, 6), "Part": (1, 0, 5), "Order": (1, 1, 6), "OrderLine": (0, 3, 7)},
    "C": {
        "Region": (1, 0, 4), "Nation": (2, 1, 6), "Supplier": (1, 1, 7), "Customer": (2, 1, 9), "Part": (1, 0, 11), "Order": (1, 1, 10), "OrderLine": (0, 3, 17),
        "Event": (0, 1, 10), "User": (1, 1, 6), "Document": (1, 0, 9), "Label": (0, 1, 6), "Conversation": (1, 0, 4), "Turn": (0, 1, 8), "Page": (0, 0, 5),
    },
}

_CHAIN = [("Nation", "Region", "n_regionkey"), ("Supplier", "Nation", "s_nationkey"), ("Customer", "Nation", "c_nationkey"), ("Order", "Customer", "o_custkey")]
_BOTH = ("min", "max")

#: Referring shape, referred shape, path, kind, number.
DEPENDENCIES = {
    "R": [("Supplier", "Nation", "s_nationkey", k, 1) for k in _BOTH] + [("OrderLine", *x, "min", 1) for x in (("Supplier", "l_suppkey"), ("Part", "l_partkey"), ("Nation", "l_orderkey/o_custkey/c_nationkey"))],
    "A": [(*x, k, 1) for x in (("Customer", "Nation", "c_nationkey"), ("Order", "Customer", "o_custkey")) for k in _BOTH],
    "B": [(*x, k, 1) for x in (*_CHAIN, ("OrderLine", "Part", "l_partkey"), ("OrderLine", "Supplier", "l_suppkey")) for k in _BOTH] + [("OrderLine", "Order", "l_orderkey", "min", 1)],
    "C": [
        (*x, k, 1)
        for x in (
            *_CHAIN, ("OrderLine", "Order", "l_orderkey"), ("OrderLine", "Part", "l_partkey"), ("OrderLine", "Supplier", "l_suppkey"), ("Event", "User", "user_id"),
            ("User", "Customer", "account"), ("Label", "Document", "label_doc"), ("Turn", "Conversation", "turn_conv"),
        )
        for k in _BOTH
    ],
}

#: The plan of schema B in configuration 5: place, shape, what it waits for.
PLAN_B = [(1, "Nation", "Region"), (2, "Customer", ""), (3, "Order", ""), (4, "OrderLine", "Part,Supplier"), (5, "Part", ""), (6, "Supplier", ""), (7, "Region", "")]

FRAGMENTS = [
    ("R", "non-recursive"), ("A", "non-recursive"), ("B", "non-recursive"), ("C", "non-recursive"), ("X1", "positive"), ("X2", "positive"),
    ("X3", "non-recursive"), ("X4", "non-recursive"), ("X5", "rejected"),
]

#: A maximum with a reference counts as negative, as more conforming values can break it.
STRATA = [
    ("X4", "ToxicLabel", 0), ("X4", "Document", 1), ("A", "Nation", 0), ("A", "Customer", 1), ("A", "Order", 2), ("R", "Nation", 0), ("R", "Part", 0),
    ("R", "Supplier", 1), ("R", "OrderLine", 1),
]


def orders(schema: str) -> list[tuple[int, int, str]]:
    return [(k, i, n) for ks, names in ORDERS[schema].items() for k in ks for i, n in enumerate(names.split(), 1)]
