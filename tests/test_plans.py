"""Planning: seeds, traversals, fragments."""

import pytest

from shapeplan.model import UnsupportedFragment, load_schema, schema_from_dict
from shapeplan.plans.depgraph import classify, dependency_graph, strata
from shapeplan.plans.order import CONFIGS, PlanConfig, pick_seed, plan_validation, traverse

ORDERS = {
    ("R", 5): "Nation Supplier OrderLine Part",
    ("A", 1): "Customer Nation Order",
    ("A", 2): "Nation Customer Order",
    ("A", 7): "Customer Nation Order",
    ("B", 1): "Nation Customer Region Supplier Order OrderLine Part",
    ("B", 5): "Nation Customer Order OrderLine Part Supplier Region",
    ("B", 3): "OrderLine Order Part Supplier Customer Nation Region",
    ("B", 8): "OrderLine Order Customer Nation Region Supplier Part",
    ("C", 1): "Customer Nation Order User Region Supplier OrderLine Event Part Conversation Turn Document Label Page",
    ("C", 5): "Customer Nation Region Supplier OrderLine Order Part User Event Conversation Turn Document Label Page",
    ("C", 6): "Nation Customer Order OrderLine Part Supplier User Event Region Conversation Turn Document Label Page",
}


@pytest.mark.parametrize(("schema", "config"), ORDERS)
def test_orders(schema, config):
    assert traverse(dependency_graph(load_schema(schema)), CONFIGS[config]) == ORDERS[schema, config].split()


@pytest.mark.parametrize(("name", "n"), [("R", 14), ("A", 16), ("B", 36), ("C", 112)])
def test_constraint_counts(name, n):
    assert load_schema(name).n_constraints == n


def test_every_order_is_a_permutation():
    dep = dependency_graph(load_schema("C"))
    for c in (*CONFIGS.values(), PlanConfig("links", seed=3), PlanConfig("referenced_first"), PlanConfig("declared")):
        assert sorted(traverse(dep, c)) == sorted(dep.names)


def test_referenced_come_first():
    plan = plan_validation(load_schema("B"), PlanConfig("referenced_first"))
    assert not any(plan.deferrals.values())


def test_deferral():
    plan = plan_validation(load_schema("B"), 5)
    assert plan.deferrals["Nation"] == ("Region",)
    assert set(plan.deferrals["OrderLine"]) == {"Part", "Supplier"}


def test_fragments():
    assert classify(load_schema("B")) == "non-recursive"
    assert classify(load_schema("X1")) == "positive"
    assert strata(load_schema("X4")) == {"ToxicLabel": 0, "Document": 1}
    with pytest.raises(UnsupportedFragment):
        classify(load_schema("X5"))


def test_a_maximum_is_antitone():
    s = schema_from_dict({"name": "t", "shapes": [{"name": "S", "target": "Order", "constraints": [{"path": "prev_order", "max": 1, "ref": "S"}]}]})
    with pytest.raises(UnsupportedFragment):
        classify(s)


def test_seed_needs_a_target():
    s = schema_from_dict({"name": "t", "shapes": [{"name": "Hub", "target": None}, {"name": "P", "target": "Order", "constraints": [{"path": "x", "min": 1, "ref": "Hub"}]}]})
    assert pick_seed(dependency_graph(s)) == "P"


def test_three_components_restart():
    s = schema_from_dict({"name": "t", "shapes": [{"name": n, "target": "Order"} for n in "abc"]})
    assert traverse(dependency_graph(s), CONFIGS[5]) == ["a", "b", "c"]
