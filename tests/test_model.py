"""Queries, classes, patterns, plan trees, the SQL front end and what is refused."""

from datetime import datetime

import pytest

from cellcount.plans import sqlfront, tree
from cellcount.plans import workloads as W
from cellcount.plans.model import CountQuery, Interval, UnsupportedQuery, compare, equivalence_classes, partition_by_pattern, restrict, subplans, validate
from cellcount.plans.sqlfront import parse_count_query


def test_classes_are_closed():
    got = equivalence_classes([("a.x", "b.x"), ("c.y", "d.y"), ("b.x", "e.x")])
    assert got == {frozenset({"a.x", "b.x", "e.x"}), frozenset({"c.y", "d.y"})}


def test_anatomy_of_a_query():
    q = parse_count_query("SELECT COUNT(*) FROM orders as o, events as e WHERE o.o_custkey = e.user_id AND e.event_type = 'click' AND o.o_orderdate >= '1998-06-30 00:00:00'::timestamp;")
    assert q.tables == {"orders", "events"}
    assert q.classes == {frozenset({"orders.o_custkey", "events.user_id"})}
    assert q.pattern.join_attrs({"orders"}, {"events"}) == {"orders.o_custkey"}
    assert dict(q.ranges) == {"events.event_type": Interval("click", True, "click", True), "orders.o_orderdate": Interval(datetime(1998, 6, 30), True)}


def test_patterns_split_a_batch():
    groups = partition_by_pattern(W.x1())
    assert [[q.id for q in qs] for qs in groups.values()] == [["x1_a"], ["x1_b"], ["x1_c", "x1_d"]]


def test_conjuncts_meet():
    q = CountQuery.build("q", ["lineitem"], (), [("lineitem.l_tax", compare(">=", 0.03)), ("lineitem.l_tax", compare("<", 0.03))])
    assert dict(q.ranges)["lineitem.l_tax"].empty and q.boxes() == []


def test_restriction_drops_what_leaves():
    q = W.x2()[4]
    sub = restrict(q, {"customer", "orders"})
    assert sub.tables == {"customer", "orders"} and {a.split(".")[0] for a, _ in sub.ranges} <= {"customer", "orders"}
    assert all(len(c) == 2 for c in sub.classes)
    assert {s.tables for s in subplans(q, 5)} == {q.tables}


def test_sql_round_trip():
    for q in W.make("w1", 60):
        back = parse_count_query(sqlfront.render_sql(q), q.id)
        assert back == q


@pytest.mark.parametrize(
    "text,reason",
    [
        ("SELECT COUNT(*) FROM lineitem l1, lineitem l2 WHERE l1.l_orderkey = l2.l_orderkey", "self-join"),
        ("SELECT COUNT(*) FROM lineitem, part WHERE l_partkey = p_partkey AND l_quantity < p_size", "equality"),
        ("SELECT COUNT(*) FROM lineitem WHERE l_tax = 0.02 OR l_tax = 0.03", "OR"),
        ("SELECT COUNT(*) FROM orders WHERE o_orderstatus IN ('F', 'P')", "IN"),
        ("SELECT COUNT(*) FROM orders WHERE o_orderstatus <> 'F'", "<>"),
        ("SELECT SUM(x) FROM orders", "COUNT"),
    ],
)
def test_refused_text(text, reason):
    with pytest.raises(UnsupportedQuery, match=reason):
        parse_count_query(text)


def test_refused_patterns():
    ring = CountQuery.build("r", ["customer", "supplier", "lineitem", "orders"], [("customer.c_nationkey", "supplier.s_nationkey"), ("supplier.s_suppkey", "lineitem.l_suppkey"), ("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey")])
    with pytest.raises(UnsupportedQuery, match="cyclic"):
        validate(ring.pattern)
    with pytest.raises(UnsupportedQuery, match="cyclic"):
        tree.build_tree(ring.pattern, "customer")
    with pytest.raises(UnsupportedQuery, match="cross product"):
        validate(CountQuery.build("c", ["region", "part"]).pattern)


def test_hub_is_the_root_and_siblings_hang_below_it():
    p = W.x2()[0].pattern
    assert tree.choose_root(p) == "customer"
    node = tree.build_tree(p, "customer")
    assert {c.table for c in node.children} == {"nation", "events", "orders"}
    folded = tree.fold_fk_pk(node, p, "root")
    assert folded.folded and folded.folded[0][0] == "nation" and {c.table for c in folded.children} == {"events", "orders"}


def test_only_the_many_side_folds_the_unique_side():
    p = CountQuery.build("q", *W.pattern("co")).pattern
    assert tree.fold_fk_pk(tree.build_tree(p, "orders"), p, "root").folded == [("customer", 0)]
    assert tree.fold_fk_pk(tree.build_tree(p, "customer"), p, "root").folded == []


def test_workload_shapes():
    assert len(W.W6) == 58 and len({CountQuery.build("q", *W.pattern(c)).pattern for c in W.W6}) == 58
    assert len(W.W2) - 3 == 31 and len(W.W1) - 3 == 16 and len(W.W3) == 18 and len(W.W9) == 16
    assert len({q.pattern for q in W.derived(W.make("w3"), "w5", False, 1)}) == 35
    assert len({q.pattern for q in W.derived(W.small("w6"), "w8", False, 1)}) == 93
    assert W.make("w1", 40) == W.make("w1", 40)
    w3 = W.make("w3")
    assert all(len(q.ranges) == len(r.ranges) for q, r in zip(w3, W.rescale(w3, 70), strict=True))
