"""Queries, orders and trees, without data."""

import pytest

from ringview.functions.rings import IntRing, ProductRing
from ringview.operators import baselines
from ringview.plans.hypergraph import classify, closure, core, edges_of, is_acyclic, is_free_connex, is_hierarchical, is_join_tree, is_q_hierarchical, join_tree, reduct, violating_pairs
from ringview.plans.query import FD, NaturalJoinQuery
from ringview.plans.varorder import VariableOrder, best_order, canonical_order, chain_order, fd_order, free_top_order
from ringview.plans.viewtree import add_indicators, build_free_top_tree, build_tree, delta_tree, explain, materialized, plan_layouts, view_count
from ringview.sources import workloads as w

TOY = NaturalJoinQuery(w.TOY.relations)
ORDER = w.TOY.variable_order
TRI = NaturalJoinQuery({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "a")})


def free(q, *names):
    return NaturalJoinQuery(q.relations, names, q.ring, q.fds, q.static)


def test_orders_parse_and_depend():
    assert str(ORDER) == "a - {b, c - {d, e}}"
    assert {x: ORDER.dep(TOY, x) for x in "abcde"} == {"a": (), "b": ("a",), "c": ("a",), "d": ("c",), "e": ("a", "c")}
    with pytest.raises(ValueError):
        VariableOrder.parse("a - {b - c, d - e}").validate(TOY)
    with pytest.raises(ValueError):
        VariableOrder.parse("a -")
    assert VariableOrder.parse("a - b; c").roots == ("a", "c")


def test_stored_views_depend_on_what_changes():
    tree = build_tree(TOY, ORDER)
    root = tree.roots[0].name
    names = {n.keys: n.name for n in tree.nodes()}
    assert materialized(tree, ()) == {root}
    assert materialized(tree, ["t"]) == {root, names[("a", "c")], names[("a",)] if names[("a",)].startswith("V_b") else "V_b_r"}
    assert len(materialized(tree, ["r", "s", "t"])) == 5
    assert view_count(tree) == 5


def test_view_counts():
    assert view_count(build_tree(w.RETAIL.query(IntRing()), w.RETAIL.variable_order)) == 9
    star6 = NaturalJoinQuery({f"r{i}": ("k", f"x{i}") for i in range(6)})
    assert view_count(build_tree(star6, VariableOrder.parse("k - {" + ", ".join(f"x{i}" for i in range(6)) + "}"))) == 7
    assert [baselines.aggregate_count(n) for n in (26, 39, 15)] == [378, 820, 136]


def test_delta_trees_and_layouts():
    tree = build_tree(TOY, ORDER)
    (steps,) = delta_tree(tree, "t")
    assert [s.cost for s in steps][:1] == ["constant"] and steps[-1].view == tree.roots[0].name and "linear" in [s.cost for s in steps]
    assert plan_layouts(tree)
    assert explain(tree).count("*") == 5


def test_classes():
    assert is_acyclic(edges_of(TOY)) and not is_acyclic(edges_of(TRI)) and set(core(edges_of(TRI))) == {"r", "s", "t"}
    assert is_free_connex(free(TOY, "a", "b", "c")) and not is_free_connex(free(TOY, "b", "c"))
    assert is_join_tree(edges_of(TOY), join_tree(edges_of(TOY))) and join_tree(edges_of(TRI)) is None
    assert not is_hierarchical(TOY)
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("a", "c")}, ("a", "b"))
    assert is_q_hierarchical(q) and is_hierarchical(free(q, "b")) and not is_q_hierarchical(free(q, "b"))
    sales = NaturalJoinQuery({r: tuple(v for v in s if v in ("day", "suppkey", "partkey")) for r, s in w.SALES.relations.items()}, ("day", "suppkey", "partkey"))
    assert violating_pairs(sales) == [("day", "partkey"), ("day", "suppkey"), ("partkey", "suppkey")]
    assert classify(sales).static_needed == ("items", "stores")
    assert is_q_hierarchical(sales, ["items", "stores"]) and not is_q_hierarchical(sales, ["stores"])


def test_dependencies():
    assert closure("abc", [FD.parse("a -> d"), FD.parse("b,d -> e")]) == set("abcde")
    q = NaturalJoinQuery({"r": ("a", "b"), "s": ("b", "c"), "t": ("c", "d")}, ("a", "b", "c", "d"), fds=(FD.parse("b -> c"), FD.parse("c -> d")))
    assert {r: set(s) for r, s in reduct(q).relations.items()} == {"r": set("abcd"), "s": set("bcd"), "t": set("cd")}
    assert str(fd_order(q)) == "d - c - b - a" or set(fd_order(q).variables) == set("abcd")
    fd_order(q).validate(q)
    keys = NaturalJoinQuery({r: tuple(v for v in s if v in ("suppkey", "day", "partkey", "nationkey")) for r, s in w.RETAIL.relations.items()}, ("suppkey", "day", "partkey", "nationkey"), fds=w.RETAIL.fds, static=w.RETAIL.static)
    assert not classify(NaturalJoinQuery(keys.relations, keys.free)).hierarchical and classify(keys).q_hierarchical_under_fds


def test_free_top_trees():
    q = free(TOY, "a", "b", "c")
    order = free_top_order(q)
    assert order.is_free_top(q.free) and order.width(q) == 1
    tree = build_free_top_tree(q, ORDER)
    assert all(set(tree.node(s).keys) <= {"a", "b", "c"} for s in tree.sources)
    with pytest.raises(ValueError):
        build_free_top_tree(free(TOY, "d"), ORDER)
    with pytest.raises(ValueError):
        free_top_order(free(TOY, "b", "c"))
    with pytest.raises(ValueError):
        canonical_order(TOY)


def test_indicators_close_cycles():
    tree = add_indicators(build_tree(TRI, VariableOrder.parse("a - b - c")))
    assert [(x.relation, set(x.onto)) for x in tree.leaves() if x.onto] == [("r", {"a", "b"})]
    loop = add_indicators(build_tree(w.loop4().query(IntRing()), w.loop4().variable_order))
    assert [x.relation for x in loop.leaves() if x.onto] == ["ac", "ac"]
    cyc = add_indicators(build_tree(w.CYCLE.query(IntRing()), w.CYCLE.variable_order))
    assert any(x.onto for x in cyc.leaves())
    assert not [x for x in add_indicators(build_tree(TOY, ORDER)).leaves() if x.onto]


def test_search_and_chains():
    assert best_order(TOY).width(TOY) == 1
    big = w.RETAIL.query(IntRing())
    best_order(big).validate(big)
    assert chain_order([10, 100, 5, 50]) == ((0, 1), 2) and chain_order([1] * 5, True) == ((0, 1), (2, 3))


def test_sql():
    q = NaturalJoinQuery.from_sql("select a, sum(b * d) as x, count(*) from r natural join s natural join t group by a", w.TOY.relations)
    assert q.free == ("a",) and isinstance(q.ring, ProductRing) and q.ring.parts[0][0] == "x"
    for bad in ("select a from r", "select sum(z) from r natural join s", "select a, sum(b) from nowhere group by a", "delete from r"):
        with pytest.raises(ValueError):
            NaturalJoinQuery.from_sql(bad, w.TOY.relations)


def test_recursive_views():
    tri = baselines.recursive_views(TRI)
    assert sum(len(v) == 2 for v in tri) == 3
    p = NaturalJoinQuery({f"e{i}": (f"a{i}", f"a{i + 1}") for i in range(1, 8)}, ("a1", "a8"))
    assert sum(len(v) > 1 for v in baselines.recursive_views(p)) == 7 * 6 // 2
