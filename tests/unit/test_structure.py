"""Bag trees and their rewrites: worked examples and properties on random trees."""

import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from roundjoin.plans import cost
from roundjoin.plans.bagtree import BagTree
from roundjoin.plans.hypergraph import Hypergraph, find_bag_tree, join_tree, query_width
from roundjoin.plans.planner import candidates, choose
from roundjoin.plans.query import JoinQuery
from roundjoin.plans.rewrite import ExtendedTree, log_depth_rewrite, log_depth_rewrite_edge_labels, log_depth_rewrite_hypertree, merge_log_depth_rewrite, merge_rewrite, predict_treewidth
from roundjoin.plans.schedule import count_rounds, sweep
from roundjoin.workloads import chain_graph, chain_tree, star_graph, star_tree, triangle_graph, triangle_tree


def random_join_tree(seed: int, n: int) -> tuple[Hypergraph, BagTree]:
    rng = random.Random(seed)
    edges, parent, fresh = {"r00": frozenset({"a0", "a1"})}, {"r00": None}, 2
    for i in range(1, n):
        p = rng.choice(sorted(edges))
        shared = rng.sample(sorted(edges[p]), rng.randint(1, len(edges[p])))
        new = [f"a{fresh + k}" for k in range(rng.randint(0 if len(shared) > 1 else 1, 2))]
        fresh += len(new)
        edges[f"r{i:02d}"], parent[f"r{i:02d}"] = frozenset(shared + new), p
    h = Hypergraph(edges)
    return h, BagTree(edges, {e: frozenset([e]) for e in edges}, parent)


trees = st.builds(random_join_tree, st.integers(0, 10**6), st.integers(1, 40))


def test_named_queries():
    for n in (2, 5, 20):
        assert (star_tree(n).depth(), star_tree(n).width(), star_tree(n).intersection_width(star_graph(n))) == (1, 1, 1)
    for n in (2, 16, 64):
        assert (chain_tree(n).depth(), chain_tree(n).width()) == (n - 1, 1)
    for k in (2, 7, 20):
        t, h = triangle_tree(k), triangle_graph(k)
        assert (t.depth(), t.width(), t.intersection_width(h), t.validate(h)) == (k - 1, 2, 1, [])
    assert query_width(triangle_graph(3)) == 2 and query_width(chain_graph(6)) == 1


def test_five_relation_example_is_acyclic():
    h = Hypergraph.from_query(JoinQuery.parse("R1(A,B,C), R2(B,F), R3(B,C,D), R4(C,D,E), R5(D,E,G)"))
    tree = join_tree(h)
    assert tree.width() == 1 and tree.validate(h) == []


def test_cyclic_search():
    h = Hypergraph.from_query(JoinQuery.parse("R(a,b), S(b,c), T(c,d), U(d,a)"))
    assert join_tree(h) is None
    tree = find_bag_tree(h)
    assert tree.width() == 2 and tree.validate(h) == []
    assert find_bag_tree(triangle_graph(12)).validate(triangle_graph(12)) == []


@pytest.mark.parametrize("n,depth", [(4, 2), (8, 3), (16, 4), (32, 5), (64, 6)])
def test_chain_depths(n, depth):
    out = log_depth_rewrite(chain_tree(n), chain_graph(n), check=True)
    assert out.tree.depth() == depth and out.tree.width() <= 3 and len(out.trace) <= math.log(n, 4 / 3) + 1


def test_triangle_chain_trace():
    h = triangle_graph(7)
    out = log_depth_rewrite(triangle_tree(7), h)
    assert [x[1:] for x in out.trace] == [(7, 1, 3), (3, 1, 1), (1, 1, 0)]
    assert (out.tree.depth(), out.tree.width(), out.tree.treewidth()) == (2, 3, 2)


@settings(max_examples=120, deadline=None)
@given(trees)
def test_log_depth_properties(case):
    h, tree = case
    iw = tree.intersection_width(h)
    for out, bound in ((log_depth_rewrite(tree, h, guard=False, check=True), max(tree.width(), 3 * iw)), (log_depth_rewrite_edge_labels(tree, h, check=True), 3 * tree.width()), (log_depth_rewrite_hypertree(tree, h), 3 * tree.width())):
        assert out.tree.validate(h) == [] and out.tree.width() <= bound
        assert len(out.trace) <= math.log(len(tree.chi), 4 / 3) + 1
        assert out.tree.depth() <= max(tree.depth(), len(out.trace))
        assert len(out.tree.chi) <= 2 * len(tree.chi)
    assert log_depth_rewrite_edge_labels(tree, h).tree.is_hypertree(h) == tree.is_hypertree(h)
    plain = log_depth_rewrite(tree, h, kind="tree", guard=False)
    assert plain.tree.validate(h) == [] and plain.tree.treewidth() <= predict_treewidth(tree)["refined"] <= predict_treewidth(tree)["general"] or tree.treewidth() >= plain.tree.treewidth()


@settings(max_examples=120, deadline=None)
@given(trees)
def test_selection_takes_a_quarter(case):
    h, tree = case
    leaves, tops = ExtendedTree(tree, h).select()
    assert len(leaves) + len(tops) >= math.ceil(len(tree.chi) / 4)


@settings(max_examples=80, deadline=None)
@given(trees)
def test_merge_and_minimal_and_complete(case):
    h, tree = case
    once = merge_rewrite(tree, h)
    assert once.validate(h) == [] and once.width() <= 2 * tree.width()
    if len(tree.chi) > 1:
        assert len(once.chi) <= 15 / 16 * len(tree.chi)
    both = merge_log_depth_rewrite(tree, h, 1).tree
    assert both.validate(h) == []
    small = once.make_minimal(h)
    assert small.validate(h) == [] and len(small.chi) <= 3 * len(h.edges)
    full = small.make_complete(h)
    assert full.validate(h) == [] and len(full.chi) <= 4 * len(h.edges) and full.depth() <= small.depth() + 1


@settings(max_examples=80, deadline=None)
@given(trees)
def test_rounds_and_potential(case):
    _, tree = case
    steps = sweep(tree)
    assert len(steps) <= tree.depth() + math.ceil(math.log2(len(tree.chi))) if len(tree.chi) > 1 else not steps
    assert count_rounds(tree)["down"] == tree.depth()
    assert tree.reroot("center").depth() <= tree.depth()


def test_validity_rules_are_checked():
    h = Hypergraph({"R": frozenset("ab"), "S": frozenset("bc")})
    assert BagTree({"x": frozenset("ab")}, {"x": frozenset("R")}, {"x": None}).validate(h)
    assert BagTree({"x": frozenset("ab"), "y": frozenset("c"), "z": frozenset("bc")}, {"x": frozenset("R"), "y": frozenset("S"), "z": frozenset("S")}, {"x": None, "y": "x", "z": "y"}).validate(h)
    assert BagTree({"x": frozenset("abc")}, {"x": frozenset("R")}, {"x": None}).validate(h)
    with pytest.raises(ValueError):
        BagTree({"x": frozenset("a"), "y": frozenset("a")}, {}, {"x": None, "y": None})


def test_costs():
    assert cost.one_round_chain_lower_bound(1e15, 1e10, 16) == pytest.approx(1e20)
    assert cost.epsilon(1e12, 1e6) == pytest.approx(2)
    assert cost.space_exponent(1e6, 1e6 / 1000**0.5, 1000) == pytest.approx(0.5)
    assert cost.chain_levels_cost(16, 1) == 48 and cost.chain_levels_cost(6, 1) == 18
    assert cost.grid_sizes([100, 300], 100) == [2, 6] and cost.grid_sent([100, 300], 100) == 100 * 6 + 300 * 2
    at = {"in_": 1e6, "out": 1e6, "m": 1e4}
    star = {m: cost.predict(m, n=10, w=1, iw=1, d=1, cover=5, **at) for m in ("parallel", "contraction", "share")}
    assert star["parallel"][1] < star["contraction"][1] and star["share"][0] == 1
    tri = {m: cost.predict(m, n=21, w=2, iw=1, d=6, **at) for m in ("decomposition", "log_depth", "contraction")}
    assert tri["decomposition"][1] < tri["log_depth"][1] < tri["contraction"][1]
    assert tri["log_depth"][0] < tri["decomposition"][0]


def test_planner():
    h = chain_graph(16)
    sizes = dict.fromkeys(h.edges, 25)
    names = {c.method for c in candidates(h, sizes, 25)}
    assert {"native", "sequential", "parallel", "log_depth", "merged_log_depth", "contraction", "share"} == names
    cheap_rounds = choose(h, dict.fromkeys(h.edges, 10**9), 10**9, round_cost=1.0, max_bag_rows=10**10)
    assert cheap_rounds.bag_rows <= 10**10


def test_parsing():
    q = JoinQuery.parse("R(A,B), R(B,C)")
    assert [a.name for a in q.atoms] == ["R", "R__2"] and q.shared == {"B"}
    with pytest.raises(ValueError):
        JoinQuery.parse("nothing")
