"""Covers, searched trees, contraction and the descendant property of edge labels."""

import math
import random

import pytest
from hypothesis import given, settings
from test_structure import trees

from roundjoin.plans.bagtree import BagTree
from roundjoin.plans.hypergraph import Hypergraph, find_bag_tree, join_tree
from roundjoin.plans.query import JoinQuery
from roundjoin.plans.rewrite import ExtendedTree, contract, log_depth_rewrite, log_depth_rewrite_edge_labels
from roundjoin.studies import grouped_chain
from roundjoin.workloads import chain_graph, chain_tree, star_graph, star_tree, triangle_graph, triangle_tree

TRI_6 = "T1(o,p), T2(o,s), T3(p,s), T4(s,nat), T5(s,reg), T6(nat,reg)"
QUERIES = {"tri_6": TRI_6, "tri_12": "C1(c,cn), C2(c,g), C3(cn,g), O1(c,o), O2(c,t), O3(o,t), " + TRI_6, "cycle_4": "Customer(nat,cust), Orders(cust,o), Line(o,s), Supp(s,nat)"}


@pytest.mark.parametrize("name", QUERIES)
def test_no_bag_is_a_product_where_a_join_does(name):
    h = Hypergraph.from_query(JoinQuery.parse(QUERIES[name]))
    tree = find_bag_tree(h)
    for t in (tree, log_depth_rewrite(tree, h, guard=False).tree, log_depth_rewrite_edge_labels(tree, h).tree):
        assert t.validate(h) == []
        for b, lam in t.lam.items():
            assert h.pieces(lam) == 1 or all(h.pieces(c) > 1 for c in [h.min_cover(t.chi[b])])
    assert all(h.pieces(lam) == 1 for lam in tree.lam.values()) and tree.width() == 2


def test_bags_with_fewer_estimated_rows_are_taken():
    h = Hypergraph.from_query(JoinQuery.parse(TRI_6))
    dear = lambda lam: 1e9 if "T1" in lam else 1.0
    assert not any("T1" in lam for lam in find_bag_tree(h, rows=dear).lam.values())
    assert any("T1" in lam for lam in find_bag_tree(h).lam.values())


def test_covers_prefer_connected_relations():
    h = Hypergraph.from_query(JoinQuery.parse("A(a,x), B(b,y), C(b,x), D(a,z)"))
    assert h.pieces(h.min_cover(frozenset("ab"))) == 1 and h.pieces("AB") == 2 and h.pieces(("A", "C", "D")) == 1


def test_contained_bags_are_absorbed():
    h = Hypergraph({"R": frozenset("ab"), "S": frozenset("bc")})
    tree = BagTree({"x": frozenset("b"), "y": frozenset("ab"), "z": frozenset("bc"), "w": frozenset("c")}, {"x": "R", "y": "R", "z": "S", "w": "S"}, {"x": None, "y": "x", "z": "x", "w": "z"})
    small = tree.absorb_contained()
    assert small.validate(h) == [] and set(small.chi) == {"y", "z"}


@settings(max_examples=80, deadline=None)
@given(trees)
def test_contraction_steps(case):
    h, tree = case
    plan = contract(tree, h)
    binary, source = tree.make_binary()
    assert binary.validate(h) == [] and max(map(len, binary.children().values())) <= 2 and all(binary.chi[b] == tree.chi[g] for b, g in source.items())
    assert plan.tree.validate(h) == [] and plan.tree.width() <= 3 * tree.width()
    assert len(plan.steps) <= math.log(len(binary.chi), 4 / 3) + 1
    gone = [b for _, leaves in plan.steps for b, _ in leaves] + [b for shunts, _ in plan.steps for s in shunts for b in s.under]
    assert sorted(gone) == sorted(plan.tree.chi)
    for shunts, _ in plan.steps:
        for s in shunts:
            assert len(s.of) <= 3 and plan.tree.chi[s.into] == frozenset().union(*(binary.chi[b] for b in s.of))


@pytest.mark.parametrize("n", (4, 8, 16, 32, 64))
def test_contraction_is_logarithmic_on_stars_chains_and_triangles(n):
    for tree, h in ((star_tree(n), star_graph(n)), (chain_tree(n), chain_graph(n)), (triangle_tree(n), triangle_graph(n))):
        assert len(contract(tree, h).steps) <= math.log2(n) + 2


@settings(max_examples=60, deadline=None)
@given(trees)
def test_edge_labels_keep_the_descendant_property(case):
    h, tree = case
    if tree.is_hypertree(h):
        x = ExtendedTree(tree, h, "edges")
        assert x.tree.edge_descendant_ok({(p, b): x.label[b] for p, b in x.tree.edges()}, h)
    broken = BagTree({"u": frozenset("ab"), "v": frozenset("b")}, {"u": frozenset(["R"]), "v": frozenset(["S"])}, {"u": None, "v": "u"})
    g = Hypergraph({"R": frozenset("ab"), "S": frozenset("bc")})
    assert broken.edge_descendant_ok({("u", "v"): (frozenset(["S"]), frozenset("b"))}, g)
    deeper = BagTree({"u": frozenset("ab"), "v": frozenset("b"), "w": frozenset("bc")}, {"u": frozenset(["R"]), "v": frozenset(["S"]), "w": frozenset(["S"])}, {"u": None, "v": "u", "w": "v"})
    assert not deeper.edge_descendant_ok({("u", "v"): (frozenset(["S"]), frozenset("b"))}, g)


def test_grouped_chains():
    for n, size, bags in ((16, 3, 6), (16, 1, 16), (9, 4, 3)):
        tree, h = grouped_chain(n, size)
        assert tree.validate(h) == [] and (len(tree.chi), tree.width()) == (bags, min(size, n))


def test_random_searches_are_valid():
    rng = random.Random(5)
    for _ in range(25):
        attrs = "abcdefg"[: rng.randint(3, 7)]
        h = Hypergraph({f"R{i}": frozenset(rng.sample(attrs, 2)) for i in range(rng.randint(3, 7))})
        if len(h.components()) == 1:
            tree = find_bag_tree(h)
            assert tree.validate(h) == []
            assert tree.width() == 1 or join_tree(h) is None
