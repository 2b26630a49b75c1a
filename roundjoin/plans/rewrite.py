"""Rewrites of bag trees: logarithmic depth in three variants, merging of neighbouring bags, and the two together."""

from __future__ import annotations

from dataclasses import dataclass, field

from .bagtree import BagTree
from .hypergraph import Hypergraph

Label = tuple[frozenset[str], frozenset[str]]  # relations and attributes


@dataclass
class ExtendedTree:
    """A bag tree in the course of a rewrite: which bags are still active, their heights, and a label for each edge between active bags.

    mode 'cover': an edge's label is a smallest cover of what its bags share, and that; 'edges': a copy of the child's label;
    'closed': the cover and all attributes of it."""

    tree: BagTree
    h: Hypergraph
    mode: str = "cover"
    active: set[str] = field(default_factory=set)
    height: dict[str, int] = field(default_factory=dict)
    label: dict[str, Label] = field(default_factory=dict)  # by the child of the edge
    made: int = 0

    def __post_init__(self):
        self.tree = self.tree.copy()
        self.active = set(self.tree.chi)
        self.height = dict.fromkeys(self.active, 0)
        for p, b in self.tree.edges():
            self.label[b] = self._label(p, b)

    def _label(self, p: str, b: str) -> Label:
        t = self.tree
        if self.mode == "edges":
            return t.lam[b], t.chi[b]
        shared = t.separator(p, b)
        if t.kind == "tree":
            return frozenset(), shared
        # among smallest covers prefer one that also covers neighbouring separators: then the new bag is a join, not a product
        around = shared.union(*(t.separator(b, c) for c, q in t.parent.items() if q == b))
        cover = self.h.min_cover(shared, prefer=around)
        return (cover, self.h.attrs(cover)) if self.mode == "closed" else (cover, shared)

    def active_children(self, b: str) -> list[str]:
        return [c for c, p in self.tree.parent.items() if p == b and c in self.active]

    def leaves(self) -> list[str]:
        return [b for b in self.tree.chi if b in self.active and not self.active_children(b)]

    def chain_tops(self) -> list[str]:
        """Active bags with one active child that has itself one active child, top-down."""
        depth = self.tree.depths()
        one = {b: kids[0] for b in self.active if len(kids := self.active_children(b)) == 1}
        return sorted((b for b, c in one.items() if c in one), key=lambda b: (depth[b], b))

    def select(self) -> tuple[list[str], list[str]]:
        """The active leaves, and chain tops no two of which are neighbours, chosen top-down: a quarter of the active bags at least."""
        chosen: set[str] = set()
        for b in self.chain_tops():
            if self.tree.parent[b] not in chosen:
                chosen.add(b)
        return self.leaves(), [b for b in self.chain_tops() if b in chosen]

    def _settle(self, b: str) -> None:
        below = [self.height[c] for c, p in self.tree.parent.items() if p == b and c not in self.active]
        self.height[b] = 1 + max(below) if below else 0

    def retire_leaf(self, b: str) -> None:
        self.active.discard(b)
        self.label.pop(b, None)
        self._settle(b)

    def fold_chain(self, u: str) -> str:
        """A new bag takes the place of u; u and its child hang under it, inactive, and the grandchild under it, active. It is labelled by the labels of the
        edge above u (if any), of that to the child and of that to the grandchild."""
        t = self.tree
        c = self.active_children(u)[0]
        g = self.active_children(c)[0]
        above = self.label.get(u)
        s = f"s{self.made}"
        while s in t.chi:
            self.made += 1
            s = f"s{self.made}"
        self.made += 1
        labels = [x for x in (above, self.label[c], self.label[g]) if x is not None]
        t.lam[s] = frozenset().union(*(x[0] for x in labels))
        t.chi[s] = frozenset().union(*(x[1] for x in labels))
        if self.mode == "cover" and self.h.pieces(t.lam[s]) > 1:
            # another cover, if as many relations can be one join instead of a product
            other = self.h.min_cover(t.chi[s])
            if len(other) <= len(t.lam[s]) and self.h.pieces(other) < self.h.pieces(t.lam[s]):
                t.lam[s] = other
        t.parent[s] = t.parent[u]
        if t.parent[u] is None:
            t.root = s
        for b in (u, c, g):
            t.parent[b] = s
        self.active -= {u, c}
        self.active.add(s)
        self.label.pop(u, None)
        self.label.pop(c)
        if above is not None:
            self.label[s] = above
        self._settle(c)
        self._settle(u)
        self.height[s] = 0
        return s


@dataclass
class Rewritten:
    """The rewritten tree and one trace row an iteration: active bags before it, leaves retired, chain tops folded."""

    tree: BagTree
    trace: list[tuple[int, int, int, int]]


def _run(tree: BagTree, h: Hypergraph, mode: str, check: bool) -> Rewritten:
    x, trace = ExtendedTree(tree, h, mode), []
    while x.active:
        leaves, tops = x.select()
        trace.append((len(trace), len(x.active), len(leaves), len(tops)))
        for u in tops:
            x.fold_chain(u)
            if check and (bad := x.tree.validate(h)):
                raise AssertionError(bad)
        for b in leaves:
            x.retire_leaf(b)
    return Rewritten(x.tree, trace)


def log_depth_rewrite(tree: BagTree, h: Hypergraph, kind: str | None = None, guard: bool = True, check: bool = False) -> Rewritten:
    """Depth O(log bags), width at most max(w, 3 iw). kind='tree' works on attributes alone. guard: the input tree comes back if the result is no less deep."""
    base = tree.copy(kind) if kind else tree
    out = _run(base, h, "cover", check)
    if guard and out.tree.depth() >= tree.depth() and tree.width() <= max(out.tree.width(), 1):
        return Rewritten(base.copy(), out.trace)
    return out


def log_depth_rewrite_edge_labels(tree: BagTree, h: Hypergraph, check: bool = False) -> Rewritten:
    """Variant that copies whole bag labels: width at most 3 w, at most twice the bags, and a hypertree stays one."""
    return _run(tree, h, "edges", check)


def log_depth_rewrite_hypertree(tree: BagTree, h: Hypergraph, check: bool = False) -> Rewritten:
    """Variant for hypertrees: new bags hold all attributes of their covers, width at most max(w, 3 iw). Where that breaks a rule, the edge-label variant."""
    out = _run(tree.copy("hypertree"), h, "closed", False)
    return out if not out.tree.validate(h) else log_depth_rewrite_edge_labels(tree, h, check)


@dataclass(frozen=True)
class Shunt:
    """A bag made of three whole bags, which then has the first two of a chain under it: into, the chain's bags, and the bags whose labels it joins."""

    into: str
    under: tuple[str, str]
    of: tuple[str, ...]


@dataclass
class Contraction:
    """The contracted tree, step by step its shunts and its leaves that go into their parent (None for the last bag), and the given bag of each copy."""

    tree: BagTree
    steps: list[tuple[list[Shunt], list[tuple[str, str | None]]]]
    source: dict[str, str]


def contract(tree: BagTree, h: Hypergraph) -> Contraction:
    """Contracts a tree to one bag: it is made binary, then in each step leaves go into their parents, two at most into one, and chains of three bags that don't touch
    become one bag that joins three whole bags of the tree. A quarter of the bags goes at least, so the steps are logarithmic in the bags, whatever the depth."""
    tree, copies = tree.make_binary()
    x, steps = ExtendedTree(tree, h, "edges"), []
    source = {b: b for b in tree.chi}  # the bag whose label the edge above an active bag has
    while x.active:
        leaves, tops = x.select()
        shunts = []
        for u in tops:
            c = x.active_children(u)[0]
            g = x.active_children(c)[0]
            top = u in x.label
            s = x.fold_chain(u)
            shunts.append(Shunt(s, (u, c), tuple(source[b] for b in ([u] if top else []) + [c, g])))
            if top:
                source[s] = source[u]
        steps.append((shunts, [(b, x.tree.parent[b]) for b in leaves]))
        for b in leaves:
            x.retire_leaf(b)
    return Contraction(x.tree, steps, copies)


def predict_treewidth(tree: BagTree) -> dict[str, int]:
    """Bounds on the treewidth after the attribute-only rewrite: the general one and the one by separators."""
    tw, tiw = tree.treewidth(), tree.tree_intersection_width()
    return {"general": 3 * tw + 2, "refined": max(tw, 3 * tiw - 1)}


def merge_bags(tree: BagTree, keep: str, gone: str) -> BagTree:
    """Two neighbours, or two leaves of one parent, become one bag with the union of their labels."""
    if not (tree.parent[gone] == keep or tree.parent[keep] == gone or tree.parent[keep] == tree.parent[gone] is not None and not tree.children()[keep] and not tree.children()[gone]):
        raise ValueError(f"{keep} and {gone} are neither neighbours nor sibling leaves")
    if tree.parent[keep] == gone:
        keep, gone = gone, keep
    chi, lam = dict(tree.chi), dict(tree.lam)
    chi[keep] |= chi.pop(gone)
    lam[keep] |= lam.pop(gone)
    parent = {b: (keep if p == gone else p) for b, p in tree.parent.items() if b != gone}
    return BagTree(chi, lam, parent, tree.kind)


def merge_rewrite(tree: BagTree, h: Hypergraph, passes: int = 1) -> BagTree:
    """Each pass pairs sibling leaves, gives an odd one to its parent, and contracts a bag with its only child where that child has evenly many leaves.
    A bag is merged once in a pass, so the width at most doubles; the bags fall to 15/16 at most."""
    for _ in range(passes):
        kids, depth, used, todo = tree.children(), tree.depths(), set(), []
        leaf = {b for b in tree.chi if not kids[b]}
        for p in sorted(tree.chi, key=lambda b: (depth[b], b)):
            low = sorted(c for c in kids[p] if c in leaf)
            if len(low) % 2 and p not in used:
                todo.append((p, low.pop()))
                used.add(p)
            todo += [(a, b) for a, b in zip(low[::2], low[1::2], strict=False)]
        for p in sorted(tree.chi, key=lambda b: (depth[b], b)):
            if len(kids[p]) == 1 and p not in used and (c := kids[p][0]) not in used and c not in leaf and len([x for x in kids[c] if x in leaf]) % 2 == 0:
                todo.append((p, c))
                used |= {p, c}
        for a, b in todo:
            tree = merge_bags(tree, a, b)
    return tree


def merge_log_depth_rewrite(tree: BagTree, h: Hypergraph, passes: int = 1) -> Rewritten:
    """Merge passes, then the log-depth rewrite."""
    return log_depth_rewrite(merge_rewrite(tree, h, passes), h)
