"""Bag trees: rooted trees whose bags carry attributes (chi) and covering relations (lam)."""

from __future__ import annotations

from typing import TYPE_CHECKING

from pyspark.sql import DataFrame, SparkSession

if TYPE_CHECKING:
    from .hypergraph import Hypergraph


class BagTree:
    """chi, lam: bag -> attributes, relations. parent: bag -> parent, None for the root. kind: 'general', 'hypertree', or 'tree' (without lam)."""

    def __init__(self, chi: dict[str, frozenset[str]], lam: dict[str, frozenset[str]], parent: dict[str, str | None], kind: str = "general"):
        self.chi = {b: frozenset(a) for b, a in chi.items()}
        self.lam = {b: frozenset(lam.get(b, ())) for b in chi}
        self.parent, self.kind = dict(parent), kind
        roots = [b for b in self.chi if self.parent.get(b) is None]
        if len(roots) != 1:
            raise ValueError(f"a bag tree has one root, not {roots}")
        self.root = roots[0]

    # structure

    def children(self, bag: str | None = None) -> dict[str, list[str]]:
        out: dict[str, list[str]] = {b: [] for b in self.chi}
        for b, p in self.parent.items():
            if p is not None:
                out[p].append(b)
        return out

    def edges(self) -> list[tuple[str, str]]:
        return [(p, b) for b, p in self.parent.items() if p is not None]

    def depths(self) -> dict[str, int]:
        kids, out, todo = self.children(), {self.root: 0}, [self.root]
        while todo:
            b = todo.pop()
            for c in kids[b]:
                out[c] = out[b] + 1
                todo.append(c)
        if len(out) != len(self.chi):
            raise ValueError("the bags are not one tree")
        return out

    def depth(self) -> int:
        return max(self.depths().values())

    def width(self) -> int:
        return max(len(x) for x in self.lam.values())

    def separator(self, a: str, b: str) -> frozenset[str]:
        return self.chi[a] & self.chi[b]

    def intersection_width(self, h: Hypergraph) -> int:
        """Most relations needed to cover what two neighbours share."""
        return max((len(h.min_cover(self.separator(p, b))) for p, b in self.edges()), default=0)

    def treewidth(self) -> int:
        return max(len(x) for x in self.chi.values()) - 1

    def tree_intersection_width(self) -> int:
        return max((len(self.separator(p, b)) for p, b in self.edges()), default=0)

    def leaf_potential(self) -> int:
        """Sum of 2^depth over the leaves; each upward round at least halves it."""
        kids, depth = self.children(), self.depths()
        return sum(2 ** depth[b] for b in self.chi if not kids[b])

    def stats(self, h: Hypergraph) -> dict:
        return {"bags": len(self.chi), "depth": self.depth(), "width": self.width(), "iw": self.intersection_width(h), "tw": self.treewidth(), "tiw": self.tree_intersection_width(), "valid": not self.validate(h)}

    # validity

    def validate(self, h: Hypergraph) -> list[str]:
        """Violations of the rules: each hyperedge inside a bag, bags of an attribute connected, attributes covered (unless a plain tree)."""
        self.depths()
        bad = [f"hyperedge {n} lies in no bag" for n, a in h.edges.items() if not any(a <= x for x in self.chi.values())]
        for v in sorted(frozenset().union(*self.chi.values())):
            tops = [b for b, x in self.chi.items() if v in x and (self.parent[b] is None or v not in self.chi[self.parent[b]])]
            if len(tops) != 1:
                bad.append(f"bags of {v} are not connected: {sorted(tops)}")
        if self.kind != "tree":
            bad += [f"bag {b} has uncovered attributes {sorted(x - h.attrs(self.lam[b]))}" for b, x in self.chi.items() if not x <= h.attrs(self.lam[b])]
        if self.kind == "hypertree" and not self.is_hypertree(h):
            bad.append("the descendant property fails")
        return bad

    def below(self) -> dict[str, frozenset[str]]:
        """Attributes in the subtree of each bag."""
        kids, out = self.children(), {}
        for b in sorted(self.chi, key=self.depths().get, reverse=True):
            out[b] = self.chi[b].union(*(out[c] for c in kids[b]))
        return out

    def is_hypertree(self, h: Hypergraph) -> bool:
        """Descendant property: what a bag's relations have in common with its subtree lies in its attributes."""
        below = self.below()
        return all(h.attrs(self.lam[b]) & below[b] <= self.chi[b] for b in self.chi)

    def edge_descendant_ok(self, labels: dict[tuple[str, str], tuple[frozenset[str], frozenset[str]]], h: Hypergraph) -> bool:
        """The same for edge labels (relations, attributes), on the subtree below each edge."""
        below = self.below()
        return all(h.edges[r] & below[c] <= chi for (_, c), (lam, chi) in labels.items() for r in lam)

    # transformations

    def copy(self, kind: str | None = None) -> BagTree:
        return BagTree(self.chi, self.lam, self.parent, kind or self.kind)

    def reroot(self, at: str = "center") -> BagTree:
        """The same tree with another root; 'center' halves the depth of a chain, 'given' changes nothing."""
        if at == "given":
            return self.copy()
        near: dict[str, set[str]] = {b: set() for b in self.chi}
        for p, b in self.edges():
            near[p].add(b)
            near[b].add(p)

        def farthest(start: str) -> list[str]:
            came, todo, last = {start: None}, [start], start
            for b in todo:
                last = b
                for c in sorted(near[b]):
                    if c not in came:
                        came[c] = b
                        todo.append(c)
            path = [last]
            while came[path[-1]] is not None:
                path.append(came[path[-1]])
            return path

        if at == "center":
            path = farthest(farthest(self.root)[0])
            at = path[len(path) // 2]
        parent, todo = {at: None}, [at]
        for b in todo:
            for c in sorted(near[b]):
                if c not in parent:
                    parent[c] = b
                    todo.append(c)
        return BagTree(self.chi, self.lam, {b: parent[b] for b in self.chi}, self.kind)

    def make_minimal(self, h: Hypergraph) -> BagTree:
        """Drops leaves, and bypasses bags with two neighbours, that hold no hyperedge which no other bag holds."""
        chi, lam, parent = dict(self.chi), dict(self.lam), dict(self.parent)
        while len(chi) > 1:
            kids: dict[str, list[str]] = {b: [] for b in chi}
            for b, p in parent.items():
                if p is not None:
                    kids[p].append(b)
            for b in sorted(chi):
                near = kids[b] + ([parent[b]] if parent[b] is not None else [])
                owns = any(a <= chi[b] and not any(a <= x for c, x in chi.items() if c != b) for a in h.edges.values())
                if len(near) > 2 or owns:
                    continue
                heir = parent[b] if parent[b] is not None else kids[b][0]
                for c in kids[b]:
                    parent[c] = heir if c != heir else None
                del chi[b], lam[b], parent[b]
                break
            else:
                break
        return BagTree(chi, lam, parent, self.kind)

    def absorb_contained(self) -> BagTree:
        """Contracts each bag whose attributes a neighbour has into that neighbour."""
        chi, lam, parent = dict(self.chi), dict(self.lam), dict(self.parent)
        while True:
            near = [(b, p) for b, p in sorted(parent.items()) if p is not None]
            pair = next(((x, y) for b, p in near for x, y in ((b, p), (p, b)) if chi[x] <= chi[y]), None)
            if pair is None:
                return BagTree(chi, lam, parent, self.kind)
            gone, heir = pair
            if parent[heir] == gone:
                parent[heir] = parent[gone]
            for b, p in parent.items():
                if p == gone and b != heir:
                    parent[b] = heir
            del chi[gone], lam[gone], parent[gone]

    def make_binary(self) -> tuple[BagTree, dict[str, str]]:
        """The tree with two children a bag at most: a bag with more becomes a chain of copies of it, each with one of the children. Also the bag of each copy."""
        kids, chi, lam, parent, source = self.children(), dict(self.chi), dict(self.lam), dict(self.parent), {b: b for b in self.chi}
        for b in self.chi:
            at, left = b, list(kids[b])
            while len(left) > 2:
                parent[left.pop(0)] = at
                copy = f"{b}~{len(kids[b]) - len(left)}"
                chi[copy], lam[copy], parent[copy], source[copy] = self.chi[b], self.lam[b], at, b
                at = copy
            for c in left:
                parent[c] = at
        return BagTree(chi, lam, parent, self.kind), source

    def make_complete(self, h: Hypergraph, strong: bool = True) -> BagTree:
        """Hangs a leaf for each hyperedge that is in no lam; with strong also for those whose attributes no bag with them in lam holds."""
        out = self.copy()
        for n, a in h.edges.items():
            if any(n in self.lam[b] and (not strong or a <= self.chi[b]) for b in self.chi):
                continue
            host = next(b for b in sorted(self.chi) if a <= self.chi[b])
            name = f"e_{n}"
            out.chi[name], out.lam[name], out.parent[name] = a, frozenset([n]), host
        return out

    # surface

    def to_df(self, spark: SparkSession) -> DataFrame:
        depth = self.depths()
        rows = [(b, self.parent[b], depth[b], sorted(self.chi[b]), sorted(self.lam[b])) for b in self.chi]
        return spark.createDataFrame(rows, "bag string, parent string, depth int, attrs array<string>, cover array<string>")

    def explain(self) -> str:
        kids, lines = self.children(), []

        def show(b: str, pad: str) -> None:
            lines.append(f"{pad}{b} chi={{{', '.join(sorted(self.chi[b]))}}} lam={{{', '.join(sorted(self.lam[b]))}}}")
            for c in kids[b]:
                show(c, pad + "  ")

        show(self.root, "")
        return "\n".join(lines)

    def dot(self) -> str:
        return "digraph {\n" + "".join(f'  "{p}" -> "{b}";\n' for p, b in self.edges()) + "}"
