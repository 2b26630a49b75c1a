"""Hypergraph of a query, covers, acyclicity and the search for bag trees."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession

from .bagtree import BagTree
from .query import JoinQuery

Attrs = frozenset


class Hypergraph:
    """A vertex per attribute, a hyperedge per atom."""

    def __init__(self, edges: dict[str, frozenset[str]]):
        self.edges = {n: frozenset(a) for n, a in edges.items()}

    @classmethod
    def from_query(cls, q: JoinQuery) -> Hypergraph:
        return cls({a.name: frozenset(a.attrs) for a in q.atoms})

    @property
    def vertices(self) -> frozenset[str]:
        return frozenset().union(*self.edges.values())

    def attrs(self, names) -> frozenset[str]:
        return frozenset().union(*(self.edges[n] for n in names))

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(n, sorted(a)) for n, a in sorted(self.edges.items())], "edge string, attrs array<string>")

    def components(self) -> list[Hypergraph]:
        """Connected parts, in the order of their first edges."""
        left, out = dict(self.edges), []
        while left:
            name, attrs = next(iter(left.items()))
            part, reach = {name: left.pop(name)}, set(attrs)
            while more := [n for n, a in left.items() if a & reach]:
                for n in more:
                    reach |= left[n]
                    part[n] = left.pop(n)
            out.append(Hypergraph({n: self.edges[n] for n in self.edges if n in part}))
        return out

    def pieces(self, names: Iterable[str]) -> int:
        """Parts that the given hyperedges fall into; a join of several parts is a product."""
        left, n = {x: self.edges[x] for x in names}, 0
        while left:
            n += 1
            _, reach = left.popitem()
            while near := [x for x, a in left.items() if a & reach]:
                for x in near:
                    reach = reach | left.pop(x)
        return n

    def min_cover(self, attrs: frozenset[str], prefer: frozenset[str] = frozenset(), k_max: int = 4) -> frozenset[str]:
        """Fewest hyperedges that cover attrs; of equally many those in the fewest unconnected parts, then those that also cover most of prefer, then by name.
        Greedy beyond k_max edges."""
        attrs = frozenset(attrs)
        if not attrs:
            return frozenset()
        useful = sorted(n for n, a in self.edges.items() if a & attrs)
        for k in range(1, k_max + 1):
            fits = [c for c in combinations(useful, k) if attrs <= self.attrs(c)]
            if fits:
                return frozenset(max(fits, key=lambda c: (-self.pieces(c), len(self.attrs(c) & prefer), [-ord(x) for x in ",".join(c)])))
        cover, left = set(), set(attrs)
        while left:
            best = max(useful, key=lambda n: len(self.edges[n] & left))
            if not self.edges[best] & left:
                raise ValueError(f"{sorted(left)} lie in no hyperedge")
            cover.add(best)
            left -= self.edges[best]
        return frozenset(cover)


def join_tree(h: Hypergraph) -> BagTree | None:
    """Width-1 bag tree by ear removal, or None if the hypergraph is cyclic or not connected."""
    left, parent, order = dict(h.edges), {}, []
    while len(left) > 1:
        for name, attrs in sorted(left.items()):
            outside = frozenset().union(*(a for n, a in left.items() if n != name))
            shared = attrs & outside
            hosts = sorted((n for n, a in left.items() if n != name and shared <= a and (shared or not attrs)), key=lambda n: (-len(left[n] & attrs), n))
            if hosts and shared:
                parent[name] = hosts[0]
                order.append(name)
                del left[name]
                break
        else:
            return None
    root = next(iter(left))
    parent[root] = None
    return BagTree({n: h.edges[n] for n in h.edges}, {n: frozenset([n]) for n in h.edges}, parent)


def _search(h: Hypergraph, k: int, connected: bool, rows: Callable[[tuple[str, ...]], float]) -> BagTree | None:
    """A bag tree of width k at most by recursive separation: a bag takes k hyperedges that cover what the part shares with its parent, and each part that is
    left connected outside the bag is solved by itself. Solved parts are remembered.

    connected: only hyperedges that share attributes make a bag, so that none is a product. Of as many hyperedges those that reach least beyond the part come
    first, then those with the fewest estimated rows."""
    names = sorted(h.edges)
    covers = {size: [(lam, h.attrs(lam), rows(lam)) for lam in combinations(names, size) if not connected or h.pieces(lam) == 1] for size in range(1, k + 1)}
    memo: dict[tuple[frozenset[str], frozenset[str]], tuple | None] = {}

    def parts(edges: frozenset[str], outside: frozenset[str]) -> list[frozenset[str]]:
        left, out = {n for n in edges if not h.edges[n] <= outside}, []
        while left:
            group, reach = set(), set()
            todo = [min(left)]
            while todo:
                n = todo.pop()
                if n in left:
                    left.discard(n)
                    group.add(n)
                    reach |= h.edges[n] - outside
                    todo += [m for m in left if h.edges[m] & reach]
            out.append(frozenset(group))
        return out

    def solve(edges: frozenset[str], link: frozenset[str]):
        key = (edges, link)
        if key not in memo:
            memo[key] = None
            scope = h.attrs(edges) | link
            for size in range(1, k + 1):
                for lam, whole, _ in sorted(covers[size], key=lambda c: (len(c[1] - scope), c[2], c[0])):
                    if not link <= whole or not (whole & (h.attrs(edges) - link) or not edges):
                        continue
                    chi = whole & scope
                    rest = parts(edges, chi)
                    if any(p == edges for p in rest):
                        continue
                    below = []
                    for p in rest:
                        sub = solve(p, h.attrs(p) & chi)
                        if sub is None:
                            break
                        below.append(sub)
                    else:
                        memo[key] = (frozenset(lam), chi, below)
                        return memo[key]
        return memo[key]

    found = solve(frozenset(names), frozenset())
    if found is None:
        return None
    chi, lam, parent = {}, {}, {}

    def place(node, above):
        name = f"b{len(chi)}"
        lam[name], chi[name], parent[name] = node[0], node[1], above
        for x in node[2]:
            place(x, name)

    place(found, None)
    return BagTree(chi, lam, parent)


def _eliminate(h: Hypergraph) -> BagTree:
    """Bag tree from a least-fill elimination order, bags covered greedily; for queries too large to search."""
    near = {v: frozenset().union(*(a for a in h.edges.values() if v in a)) - {v} for v in h.vertices}
    bags, order = {}, []
    while near:
        v = min(near, key=lambda x: (sum(1 for a, b in combinations(sorted(near[x]), 2) if b not in near[a]), len(near[x]), x))
        bags[v] = frozenset({v}) | near[v]
        order.append(v)
        for a in near[v]:
            near[a] = (near[a] | near[v]) - {a, v}
        del near[v]
    at = {v: i for i, v in enumerate(order)}
    parent = {}
    for v in order:
        later = [x for x in bags[v] if x != v]
        parent[v] = min(later, key=at.get) if later else None
    roots = [v for v in order if parent[v] is None]
    for r in roots[:-1]:
        parent[r] = roots[-1]
    tree = BagTree({f"b{at[v]}": bags[v] for v in order}, {f"b{at[v]}": h.min_cover(bags[v]) for v in order}, {f"b{at[v]}": None if parent[v] is None else f"b{at[parent[v]]}" for v in order})
    return tree.make_minimal(h)


def find_bag_tree(h: Hypergraph, k_max: int = 4, method: str = "auto", rows: Callable[[tuple[str, ...]], float] = lambda lam: 0.0) -> BagTree:
    """A bag tree: ear removal for acyclic queries, else the least width that the search finds, else (large queries) elimination.

    Of trees of the least width one without product bags is taken where there is one. rows: estimated rows of the join of some hyperedges, if known."""
    if method in ("auto", "ears") and (tree := join_tree(h)) is not None:
        return tree
    if method == "search" or method == "auto" and len(h.edges) <= 24:
        for k in range(1, k_max + 1):
            for connected in (True, False):
                if (tree := _search(h, k, connected, rows)) is not None:
                    return tree.absorb_contained().make_minimal(h)
        if method == "search":
            raise ValueError(f"no bag tree of width {k_max} at most")
    return _eliminate(h)


def query_width(h: Hypergraph, k_max: int = 4) -> int:
    """Least width over the bag trees searched, 1 exactly for acyclic queries."""
    return find_bag_tree(h, k_max, "auto").width()
