"""Statistics of a query's relations, gathered in one job, and the public join that plans by them."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce as fold

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.hypergraph import Hypergraph, find_bag_tree
from ..plans.planner import Choice, choose
from ..plans.query import JoinQuery
from ..plans.rewrite import log_depth_rewrite, merge_log_depth_rewrite
from . import baselines as B
from .decomposition import MAX_BAG_ROWS, decomposition_join
from .reducer import Runner, acyclic_join_sequential, hub_tree_join


@dataclass(frozen=True)
class Stats:
    """Rows of each atom, and how many values (about) each of its attributes has."""

    rows: dict[str, int]
    values: dict[str, dict[str, int]]

    @classmethod
    def of(cls, q: JoinQuery) -> Stats:
        """One job with one scan of each atom: counts and HyperLogLog sketches, whose size doesn't grow."""
        each = [
            a.df.select([F.col(c) for c in a.attrs]).agg(F.lit(a.name).alias("atom"), F.count("*").alias("n"), F.array(*[F.approx_count_distinct(c) for c in a.attrs]).alias("d")) for a in q.atoms
        ]
        got = {r.atom: r for r in fold(lambda x, y: x.unionAll(y), each).collect()}
        return cls({a.name: got[a.name].n for a in q.atoms}, {a.name: {c: max(1, min(d, got[a.name].n)) for c, d in zip(a.attrs, got[a.name].d, strict=True)} for a in q.atoms})

    @property
    def distinct(self) -> dict[str, int]:
        """Most values of each attribute in any atom."""
        out: dict[str, int] = {}
        for own in self.values.values():
            for c, d in own.items():
                out[c] = max(d, out.get(c, 1))
        return out

    def join_rows(self, names) -> float:
        """Estimated rows of the natural join of some atoms: of a shared attribute all atoms but that with the fewest values keep one value's share."""
        rows = math.prod(float(self.rows[n]) for n in names)
        for c in {c for n in names for c in self.values[n]}:
            rows /= math.prod(sorted(self.values[n][c] for n in names if c in self.values[n])[1:])
        return rows


def plan(q: JoinQuery, stats: Stats | None = None, m: int | None = None, round_cost: float = 1e6, max_bag_rows: int = MAX_BAG_ROWS) -> Choice:
    """The cheapest method by predicted rounds and tuples; see planner.choose."""
    stats = stats or Stats.of(q)
    out = int(min(1e18, stats.join_rows([a.name for a in q.atoms])))
    return choose(Hypergraph.from_query(q), stats.rows, out, m, round_cost, max_bag_rows, distinct=stats.distinct)


def join(q: JoinQuery, method: str = "auto", m: int | None = None, stats: Stats | None = None, max_bag_rows: int = MAX_BAG_ROWS, round_cost: float = 1e6, passes: int = 1) -> DataFrame:
    """The full join of q. method: auto (by statistics), native, sequential, parallel, decomposition, log_depth, merged_log_depth, contraction, share, hash, hub
    or single. m: tuples a reducer holds, for grid joins. Trees are searched with the statistics, so of equally wide bags those with fewer rows are taken."""
    h = Hypergraph.from_query(q)
    if len(h.components()) > 1:
        return decomposition_join(q, m=m, physical="grid" if m else "native", max_bag_rows=max_bag_rows)
    stats = stats or Stats.of(q)
    if method == "auto":
        method = plan(q, stats, m, round_cost, max_bag_rows).method
    if method == "native":
        return B.native_join(q, rows=stats.rows)
    if method in ("single", "share"):
        return {"single": B.single_machine_join, "share": B.one_round_share_join}[method](q)
    tree = find_bag_tree(h, rows=stats.join_rows).reroot("center")
    if method == "contraction":
        return B.contraction_join(q, tree, m, physical="grid" if m else "native")
    if method == "sequential" and tree.width() == 1:
        return acyclic_join_sequential(tree, q.bound(), Runner(q.shared)).select(*q.attributes)
    trees = {"log_depth": lambda: log_depth_rewrite(tree, h).tree, "merged_log_depth": lambda: merge_log_depth_rewrite(tree, h, passes).tree}
    known = ("sequential", "parallel", "decomposition", "hash", "hub", *trees)
    if method not in known:
        raise ValueError(f"no method {method!r}")
    if method == "hub" and tree.width() == 1:
        return hub_tree_join(tree, q.bound(), q.shared).select(*q.attributes)
    physical = "grid" if m else "hash" if method == "hash" else "native"
    return decomposition_join(q, trees.get(method, lambda: tree)(), m, physical, max_bag_rows=max_bag_rows)
