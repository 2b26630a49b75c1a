"""Decomposition joins: bags are materialised in one round, then joined as an acyclic query along their tree."""

from __future__ import annotations

from functools import reduce as fold

from pyspark.sql import DataFrame

from ..plans.bagtree import BagTree
from ..plans.cost import CostLedger, join_cost
from ..plans.hypergraph import Hypergraph, find_bag_tree
from ..plans.query import JoinQuery
from . import primitives as P
from .reducer import Runner, acyclic_join_parallel


#: Most rows that a product bag may have unless the call says otherwise.
MAX_BAG_ROWS = 10**9


class BagTooLarge(RuntimeError):
    """A bag could exceed the rows allowed."""


def _ordered(names: list[str], rels: dict[str, DataFrame]) -> list[str]:
    """Relations of a bag so that each shares an attribute with those before it, as far as can be; products come last."""
    left, out = sorted(names), []
    while left:
        have = {c for n in out for c in rels[n].columns}
        nxt = next((n for n in left if have & set(rels[n].columns)), left[0])
        left.remove(nxt)
        out.append(nxt)
    return out


def bag_bound(tree: BagTree, sizes: dict[str, int]) -> dict[str, int]:
    """Most rows of each bag: the product of its relations' sizes."""
    out = {}
    for b, lam in tree.lam.items():
        rows = 1
        for n in lam:
            rows *= sizes[n]
        out[b] = rows
    return out


def _guard(parts: dict[str, list[DataFrame]], max_rows: int) -> None:
    """Refuses bags that are products of more than max_rows rows; the relations of all product bags are counted in one job."""
    products = {b: [d for d in ds] for b, ds in parts.items() if len(ds) > 1 and _unconnected(ds)}
    known = iter(P.counts([d for ds in products.values() for d in ds]))
    for b, ds in products.items():
        rows = 1
        for _ in ds:
            rows *= next(known)
        if rows > max_rows:
            raise BagTooLarge(f"bag {b} could have {rows} rows, more than {max_rows}")


def _unconnected(dfs: list[DataFrame]) -> bool:
    """Whether a relation shares no attribute with those before it."""
    have = set(dfs[0].columns)
    for d in dfs[1:]:
        if not have & set(d.columns):
            return True
        have |= set(d.columns)
    return False


def materialize_bags(tree: BagTree, rels: dict[str, DataFrame], run: Runner, project: bool = True, max_rows: int | None = MAX_BAG_ROWS) -> dict[str, DataFrame]:
    """Join of each bag's relations. project: to the bag's attributes, without duplicates; relations without shared attributes are cut to the bag's attributes
    first, so that a product is one of key values only. A product that could have more than max_rows rows raises BagTooLarge."""
    parts: dict[str, list[DataFrame]] = {}
    for b in tree.chi:
        chi = tree.chi[b]
        parts[b] = []
        for n in _ordered(list(tree.lam[b]), rels):
            df = rels[n]
            others = {c for m in tree.lam[b] if m != n for c in rels[m].columns}
            useful = [c for c in df.columns if c in chi or c in others or c.startswith("__m_")]
            if project and len(useful) < len(df.columns):
                df = run.made(df.select(*useful).dropDuplicates() if useful else df.select().limit(1), df)
            parts[b].append(df)
    if max_rows is not None:
        _guard(parts, max_rows)
    out = {}
    for b, dfs in parts.items():
        chi = tree.chi[b]
        if run.ledger is not None and len(dfs) > 1:
            sent = join_cost([run.size(d) for d in dfs], run.m_or_none())
            dfs = [run.table(d) for d in dfs]
        joined = P.grid_join(dfs, run.m, loads=run.loads) if run.physical == "grid" and len(dfs) > 1 else fold(lambda x, y: P.natural_join(x, y, run.loose(x, y), hint=run.hint(y, x)), dfs)
        if project and set(joined.columns) - chi:
            joined = joined.select(*[c for c in joined.columns if c in chi]).dropDuplicates()
        out[b] = run.keyed(run.made(joined, *dfs), run.key(joined)) if len(dfs) > 1 else joined
        if run.ledger is not None and len(dfs) > 1:
            run.note(1, "materialise", b, sent, joined)
            out[b] = run.table(joined)
    run.at += int(tree.width() > 1)
    return run.settle(out)


def decomposition_join(q: JoinQuery, tree: BagTree | None = None, m: int | None = None, physical: str = "native", project_bags: bool = True, barrier: str = "auto", ledger: CostLedger | None = None, max_bag_rows: int | None = MAX_BAG_ROWS, bag: bool = False, reduce: bool = True) -> DataFrame:
    """The full join of q along a bag tree (searched for if none is given); components of a disconnected query are joined apart and multiplied.

    bag: multiset semantics, with the number of copies of each answer in __mult."""
    h = Hypergraph.from_query(q)
    rels = q.bound(bag=bag)
    if len(parts := h.components()) > 1:
        if tree is not None:
            raise ValueError("a disconnected query has a tree for each component; leave tree out")
        done = [_connected(q, p, find_bag_tree(p), rels, m, physical, project_bags, barrier, ledger, max_bag_rows, reduce) for p in parts]
        return _finish(fold(lambda a, b: a.crossJoin(b), done), q, bag)
    return _finish(_connected(q, h, tree or find_bag_tree(h), rels, m, physical, project_bags, barrier, ledger, max_bag_rows, reduce), q, bag)


def _connected(q: JoinQuery, h: Hypergraph, tree: BagTree, rels, m, physical, project, barrier, ledger, max_rows, reduce) -> DataFrame:
    if tree.kind == "tree":
        tree = BagTree(tree.chi, {b: h.min_cover(x) for b, x in tree.chi.items()}, tree.parent)
    tree = tree.make_complete(h, strong=project)
    carried = {n: [c for c in rels[n].columns if c.startswith("__m_")] for n in h.edges}
    if any(carried.values()):
        # multiplicities ride with the first bag that holds their atom whole
        tree = tree.copy()
        for n, cols in carried.items():
            home = next(b for b in sorted(tree.chi) if n in tree.lam[b] and h.edges[n] <= tree.chi[b])
            tree.chi[home] = tree.chi[home] | frozenset(cols)
    run = Runner(q.shared, m, physical, barrier, ledger=ledger)
    for a in q.atoms:
        if a.key and a.name in h.edges:
            run.keyed(rels[a.name], frozenset(a.key))
    bags = materialize_bags(tree, {n: rels[n] for n in h.edges}, run, project, max_rows)
    if any(carried.values()):
        bags = {b: d.select(*[c for c in d.columns if not c.startswith("__m_") or c in tree.chi[b]]) for b, d in bags.items()}
    return acyclic_join_parallel(tree, bags, run, reduce)


def _finish(df: DataFrame, q: JoinQuery, bag: bool) -> DataFrame:
    from pyspark.sql import functions as F

    if not bag:
        return df.select(*q.attributes)
    mult = fold(lambda a, b: a * b, [F.col(f"__m_{a.name}") for a in q.atoms])
    return df.select(*q.attributes, mult.alias("__mult"))


def expand_multiset(df: DataFrame) -> DataFrame:
    """Each answer as often as __mult says."""
    from pyspark.sql import functions as F

    return df.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__mult")))).drop("__copy", "__mult")


def decomposition_sql(q: JoinQuery, tree: BagTree | None = None, distinct: bool = True) -> str:
    """Text of the decomposition join over views named like the atoms, whose columns are the attributes: bags, semijoins up, joins down. Plain SQL."""
    h = Hypergraph.from_query(q)
    tree = (tree or find_bag_tree(h)).make_complete(h)
    depth, kids, ctes = tree.depths(), tree.children(), []
    shared = q.shared

    def matched(a: str, b: str, on) -> str:
        return " AND ".join(f"{a}.{c} = {b}.{c}" if c in shared else f"{a}.{c} IS NOT DISTINCT FROM {b}.{c}" for c in sorted(on)) or "TRUE"

    for b in sorted(tree.chi, key=lambda b: (-depth[b], b)):
        names = _ordered_names(sorted(tree.lam[b]), h)
        chi = ", ".join(sorted(tree.chi[b]))
        rows, have = names[0], set(h.edges[names[0]])
        for n in names[1:]:
            on = have & h.edges[n]
            rows += f" JOIN {n} USING ({', '.join(sorted(on))})" if on else f" CROSS JOIN {n}"
            have |= h.edges[n]
        known = [f"{c} IS NOT NULL" for c in sorted(tree.chi[b] & shared)] + [f"({test})" for attr, test in q.filters if attr in tree.chi[b]]
        ctes.append(f"bag_{b} AS (SELECT {'DISTINCT ' if distinct else ''}{chi} FROM {rows}{' WHERE ' + ' AND '.join(known) if known else ''})")
        tests = [f"EXISTS (SELECT 1 FROM up_{c} WHERE {matched(f'up_{c}', f'bag_{b}', tree.separator(b, c))})" for c in kids[b]]
        ctes.append(f"up_{b} AS (SELECT * FROM bag_{b}{' WHERE ' + ' AND '.join(tests) if tests else ''})")
    joined, have = f"up_{tree.root}", set(tree.chi[tree.root])
    for b in sorted(tree.chi, key=lambda b: (depth[b], b))[1:]:
        if tree.chi[b] - have:
            on = tree.chi[b] & have
            joined += f" JOIN up_{b} USING ({', '.join(sorted(on))})" if on else f" CROSS JOIN up_{b}"
            have |= tree.chi[b]
    return f"WITH {', '.join(ctes)} SELECT {', '.join(q.attributes)} FROM {joined}"


def _ordered_names(names: list[str], h: Hypergraph) -> list[str]:
    left, out = list(names), []
    while left:
        have = h.attrs(out) if out else frozenset()
        out.append(next((n for n in left if have & h.edges[n]), left[0]))
        left.remove(out[-1])
    return out
