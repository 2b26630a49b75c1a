"""Baselines: the one-round share join, tree contraction, a single machine, and plans left to Catalyst."""

from __future__ import annotations

import math
from functools import reduce as fold
from itertools import combinations_with_replacement

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.bagtree import BagTree
from ..plans.cost import CostLedger, join_cost, semijoin_cost
from ..plans.hypergraph import Hypergraph, find_bag_tree
from ..plans.query import JoinQuery
from ..plans.rewrite import Contraction, contract
from . import primitives as P
from .decomposition import _ordered, materialize_bags
from .reducer import Runner


def best_shares(q: JoinQuery, sizes: dict[str, int], reducers: int) -> dict[str, int]:
    """Powers of two, one for each shared attribute, whose product is the largest power of two within `reducers`, that send the fewest copies: all splits where
    they are few, else the attribute whose doubling costs least, time after time, then single exchanges while they help."""
    attrs, bits = sorted(q.shared), int(math.log2(max(1, reducers)))
    if not attrs:
        return {}

    def sent(split: tuple[int, ...]) -> int:
        return share_sent(q, sizes, {a: 2**k for a, k in zip(attrs, split, strict=True)})

    if math.comb(len(attrs) + bits - 1, bits) <= 5_000:
        best = min((tuple(map(chosen.count, range(len(attrs)))) for chosen in combinations_with_replacement(range(len(attrs)), bits)), key=sent)
    else:
        moved = lambda split, i, j: tuple(k - (x == i) + (x == j) for x, k in enumerate(split))
        best = (0,) * len(attrs)
        for _ in range(bits):
            best = min((moved(best, None, j) for j in range(len(attrs))), key=sent)
        while (other := min((moved(best, i, j) for i in range(len(attrs)) if best[i] for j in range(len(attrs))), key=sent)) != best and sent(other) < sent(best):
            best = other
    return {a: 2**k for a, k in zip(attrs, best, strict=True)}


def share_sent(q: JoinQuery, sizes: dict[str, int], shares: dict[str, int]) -> int:
    """Tuples that the share join sends."""
    return sum(sizes[x.name] * math.prod(s for a, s in shares.items() if a not in x.attrs) for x in q.atoms)


def one_round_share_join(q: JoinQuery, reducers: int = 16, shares: dict[str, int] | str = "auto") -> DataFrame:
    """Reducers are a grid with an axis for each attribute; a tuple goes to its hashed place on the axes of its attributes and to all places on the others.
    Each cell is one partition, to which every relation is sent once and where all joins are done, so nothing that they make is sent."""
    rels = q.bound()
    if shares == "auto":
        shares = best_shares(q, dict(zip(rels, P.counts(list(rels.values())), strict=True)), reducers)
    axes = {a: s for a, s in shares.items() if s > 1}
    placed = {}
    for n, d in rels.items():
        cell = F.lit(0)
        for a, s in axes.items():
            if a in d.columns:
                place = F.pmod(F.xxhash64(F.lit(31), F.col(a)), F.lit(s)).cast("int")
            else:
                d = d.withColumn(f"__x_{a}", F.explode(F.sequence(F.lit(0), F.lit(s - 1))))
                place = F.col(f"__x_{a}")
            cell = cell * s + place
        placed[n] = d.select(*rels[n].columns, cell.alias("__cell")).repartitionById(math.prod(axes.values()), "__cell") if axes else d
    order = _ordered(list(rels), rels)
    # merged, never broadcast: Spark takes the copies of a small relation to be as small as the relation, and would gather all of them on the driver
    joined = fold(lambda x, y: P.natural_join(x, y, hint="merge"), [placed[n] for n in order])
    return joined.select(*q.attributes)


def contracted(q: JoinQuery, tree: BagTree | None = None) -> BagTree:
    """The tree that contraction makes: each new bag joins the relations of three whole bags."""
    h = Hypergraph.from_query(q)
    return contract(tree or find_bag_tree(h), h).tree


def _contract_reduce(plan: Contraction, bags: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """First half: the steps of the contraction, then the same steps backwards. A shunt joins three given bags, as reduced so far, and is marked by semijoins
    with the two bags that it takes under it; a leaf marks its parent. Backwards all are reduced by what they went into."""
    value = dict(bags)
    for shunts, leaves in plan.steps:
        made, most = {}, 0
        for s in shunts:
            joined = fold(run.join, [value[b] for b in dict.fromkeys(s.of)])
            sent = join_cost([run.size(value[b]) for b in s.of], run.m_or_none()) if run.ledger is not None else 0
            run.note(1, "shunt", s.into, sent, joined)
            made[s.into] = fold(run.semi, [value[b] for b in s.under], joined)
            if run.ledger is not None:
                costs = [semijoin_cost(run.size(joined), run.size(value[b]), run.m_or_none()) for b in s.under]
                run.note(1 + sum(c[0] for c in costs), "semijoin mark", s.into, sum(c[1] for c in costs), made[s.into])
                most = max(most, 1 + sum(c[0] for c in costs))
        value |= run.settle(made, 2)
        run.at += most
        fresh, most = {}, {}
        for b, p in leaves:
            if p is not None:
                parent = fresh.get(p, value[p])
                fresh[p] = run.semi(parent, value[b])
                if run.ledger is not None:
                    rounds, sent = semijoin_cost(run.size(parent), run.size(value[b]), run.m_or_none())
                    most[p] = most.get(p, 0) + rounds
                    run.note(most[p], "semijoin leaf", p, sent, fresh[p])
        value |= run.settle(fresh, 2)
        run.at += max(most.values(), default=0)
    for shunts, leaves in reversed(plan.steps):
        pairs = [(b, p) for b, p in leaves if p is not None]
        for some in (pairs, [(b, s.into) for s in shunts for b in s.under]):
            fresh, most = {}, 0
            for b, p in some:
                fresh[b] = run.semi(value[b], value[p])
                if run.ledger is not None:
                    rounds, sent = semijoin_cost(run.size(value[b]), run.size(value[p]), run.m_or_none())
                    run.note(rounds, "semijoin back", b, sent, fresh[b])
                    most = max(most, rounds)
            value |= run.settle(fresh, 2)
            run.at += most
    return value


def _contract_join(plan: Contraction, value: dict[str, DataFrame], run: Runner) -> DataFrame:
    """Second half: the steps again, by joins. A shunt joins what its two bags have gathered; a leaf's gatherings go into its parent."""
    got, last = dict(value), None
    for shunts, leaves in plan.steps:
        fresh, most = {}, 0
        for s in shunts:
            fresh[s.into] = fold(run.join, [got[b] for b in s.under], got[s.into])
            if run.ledger is not None:
                run.note(2, "join shunt", s.into, join_cost([run.size(got[b]) for b in (s.into, *s.under)], run.m_or_none()), fresh[s.into])
                most = 2
        got |= run.settle(fresh)
        run.at += most
        fresh, taken = {}, {}
        for b, p in leaves:
            last = b
            if p is not None:
                parent = fresh.get(p, got[p])
                fresh[p] = run.join(parent, got[b])
                if run.ledger is not None:
                    taken[p] = taken.get(p, 0) + 1
                    run.note(taken[p], "join leaf", p, join_cost([run.size(parent), run.size(got[b])], run.m_or_none()), fresh[p])
        got |= fresh if len(leaves) == 1 else run.settle(fresh)
        run.at += max(taken.values(), default=0)
    return got[last]


def _contraction(q: JoinQuery, tree: BagTree | None, run: Runner) -> tuple[Contraction, dict[str, DataFrame], Hypergraph]:
    h = Hypergraph.from_query(q)
    rels = q.bound()
    for a in q.atoms:
        run.keyed(rels[a.name], frozenset(a.key or ()))
    base = (tree or find_bag_tree(h)).make_complete(h)
    plan, bags = contract(base, h), materialize_bags(base, rels, run)
    return plan, {b: bags[given] for b, given in plan.source.items()}, h


def contraction_join(q: JoinQuery, tree: BagTree | None = None, m: int | None = None, physical: str = "native", ledger: CostLedger | None = None) -> DataFrame:
    """Three-way contraction join: bags are materialised, then a full reduction and the joins take a logarithmic number of steps each, whatever the depth, with
    intermediates that join three whole bags."""
    run = Runner(q.shared, m, physical, ledger=ledger)
    plan, bags, _ = _contraction(q, tree, run)
    return _contract_join(plan, _contract_reduce(plan, bags, run), run).select(*q.attributes)


def contraction_reduce(q: JoinQuery, tree: BagTree | None = None) -> dict[str, DataFrame]:
    """Relations of q without dangling tuples, by the first half of the contraction join."""
    run = Runner(q.shared)
    plan, bags, h = _contraction(q, tree, run)
    reduced = _contract_reduce(plan, bags, run)
    home = {n: next(b for b in sorted(bags) if n in plan.tree.lam[b] and h.edges[n] <= plan.tree.chi[b]) for n in h.edges}
    return {n: reduced[home[n]].select(*sorted(h.edges[n])).dropDuplicates() for n in h.edges}


def single_machine_join(q: JoinQuery) -> DataFrame:
    """Everything on one machine, for inputs that fit on it."""
    return native_join(q, partitions=1)


def native_join(q: JoinQuery, partitions: int | None = None, rows: dict[str, int] | None = None) -> DataFrame:
    """Left-deep plan over the atoms, without reduction; order and strategy are Catalyst's. rows: of each atom, if counted: those of more than SMALL_ROWS are merged."""
    rels = q.bound()
    first, *rest = _ordered(list(rels), rels)
    joined, large = rels[first], {n for n, k in (rows or {}).items() if k > P.SMALL_ROWS}
    for i, n in enumerate(rest):
        # the first relation is large or small by itself; what is joined already counts as the product of all sizes
        joined = P.natural_join(joined, rels[n], hint="merge" if n in large or i == 0 and first in large else None)
    out = joined.select(*q.attributes)
    return out.coalesce(partitions) if partitions else out
