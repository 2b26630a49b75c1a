"""Reducer joins along a tree: dangling tuples go by semijoins up and down, then the rest is joined, one operation or one level a round."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce as fold
from weakref import WeakKeyDictionary, WeakSet

from pyspark.sql import DataFrame

from ..plans.bagtree import BagTree
from ..plans.cost import CostLedger, join_cost, semijoin_cost
from ..plans.schedule import levels, sweep
from ..scratch import shuffles_dropped
from . import primitives as P


@dataclass
class Runner:
    """How operations run: physical ('native', 'grid' with m tuples a reducer, 'hash'), what ends a round, and an optional ledger.

    how: a barrier of primitives.barrier, or 'auto', which writes a round's result only when more than `limit` scans stand in its plan: a reduced relation
    is used going up, going down and in the join, so plans that are never cut grow with the power of the depth. Grid joins also count and measure what they
    join before they run, so there every result is written, and every given relation from which duplicates are removed. All relations are sets.

    A ledger counts every relation, which runs it and keeps it (see CostLedger.keep); without one the plan stays lazy. exact: attributes in which nulls can't be (the shared ones).
    One that writes doesn't write what is there already: a semijoin that drops nothing is its given relation, and isn't run a second time; a join in which each tuple
    of one side is known to have exactly one partner has as many tuples, and stays a plan.

    literal: sibling leaves meet in the pairs and triples of the schedule, in every phase. That is how grid joins and ledgers run. Else a semijoin's result
    takes the parent's place at once, and Spark runs side by side what doesn't depend on each other."""

    exact: frozenset[str]
    m: int | None = None
    physical: str = "native"
    how: str = "auto"
    limit: int = 10
    ledger: CostLedger | None = None
    at: int = 0
    loads: list[int] = field(default_factory=list)  # fullest reducer of each grid join
    _known: WeakKeyDictionary[DataFrame, int] = field(default_factory=WeakKeyDictionary)
    _keys: WeakKeyDictionary[DataFrame, frozenset[str]] = field(default_factory=WeakKeyDictionary)
    _scans: WeakKeyDictionary[DataFrame, int] = field(default_factory=WeakKeyDictionary)
    _tables: WeakKeyDictionary[DataFrame, DataFrame] = field(default_factory=WeakKeyDictionary)  # of what the ledger has counted
    _semis: WeakKeyDictionary[DataFrame, tuple[DataFrame, DataFrame]] = field(default_factory=WeakKeyDictionary)  # what a semijoin is of
    _whole: WeakKeyDictionary[DataFrame, WeakSet[DataFrame]] = field(default_factory=WeakKeyDictionary)  # relations in which each tuple of this one has a partner
    _lacking: WeakKeyDictionary[DataFrame, WeakSet[DataFrame]] = field(default_factory=WeakKeyDictionary)  # and in which some have none
    _wide: WeakKeyDictionary[DataFrame, tuple[DataFrame, ...]] = field(default_factory=WeakKeyDictionary)  # see widened; the relation, and all that must stay for the plan

    def scans(self, df: DataFrame) -> int:
        """Scans in the plan of df since its lineage was cut."""
        return self._scans.get(df, 1)

    def made(self, out: DataFrame, *of: DataFrame) -> DataFrame:
        self._scans[out] = sum(map(self.scans, of))
        return out

    @property
    def literal(self) -> bool:
        return self.physical == "grid" or self.ledger is not None

    @property
    def writes(self) -> bool:
        return self.ledger is not None and self.ledger.written

    def keyed(self, df: DataFrame, key: frozenset[str] | None) -> DataFrame:
        """Notes that no two tuples of df agree on key."""
        if key:
            self._keys[df] = frozenset(key)
        return df

    def key(self, df: DataFrame) -> frozenset[str] | None:
        return self._keys.get(df)

    def loose(self, a: DataFrame, b: DataFrame) -> frozenset[str]:
        return frozenset(P.common(a, b)) - self.exact

    def size(self, df: DataFrame) -> int:
        """Rows of df. With a ledger it is kept. Not written is a given relation that needs no duplicates removed: that can be read as well from where it comes."""
        if df not in self._known and self.ledger is not None:
            with shuffles_dropped(df.sparkSession):
                self._keep(df)
        elif df not in self._known:
            self._known[df] = df.count()
        return self._known[df]

    def _keep(self, df: DataFrame) -> None:
        """Counts df, and has the ledger keep it, or, if it is a semijoin that has dropped nothing, takes what it is of in its place."""
        rows = None
        if df in self._semis:
            s, r = self._semis[df]
            if (rows := df.count()) == self.size(s):
                self._whole.setdefault(s, WeakSet()).add(r)
                self._tables[df], self._known[df] = s, rows
                return
        table = df
        if not self.ledger.written or df.columns and (df in self._scans or self.key(df) is None):
            table = self._tables[df] = self.keyed(self.ledger.keep(df), self.key(df))
        self._known[df] = self._known[table] = table.count() if rows is None else rows
        if df in self._semis and s in self._whole.get(r, ()):
            # the partners that r's tuples have in s are partners of r's, so they are all left
            self._whole[r].add(table)

    def widened(self, df: DataFrame) -> DataFrame:
        """The relation each of whose tuples is in exactly one tuple of df, and those are all; df itself, if no other is known."""
        return self._wide[df][0] if df in self._wide else df

    def _widen(self, a: DataFrame, b: DataFrame, out: DataFrame) -> DataFrame:
        """Notes that out, the join of a and b, only adds attributes to tuples of one of them, where that is known."""
        on = set(P.common(a, b))
        for x, y in ((a, b), (b, a)):
            base = self.widened(x)
            if on == set(base.columns) and base is self.widened(y) or on <= set(base.columns) and self.key(y) is not None and self.key(y) <= on and self._full(base, y):
                self._wide[out], self._known[out] = (base, a, b), self.size(base)
                break
        return out

    def _full(self, s: DataFrame, r: DataFrame) -> bool:
        """Whether each tuple of s has a partner in r, of which the common attributes are a key: if it isn't known, their semijoin is counted."""
        if r not in self._whole.get(s, ()) and r not in self._lacking.get(s, ()):
            with shuffles_dropped(s.sparkSession):
                rows = P.semijoin(s, r, null_safe=self.loose(s, r), unique=True, hint=self.hint(r)).count()
            (self._whole if rows == self.size(s) else self._lacking).setdefault(s, WeakSet()).add(r)
        return r in self._whole.get(s, ())

    def _added(self, df: DataFrame) -> list[DataFrame]:
        """The relations whose join df is."""
        return [x for d in self._wide[df][1:] for x in self._added(d)] if df in self._wide else [df]

    def _within(self, a: DataFrame, b: DataFrame) -> bool:
        """Whether a is b, or b with more attributes by joins, so that a joined with b is a."""
        return a is b or a in self._wide and (b is self.widened(a) or any(self._within(d, b) for d in self._wide[a][1:]))

    def _partnered(self, s: DataFrame, r: DataFrame) -> bool:
        """Whether each tuple of s is known to have a partner in r."""
        base, on = self.widened(s), set(P.common(s, r))
        return self._within(s, r) or on <= set(base.columns) and (r in self._whole.get(base, ()) or base is self.widened(r))

    def table(self, df: DataFrame) -> DataFrame:
        """df as the ledger has written it, or itself."""
        return self._tables.get(df, df)

    def hint(self, r: DataFrame, l: DataFrame | None = None) -> str | None:  # noqa: E741
        """How r joins l, or filters another relation, where a ledger has counted what is small: the tables that it writes are compressed, and their bytes
        tell Spark little about their rows. A relation that isn't known to be small is merged."""
        if self.ledger is None:
            return None
        small = lambda d: self._known.get(d, P.SMALL_ROWS + 1) <= P.SMALL_ROWS
        return "broadcast" if small(r) else None if l is not None and small(l) else "merge"

    def semi(self, s: DataFrame, r: DataFrame) -> DataFrame:
        if self.writes:
            self.size(s)
        s, r = self.table(s), self.table(r)
        if self.writes and self._partnered(s, r):
            return s
        physical = "grid" if self.physical == "grid" and not self.loose(s, r) else "native"
        on = set(P.common(s, r))
        unique = on == set(r.columns) or (self.key(r) is not None and self.key(r) <= on)
        out = self.keyed(self.made(P.semijoin(s, r, self.m, physical, self.loose(s, r), unique, self.hint(r), sets=True, key=self.key(s)), s, r), self.key(s))
        if self.writes:
            self._semis[out] = s, r
        return out

    def join(self, a: DataFrame, b: DataFrame) -> DataFrame:
        a, b = self.table(a), self.table(b)
        if self.writes and (self._within(a, b) or self._within(b, a)):
            return a if self._within(a, b) else b
        if self.writes and self.widened(a) is self.widened(b):
            # the relation that both have widened meets itself, so only what b has added to it is left to join
            return fold(self.join, (d for d in self._added(b) if not self._within(a, d)), a)
        loose = self.loose(a, b)
        if self.physical == "grid" and not loose:
            if self.ledger is None:
                a, b = self.settle({"a": a, "b": b}).values()
            keys, on = [self.key(d) or frozenset(d.columns) for d in (a, b)], set(P.common(a, b))
            # a tuple with one partner at most is in one answer at most
            key = keys[0] if keys[1] <= on else keys[1] if keys[0] <= on else keys[0] | keys[1]
            return self.keyed(self.made(P.grid_join([a, b], self.m, loads=self.loads, keys=keys), a, b), key)
        out = self.made(P.natural_join(a, b, loose, hint="shuffle_hash" if self.physical == "hash" else self.hint(b, a)), a, b)
        return self._widen(a, b, out) if self.writes else out

    def both(self, a: DataFrame, b: DataFrame) -> DataFrame:
        a, b = self.table(a), self.table(b)
        return self.keyed(self.made(P.natural_join(a, b, self.loose(a, b), "left_semi"), a, b), self.key(a))

    def settle(self, rels: dict[str, DataFrame], times: int = 1) -> dict[str, DataFrame]:
        """times: how often each is going to be read. A ledger has them written already, or counts them now."""
        if self.ledger is not None:
            for d in rels.values():
                self.size(d)
            return {k: self.table(d) for k, d in rels.items()}
        if self.how != "auto":
            return P.barrier(rels, self.how)
        grid = self.physical == "grid"
        written = P.barrier({k: d for k, d in rels.items() if self.scans(d) * times > (1 if grid else self.limit) or grid and d not in self._scans and self.key(d) is None}, "parquet")
        return rels | {k: self.keyed(d, self.key(rels[k]) or (frozenset(d.columns) if grid else None)) for k, d in written.items()}

    def note(self, rounds: int, op: str, bag: str, sent: int, out: DataFrame) -> None:
        if self.ledger is not None:
            self.ledger.add(self.at + rounds, op, bag, sent, self.size(out), max(self.loads, default=0))
            self.loads.clear()

    def m_or_none(self) -> int | None:
        return self.m if self.physical == "grid" else None


def _up(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Upward phase: what each relation keeps when everything below it has its say."""
    return _up_by_rounds(tree, rels, run) if run.literal else _up_by_levels(tree, rels, run)


def _up_by_levels(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Every relation of a level is filtered by all its children. What is read again later, in the join, is settled."""
    value, kids = dict(rels), tree.children()
    for pairs in reversed(levels(tree)):
        inner = {p: fold(run.semi, (value[c] for c in kids[p]), value[p]) for p in dict.fromkeys(p for p, _ in pairs)}
        value |= {p: d for p, d in inner.items() if p == tree.root} | run.settle({p: d for p, d in inner.items() if p != tree.root})
    return value


def _up_by_rounds(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """All leaves of a round together, siblings in pairs and triples."""
    value, message, kept = dict(rels), {}, {}
    own = lambda b: message.get(b, value[b])
    for steps in sweep(tree):
        fresh, most = {}, 0
        for s in steps:
            for b in s.group:
                kept.setdefault(b, value[b])
            parent = value[s.parent]
            if s.kind == "lone":
                out = run.semi(parent, own(s.group[0]))
                rounds, sent = semijoin_cost(run.size(parent), run.size(own(s.group[0])), run.m_or_none()) if run.ledger is not None else (1, 0)
            else:
                out = fold(run.semi, (own(b) for b in s.group), parent) if run.physical != "grid" else fold(run.both, [run.semi(parent, own(b)) for b in s.group])
                if run.ledger is not None:
                    costs = [semijoin_cost(run.size(parent), run.size(own(b)), run.m_or_none()) for b in s.group]
                    rounds, sent = max(c[0] for c in costs) + len(s.group) - 1, sum(c[1] for c in costs) + 2 * (len(s.group) - 1) * run.size(out)
                else:
                    rounds, sent = len(s.group), 0
            run.note(rounds, f"semijoin up {s.kind}", s.into, sent, out)
            fresh[(s.kind == "lone", s.into)] = out
            most = max(most, rounds)
        run.at += most
        settled = run.settle({f"{k[0]:d}{k[1]}": d for k, d in fresh.items()})
        for key, d in settled.items():
            (value if key[0] == "1" else message)[key[1:]] = d
    kept[tree.root] = value[tree.root]
    return kept


def _down(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Downward phase: all children of a level together."""
    value = dict(rels)
    for pairs in levels(tree):
        fresh, most = {}, 0
        for p, b in pairs:
            fresh[b] = run.semi(value[b], value[p])
            rounds, sent = semijoin_cost(run.size(value[b]), run.size(value[p]), run.m_or_none()) if run.ledger is not None else (1, 0)
            run.note(rounds, "semijoin down", b, sent, fresh[b])
            most = max(most, rounds)
        run.at += most
        value |= run.settle(fresh)
    return value


def _join_downward(tree: BagTree, rels: dict[str, DataFrame], run: Runner, reduced: bool) -> DataFrame:
    """Join from the root down. After the upward phase the root has no dangling tuple, so each join does what the downward semijoin would do before it, and no
    intermediate is larger than the result. reduced: a relation whose attributes its parent has is skipped, as it has filtered the parent already."""
    out = rels[tree.root]
    for pairs in levels(tree):
        for p, b in pairs:
            if not reduced or set(rels[b].columns) - set(rels[p].columns):
                out = run.join(out, rels[b])
    return out


def _join(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> DataFrame:
    """Join phase, all leaves of a round together; of siblings each is joined to the parent first and the results on all the parent's attributes."""
    value = dict(rels)
    for steps in sweep(tree):
        fresh, most = {}, 0
        for s in steps:
            parent, parts = value[s.parent], [value[b] for b in s.group]
            if s.kind == "lone":
                out, rounds = run.join(parent, parts[0]), 1
            else:
                out, rounds = fold(run.join, [run.join(p, parent) for p in parts]), len(parts)
            sent = join_cost([run.size(parent), *map(run.size, parts)], run.m_or_none()) if run.ledger is not None else 0
            run.note(rounds, f"join {s.kind}", s.into, sent, out)
            fresh[s.into] = out
            most = max(most, rounds)
        run.at += most
        value |= run.settle(fresh)
    return value[tree.root]


def reduce_up(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Relations without tuples that lack a partner below."""
    return _up(tree, rels, run)


def reduce_down(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Relations without tuples that lack a partner above."""
    return _down(tree, rels, run)


def full_reduce(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> dict[str, DataFrame]:
    """Relations without dangling tuples: no later intermediate is larger than the result."""
    return _down(tree, _up(tree, rels, run), run)


def acyclic_join_parallel(tree: BagTree, rels: dict[str, DataFrame], run: Runner, reduce: bool = True) -> DataFrame:
    """Level-parallel reducer join. reduce=False leaves the semijoins out."""
    if run.literal:
        return _join(tree, full_reduce(tree, rels, run) if reduce else rels, run)
    return _join_downward(tree, _up(tree, rels, run) if reduce else rels, run, reduce)


def acyclic_join_sequential(tree: BagTree, rels: dict[str, DataFrame], run: Runner) -> DataFrame:
    """One operation a round: 2(n-1) semijoins, n-1 joins."""
    value, order = dict(rels), sorted(tree.chi, key=tree.depths().get, reverse=True)

    def done(op: str, bag: str, df: DataFrame, cost: tuple[int, int]) -> DataFrame:
        run.note(cost[0], op, bag, cost[1], df)
        run.at += cost[0]
        return run.settle({bag: df})[bag]

    def semi_cost(s: DataFrame, r: DataFrame) -> tuple[int, int]:
        return semijoin_cost(run.size(s), run.size(r), run.m_or_none()) if run.ledger is not None else (1, 0)

    for b in order:
        if (p := tree.parent[b]) is not None:
            cost = semi_cost(value[p], value[b])
            value[p] = done("semijoin up", p, run.semi(value[p], value[b]), cost)
    for b in reversed(order):
        if (p := tree.parent[b]) is not None:
            cost = semi_cost(value[b], value[p])
            value[b] = done("semijoin down", b, run.semi(value[b], value[p]), cost)
    for b in order:
        if (p := tree.parent[b]) is not None:
            sent = join_cost([run.size(value[p]), run.size(value[b])], run.m_or_none()) if run.ledger is not None else 0
            value[p] = done("join", p, run.join(value[p], value[b]), (1, sent))
    return value[tree.root]


def serial_reducer_join(tree: BagTree, rels: dict[str, DataFrame], exact: frozenset[str]) -> DataFrame:
    """The single-machine form: one lazy plan of left semi and inner joins, without barriers."""
    return acyclic_join_sequential(tree, rels, Runner(exact, how="none" if len(tree.chi) <= 4 else "auto"))


def hub_semijoin(hub: DataFrame, children: list[DataFrame], exact: frozenset[str], run: Runner | None = None) -> DataFrame:
    """Hub tuples with a partner in every child: the semijoins run side by side, and their results meet on all the hub's attributes in a second round."""
    run = run or Runner(exact)
    return fold(run.semi, [run.semi(hub, c) for c in children]) if children else hub


def hub_join(hub: DataFrame, children: list[DataFrame], exact: frozenset[str], run: Runner | None = None) -> DataFrame:
    """Skew-free join of a hub with all its children in two rounds, whatever their number: each child with the hub, then all results on the hub's attributes."""
    if not children:
        return hub
    run = run or Runner(exact)
    return fold(run.join, [run.join(hub, c) for c in children])


def hub_tree_join(tree: BagTree, rels: dict[str, DataFrame], exact: frozenset[str], run: Runner | None = None) -> DataFrame:
    """Two rounds a level: the tree is reduced up by hub semijoins, inner relations are reduced down, and hub joins go from the deepest level on. Leaves need no
    downward semijoin, as the join with their hub is one."""
    depth, kids, value = tree.depths(), tree.children(), dict(rels)
    order, run = sorted(tree.chi, key=depth.get, reverse=True), run or Runner(exact)
    for b in order:
        if kids[b]:
            value |= run.settle({b: hub_semijoin(value[b], [value[c] for c in kids[b]], exact, run)}, len(kids[b]))
    for pairs in levels(tree):
        value |= run.settle({b: run.semi(value[b], value[p]) for p, b in pairs if kids[b]})
    for b in order:
        if kids[b]:
            joined = hub_join(value[b], [value[c] for c in kids[b]], exact, run)
            value |= {b: joined} if b == tree.root else run.settle({b: joined})
    return value[tree.root]
