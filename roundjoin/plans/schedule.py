"""Rounds of the reducer joins: which leaves meet in which round, known before any data are read."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .bagtree import BagTree


@dataclass(frozen=True)
class Step:
    """kind: lone (into = parent), pair or triple (into = first of the group, which then stands for all), with the parent they share."""

    kind: str
    into: str
    group: tuple[str, ...]
    parent: str


def sweep(tree: BagTree) -> list[list[Step]]:
    """Upward rounds: in each, a leaf without sibling leaves goes into its parent, sibling leaves meet in pairs, the last three of an odd number together."""
    parent = dict(tree.parent)
    rounds = []
    while len(parent) > 1:
        inner = {p for p in parent.values() if p is not None}
        by_parent: dict[str, list[str]] = {}
        for b in tree.chi:
            if b in parent and b not in inner:
                by_parent.setdefault(parent[b], []).append(b)
        steps = []
        for p, low in by_parent.items():
            if len(low) == 1:
                steps.append(Step("lone", p, (low[0],), p))
                continue
            while low:
                group = tuple(low[:3] if len(low) == 3 else low[:2])
                low = low[len(group) :]
                steps.append(Step("pair" if len(group) == 2 else "triple", group[0], group, p))
        for s in steps:
            for b in s.group if s.kind == "lone" else s.group[1:]:
                del parent[b]
        rounds.append(steps)
    return rounds


def levels(tree: BagTree) -> list[list[tuple[str, str]]]:
    """(parent, child) by depth of the child."""
    depth = tree.depths()
    out: list[list[tuple[str, str]]] = [[] for _ in range(max(depth.values()))]
    for p, b in tree.edges():
        out[depth[b] - 1].append((p, b))
    return out


def count_rounds(tree: BagTree, c: int = 1, materialise: bool = False) -> dict[str, int]:
    """Rounds of each phase, c being those of a semijoin."""
    up = sum(max(c + (1 if s.kind == "pair" else 2 if s.kind == "triple" else 0) for s in steps) for steps in sweep(tree))
    join = sum(max({"lone": 1, "pair": 2, "triple": 3}[s.kind] for s in steps) for steps in sweep(tree))
    down = c * len(levels(tree))
    first = int(materialise and tree.width() > 1)
    return {"materialise": first, "up": up, "down": down, "join": join, "total": first + up + down + join}


def explain_rounds(spark: SparkSession, tree: BagTree) -> DataFrame:
    """The schedule as rows (phase, round, op, bag, with)."""
    rows = []
    for phase in ("up", "join"):
        for i, steps in enumerate(sweep(tree)):
            rows += [(phase, i + 1, s.kind, s.into, ",".join(s.group)) for s in steps]
    for i, pairs in enumerate(levels(tree)):
        rows += [("down", i + 1, "semijoin", b, p) for p, b in pairs]
    return spark.createDataFrame(rows, "phase string, round int, op string, bag string, others string")
