"""Costs: a ledger of rounds and tuples for what was run or planned, and the closed forms of the methods."""

from __future__ import annotations

import math
import weakref
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from .. import scratch
from .bagtree import BagTree


def grid_sizes(sizes: list[int], m: int) -> list[int]:
    """Groups that the grid join cuts each relation into so that a reducer gets m tuples at most on average."""
    return [max(1, -(-len(sizes) * s // m)) for s in sizes]


def grid_sent(sizes: list[int], m: int) -> int:
    """Tuples that the grid join sends: each relation once to every combination of the others' groups."""
    g = grid_sizes(sizes, m)
    return sum(s * math.prod(g[:i] + g[i + 1 :]) for i, s in enumerate(sizes))


def distinct_rounds(copies: int, m: int) -> int:
    """Rounds of staged duplicate removal of at most `copies` copies."""
    return 0 if copies <= 1 else 1 + math.ceil(math.log(copies**2) / math.log(max(2.0, math.sqrt(m))))


def semijoin_cost(s: int, r: int, m: int | None) -> tuple[int, int]:
    """Rounds and tuples sent of one semijoin of s with r; without m by hashing, in one round."""
    if m is None:
        return 1, s + r
    copies = grid_sizes([s, r], m)[1]
    rounds = distinct_rounds(copies, m)
    return 1 + rounds, grid_sent([s, r], m) + rounds * copies * s


def join_cost(sizes: list[int], m: int | None) -> int:
    return sum(sizes) if m is None else grid_sent(sizes, m)


@dataclass
class CostLedger:
    """One entry an operation; operations of the same round run together. Relations that were counted are kept while they are in use, or until release()."""

    entries: list[tuple[int, str, str, int, int, int]] = field(default_factory=list)
    machine: int | None = None
    written: bool = False
    kept: list[tuple[weakref.ref, SparkSession, str]] = field(default_factory=list)  # what reads a table, and the table
    persisted: list[DataFrame] = field(default_factory=list)

    def keep(self, df: DataFrame) -> DataFrame:
        """What later operations read in place of df: df kept in executors, until release(), or, if written, a table in the shared folder, so that no later plan
        holds df's. Tables that nothing refers to any more are removed first, so what was made of them must have run."""
        if not self.written:
            self.persisted.append(df.persist())
            return df
        self._remove(lambda reader: reader() is None)
        spark, path = df.sparkSession, scratch.scratch_path(df.sparkSession, "ledger")
        df.write.parquet(path)
        table = spark.read.schema(df.schema).parquet(path)
        self.kept.append((weakref.ref(table), spark, path))
        return table

    def release(self) -> None:
        self._remove(lambda reader: True)
        while self.persisted:
            self.persisted.pop().unpersist()

    def _remove(self, test) -> None:
        for entry in [e for e in self.kept if test(e[0])]:
            scratch.remove(*entry[1:])
            self.kept.remove(entry)

    def add(self, round_: int, op: str, bag: str, sent: int, produced: int, load: int = 0) -> None:
        self.entries.append((round_, op, bag, sent, produced, load))

    def rounds(self) -> int:
        return max((e[0] for e in self.entries), default=0)

    def communication(self) -> int:
        """Tuples sent to reducers and produced by them."""
        return sum(e[3] + e[4] for e in self.entries)

    def by_round(self) -> dict[int, int]:
        out: dict[int, int] = {}
        for e in self.entries:
            out[e[0]] = out.get(e[0], 0) + e[3] + e[4]
        return out

    def max_load(self) -> int:
        return max((e[5] for e in self.entries), default=0)

    def machines(self) -> int | None:
        """Reducers of size `machine` that the communication fills."""
        return -(-self.communication() // self.machine) if self.machine else None

    def sizes(self) -> dict[str, int]:
        """Largest relation that each kind of operation produced."""
        out: dict[str, int] = {}
        for _, op, _, _, produced, _ in self.entries:
            out[op] = max(out.get(op, 0), produced)
        return out

    def dangling(self) -> dict[str, int]:
        """Tuples after the last semijoin on each bag."""
        return {bag: produced for _, op, bag, _, produced, _ in self.entries if op.startswith("semijoin")}

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.entries, "round int, op string, bag string, sent long, produced long, max_load long")


def epsilon(in_: float, m: float) -> float:
    return math.log(in_) / math.log(m)


def space_exponent(in_: float, m: float, p: float) -> float:
    """e' with m = in / p^(1 - e')."""
    return 1 - math.log(in_ / m) / math.log(p)


def mrc_feasible(in_: float, load: float, total: float, eps: float) -> bool:
    """Within the limits in^(1-eps) a reducer and in^(2-2eps) in all."""
    return load <= in_ ** (1 - eps) and total <= in_ ** (2 - 2 * eps)


def blow_up(x: float, m: float) -> float:
    """B(X, M) = X^2 / M."""
    return x * x / m


def one_round_chain_lower_bound(in_: float, m: float, n: int) -> float:
    return (in_ / m) ** (n / 4)


def predict(method: str, in_: float, out: float, m: float, n: int, w: int = 1, iw: int = 1, d: int = 1, passes: int = 1, cover: float | None = None, relaxed: bool = False) -> tuple[float, float]:
    """Rounds and tuples of a method, asymptotic, with constants 1. cover: exponent of the one-round grid (half the atoms of a star, a sixth of a triangle
    chain's). relaxed: without bounds on m and w."""
    log_n = max(1.0, math.log2(n))
    wide = max(w, 3 * iw)
    forms = {
        "sequential": (n, n * blow_up(in_ + out, m)),
        "parallel": (d + log_n, n * blow_up(in_ + out, m)),
        "decomposition": (d + log_n, n * blow_up(in_**w + out, m)),
        "linear": (n, n * blow_up(in_**w + out, m)),
        "log_depth": (log_n, n * blow_up(in_**wide + out, m)),
        "merged": (max(1.0, math.log2(max(2.0, (15 / 16) ** passes * n))), n * blow_up(in_ ** (2**passes * wide) + out, m)),
        "contraction": (log_n, n * blow_up(in_ ** (3 * w) + out, m)),
        "share": (1, (in_ / m) ** (cover if cover is not None else n / 2) + out),
        "single_machine": (1, out),
        "hash": (d + log_n, n * (in_**w + out)),
        "hub": (d, n * (in_**w + out)),
    }
    rounds, sent = forms[method]
    if relaxed:
        more = w * math.log(in_) / math.log(m)
        rounds, sent = rounds * more, sent * max(more, w**w)
    return rounds, sent


def parallel_steps(tree: BagTree) -> int:
    """Steps of the decomposition join on the tree with one processor a tuple: three sweeps of depth + log bags."""
    return 3 * (tree.depth() + math.ceil(math.log2(max(2, len(tree.chi)))))


def chain_levels_cost(levels: int, c: int) -> int:
    """Rounds of `levels` levels with a semijoin up, one down and a join each."""
    return levels * (2 * c + 1)
