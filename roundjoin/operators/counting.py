"""Aggregates over a join that is never produced: counts are summed bottom-up along the tree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.bagtree import BagTree
from ..plans.hypergraph import Hypergraph, find_bag_tree
from ..plans.query import JoinQuery
from . import primitives as P
from .decomposition import materialize_bags
from .reducer import Runner


def _weighted(q: JoinQuery, tree: BagTree | None, root_with: frozenset[str]) -> DataFrame:
    """The root bag's tuples with __w, the number of answers that each is part of."""
    h = Hypergraph.from_query(q)
    tree = (tree or find_bag_tree(h)).make_complete(h)
    if root_with:
        home = next((b for b in sorted(tree.chi) if root_with <= tree.chi[b]), None)
        if home is None:
            raise ValueError(f"{sorted(root_with)} lie in no one bag")
        tree = tree.reroot(home)
    run = Runner(q.shared)
    value = {b: d.withColumn("__w", F.lit(1).cast("decimal(38,0)")) for b, d in materialize_bags(tree, q.bound(), run).items()}
    for b in sorted(tree.chi, key=tree.depths().get, reverse=True):
        if (p := tree.parent[b]) is not None:
            on = sorted(tree.separator(p, b))
            sums = value[b].groupBy(*on).agg(F.sum("__w").alias("__c"))
            joined = P.natural_join(value[p], sums, frozenset(on) - q.shared)
            value[p] = joined.withColumn("__w", (F.col("__w") * F.col("__c")).cast("decimal(38,0)")).drop("__c")
    return value[tree.root]


def count_join(q: JoinQuery, tree: BagTree | None = None) -> DataFrame:
    """n_answers, one row."""
    return _weighted(q, tree, frozenset()).agg(F.coalesce(F.sum("__w"), F.lit(0)).cast("long").alias("n_answers"))


def aggregate_join(q: JoinQuery, keys: list[str], tree: BagTree | None = None) -> DataFrame:
    """keys, n_answers. The keys must lie in one bag, which becomes the root."""
    return _weighted(q, tree, frozenset(keys)).groupBy(*keys).agg(F.sum("__w").cast("long").alias("n_answers"))
