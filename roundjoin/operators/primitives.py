"""Relational primitives: grid, hash and hybrid joins, staged duplicate removal, semijoins, intersection, reducer load, round barriers.

Columns named __g<i>, __salt and __r_<attribute> are internal. Everything random is a seeded hash, so retried tasks give the same rows."""

from __future__ import annotations

import math
import re
from concurrent.futures import ThreadPoolExecutor
from functools import reduce as fold

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cost import grid_sizes
from ..scratch import scratch_path, shuffles_dropped


#: Groups on an axis of a grid join up to which tuples are copied to all of them, partner or not.
WHOLE_AXIS = 4
#: Types whose values are equal only if their bits are, so that equal values have one hash: no floats, no collations.
EXACT = re.compile(r"boolean|tinyint|smallint|int|bigint|decimal\(.*\)|string|binary|date|timestamp(_ntz)?")
#: Rows up to which it is left to Spark whether a counted relation is broadcast. It goes by the size of files, from which the rows of a few narrow columns can't be told:
#: of millions of rows it takes two columns to be small, and gathers them on the driver.
SMALL_ROWS = 50_000


class ReducerOverflow(RuntimeError):
    """A reducer would receive more tuples than it can hold."""


def tuple_hash(columns: list[str], seed: int, buckets: int, portable: bool = False) -> Column:
    """Bucket of a tuple by all the given columns. portable: by MD5 of their text, which other systems have too."""
    if portable:
        text = F.concat_ws("|", F.lit(str(seed)), *[F.col(c).cast("string") for c in columns])
        return F.pmod(F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long"), F.lit(buckets))
    return F.pmod(F.xxhash64(F.lit(seed), *[F.col(c) for c in columns]), F.lit(buckets))


def common(l: DataFrame, r: DataFrame) -> list[str]:  # noqa: E741
    return [c for c in l.columns if c in r.columns]


def natural_join(l: DataFrame, r: DataFrame, null_safe: frozenset[str] = frozenset(), how: str = "inner", hint: str | None = None) -> DataFrame:  # noqa: E741
    """Join on all shared columns. null_safe: those in which nulls match, as when copies of one relation meet again. A product where nothing is shared."""
    on = common(l, r)
    if hint:
        r = r.hint(hint)
    if not on:
        if how == "inner":
            return l.crossJoin(r)
        return l.join(r, F.lit(True), how)
    if not null_safe & set(on):
        return l.join(r, on, how)
    other = r.select(*[F.col(c).alias(f"__r_{c}" if c in on else c) for c in r.columns])
    test = None
    for c in on:
        t = F.col(c).eqNullSafe(F.col(f"__r_{c}")) if c in null_safe else F.col(c) == F.col(f"__r_{c}")
        test = t if test is None else test & t
    joined = l.join(other, test, how)
    return joined.drop(*[f"__r_{c}" for c in on]) if how == "inner" else joined


def counts(dfs: list[DataFrame]) -> list[int]:
    """Rows of each relation, counted in one job."""
    if not dfs:
        return []
    with shuffles_dropped(dfs[0].sparkSession):
        each = [d.select(F.lit(i).alias("i")).groupBy("i").count() for i, d in enumerate(dfs)]
        got = {r["i"]: r["count"] for r in fold(lambda a, b: a.unionAll(b), each).collect()}
    return [got.get(i, 0) for i in range(len(dfs))]


def overflow_bound(m: int, groups: list[int]) -> int:
    """Tuples that a reducer of m is allowed: groups of hashed tuples have m / z on average and exceed that by six deviations with a chance below 10^-8."""
    z = max(1, len(groups))
    return m if math.prod(groups) == 1 else math.ceil(m + 6 * math.sqrt(z * m) + 6 * z)


def grid_join(dfs: list[DataFrame], m: int | None = None, seed: int = 17, groups: list[int] | None = None, sizes: list[int] | None = None, check: bool | None = None, loads: list[int] | None = None, portable: bool = False, keys: list[frozenset[str] | None] | None = None) -> DataFrame:
    """Join of z relations by all combinations of hashed groups: any skew, any or no shared attributes, one co-partitioned round.

    A tuple is copied to every cell of its group, or, along an axis of more than WHOLE_AXIS groups whose relation shares attributes with it, only to the cells
    whose group there holds a partner: the others would get copies that join with nothing. A table of keys and groups tells these groups, or, where the tuple has
    all attributes of that relation, or of its key, its own values, as they are those of its only partner. Cells are never broadcast, as Spark takes a relation's copies to be as
    small as the relation.

    m: tuples a reducer holds, from which the groups follow (counting the relations in one job unless sizes are given). The load of the fullest reducer is
    measured before the join, which raises ReducerOverflow if it is over m (check) or over overflow_bound (check None, the default, where the groups follow
    from m); check=False measures nothing. loads: takes the measured load.

    keys: of each relation, attributes on which no two of its tuples agree. It is dealt by them, as evenly as by whole tuples."""
    axes = [f"__g{i}" for i in range(len(dfs))]
    bound = None if check is False or m is None or check is None and groups else m
    groups = groups or grid_sizes(sizes or counts(dfs), m)
    if check is None and bound is not None:
        bound = overflow_bound(m, groups)
    by = [[c for c in d.columns if not keys or not keys[i] or not keys[i] <= set(d.columns) or c in keys[i]] for i, d in enumerate(dfs)]
    group = lambda i: tuple_hash(by[i], seed + i, groups[i], portable).cast("int")
    dealt = [d.withColumn(axes[i], group(i)) for i, d in enumerate(dfs)]
    if bound is not None:
        load = capacity([d.select(axes[i]) for i, d in enumerate(dealt)], axes)
        if loads is not None:
            loads.append(load)
        if load > bound:
            raise ReducerOverflow(f"a reducer would receive {load} tuples, more than {bound}")
    placed = []
    for i, d in enumerate(dealt):
        for j, axis in enumerate(axes):
            if j != i:
                on = common(dfs[i], dfs[j])
                told = {(c, t) for c, t in dfs[j].dtypes if c in by[j]}
                if on and groups[j] > WHOLE_AXIS and told <= set(dfs[i].dtypes) and all(EXACT.fullmatch(t) for _, t in told):
                    d = d.withColumn(axis, group(j))
                elif on and groups[j] > WHOLE_AXIS:
                    # inner: a tuple without a partner in any group is in no answer
                    # sent once, by what is joined on, which is where duplicates meet as well
                    d = d.join(dealt[j].select(*on, axis).repartition(*on).dropDuplicates().hint("merge"), on)
                else:
                    d = d.withColumn(axis, F.explode(F.sequence(F.lit(0), F.lit(groups[j] - 1))) if groups[j] > 1 else F.lit(0))
        placed.append(d)
    out = placed[0]
    for d in placed[1:]:
        out = out.join(d.hint("merge"), common(out, d))
    return out.drop(*axes)


def capacity(dealt: list[DataFrame], axes: list[str]) -> int:
    """Most tuples that one cell receives from all relations. A cell is one group of each relation, so the fullest is that of the fullest groups, and no
    copies need to be made to find it: one aggregation over each relation's group numbers, in one job."""
    groups = fold(lambda a, b: a.unionAll(b), [d.groupBy(F.col(axes[i]).alias("g")).count().select(F.lit(i).alias("i"), "count") for i, d in enumerate(dealt)])
    return int(sum(r.m for r in groups.groupBy("i").agg(F.max("count").alias("m")).collect()))


def hash_join(l: DataFrame, r: DataFrame, strategy: str | None = None) -> DataFrame:  # noqa: E741
    """Partition both sides by their common attributes, without copies; strategy: shuffle_hash, merge or broadcast."""
    return natural_join(l, r, hint=strategy)


def heavy_keys(df: DataFrame, keys: list[str], share: float, sample: float | None = None, seed: int = 5) -> DataFrame:
    """Keys that at least `share` of the rows have, counted on all rows or on a sampled fraction of them; 1/share rows at most."""
    rows = df if sample is None else df.sample(fraction=sample, seed=seed)
    counts = rows.groupBy(*keys).count()
    total = rows.agg(F.count("*").alias("__total"))
    return counts.crossJoin(F.broadcast(total)).where(F.col("count") >= share * F.col("__total")).select(*keys, "count")


def heavy_keys_sketched(df: DataFrame, keys: list[str], share: float, width: int = 4096, depth: int = 4, seed: int = 5) -> DataFrame:
    """The same keys by a count-min sketch: `depth` rows of `width` counters, aggregated first, tell which keys can reach the share, as a counter never is too
    small; only rows of such keys are counted. The sketch, width * depth counters at most, is what is broadcast."""
    tag = F.array(*[F.struct(F.lit(d).alias("d"), F.pmod(F.xxhash64(F.lit(seed + d), *keys), F.lit(width)).cast("int").alias("w")) for d in range(depth)])
    sketch = df.select(F.explode(tag).alias("t")).groupBy("t.d", "t.w").count()
    total = F.broadcast(df.agg(F.count("*").alias("__total")))
    hot = sketch.crossJoin(total).where(F.col("count") >= share * F.col("__total"))
    cells = F.broadcast(hot.groupBy().agg(F.collect_set(F.struct("d", "w")).alias("__cells")))
    able = df.select(*keys, tag.alias("__t")).crossJoin(cells).where(F.size(F.array_except("__t", "__cells")) == 0)
    return able.groupBy(*keys).count().crossJoin(total).where(F.col("count") >= share * F.col("__total")).select(*keys, "count")


def is_matching(df: DataFrame) -> DataFrame:
    """One row, a boolean for each column: its values are all there and all different, so that any join on it is key to key."""
    return df.agg(*[((F.count(c) == F.count("*")) & (F.count_distinct(c) == F.count("*"))).alias(c) for c in df.columns])


def hybrid_join(l: DataFrame, r: DataFrame, m: int, share: float = 0.01, sample: float | None = None) -> DataFrame:  # noqa: E741
    """Light keys by hashing; keys that hold `share` of either side by the grid join. The heavy keys are 2/share at most, so they are broadcast."""
    on = common(l, r)
    heavy = heavy_keys(l, on, share, sample).select(*on).union(heavy_keys(r, on, share, sample).select(*on)).distinct()
    heavy = F.broadcast(heavy.where(" AND ".join(f"`{c}` IS NOT NULL" for c in on)))
    light = l.join(heavy, on, "left_anti").join(r.join(heavy, on, "left_anti"), on)
    hot = grid_join([l.join(heavy, on, "left_semi"), r.join(heavy, on, "left_semi")], m)
    return light.unionByName(hot.select(*light.columns))


def staged_distinct(df: DataFrame, copies: int, m: int, seed: int = 23) -> DataFrame:
    """Duplicate removal by stages: copies are scattered over salted cells, and sqrt(m) cells are merged at a time, so no reducer meets many copies at once."""
    columns, base = df.columns, max(2, int(math.sqrt(m)))
    cells = max(1, copies)
    out = df.withColumn("__salt", F.pmod(F.xxhash64(F.lit(seed), F.monotonically_increasing_id()), F.lit(cells)))
    while cells > 1:
        out = out.dropDuplicates([*columns, "__salt"])
        cells = -(-cells // base)
        out = out.withColumn("__salt", F.floor(F.col("__salt") / base).cast("long"))
    return out.drop("__salt").dropDuplicates(columns)


def semijoin(s: DataFrame, r: DataFrame, m: int | None = None, physical: str = "native", null_safe: frozenset[str] = frozenset(), unique: bool = False, hint: str | None = None, sets: bool = False, key: frozenset[str] | None = None) -> DataFrame:
    """Tuples of s with a partner in r. 'native': left semi join with the distinct keys; 'grid': grid join of s with the keys, then staged duplicate removal.
    unique: r has no two tuples with the same keys, so none need to be removed. sets: s has no two equal tuples, and as each joins with one of the keys at most, no
    stages are run. key: of s, for the grid."""
    on = common(s, r)
    keys = (r.select(*on) if unique else r.select(*on).dropDuplicates()) if on else r.limit(1).select(F.lit(1).alias("__any"))
    if physical == "grid" and on:
        groups = grid_sizes(counts([s, keys]), m)
        met = grid_join([s, keys], groups=groups, keys=[key, None]).select(*s.columns)
        return met if sets else staged_distinct(met, groups[1], m)
    return natural_join(s, keys, null_safe, "left_semi", hint)


def intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    """Tuples in both, nulls being equal."""
    return a.intersect(b.select(*a.columns))


def barrier(dfs: dict[str, DataFrame], how: str = "none") -> dict[str, DataFrame]:
    """End of a round: 'none' keeps lineage, 'persist' keeps data in executors, 'checkpoint' and 'parquet' write them to the shared folder."""
    if how == "none":
        return dfs
    if how == "persist":
        return {k: d.persist() for k, d in dfs.items()}

    if how not in ("checkpoint", "parquet"):
        raise ValueError(f"no barrier {how!r}")

    def write(d: DataFrame) -> DataFrame:
        spark = d.sparkSession
        path = scratch_path(spark, "round")
        if how == "checkpoint":
            return d.checkpoint()
        d.write.parquet(path)
        return spark.read.schema(d.schema).parquet(path)

    if not dfs:
        return {}
    # the relations of a round are written side by side
    with shuffles_dropped(next(iter(dfs.values())).sparkSession), ThreadPoolExecutor(max_workers=8) as pool:
        return dict(zip(dfs, pool.map(write, dfs.values()), strict=True))
