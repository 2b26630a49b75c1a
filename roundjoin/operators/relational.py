"""Relational operators around the joins: projection, filters, joins of all kinds, aggregates, windows, order, sets."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.query import JoinQuery


def project(df: DataFrame, cols: list[str | Column]) -> DataFrame:
    return df.select(*cols)


def filter_rows(df: DataFrame, pred: str | Column) -> DataFrame:
    return df.where(pred)


def push_predicate(q: JoinQuery, attr: str, pred: str) -> JoinQuery:
    """The predicate on every atom that has the attribute."""
    return q.filtered(attr, pred)


def equi_join(l: DataFrame, r: DataFrame, on: list[str], how: str = "inner", strategy: str | None = None) -> DataFrame:  # noqa: E741
    """strategy: broadcast, merge, shuffle_hash or shuffle_replicate_nl."""
    return l.join(r.hint(strategy) if strategy else r, on, how)


def semi_join(l: DataFrame, r: DataFrame, on: list[str]) -> DataFrame:  # noqa: E741
    return l.join(r.select(*on), on, "left_semi")


def anti_join(l: DataFrame, r: DataFrame, on: list[str]) -> DataFrame:  # noqa: E741
    """Dangling tuples of l."""
    return l.join(r.select(*on), on, "left_anti")


def theta_join(l: DataFrame, r: DataFrame, cond: Column, how: str = "inner") -> DataFrame:  # noqa: E741
    return l.join(r, cond, how)


def range_join(l: DataFrame, r: DataFrame, point: str, lo: str, hi: str, width: int) -> DataFrame:  # noqa: E741
    """Rows whose point lies in [lo, hi]: each range is dealt to the buckets it meets, so the join is an equijoin with a residual test."""
    a = l.withColumn("__bucket", F.floor(F.col(point) / width))
    b = r.where(F.col(lo) <= F.col(hi)).withColumn("__bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return a.join(b, "__bucket").where(F.col(point).between(F.col(lo), F.col(hi))).drop("__bucket")


def interval_join(l: DataFrame, r: DataFrame, left_ts: str, right_ts: str, before_s: int, after_s: int, keys: list[str]) -> DataFrame:  # noqa: E741
    """Pairs with equal keys whose right time is within [left - before_s, left + after_s], in whole seconds; times (or seconds as whole numbers) are dealt to windows of that length, so hot keys spread."""
    width = max(1, before_s + after_s)
    seconds = lambda df, c: F.col(c) if isinstance(df.schema[c].dataType, T.IntegralType) else F.unix_timestamp(c)
    at, other = seconds(l, left_ts), seconds(r, right_ts)
    a = l.withColumn("__w", F.explode(F.sequence(F.floor((at - before_s) / width), F.floor((at + after_s) / width))))
    b = r.withColumn("__w", F.floor(other / width))
    gap = other - at
    return a.join(b, [*keys, "__w"]).where((gap >= -before_s) & (gap <= after_s)).drop("__w")


def nearest_second(ts: str) -> Column:
    """Seconds since 1970 as a whole number, rounded to the nearest one and from the middle to the even one; a time without a zone counts as UTC."""
    return F.rint(F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', CAST({ts} AS TIMESTAMP_NTZ))") / 1e6).cast("long")


def asof_join(l: DataFrame, r: DataFrame, ts: str, keys: list[str], value: str, width: int | None = None) -> DataFrame:  # noqa: E741
    """Each left row with the value of the last right row of its keys at or before its time (null if none). Right values must not be null.

    width: seconds (or units of an integer time) of the time buckets that a key's rows are dealt to, so that a hot key is many tasks; what a bucket takes over from
    those before it comes from a table with a row for each key and bucket that has right rows or is asked for. Without it a key is one task."""
    bucket = F.floor((F.unix_timestamp(ts) if isinstance(l.schema[ts].dataType, (T.TimestampType, T.TimestampNTZType, T.DateType)) else F.col(ts)) / (width or 1)).alias("__b")
    parts = [*keys, "__b"] if width else keys
    left = l.withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(r.schema[value].dataType))
    right = r.select(*keys, ts, F.lit(0).alias("__side"), F.col(value).alias("__v"))
    for c in l.columns:
        if c not in right.columns:
            right = right.withColumn(c, F.lit(None).cast(l.schema[c].dataType))
    w = Window.partitionBy(*parts).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right)
    name = value if value not in l.columns else f"asof_{value}"
    if not width:
        return both.withColumn("__last", F.last("__v", ignorenulls=True).over(w)).where("__side = 1").select(*l.columns, F.col("__last").alias(name))
    both = both.withColumn("__b", bucket)
    ends = both.groupBy(*parts).agg(F.max_by("__v", F.when(F.col("__v").isNotNull(), F.col(ts))).alias("__end"))
    before = Window.partitionBy(*keys).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    taken = ends.select(*keys, "__b", F.last("__end", ignorenulls=True).over(before).alias("__taken"))
    within = both.withColumn("__last", F.last("__v", ignorenulls=True).over(w)).where("__side = 1")
    same = [F.col(f"x.{c}").eqNullSafe(F.col(f"y.{c}")) for c in parts]
    joined = within.alias("x").join(taken.alias("y"), same)
    return joined.select(*[F.col(f"x.{c}") for c in l.columns], F.coalesce("__last", "__taken").alias(name))


def aggregate(df: DataFrame, keys: list[str], aggs: dict[str, Column]) -> DataFrame:
    return df.groupBy(*keys).agg(*[c.alias(n) for n, c in aggs.items()])


def count_distinct_by(df: DataFrame, keys: list[str], col: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.count_distinct(col).alias(f"distinct_{col}"))


def approx_distinct(df: DataFrame, col: str, error: float = 0.02) -> DataFrame:
    return df.agg(F.approx_count_distinct(col, error).alias(f"approx_{col}"))


def cube(df: DataFrame, keys: list[str], aggs: dict[str, Column]) -> DataFrame:
    return df.cube(*keys).agg(F.grouping_id().alias("gid"), *[c.alias(n) for n, c in aggs.items()])


def rollup(df: DataFrame, keys: list[str], aggs: dict[str, Column]) -> DataFrame:
    return df.rollup(*keys).agg(F.grouping_id().alias("gid"), *[c.alias(n) for n, c in aggs.items()])


def grouping_sets(df: DataFrame, sets: list[list[str]], aggs: dict[str, Column]) -> DataFrame:
    keys = list(dict.fromkeys(k for s in sets for k in s))
    return df.groupingSets([[F.col(k) for k in s] for s in sets], *keys).agg(*[c.alias(n) for n, c in aggs.items()])


def pivot_counts(df: DataFrame, key: str, col: str, values: list[str]) -> DataFrame:
    return df.groupBy(key).pivot(col, values).count().na.fill(0)


def unpivot(df: DataFrame, ids: list[str], values: list[str], name: str = "name", value: str = "value") -> DataFrame:
    return df.unpivot(ids, values, name, value)


def window_rank(df: DataFrame, keys: list[str], order: list[Column]) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.select("*", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


def window_lag_lead(df: DataFrame, keys: list[str], order: list[Column], col: str) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.select("*", F.lag(col).over(w).alias(f"prev_{col}"), F.lead(col).over(w).alias(f"next_{col}"))


def window_frame(df: DataFrame, keys: list[str], order: list[Column], agg: Column, name: str, lo: int, hi: int, kind: str = "rows") -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(*order)
    w = w.rowsBetween(lo, hi) if kind == "rows" else w.rangeBetween(lo, hi)
    return df.select("*", agg.over(w).alias(name))


def sort_limit(df: DataFrame, order: list[Column], n: int) -> DataFrame:
    return df.orderBy(*order).limit(n)


def topk_per_group(df: DataFrame, keys: list[str], order: list[Column], k: int) -> DataFrame:
    """Spark limits each group before the shuffle."""
    return df.withColumn("__rn", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).where(F.col("__rn") <= k).withColumnRenamed("__rn", "rn")


def union_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b)


def union_set(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def intersect_set(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def intersect_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersectAll(b)


def except_set(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.subtract(b)


def except_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b)


def window_shares(df: DataFrame, keys: list[str], order: list[Column], tiles: int = 4) -> DataFrame:
    """Tile, relative rank and cumulative share of each row in its group."""
    w = Window.partitionBy(*keys).orderBy(*order)
    return df.select("*", F.ntile(tiles).over(w).alias("tile"), F.percent_rank().over(w).alias("relative"), F.cume_dist().over(w).alias("share"))


def window_ends(df: DataFrame, keys: list[str], order: list[Column], col: str, n: int = 2) -> DataFrame:
    """First, last and n-th value of a column over each whole group."""
    w = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.select("*", F.first(col).over(w).alias("first_value"), F.last(col).over(w).alias("last_value"), F.nth_value(col, n).over(w).alias("nth_value"))


def lateral_join(l: DataFrame, r: Callable[[Callable[[str], Column]], DataFrame], how: str = "inner") -> DataFrame:  # noqa: E741
    """Joins each row of l with the rows of r(outer), where outer(name) stands for a column of that row."""
    return l.lateralJoin(r(lambda name: F.col(name).outer()), how=how)


def exists_in(l: DataFrame, r: DataFrame, left_key: str, right_key: str) -> DataFrame:  # noqa: E741
    """Rows of l for which the correlated subquery finds a row in r."""
    return l.where(r.where(F.col(right_key) == F.col(left_key).outer()).exists())


def above_scalar(df: DataFrame, col: str, agg: Column) -> DataFrame:
    """Rows whose column exceeds an aggregate over the whole table, as a scalar subquery."""
    return df.where(F.col(col) > df.agg(agg).scalar())


def sketch_distinct(df: DataFrame, keys: list[str], col: str, log_k: int = 12) -> DataFrame:
    """Mergeable sketches of the distinct values of a column, one for each group."""
    return df.groupBy(*keys).agg(F.hll_sketch_agg(col, log_k).alias("sketch"))


def merge_sketches(sketches: DataFrame, name: str = "estimate") -> DataFrame:
    """Estimate of the distinct values that all sketches have seen together."""
    return sketches.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias(name))
