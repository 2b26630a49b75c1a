"""Bundles of built-in functions on columns of the given tables, and the user-defined functions of the engine."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def fn_string(customer: DataFrame) -> DataFrame:
    n = F.col("c_name")
    return customer.select("c_custkey", F.lower(n).alias("low"), F.substring(n, 1, 4).alias("head"), F.length(n).cast("long").alias("len"), F.concat_ws("-", "c_mktsegment", n).alias("tag"), F.regexp_extract(n, "([0-9]+)", 1).alias("digits"), F.levenshtein(n, F.lit("Customer")).cast("long").alias("lev"))


def fn_url(pages: DataFrame) -> DataFrame:
    return pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PROTOCOL")).alias("protocol"))


def fn_date(orders: DataFrame) -> DataFrame:
    d = F.col("o_orderdate")
    return orders.select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month_start"), F.datediff(d, F.lit("1992-01-01")).cast("long").alias("days"))


def fn_math(lineitem: DataFrame) -> DataFrame:
    q = F.col("l_quantity").cast("decimal(12,2)")
    return lineitem.select("l_orderkey", "l_linenumber", F.floor(q / 7).cast("long").alias("sevenths"), F.pmod(F.col("l_partkey"), F.lit(13)).cast("long").alias("part_mod"), F.greatest("l_partkey", "l_suppkey").alias("top_key"), F.round(q, 0).cast("long").alias("rounded")).groupBy("sevenths", "part_mod").agg(F.count("*").alias("n"), F.max("top_key").alias("top_key"), F.sum("rounded").alias("rounded"))


def fn_array(embeddings: DataFrame) -> DataFrame:
    big = F.filter("embedding", lambda x: x > 0)
    return embeddings.select("vec_id", F.size("embedding").cast("long").alias("dim"), F.size(big).cast("long").alias("positive"), (F.array_position(F.col("embedding"), F.array_max("embedding")) - 1).alias("argmax"))


def fn_map(orders: DataFrame) -> DataFrame:
    counts = orders.groupBy("o_custkey", "o_orderstatus").count().groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "count"))).alias("m"))
    return counts.select("o_custkey", F.coalesce(F.try_element_at("m", F.lit("F")), F.lit(0)).alias("n_f"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


def fn_json(events: DataFrame) -> DataFrame:
    return events.select("event_id", F.get_json_object("props", "$.page").alias("page"), F.size(F.json_object_keys("props")).cast("long").alias("n_keys"))


@F.pandas_udf(T.LongType())
def cell_id_udf(keys: pd.Series, buckets: pd.Series) -> pd.Series:
    """Bucket of an integer key by a multiplicative hash; the Arrow form of the native expression in cell_id."""
    return ((keys * 2654435761) % 4294967296) % buckets


def cell_id(keys, buckets):
    """The same in native functions."""
    return F.pmod(F.pmod(keys * F.lit(2654435761), F.lit(4294967296)), buckets)


@F.pandas_udf(T.LongType())
def load_histogram_udaf(cells: pd.Series) -> int:
    """Most rows that one cell holds."""
    return int(cells.value_counts().max()) if len(cells) else 0


@F.udtf(returnType=T.StructType([T.StructField("cell", T.IntegerType())]))
class grid_cells_udtf:  # noqa: N801
    """Cells of a tuple that is copied along one axis."""

    def eval(self, own: int, size: int):
        for j in range(size):
            yield (own * size + j,)
