"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TABLES = tuple("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())


def load_tables(spark: SparkSession, sf_dir: str, names: tuple[str, ...] | None = None) -> dict[str, DataFrame]:
    """The given tables; schemas come from the footers."""
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names or TABLES}


def read_source(spark: SparkSession, path: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **opts) -> DataFrame:
    reader = spark.read.format(fmt).options(**opts)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write_sink(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "errorifexists", **opts) -> str:
    writer = df.write.format(fmt).mode(mode).options(**opts)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
    return path


def stage_bucketed(df: DataFrame, table: str, keys: list[str], buckets: int, path: str | None = None) -> DataFrame:
    """Writes df as a table bucketed and sorted by keys, so that later joins on them need no exchange. path: where its files go, the warehouse if omitted."""
    df.sparkSession.sql(f"DROP TABLE IF EXISTS {table}")
    writer = df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys)
    (writer.option("path", path) if path else writer).saveAsTable(table)
    return df.sparkSession.table(table)


def read_stream(spark: SparkSession, path: str, schema: T.StructType, fmt: str = "parquet", **opts) -> DataFrame:
    return spark.readStream.format(fmt).schema(schema).options(**opts).load(path)


def register_views(q) -> None:
    """A temporary view for each atom, under its name."""
    for a in q.atoms:
        a.df.createOrReplaceTempView(a.name)
