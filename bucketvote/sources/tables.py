"""The given tables, views over them, and reading and writing in other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = tuple("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split())


def load(spark: SparkSession, folder: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{folder}/{name}.parquet")


def balanced(df: DataFrame) -> DataFrame:
    """df over all cores where its files give no more splits than that (splits of one row group leave all work to one task); else df itself, with no shuffle.

    Filters and column choices still reach the scan: the optimizer moves both below a round-robin repartition.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() <= cores else df


def register_views(spark: SparkSession, folder: str) -> None:
    for name in TABLES:
        load(spark, folder, name).createOrReplaceTempView(name)


def write(df: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] | None = None, mode: str = "errorifexists") -> None:
    out = df.write.format(kind).mode(mode)
    (out.partitionBy(*partition_by) if partition_by else out).save(path)


def read(spark: SparkSession, path: str, kind: str = "parquet", schema=None) -> DataFrame:
    reader = spark.read.format(kind)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def save_index(index: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Partitioned by table, so that a probe of few tables prunes files; sorted by key, so that row groups prune too."""
    index.repartition("table_id", "bucket_key").sortWithinPartitions("table_id", "bucket_key").write.mode(mode).partitionBy("table_id").parquet(path)


def load_index(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.read.schema(schema).parquet(path)
