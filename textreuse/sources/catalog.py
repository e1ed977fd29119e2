"""Tables by name, with column pruning left to the reader of the plan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; timestamps without a zone are read as UTC."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    plain = [f.name for f in df.schema.fields if isinstance(f.dataType, T.TimestampNTZType)]
    return df.withColumns({c: F.col(c).cast("timestamp") for c in plain}) if plain else df


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``doc_id, text`` of the collection, spread over the cores: a small file is one split."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return spread(docs, "doc_id")


def spread(df: DataFrame, key: str) -> DataFrame:
    """Deal rows by ``key`` if fewer partitions of the scan have rows than the session has cores; a large table stays as it is.

    A row group is read by one task whole, however many splits a file has; the count of rows by partition reads no column.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    filled = df.groupBy(F.spark_partition_id().alias("_p")).count().limit(cores).count()
    return df.repartition(cores, key) if filled < cores else df


def longs(df: DataFrame) -> DataFrame:
    """Integers of all widths as BIGINT, as results are compared with SQL."""
    narrow = [f.name for f in df.schema.fields if isinstance(f.dataType, T.IntegerType | T.ShortType | T.ByteType)]
    return df.withColumns({c: F.col(c).cast("bigint") for c in narrow}) if narrow else df
