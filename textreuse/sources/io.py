"""Sinks and sources of records: JSON lines in part files, CSV, and partitioned or bucketed Parquet. Schemas are declared, never inferred."""

from __future__ import annotations

import gc
import pickle
import re
import sys
import uuid

from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need no installed copy of this package

CORRUPT = "_corrupt"


def write_jsonl(df: DataFrame, path: str) -> None:
    """Gzip part files, one JSON object a line; nulls are left out, as optional keys are."""
    df.write.option("compression", "gzip").json(path)


def read_jsonl(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    """Records with a column that holds lines which are no such object; missing keys read as NULL."""
    wide = T.StructType([*schema.fields, T.StructField(CORRUPT, T.StringType())])
    return spark.read.schema(wide).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", CORRUPT).json(path)


def write_editions(records: DataFrame, path: str, texts: tuple[str, ...] = ("a_text", "b_text")) -> None:
    """Two archives of the records below ``path``: ``full`` as they are, ``metadata`` without the texts."""
    write_jsonl(records, f"{path}/full")
    write_jsonl(records.drop(*texts), f"{path}/metadata")


def write_csv(df: DataFrame, path: str) -> None:
    df.write.option("header", True).option("escape", '"').csv(path)


def read_csv(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(schema).option("header", True).option("escape", '"').csv(path)


def write_partitioned(df: DataFrame, path: str, by: list[str]) -> None:
    """Parquet folders by value; rows of a value are brought together first, so files stay few."""
    df.repartition(*by).write.partitionBy(*by).parquet(path)


def read_partitioned(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(schema).parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 256) -> None:
    """A table bucketed and sorted by ``key``: later joins on it need no shuffle. For stored grams and postings."""
    df.write.bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. Only a session of one machine, as in tests, may leave it unset."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or "file:///tmp/checkpoints").rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written below the shared folder and read back."""
    path = f"{shared_folder(df.sparkSession)}/textreuse-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder below the shared one that nothing reads any more."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def discard(df: DataFrame) -> None:
    """Delete what :func:`stored` wrote of ``df``."""
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if folder.rpartition("/")[2].startswith("textreuse-"):
            delete(df.sparkSession, folder)


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of frames that nothing refers to any more: they stay until the driver's garbage is collected."""
    gc.collect()
    spark._jvm.System.gc()


def put(folder: str, arrays: dict) -> str:
    """Write arrays as a new file of ``folder``, from a task; its name."""
    from pyarrow import fs

    store, where = fs.FileSystem.from_uri(folder)
    store.create_dir(where, recursive=True)
    name = f"{uuid.uuid4().hex}.pickle"
    with store.open_output_stream(f"{where}/{name}") as out:
        pickle.dump(arrays, out, protocol=5)
    return name


def get(folder: str, name: str) -> dict:
    """Arrays that :func:`put` wrote."""
    from pyarrow import fs

    store, where = fs.FileSystem.from_uri(folder)
    with store.open_input_stream(f"{where}/{name}") as given:
        return pickle.load(given)
