"""Shared pieces of the training-data operators.

Intermediate results that are read more than once, or that end a long lineage,
are written as Parquet below the folder that the cluster names in
``spark.checkpoint.dir`` and read back, so that a lost executor costs one task
and never the whole chain.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Sequence

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: White space that ends a word: space, and tab to carriage return.
SPACE = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"

#: Used only in a session of one machine that names no shared folder, as in tests.
LOCAL_FOLDER = "file:///tmp/checkpoints"

#: Estimated bytes up to which a side is broadcast; beyond it the join shuffles.
BROADCAST_BYTES = 64 << 20


def ship_by_value() -> None:
    """Pickle this subpackage's functions by value, so that executors need no installed copy."""
    import textreuse.llm as package

    cloudpickle.register_pickle_by_value(package)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spread(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def spread(stored: DataFrame) -> DataFrame:
    """A stored table, its rows dealt over the cores if fewer partitions than cores have any; a larger table stays as it is.

    Splits are cut by bytes, but a row group goes to one of them whole, so splits that have rows are counted. The count
    reads no column. Rows are dealt by their place, so that no key gathers them.
    """
    cores = stored.sparkSession.sparkContext.defaultParallelism
    if stored.groupBy(F.spark_partition_id().alias("p")).count().limit(cores).count() >= cores:
        return stored
    # A name that the table cannot have: the longest of its names, and more.
    place = "_" + max([*stored.columns, "place"], key=len)
    return stored.withColumn(place, F.monotonically_increasing_id()).repartition(cores, place).drop(place)


def shared_folder(spark: SparkSession) -> str:
    """Folder that the driver and all executors see; on a cluster it must be named."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or LOCAL_FOLDER).rstrip("/")


class Scratch:
    """Tables below the shared folder, each with a fresh name."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/textreuse-{label}-{uuid.uuid4().hex}"
        self.made = 0

    def path(self, name: str) -> str:
        self.made += 1
        return f"{self.root}/{self.made}-{name}"

    def cut(self, df: DataFrame, name: str = "table") -> DataFrame:
        """Write ``df`` and read it back: its lineage then starts at the files."""
        where = self.path(name)
        df.write.parquet(where)
        return self.spark.read.schema(df.schema).parquet(where)

    def drop(self, *frames: DataFrame | None) -> None:
        """Delete tables made by :meth:`cut` that nothing reads any more. Only tables of this scratch go."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        for frame in frames:
            folders = {f.rpartition("/")[0] for f in frame.inputFiles()} if frame is not None else set()
            for folder in folders:
                where = jvm.org.apache.hadoop.fs.Path(folder)
                if self.root.rpartition("/")[2] in folder:
                    where.getFileSystem(conf).delete(where, True)


def estimated_bytes(side: DataFrame) -> int:
    """Size of a stored table in memory: 32 bytes a row, 16 a column, and its text and binary content."""
    wide = [F.octet_length(c) if kind in ("string", "binary") else F.octet_length(F.col(c).cast("string")) for c, kind in side.dtypes if kind in ("string", "binary") or kind.startswith(("struct", "array", "map"))]
    content = sum((F.coalesce(c, F.lit(0)) for c in wide), F.lit(0))
    r = side.agg(F.count(F.lit(1)).alias("n"), F.sum(content).alias("content")).first()
    return r["n"] * (32 + 16 * len(side.columns)) + (r["content"] or 0)


def small_or_shuffled(side: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """``side``, a stored table, with a broadcast hint if it is within the bound, else as it is."""
    return F.broadcast(side) if estimated_bytes(side) <= most else side


def words(text: Column) -> Column:
    """Words of a whole text; none for null."""
    return F.coalesce(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.array().cast("array<string>"))


def n_words(text: Column) -> Column:
    """Number of words as a long; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once a row and hand it to ``body``.

    The optimiser may copy an expression into a lambda, where it would run once an element; a lambda's own variable stays as it is.
    """
    return F.transform(F.array(value), body)[0]


def running_totals(df: DataFrame, order: Sequence[Column | str], values: dict[str, Column], scratch: Scratch, blocks: int | None = None) -> DataFrame:
    """``df`` with inclusive running sums of ``values`` in a total order.

    Rows are dealt by range into blocks, summed in each block by a window, and moved by the sums of the blocks before.
    No task holds more than a block, whatever the keys; only one row a block meets in a single task.
    """
    n = blocks or max(8, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = scratch.cut(df.withColumns(dict(values)).repartitionByRange(n, *order).withColumn("_block", F.spark_partition_id()), "ranged")
    within = Window.partitionBy("_block").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    before = Window.orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    sums = dealt.groupBy("_block").agg(*(F.sum(c).alias(f"_sum_{c}") for c in values))
    starts = sums.select("_block", *(F.coalesce(F.sum(f"_sum_{c}").over(before), F.lit(0)).alias(f"_start_{c}") for c in values))
    out = dealt.withColumns({f"_in_{c}": F.sum(c).over(within) for c in values}).join(F.broadcast(starts), "_block")
    keep = [c for c in dealt.columns if c not in values and c != "_block"]
    return out.select(*keep, *((F.col(f"_in_{c}") + F.col(f"_start_{c}")).alias(c) for c in values))
