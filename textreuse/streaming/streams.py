"""Streaming twins: windows, sessions, de-duplication, interval joins, keyed state, and incremental retrieval.

Each run reads a table as a file stream, processes what is there, and ends. The results
equal the batch answers, which are their SQL.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from .. import oracles as sql
from ..operators import retrieval as sr
from ..registry import query
from ..sources.catalog import load
from ..sources.io import shared_folder


def _shared(spark: SparkSession, label: str) -> str:
    return f"{shared_folder(spark)}/textreuse-{label}-{uuid.uuid4().hex}"


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table's files as a stream, with the table's schema."""
    flat = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    rows = spark.readStream.schema(flat.schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/{name}.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def run(rows: DataFrame, mode: str = "append") -> DataFrame:
    """Process all available input into tables below the shared folder, and read the result: of ``complete`` mode the last one."""
    spark = rows.sparkSession
    state, out = _shared(spark, "state"), _shared(spark, "stream")
    if mode == "append":
        rows.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(rows.schema).parquet(out)
    done: list[int] = []

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
        done.append(number)

    rows.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{out}/batch={max(done)}") if done else spark.createDataFrame([], rows.schema)


_STAMP = "strftime({}, '%Y-%m-%d %H:%M:%S')"
_stamp = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query("st_tumbling", f"select {_STAMP.format('date_trunc(' + chr(39) + 'hour' + chr(39) + ', ts)')} as start, event_type, count(*) as n from events group by 1, 2")
def st_tumbling(spark, sf_dir):
    rows = stream(spark, sf_dir, "events").withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return run(rows.select(_stamp(F.col("window.start")).alias("start"), "event_type", "n"), "complete")


@query("st_sliding", f"with s as (select event_id, time_bucket(interval '30 minutes', ts) - i * interval '30 minutes' as start from events, range(2) r(i)) select {_STAMP.format('start')} as start, count(*) as n from s group by 1")
def st_sliding(spark, sf_dir):
    rows = stream(spark, sf_dir, "events").withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return run(rows.select(_stamp(F.col("window.start")).alias("start"), "n"), "complete")


@query("st_session", f"with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts range unbounded preceding) as k from g) select user_id, {_STAMP.format('min(ts)')} as start, count(*) as n from s group by user_id, k")
def st_session(spark, sf_dir):
    rows = stream(spark, sf_dir, "events").withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return run(rows.select("user_id", _stamp(F.col("session_window.start")).alias("start"), "n"), "complete")


@query("st_dedup", "select distinct md5(text) as h from documents")
def st_dedup(spark, sf_dir):
    return run(stream(spark, sf_dir, "documents").select(F.md5("text").alias("h")).dropDuplicates(["h"]))


@query("st_interval_join", "select v.event_id as view, p.event_id as purchase from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour")
def st_interval_join(spark, sf_dir):
    side = lambda kind, name: stream(spark, sf_dir, "events").where(F.col("event_type") == kind).select(F.col("user_id").alias(f"{name}_user"), F.col("event_id").alias(name), F.col("ts").alias(f"{name}_ts")).withWatermark(f"{name}_ts", "1 hour")
    on = F.expr("view_user = purchase_user and purchase_ts >= view_ts and purchase_ts <= view_ts + interval 1 hour")
    return run(side("view", "view").join(side("purchase", "purchase"), on).select("view", "purchase"))


@query("st_state_sketch", "select source, count(distinct md5(text)) as texts from documents group by 1")
def st_state_sketch(spark, sf_dir):
    """Distinct texts by source, with keyed state: a source and a digest is a key, so that no state grows with a source."""

    def update(key, batches, state: GroupState):
        for _ in batches:
            pass
        if not state.exists:
            state.update((True,))
            yield pd.DataFrame({"source": [key[0]], "h": [key[1]]})

    rows = stream(spark, sf_dir, "documents").select("source", F.md5("text").alias("h")).groupBy("source", "h")
    first = run(rows.applyInPandasWithState(update, "source string, h string", "seen boolean", "append", GroupStateTimeout.NoTimeout))
    return first.groupBy("source").agg(F.count(F.lit(1)).alias("texts"))


@query("st_incremental_candidates")
def st_incremental_candidates(spark, sf_dir):
    return _incremental(spark, sf_dir, "xx")


@query("st_incremental_candidates_md5", f"with {sql.candidates()} select a_doc, b_doc from cand")
def st_incremental_candidates_md5(spark, sf_dir):
    """The same by the family that SQL can compute too."""
    return _incremental(spark, sf_dir, "md5")


def _incremental(spark: SparkSession, sf_dir: str, family: str) -> DataFrame:
    """Candidate pairs of a collection that arrives as a stream: new postings meet the stored ones and one another.

    A micro-batch writes its postings and pairs under its own number, so that one that runs again overwrites itself.
    """
    posts, pairs = _shared(spark, "postings"), _shared(spark, "candidates")
    sketched = lambda docs: sr.sketched(docs, family=family)
    schema = sr.postings(sketched(load(spark, sf_dir, "documents").limit(0))).schema

    def arrive(batch: DataFrame, number: int) -> None:
        new = sr.postings(sketched(batch.select("doc_id", "text")))
        new.write.mode("overwrite").parquet(f"{posts}/batch={number}")
        new = batch.sparkSession.read.schema(schema).parquet(f"{posts}/batch={number}")
        old = batch.sparkSession.read.schema(schema).parquet(f"{posts}/batch=*").where(F.regexp_extract(F.input_file_name(), "batch=([0-9]+)", 1).cast("long") < number)
        _meet(new, old).write.mode("overwrite").parquet(f"{pairs}/batch={number}")

    rows = stream(spark, sf_dir, "documents")
    rows.writeStream.foreachBatch(arrive).option("checkpointLocation", _shared(spark, "state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{pairs}/batch=*").select("a_doc", "b_doc").distinct()


def _meet(new: DataFrame, old: DataFrame) -> DataFrame:
    """Pairs of a new document with a new or an old one."""
    a = new.select("slot", "hash", F.col("doc_id").alias("x"))
    b = new.union(old).select("slot", "hash", F.col("doc_id").alias("y"))
    return a.join(b, ["slot", "hash"]).where("x <> y").select(F.least("x", "y").alias("a_doc"), F.greatest("x", "y").alias("b_doc")).distinct()
