"""Conflict-constrained best-fit packing of documents into sequences.

A bin holds ``capacity`` words. Two pieces of one source, or of one cluster of
duplicates, never share a bin: each bin carries a bitmap of the sources and one of
the clusters in it. Bins are ordered by what is left in them; for a piece the search
starts at the tightest bin that is large enough and goes on to its successors until
one is compatible. Pieces come longest first. A document longer than a bin is cut
into full pieces, each of which opens a bin of its own, and a rest.

Clusters are equal texts (lower case, blanks joined), or what the column ``cluster``
names, such as the components of :mod:`neardup`; nulls there conflict with nothing.

Scale: rows are dealt by a hash of their id into packs of about ``pack_rows`` rows,
each packed by one task with bounded memory; texts never move. A hot source or a
large cluster is spread over all packs and costs bins, not time: a pack's search is
bounded by its own bins. Best fit is exact within a pack; what the split costs in bins
against one pack of all rows is measured in the README. Rows of an id that repeats,
null ids too, are dealt by their place, so that no id fills a pack.

Cases: a null or empty text has no piece: one row without a bin. A null source
conflicts with nothing. Rows that repeat are separate pieces of one cluster. Very long
texts are cut into pieces. Pieces of one length stand by id, ties in bins by number. An
empty table gives an empty result. Other columns are passed by, whatever their names.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE, Scratch, n_words, small_or_shuffled


@dataclass(frozen=True)
class Bins:
    capacity: int = 2048
    pack_rows: int = 4000


def best_fit(lengths: list[int], sources: list, clusters: list, capacity: int) -> list[tuple[int, int]]:
    """Bin and offset of each piece, given longest first."""
    source_bit: dict = {}
    cluster_bit: dict = {}
    bit = lambda known, value: 0 if value is None else 1 << known.setdefault(value, len(known))
    order: list[tuple[int, int]] = []  # (what is left, bin), ascending
    maps: list[list[int]] = []
    placed = []
    for size, source, cluster in zip(lengths, sources, clusters, strict=True):
        s, c = bit(source_bit, source), bit(cluster_bit, cluster)
        at = bisect_left(order, (size, -1))
        while at < len(order) and (maps[order[at][1]][0] & s or maps[order[at][1]][1] & c):
            at += 1
        if at < len(order):
            left, b = order.pop(at)
        else:
            left, b = capacity, len(maps)
            maps.append([0, 0])
        maps[b][0] |= s
        maps[b][1] |= c
        placed.append((b, capacity - left))
        insort(order, (left - size, b))
    return placed


PLACED = "doc_id string, piece long, start_word long, n_words long, source string, cluster string, bin_id long, bin_offset long"


def pack(docs: DataFrame, bins: Bins = Bins(), text: str = "text", key: str = "doc_id", source: str = "source", cluster: str | None = None) -> DataFrame:
    """A row for each piece: its document, words, cluster, bin and offset in the bin."""
    scratch = Scratch(docs.sparkSession, "packing")
    plain = F.xxhash64(F.lower(F.trim(F.regexp_replace(F.col(text), SPACE + "+", " "))))
    group = plain if cluster is None else F.col(cluster).cast("long")
    rows = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(source).cast("string").alias("source"), n_words(F.col(text)).alias("size"), group.alias("cluster"), F.monotonically_increasing_id().alias("_place"))
    rows = scratch.cut(rows, "sizes")
    again = scratch.cut(rows.groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias("_again")), "repeated")
    if again.isEmpty():
        rows = rows.withColumn("_place", F.lit(0).cast("long"))
    else:
        there = rows.join(small_or_shuffled(again.withColumn("_many", F.lit(True))), F.col("doc_id").eqNullSafe(F.col("_again")), "left").drop("_again")
        rows = there.withColumn("_place", F.when(F.col("_many"), F.col("_place")).otherwise(F.lit(0))).drop("_many")
    cap = F.lit(bins.capacity).cast("long")
    pieces = rows.withColumn("piece", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0).cast("long"), F.floor((F.col("size") - 1) / cap).cast("long")))))
    pieces = pieces.withColumns({"start_word": F.col("piece") * cap, "n_words": F.least(cap, F.col("size") - F.col("piece") * cap)})
    packs = max(1, -(-rows.count() // bins.pack_rows))
    base = F.shiftleft(F.pmod(F.xxhash64("doc_id", "_place"), F.lit(packs)).cast("long"), 32)
    none = pieces.where("size = 0").select("doc_id", "piece", "start_word", "n_words", "source", "cluster", F.lit(None).cast("long").alias("bin_id"), F.lit(None).cast("long").alias("bin_offset"))
    # A full piece finds no bin with room and opens one; its residual of 0 is never looked at again. Ids travel as text, as pandas has no null integer.
    rest = pieces.where("size > 0").select(F.col("doc_id").cast("string").alias("doc_id"), "piece", "start_word", "n_words", "source", F.col("cluster").cast("string").alias("cluster"), base.alias("_pack"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.assign(_n=pd.to_numeric(group["doc_id"])).sort_values(["n_words", "_n", "doc_id", "piece", "cluster", "source"], ascending=[False, *[True] * 5], na_position="first", kind="stable")
        sources, clusters = ([None if pd.isna(x) else x for x in group[c]] for c in ("source", "cluster"))
        where = best_fit(group["n_words"].tolist(), sources, clusters, bins.capacity)
        number = int(group["_pack"].iloc[0])
        out = group[["doc_id", "piece", "start_word", "n_words", "source", "cluster"]].copy()
        out["bin_id"] = np.array([number + b for b, _ in where], np.int64)
        out["bin_offset"] = np.array([o for _, o in where], np.int64)
        return out

    packed = rest.groupBy("_pack").applyInPandas(run, PLACED)
    return packed.withColumns({c: F.col(c).cast("long") for c in ("doc_id", "cluster")}).unionByName(none)
