"""Sharding by a minimax contiguous partition of atomic groups.

Rows with equal texts form a group that is never torn. Groups stand in the order of
their smallest id; the shards are contiguous runs of that order. The largest shard
is as small as any contiguous partition allows: a binary search over the capacity,
in which a greedy pass fills shard after shard, finds it, and the cuts of that last
pass are taken.

Scale: the ordered group sizes stay in a distributed table of running totals, in
blocks. The greedy pass asks one thing only, "the last group that ends within x";
the driver holds one row a block and answers at block level, with bounds that
usually decide a capacity; where they do not, it reads the one block in question.

Cases: a null text has no bytes and size 1, and all null texts are one group; an
empty text is another group. Ids that are null come first; groups whose smallest ids tie
stand by digest. Repeated rows share a group. A very long text is one group like others,
and bounds the capacity from below. With fewer groups than shards, trailing shards stay
empty. An empty table gives an empty result. Other columns are passed by, whatever their
names.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, running_totals


class Ends:
    """Running totals of ordered groups: blocks on the driver, single groups on demand."""

    def __init__(self, blocks: list[tuple[int, int, int]], load: Callable[[int], list[int]]):
        self.blocks = sorted(blocks, key=lambda b: b[1:])  # (block, first end, last end)
        self.firsts = [b[1] for b in self.blocks]
        self.lasts = [b[2] for b in self.blocks]
        self.load, self.held = load, {}

    @property
    def total(self) -> int:
        return self.lasts[-1] if self.lasts else 0

    def within(self, x: int) -> int:
        """The largest group end that is at most x; 0 if there is none."""
        k = bisect_right(self.firsts, x) - 1
        if k < 0:
            return 0
        if self.lasts[k] <= x:
            return self.lasts[k]
        name = self.blocks[k][0]
        if name not in self.held:
            self.held[name] = sorted(self.load(name))
        ends = self.held[name]
        return ends[bisect_right(ends, x) - 1]

    def roughly(self, x: int) -> tuple[int, int]:
        """Bounds of :meth:`within` that need no block: a block's own end below, x itself above."""
        k = bisect_right(self.firsts, x) - 1
        if k < 0:
            return 0, 0
        return (self.lasts[k], self.lasts[k]) if self.lasts[k] <= x else (self.firsts[k], x)


def fits(ends: Ends, capacity: int, shards: int) -> bool:
    """Whether greedy filling needs at most ``shards`` shards of ``capacity``."""
    low = high = 0
    for _ in range(shards):
        low, high = ends.roughly(low + capacity)[0], ends.roughly(high + capacity)[1]
    if low >= ends.total:
        return True
    if high < ends.total:
        return False
    at = 0
    for _ in range(shards):
        at = ends.within(at + capacity)
    return at >= ends.total


def minimax_cuts(ends: Ends, largest: int, shards: int) -> tuple[int, list[int]]:
    """The smallest feasible capacity, and the total at which each shard ends."""
    low = max(largest, -(-ends.total // shards))
    high = low + largest
    while low < high:
        middle = (low + high) // 2
        low, high = (low, middle) if fits(ends, middle, shards) else (middle + 1, high)
    cuts, at = [], 0
    for _ in range(shards):
        at = ends.within(at + low)
        cuts.append(at)
    return low, cuts


def shard(docs: DataFrame, shards: int = 8, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Shard, slot in the shard, size and checksum of every row of ``docs``."""
    scratch = Scratch(docs.sparkSession, "shards")
    utf8 = F.encode(F.col(text), "UTF-8")
    rows = scratch.cut(
        docs.select(
            F.col(key).alias("doc_id"),
            (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + 1).cast("long").alias("size"),
            F.coalesce(F.crc32(utf8), F.lit(0)).cast("long").alias("text_crc32"),
            F.coalesce(F.md5(utf8), F.lit("null")).alias("group"),
        ),
        "rows",
    )
    groups = rows.groupBy("group").agg(F.min("doc_id").alias("first"), F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n"))
    groups = scratch.cut(groups, "groups")
    # Running totals of groups; a group's end names it, as every size is at least 1.
    order = [F.col("first").asc_nulls_first(), F.col("group")]
    summed = running_totals(groups, order, {"end": F.col("bytes"), "row_end": F.col("n")}, scratch)
    blocks = F.floor(F.col("row_end") / F.lit(100_000))
    summed = scratch.cut(summed.withColumn("block", blocks), "ends")
    firsts = summed.groupBy("block").agg(F.min("end").alias("a"), F.max("end").alias("z"), F.max("bytes").alias("m")).collect()
    ends = Ends([(r["block"], r["a"], r["z"]) for r in firsts], lambda b: [r["end"] for r in summed.where(F.col("block") == b).select("end").collect()])
    _, cuts = minimax_cuts(ends, max((r["m"] for r in firsts), default=1), shards)
    number = F.lit(0)
    for cut in cuts[:-1]:
        number = number + F.when(F.col("end") > cut, 1).otherwise(0)
    placed = summed.withColumn("shard", number.cast("int"))
    starts = placed.groupBy("shard").agg(F.min(F.col("row_end") - F.col("n")).alias("_start"))
    # Rows join back by group without their texts; a hot group is split by the engine.
    members = rows.join(placed.select("group", "first", "shard"), "group")
    ordered = running_totals(members, [F.col("first").asc_nulls_first(), F.col("group"), F.col("doc_id")], {"_row": F.lit(1).cast("long")}, scratch)
    out = ordered.join(F.broadcast(starts), "shard")
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("_row") - 1 - F.col("_start")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(placed: DataFrame, docs: DataFrame, path: str, key: str = "doc_id") -> None:
    """Write the documents as one folder a shard, each ordered by slot. Ids must be unique here."""
    rows = docs.join(placed.select(F.col("doc_id").alias("_id"), "shard", "slot"), F.col(key) == F.col("_id")).drop("_id")
    rows.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
