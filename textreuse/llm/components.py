"""Connected components by hooking and contraction.

Each round every node hooks to its neighbour of least rank, pointers jump twice, and
edges are rewritten to the new labels; those inside a component vanish. Ranks are
hashes of the ids, so the number of rounds is logarithmic also on long chains. Each
round is written to the shared folder; nothing but an "are there edges left" comes
to the driver.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch


def _least(node: Column) -> Column:
    """Rank and id, ordered by rank."""
    return F.struct(F.xxhash64(node).alias("rank"), node.alias("id"))


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """``node, label`` for every node of ``edges`` (``a``, ``b`` longs): equal labels in a component, a node's id as label."""
    left = scratch.cut(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    known: DataFrame | None = None
    while not left.isEmpty():
        both = left.select("a", "b").union(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hook = both.groupBy(F.col("a").alias("node")).agg(F.min(_least(F.col("b"))).alias("best"))
        hooks = hook = scratch.cut(hook.select("node", F.least(F.col("best"), _least(F.col("node")))["id"].alias("up")), "hooks")
        for _ in range(2):
            above = hook.select(F.col("node").alias("up"), F.col("up").alias("top"))
            hook = hook.join(above, "up").select("node", F.col("top").alias("up"))
        hook = scratch.cut(hook, "parents")
        scratch.drop(hooks)
        before = known
        if known is None:
            known = scratch.cut(hook.select("node", F.col("up").alias("label")), "labels")
        else:
            moved = known.join(hook.select(F.col("node").alias("label"), "up"), "label", "left")
            known = scratch.cut(moved.select("node", F.coalesce("up", "label").alias("label")), "labels")
        to = lambda end: hook.select(F.col("node").alias(end), F.col("up").alias(f"_{end}"))
        moved = left.join(to("a"), "a").join(to("b"), "b").where("_a <> _b")
        rest = scratch.cut(moved.select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b")).distinct(), "edges")
        scratch.drop(before, hook, left)
        left = rest
    return known if known is not None else edges.select(F.col("a").alias("node"), F.col("a").alias("label")).limit(0)
