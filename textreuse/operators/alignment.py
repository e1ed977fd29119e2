"""Text alignment: word n-grams, seeds by hash equi-joins, and extension into reuse cases.

Grams leave the row once, with their spans. Seeds come from one equi-join of the grams
with themselves (seed-first, exact), or from candidate pairs (the paper's order).
Extension is gaps-and-islands over windows of a pair, after consecutive seeds on a
diagonal have become one run.
"""

from __future__ import annotations

import sys

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import stored
from .normalize import let, worded

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need no installed copy of this package

PAIR = ["a_doc", "b_doc"]
SPAN = ["a_begin", "a_end", "b_begin", "b_end"]


def grams(rows: DataFrame, n: int = 8, k: int | None = None, family: str = "xx", order: bool = True, context: bool = False) -> DataFrame:
    """``doc_id, pos, begin, end, g`` of the n-grams that overlap in k words (default n - 1).

    ``g`` is a 64-bit hash or, for family ``text``, the words themselves. Without ``order`` words are sorted first. With
    ``context`` each gram also has those before and after it, ``before`` and ``after``; null at the ends of a text.
    """
    step = n - (n - 1 if k is None else k)

    def gram(units: Column, p: Column) -> Column:
        if family == "text":
            part = F.slice(units, p + 1, n)
            return F.array_join(part if order else F.array_sort(part), " ")
        return F.xxhash64(*(F.get(units, p + i) for i in range(n))) if order else F.xxhash64(F.array_sort(F.slice(units, p + 1, n)))

    def cut(units: Column) -> Column:
        # Not a filter, which the optimiser would move below a deal of the rows and so evaluate twice.
        starts = F.when(F.size("words") >= n, F.sequence(F.lit(0), F.size("words") - n, F.lit(step))).otherwise(F.array().cast("array<int>"))

        def placed(p: Column, g: Column, *around: Column) -> Column:
            end = F.get(F.col("begins"), p + n - 1) + F.length(F.get(F.col("words"), p + n - 1))
            return F.struct(p.alias("pos"), F.get(F.col("begins"), p).alias("begin"), end.alias("end"), g.alias("g"), *around)

        if not context:
            return F.transform(starts, lambda p: placed(p, gram(units, p)))
        found = F.transform(starts, lambda p: gram(units, p))
        return let(found, lambda gs: F.transform(gs, lambda g, i: placed(i * step, g, F.get(gs, i - 1).alias("before"), F.get(gs, i + 1).alias("after"))))

    # A word is hashed once, and a gram is the hash of its words' hashes: no text is built for it.
    units = F.col("words") if family == "text" else F.transform("words", lambda w: F.xxhash64(w))
    out = rows.select("doc_id", F.explode(let(units, cut)).alias("x"))
    return out.select("doc_id", "x.*")


def sentences(docs: DataFrame) -> DataFrame:
    """Sentences as chunks, the other answer to how a text is divided."""
    cut = F.filter(F.split("text", r"[.!?]+[\x20\n]+"), lambda s: F.length(F.trim(s)) > 0)
    return docs.select("doc_id", F.posexplode(cut).alias("pos", "sentence"))


def shared_grams(gs: DataFrame) -> DataFrame:
    """Grams of more than one document: the only ones that can be seeds. Most distinct grams go here, before positions move."""
    return gs.groupBy("g").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo <> hi").select("g")


def _sides(a: DataFrame, b: DataFrame) -> tuple[DataFrame, DataFrame]:
    pick = lambda df, s: df.select("g", F.col("doc_id").alias(f"{s}_doc"), F.col("pos").alias(f"{s}_pos"), F.col("begin").alias(f"{s}_begin"), F.col("end").alias(f"{s}_end"))
    return pick(a, "a"), pick(b, "b")


SEED = ["a_doc", "b_doc", "a_pos", "b_pos", *SPAN]


def seeds_by_index(gs: DataFrame, other: DataFrame | None = None, prune: bool = False) -> DataFrame:
    """Equal grams of two documents, over the whole collection. ``other`` gives the grams of the b side, if they differ."""
    if prune:
        gs = gs.join(shared_grams(gs), "g", "left_semi")
    a, b = _sides(gs, gs if other is None else other)
    return a.join(b, "g").where("a_doc < b_doc").select(*SEED)


def seeds_between(gs: DataFrame, other: DataFrame) -> DataFrame:
    """Equal grams of two collections, each with ids of its own."""
    a, b = _sides(gs, other)
    return a.join(b, "g").select(*SEED)


def seeds_by_candidates(pairs: DataFrame, gs: DataFrame, plan: str = "candidates") -> DataFrame:
    """Seeds of the candidate pairs. Two orders of the joins give the same rows: ``candidates`` brings the grams of both
    documents to each pair, ``index`` keeps of all equal grams those of a candidate pair."""
    if plan == "index":
        return seeds_by_index(gs, prune=True).join(pairs, PAIR, "left_semi").select(*SEED)
    a, b = _sides(gs, gs)
    return pairs.join(a, "a_doc").join(b, ["b_doc", "g"]).select(*SEED)


def runs(seeds: DataFrame) -> DataFrame:
    """Consecutive seeds on one diagonal as one row: the window of a dense pair shrinks by orders of magnitude."""
    along = Window.partitionBy("a_doc", "b_doc", "_diagonal").orderBy("a_pos")
    rows = seeds.withColumn("_diagonal", F.col("a_pos") - F.col("b_pos")).withColumn("_run", F.col("a_pos") - F.row_number().over(along))
    return rows.groupBy("a_doc", "b_doc", "_diagonal", "_run").agg(
        F.min("a_begin").alias("a_begin"), F.max("a_end").alias("a_end"), F.min("b_begin").alias("b_begin"), F.max("b_end").alias("b_end"), F.count(F.lit(1)).alias("n_seeds")
    ).drop("_diagonal", "_run")


def runs_of_grams(gs: DataFrame, prune: bool = True, store: bool = False) -> DataFrame:
    """The runs of all seeds of a collection, from its grams with context (``k = n - 1``).

    A seed is inside a run if the grams before are equal too, and those after. Only the first and the last seed of a run
    leave the join, so what is shuffled and sorted is two rows a run, however long the copied passage is. Both sides of
    the join read the grams: with ``store`` those of more than one document are written once instead of made twice.
    """
    if prune:
        gs = gs.join(shared_grams(gs), "g", "left_semi")
    if store:
        gs = stored(gs, "shared-grams")
    side = lambda s: gs.select("g", *(F.col(c).alias(f"{s}_{c}") for c in ("pos", "begin", "end", "before", "after")), F.col("doc_id").alias(f"{s}_doc"))
    differ = lambda c: ~F.coalesce(F.col(f"a_{c}") == F.col(f"b_{c}"), F.lit(False))
    ends = side("a").join(side("b"), "g").where((F.col("a_doc") < F.col("b_doc")) & (differ("before") | differ("after")))
    # Dealt by pair at once: the window of a diagonal needs no finer deal, and the windows of a pair no further one.
    rows = ends.select(*PAIR, "a_pos", *SPAN, (F.col("a_pos") - F.col("b_pos")).alias("_diagonal"), differ("before").cast("int").alias("_first")).repartition(*PAIR)
    along = Window.partitionBy("a_doc", "b_doc", "_diagonal").orderBy("a_pos").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("_run", F.sum("_first").over(along))
    return rows.groupBy("a_doc", "b_doc", "_diagonal", "_run").agg(
        F.min("a_begin").alias("a_begin"), F.max("a_end").alias("a_end"), F.min("b_begin").alias("b_begin"), F.max("b_end").alias("b_end"), (F.max("a_pos") - F.min("a_pos") + 1).cast("bigint").alias("n_seeds")
    ).drop("_diagonal", "_run")


def _split(rows: DataFrame, side: str, delta: int | Column, keys: list[str], name: str) -> DataFrame:
    order = Window.partitionBy(*keys).orderBy(f"{side}_begin", f"{side}_end")
    before = F.max(f"{side}_end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    gap = F.when(F.col(f"{side}_begin") - before > delta, 1).otherwise(0)
    numbered = rows.withColumn("_gap", gap)
    # A range frame counts the gap before rows that tie for all of them, so the result does not depend on their order.
    return numbered.withColumn(name, F.sum("_gap").over(order.rangeBetween(Window.unboundedPreceding, Window.currentRow))).drop("_gap")


def islands(spans: DataFrame, delta: int | Column = 250, rounds: int = 2, more_keys: list[str] | None = None) -> DataFrame:
    """Group spans of a pair by gaps: split along a, then along b inside, ``rounds`` times. Group numbers are columns ``_g*``."""
    keys = [*PAIR, *(more_keys or [])]
    for r in range(rounds):
        for side in ("a", "b"):
            name = f"_g{r}{side}"
            spans = _split(spans, side, delta, keys, name)
            keys = [*keys, name]
    return spans


def settled(spans: DataFrame, delta: int | Column = 250, more_keys: list[str] | None = None) -> DataFrame:
    """Islands split until a round splits none any more. The group is one number, ``_g``; each round is stored."""
    keys = [*PAIR, *(more_keys or [])]
    spans, groups = spans.withColumn("_g", F.lit(0).cast("bigint")), -1
    while True:
        for side in ("a", "b"):
            spans = _split(spans, side, delta, [*keys, "_g"], "_part")
            spans = spans.withColumn("_g", F.xxhash64("_g", F.lit(side), "_part")).drop("_part")
        spans = stored(spans, "islands")
        now = spans.select(*keys, "_g").distinct().count()
        if now == groups:
            return spans
        groups = now


def merge(spans: DataFrame, delta: int | Column = 250, rounds: int | None = 2, min_seeds: int = 1, more_keys: list[str] | None = None) -> DataFrame:
    """Cases: spans of a pair that stay within ``delta`` characters of one another in both documents, by islands.

    Without a number of ``rounds`` they are split until nothing changes.
    """
    if "n_seeds" not in spans.columns:
        spans = spans.withColumn("n_seeds", F.lit(1))
    if rounds is None:
        whole = settled(spans, delta, more_keys)
        return _spans(whole.groupBy(*PAIR, *(more_keys or []), "_g")).where(F.col("n_seeds") >= min_seeds).drop("_g")
    grouped = islands(spans, delta, rounds, more_keys)
    keys = [*PAIR, *(more_keys or []), *(c for c in grouped.columns if c.startswith("_g"))]
    return _spans(grouped.groupBy(*keys)).where(F.col("n_seeds") >= min_seeds).drop(*(k for k in keys if k.startswith("_g")))


def _spans(grouped) -> DataFrame:
    return grouped.agg(F.min("a_begin").alias("a_begin"), F.max("a_end").alias("a_end"), F.min("b_begin").alias("b_begin"), F.max("b_end").alias("b_end"), F.sum("n_seeds").cast("bigint").alias("n_seeds"))


def chains(run_rows: DataFrame, delta: int = 250) -> DataFrame:
    """Order-preserving cases: a new one starts where b turns back or a gap exceeds ``delta``."""
    order = Window.partitionBy(*PAIR).orderBy("a_begin", "b_begin", "a_end", "b_end")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    turn = (F.col("b_begin") < F.lag("b_begin").over(order)) | (F.col("a_begin") - F.max("a_end").over(before) > delta) | (F.col("b_begin") - F.lag("b_end").over(order) > delta)
    rows = run_rows.withColumn("_turn", F.when(turn, 1).otherwise(0))
    rows = rows.withColumn("_chain", F.sum("_turn").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return _spans(rows.groupBy(*PAIR, "_chain")).drop("_chain")


CASE = "a_doc long, b_doc long, a_begin int, a_end int, b_begin int, b_end int, n_seeds long"


def single_links(pair: np.ndarray, a0: np.ndarray, a1: np.ndarray, b0: np.ndarray, b1: np.ndarray, delta: int, near: str, cells: int = 4_000_000) -> np.ndarray:
    """For runs ordered by pair (numbered from 0 on) and spans the first run of the component of each, linked as :func:`components` says."""

    def link(root: np.ndarray, u: np.ndarray, v: np.ndarray) -> None:
        """Joins the trees of u and v; all nodes point to their roots before and after."""
        while len(u):
            u, v = root[u], root[v]
            apart = u != v
            u, v = u[apart], v[apart]
            np.minimum.at(root, np.maximum(u, v), np.minimum(u, v))
            while not np.array_equal(up := root[root], root):
                root[:] = up

    n, root = len(pair), np.arange(len(pair))
    base = pair * (int(max(a1.max(), b1.max())) + delta + 1)  # keeps the places of one pair below those of the next
    if near == "either":
        for begin, end in ((a0, a1), (b0, b1)):
            order = np.lexsort((end, begin, pair))
            far = np.maximum.accumulate((end + base)[order])
            open_ = (begin + base)[order][1:] - far[:-1] <= delta
            open_ &= pair[order][1:] == pair[order][:-1]
            link(root, order[:-1][open_], order[1:][open_])  # all that stand between two gaps are one
        return root
    here, starts = np.arange(n), np.flatnonzero(np.diff(pair, prepend=-1))
    # The range may not leave the pair, which the base alone does not ensure for a negative delta.
    size = np.maximum(np.searchsorted(a0 + base, a1 + base + delta, side="right") - here - 1, 0)
    size = np.minimum(size, np.append(starts[1:], n)[pair] - here - 1)
    ends, at = np.cumsum(size), 0
    while at < n:
        last = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + cells, side="right")))
        part = size[at:last]
        i = np.repeat(here[at:last], part)
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(part) - part, part)
        close = np.maximum(b0[i], b0[j]) - np.minimum(b1[i], b1[j]) <= delta
        link(root, i[close], j[close])
        at = last
    return root


def components(run_rows: DataFrame, delta: int = 250, near: str = "both", batch_rows: int = 200_000) -> DataFrame:
    """Single-link components of runs: linked if near in both documents, or in at least one.

    Two runs are near on a side if the gap of their spans is at most ``delta``. Rows of a pair stand together in a task, and
    many pairs are treated at once, as most have few runs: for ``either`` neighbours along each side are linked, for ``both``
    the runs that follow near along a are a range, of which those near in b are linked.
    """

    span, names = list(SPAN), [*PAIR, *SPAN, "n_seeds"]

    def found(rows: pd.DataFrame) -> pd.DataFrame:
        first = np.ones(len(rows), bool)
        first[1:] = (np.diff(rows["a_doc"].to_numpy()) != 0) | (np.diff(rows["b_doc"].to_numpy()) != 0)
        a0, a1, b0, b1 = (rows[c].to_numpy().astype(np.int64) for c in span)
        root = single_links(np.cumsum(first) - 1, a0, a1, b0, b1, delta, near)
        order = np.argsort(root, kind="stable")
        starts = np.flatnonzero(np.diff(root[order], prepend=-1))
        of = lambda how, v: how.reduceat(v[order], starts)
        keys = [rows[c].to_numpy()[order][starts] for c in names[:2]]
        values = [*keys, of(np.minimum, a0), of(np.maximum, a1), of(np.minimum, b0), of(np.maximum, b1), of(np.add, rows["n_seeds"].to_numpy())]
        return pd.DataFrame(dict(zip(names, values, strict=True)))

    def run(batches):
        held, n = [], 0
        for batch in batches:
            if not len(batch):
                continue
            held, n = [*held, batch], n + len(batch)
            if n < batch_rows:
                continue
            ends = batch[names[:2]].to_numpy()[-1]
            last = (batch[names[:2]].to_numpy() == ends).all(axis=1)
            if last.all():
                continue  # a pair that goes on; it may begin in an earlier batch
            yield found(pd.concat([*held[:-1], batch[~last]], ignore_index=True))
            held, n = [batch[last]], int(last.sum())
        if held:
            yield found(pd.concat(held, ignore_index=True))

    # A window brings the rows of a pair together and sorts them, without a shuffle if they are dealt by pair already.
    nth = F.row_number().over(Window.partitionBy(*PAIR).orderBy(*SPAN))
    return run_rows.select(*PAIR, *SPAN, F.col("n_seeds").cast("bigint").alias("n_seeds"), nth.alias("_nth")).mapInPandas(run, CASE)


def cases_of(docs: DataFrame, n: int = 8, k: int | None = None, delta: int = 250, family: str = "xx", min_seeds: int = 1, store: bool = False) -> DataFrame:
    """The whole alignment of a collection, seed-first: cases of ``docs``. One plan from scan to case, unless grams are to be stored between."""
    if k is None or k == n - 1:
        return merge(runs_of_grams(grams(worded(docs), n, k, family, context=True), store=store), delta, min_seeds=min_seeds)
    return merge(seeds_by_index(grams(worded(docs), n, k, family), prune=True), delta, min_seeds=min_seeds)
