"""Exact top-k inner products by norm-bucketed retrieval.

Vectors are ordered by length into buckets. For a query with k-th best score s so far,
a bucket can only help if s / (|q| * longest of the bucket) is at most 1: this is the
local cosine threshold. Above 1 the bucket is skipped. A high threshold prunes by a
coordinate: at the query's strongest coordinate a vector's normalised value must lie in
an interval that the threshold gives. A low one prunes by length: only the front of the
bucket, up to the length s / |q|, is looked at. Survivors are verified by exact integer
products. (Public method: Teflioudi, Gemulla, Mykytiuk, 2015.)

Scale: candidates are dealt by range of length into blocks, queries by hash; a pair of
blocks is one task, which returns k rows a query. Queries meet the block of the longest
vectors first. Their k-th scores there are lower bounds, by which a query then visits
only the blocks whose longest vector can still reach its bound: others are not joined.
The driver holds a length a block.

Cases: vectors that are null or hold null, NaN or infinite components take no part, nor
do rows with a null id. Only vectors of equal dimension meet. Rows are told by their
place, not by their id: of rows that repeat an id each is a query of its own, with all
other rows as candidates, those of its id too. Ties go to the smaller id. A query with
no candidates has no rows. Empty tables give none. Long vectors are rows like others.
Other columns are passed by, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, small_or_shuffled


@dataclass(frozen=True)
class TopK:
    k: int = 5
    scale: int = 256
    every: int = 50
    query_block: int = 1024
    candidate_block: int = 8192
    bucket: int = 512
    #: Local threshold from which coordinates prune; below it lengths do.
    coordinate_from: float = 0.6


def integer_vectors(rows: DataFrame, scale: int, key: str, vector: str) -> DataFrame:
    """``id, row, v, norm, dim`` of the rows that take part, with ``v = floor(scale * x)``; ``row`` is a number of its own."""
    bad: Column = F.exists(F.col(vector), lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    good = rows.where(F.col(vector).isNotNull() & F.col(key).isNotNull() & ~F.coalesce(bad, F.lit(True)))
    ints = good.select(F.col(key).cast("long").alias("id"), F.transform(F.col(vector), lambda x: F.floor(x.cast("double") * scale).cast("double")).alias("v"))
    return ints.withColumn("row", F.monotonically_increasing_id()).withColumns({"norm": F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)), "dim": F.size("v")})


def best_in_blocks(queries: np.ndarray, query_rows: np.ndarray, bounds: np.ndarray, block: np.ndarray, ids: np.ndarray, rows_of: np.ndarray, how: TopK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row of the query, id and score of each query's k best in the block that are not below the query's bound."""
    norms = np.sqrt((block * block).sum(axis=1))
    order = np.lexsort((ids, -norms))
    block, ids, rows_of, norms = block[order], ids[order], rows_of[order], norms[order]
    unit = block / np.where(norms > 0, norms, 1)[:, None]
    lengths = np.sqrt((queries * queries).sum(axis=1))
    exact = float(norms.max(initial=0)) * float(lengths.max(initial=0)) < 2.0**52
    whole = None if exact else block.astype(object)
    score = np.full((len(queries), how.k), -np.inf) if exact else np.full((len(queries), how.k), -np.inf, object)
    name = np.full((len(queries), how.k), np.iinfo(np.int64).max)
    for at in range(0, len(block), how.bucket):
        part = slice(at, min(at + how.bucket, len(block)))
        own, own_ids, own_rows, own_norms, own_unit = block[part], ids[part], rows_of[part], norms[part], unit[part]
        longest = own_norms[0]
        for q in range(len(queries)):
            least, reach = max(float(score[q, -1]), float(bounds[q])), float(lengths[q])
            local = least / (reach * longest) if reach * longest > 0 else (-np.inf if least <= 0 else np.inf)
            if local > 1 + 1e-9:
                continue
            if local >= how.coordinate_from:
                direction = queries[q] / reach
                c = int(np.abs(direction).argmax())
                x, t = direction[c], min(1.0, local)
                slack = np.sqrt((1 - t * t) * max(0.0, 1 - x * x))
                low, high = x * t - slack - 1e-9, x * t + slack + 1e-9
                # Past the pole the interval is open: the query's own value beats the threshold.
                low, high = (low if x < t else low), (high if x < t else np.inf)
                low = low if -x < t else -np.inf
                rows = np.flatnonzero((own_unit[:, c] >= low) & (own_unit[:, c] <= high))
            elif reach > 0 and least > 0:
                rows = np.arange(np.searchsorted(-own_norms, -(least / reach) * (1 - 1e-9), side="right"))
            else:
                rows = np.arange(len(own))
            if not len(rows):
                continue
            products = own[rows] @ queries[q] if exact else np.array([sum(int(a) * int(b) for a, b in zip(v, queries[q], strict=True)) for v in whole[part][rows]], object)
            ok = (products >= max(score[q, -1], bounds[q])) & (own_rows[rows] != query_rows[q])
            if not ok.any():
                continue
            s, n = np.concatenate([score[q], products[ok]]), np.concatenate([name[q], own_ids[rows][ok]])
            top = np.lexsort((n, -s))[: how.k]
            score[q], name[q] = s[top], n[top]
    found = np.isfinite(score.astype(float))
    row = np.repeat(np.arange(len(queries)), how.k).reshape(score.shape)
    return row[found], name[found], score[found].astype(np.int64)


RESULT = "query_id long, query_row long, vec_id long, score long"


def met(left: DataFrame, right: DataFrame, how: TopK) -> DataFrame:
    """The best of each query in each block that it meets: equal ``qb, cb``. ``left`` has a ``bound`` for each query."""

    def run(queries: pd.DataFrame, block: pd.DataFrame) -> pd.DataFrame:
        out = []
        for dim, some in queries.groupby("dim"):
            other = block[block["dim"] == dim]
            if len(other):
                ids, rows = some["id"].to_numpy(np.int64), some["row"].to_numpy(np.int64)
                at, name, score = best_in_blocks(np.stack(some["v"].to_list()), rows, some["bound"].to_numpy(float), np.stack(other["v"].to_list()), other["id"].to_numpy(np.int64), other["row"].to_numpy(np.int64), how)
                out.append(pd.DataFrame({"query_id": ids[at], "query_row": rows[at], "vec_id": name, "score": score}))
        return pd.concat(out) if out else pd.DataFrame({c: pd.Series(dtype="int64") for c in ("query_id", "query_row", "vec_id", "score")})

    pick = ["qb", "cb", "id", "row", "v", "dim"]
    return left.select(*pick, "bound").groupBy("qb", "cb").cogroup(right.select(*pick).groupBy("qb", "cb")).applyInPandas(run, RESULT)


def search(rows: DataFrame, how: TopK = TopK(), key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """``query_id, rank, vec_id, score``: the k best rows for every row whose id is divisible by ``how.every``."""
    scratch = Scratch(rows.sparkSession, "topk")
    ints = scratch.cut(integer_vectors(rows, how.scale, key, vector), "vectors")
    asked = ints.where(F.col("id") % how.every == 0)
    n, m = ints.count(), asked.count()
    blocks, groups = max(1, -(-n // how.candidate_block)), max(1, -(-m // how.query_block))
    dealt = scratch.cut(ints.repartitionByRange(blocks, F.col("norm").desc(), "id").withColumn("cb", F.spark_partition_id()), "blocks")
    longest = [(r["cb"], r["top"]) for r in dealt.groupBy("cb").agg(F.max("norm").alias("top")).orderBy("cb").collect()]
    queries = asked.withColumn("qb", F.pmod(F.xxhash64("row"), F.lit(groups)).cast("int"))
    rank = F.row_number().over(Window.partitionBy("query_row").orderBy(F.col("score").desc(), "vec_id"))
    every = F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))
    head, tail = longest[0][0] if longest else 0, [(b, top) for b, top in longest[1:] if top is not None]
    first = met(queries.withColumns({"cb": F.lit(head), "bound": F.lit(float("-inf"))}), dealt.where(F.col("cb") == head).withColumn("qb", every), how)
    if tail:
        first = scratch.cut(first, "first")
        bounds = first.groupBy("query_row").agg(F.min("score").cast("double").alias("least"), F.count(F.lit(1)).alias("found"))
        bounds = bounds.where(F.col("found") >= how.k).select(F.col("query_row").alias("row"), (F.col("least") - F.abs("least") * 1e-12).alias("bound"))
        queries = queries.join(bounds, "row", "left").withColumn("bound", F.coalesce("bound", F.lit(float("-inf"))))
        # Blocks come by falling length: those that can reach a query's bound are a head of the list. A margin covers rounding.
        table = F.split(F.lit(",".join(f"{b}:{top!r}" for b, top in tail)), ",")
        tops = F.transform(table, lambda x: F.struct(F.split(x, ":")[0].cast("int").alias("cb"), F.split(x, ":")[1].cast("double").alias("top")))
        reach = F.filter(tops, lambda t: t["top"] * F.col("norm") * (1 + 1e-9) >= F.col("bound"))
        queries = scratch.cut(queries.withColumn("cb", F.explode(F.transform(reach, lambda t: t["cb"]))), "visits")
        needed = scratch.cut(queries.select("qb", "cb").distinct(), "pairs")
        rest = met(queries, dealt.join(small_or_shuffled(needed), "cb"), how)
        first = first.unionByName(rest)
    return first.withColumn("rank", rank).where(F.col("rank") <= how.k).select("query_id", "rank", "vec_id", "score")
