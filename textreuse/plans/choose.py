"""Which order of joins finds the seeds, and what a physical plan consists of."""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.alignment import PAIR, runs, runs_of_grams, seeds_by_candidates
from ..operators.retrieval import candidates
from ..sources.io import stored


@dataclass(frozen=True)
class Volumes:
    """Rows that each order of joins would make."""

    grams: int
    seed_rows: int
    bucket_pairs: int


def volumes(grams: DataFrame, posts: DataFrame) -> Volumes:
    """Counts from one aggregate each: pairs of equal grams in different documents, and pairs in fingerprint buckets."""
    g = grams.groupBy("g").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n").alias("all"), F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("pairs")).first()
    b = posts.groupBy("slot", "hash").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("pairs")).first()
    return Volumes(int(g["all"] or 0), int(g["pairs"] or 0), int(b["pairs"] or 0))


def choose_seed_plan(v: Volumes) -> str:
    """``index`` (seed-first) is bound by its output; ``candidates`` must list its pairs and then join grams to each.

    Candidates win only where buckets make fewer pairs than equal grams do.
    """
    return "candidates" if v.bucket_pairs < v.seed_rows else "index"


def planned_seeds(posts: DataFrame, grams: DataFrame) -> DataFrame:
    """Seeds of the candidate pairs of ``posts``, by the order of joins that makes fewer rows."""
    return seeds_by_candidates(candidates(posts), grams, choose_seed_plan(volumes(grams, posts)))


def planned_runs(posts: DataFrame, grams: DataFrame) -> DataFrame:
    """Runs of the seeds of the candidate pairs, from grams with context, by the cheaper order of joins.

    A run is of one pair, so runs can be made of all seeds and then kept by pair.
    """
    posts = stored(posts, "postings")
    if choose_seed_plan(volumes(grams, posts)) == "candidates":
        return runs(seeds_by_candidates(candidates(posts), grams))
    return runs_of_grams(grams, store=True).join(candidates(posts), PAIR, "left_semi")


def describe(df: DataFrame) -> dict[str, int]:
    """How many of each costly operator the physical plan has."""
    text = df._jdf.queryExecution().executedPlan().toString()
    names = re.findall(r"\b(Exchange|BroadcastExchange|ReusedExchange|SortMergeJoin|ShuffledHashJoin|BroadcastHashJoin|BroadcastNestedLoopJoin|CartesianProduct|Window|Generate|BatchEvalPython|ArrowEvalPython|FlatMapGroupsInPandas|MapInPandas)\b", text)
    return dict(Counter(names))
