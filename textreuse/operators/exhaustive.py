"""Exhaustive and second-opinion baselines. They are quadratic or approximate on purpose; use them on small collections."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import prefix
from .alignment import SEED


def seeds_nested_loop(grams: DataFrame) -> DataFrame:
    """Reference meaning of seeding: every gram of one document is compared with every gram of another."""
    side = lambda s: grams.select(F.col("g").alias(f"{s}_g"), F.col("doc_id").alias(f"{s}_doc"), *(F.col(c).alias(f"{s}_{c}") for c in ("pos", "begin", "end")))
    return side("a").crossJoin(side("b")).where("a_doc < b_doc and a_g <=> b_g").select(*SEED)


def compared(grams: DataFrame, other: DataFrame) -> DataFrame:
    """Every gram of one collection against every gram of another: the product of both, for a small first one."""
    side = lambda df, s: df.select(F.col("g").alias(f"{s}_g"), F.col("doc_id").alias(f"{s}_doc"), *(F.col(c).alias(f"{s}_{c}") for c in ("pos", "begin", "end")))
    return side(grams, "a").crossJoin(side(other, "b")).where("a_g <=> b_g").select(*SEED)


def passage_pairs_by_prefix(passages: DataFrame, min_jaccard: float) -> DataFrame:
    """The pairs of :func:`passage_pairs_exact` over a whole collection, without a shuffled row for a pair; see :mod:`prefix`."""
    return prefix.passage_pairs(passages, min_jaccard)


def passage_pairs_exact(passages: DataFrame, min_jaccard: float) -> DataFrame:
    """Pairs of passages of different documents whose sets of words reach a Jaccard similarity: exact, by a join on words."""
    words = passages.select("doc_id", "passage_no", F.explode(F.array_distinct("words")).alias("word"))
    size = words.groupBy("doc_id", "passage_no").agg(F.count(F.lit(1)).alias("n"))
    side = lambda df, s, extra: df.select(F.col("doc_id").alias(f"{s}_doc"), F.col("passage_no").alias(f"{s}_passage"), F.col(extra).alias(extra if extra == "word" else f"{s}_n"))
    keys = ["a_doc", "a_passage", "b_doc", "b_passage"]
    shared = side(words, "a", "word").join(side(words, "b", "word"), "word").where("a_doc < b_doc").groupBy(*keys).agg(F.count(F.lit(1)).alias("shared"))
    rows = shared.join(side(size, "a", "n"), keys[:2]).join(side(size, "b", "n"), keys[2:])
    return rows.withColumn("jaccard", F.col("shared") / (F.col("a_n") + F.col("b_n") - F.col("shared"))).where(F.col("jaccard") >= min_jaccard).select(*keys, "jaccard")


def ml_minhash(passages: DataFrame, min_jaccard: float, tables: int = 10, features: int = 1 << 18) -> DataFrame:
    """Spark ML's MinHash join as a second opinion; it verifies what collides, so it returns no false pairs but may miss some."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    bags = HashingTF(inputCol="words", outputCol="features", numFeatures=features, binary=True).transform(passages.where(F.size("words") > 0))
    model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=7).fit(bags)
    pairs = model.approxSimilarityJoin(bags, bags, 1 - min_jaccard, distCol="distance").where("datasetA.doc_id < datasetB.doc_id")
    return pairs.select(F.col("datasetA.doc_id").alias("a_doc"), F.col("datasetA.passage_no").alias("a_passage"), F.col("datasetB.doc_id").alias("b_doc"), F.col("datasetB.passage_no").alias("b_passage"), (1 - F.col("distance")).alias("jaccard"))
