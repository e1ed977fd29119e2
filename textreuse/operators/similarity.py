"""Similarity notions between passages and documents, as equi-joins on words."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .normalize import clean, words


def above(pairs: DataFrame, measure: str, tau: float) -> DataFrame:
    """Potential reuse: pairs whose similarity reaches the threshold."""
    return pairs.where(F.col(measure) >= tau)


def _bags(items: DataFrame, docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    count = lambda df, key: df.select(F.col(key), F.explode(words(clean(F.col("text")))).alias("word")).groupBy(key, "word").agg(F.count(F.lit(1)).alias("n"))
    return count(items, "item_id"), count(docs, "doc_id")


def set_overlap(items: DataFrame, docs: DataFrame) -> DataFrame:
    """Shared words, Jaccard and containment of every item and document that share a word."""
    a, b = (df.drop("n") for df in _bags(items, docs))
    size = lambda df, key: df.groupBy(key).agg(F.count(F.lit(1)).alias(f"_{key}"))
    shared = a.join(b, "word").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("shared"))
    rows = shared.join(size(a, "item_id"), "item_id").join(size(b, "doc_id"), "doc_id")
    return rows.withColumns({"jaccard": F.col("shared") / (F.col("_item_id") + F.col("_doc_id") - F.col("shared")), "containment": F.col("shared") / F.col("_item_id")})


def bow_cosine(items: DataFrame, docs: DataFrame) -> DataFrame:
    """Cosine of the term-occurrence vectors."""
    a, b = _bags(items, docs)
    norm = lambda df, key: df.groupBy(key).agg(F.sqrt(F.sum(F.col("n") * F.col("n"))).alias(f"_{key}"))
    dot = a.join(b.withColumnRenamed("n", "m"), "word").groupBy("item_id", "doc_id").agg(F.sum(F.col("n") * F.col("m")).alias("dot"))
    rows = dot.join(norm(a, "item_id"), "item_id").join(norm(b, "doc_id"), "doc_id")
    return rows.withColumn("cosine", F.col("dot") / (F.col("_item_id") * F.col("_doc_id")))


def dense_top_k(vectors: DataFrame, k: int = 3, block: int = 2048) -> DataFrame:
    """The k nearest vectors of each by cosine: the semantic contrast. Blocks of rows meet as matrix products."""
    n = max(1, -(-vectors.count() // block))
    rows = vectors.where("embedding is not null").select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(n)).alias("_b"))
    left = rows.withColumn("_o", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).withColumnsRenamed({"_b": "_i", "_o": "_j"})
    right = rows.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).withColumnRenamed("_b", "_j").withColumn("_j", F.col("_j").cast("int"))
    left = left.withColumn("_i", F.col("_i").cast("int"))

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"a_id": [], "b_id": [], "cosine": []}).astype({"a_id": "int64", "b_id": "int64"})
        x, y = (np.stack(df["embedding"].to_list()).astype(float) for df in (a, b))
        c = np.round((x / np.linalg.norm(x, axis=1)[:, None]) @ (y / np.linalg.norm(y, axis=1)[:, None]).T, 4)
        ids, other = a["vec_id"].to_numpy(), b["vec_id"].to_numpy()
        out = []
        for i in range(len(ids)):
            order = np.lexsort((other, -c[i]))
            order = order[other[order] != ids[i]][:k]
            out += [(ids[i], other[j], c[i, j]) for j in order]
        return pd.DataFrame(out, columns=["a_id", "b_id", "cosine"])

    best = left.groupBy("_i", "_j").cogroup(right.groupBy("_i", "_j")).applyInPandas(run, "a_id long, b_id long, cosine double")
    rank = F.row_number().over(Window.partitionBy("a_id").orderBy(F.col("cosine").desc(), "b_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k)


def contained(items: DataFrame, docs: DataFrame, least_words: int = 1) -> DataFrame:
    """Items that a document contains whole, after cleaning.

    An inner word of an item stands whole in every document that contains it, as words are joined by single spaces. The
    rarest such word is the key of an equi-join, so no product of the tables is formed; containment is tested on what joins.
    Items of one or two words have no inner word and meet all documents.
    """
    a = items.select("item_id", clean(F.col("text")).alias("_t")).where("_t <> ''")
    a = a.withColumn("_w", words(F.col("_t"))).where(F.size("_w") >= least_words)
    d = docs.select("doc_id", clean(F.col("text")).alias("_c")).withColumn("_w", words(F.col("_c")))
    keys = d.select("doc_id", F.explode(F.array_distinct(F.transform("_w", lambda w: F.xxhash64(w)))).alias("_h"))
    rare = keys.groupBy("_h").agg(F.count(F.lit(1)).alias("_n"))
    best = a.where(F.size("_w") >= 3).select("item_id", "_t", F.explode(F.slice("_w", 2, F.size("_w") - 2)).alias("_x")).withColumn("_h", F.xxhash64("_x")).join(rare, "_h")
    best = best.groupBy("item_id", "_t").agg(F.min(F.struct("_n", "_h")).alias("_m")).select("item_id", "_t", F.col("_m._h").alias("_h"))
    pairs = best.join(keys, "_h").select("item_id", "_t", "doc_id").distinct()
    found = pairs.join(d.select("doc_id", "_c"), "doc_id").where(F.contains("_c", "_t")).select("item_id", "doc_id")
    short = a.where(F.size("_w") < 3)
    return found.unionAll(short.join(d, F.contains("_c", "_t")).select("item_id", "doc_id"))
