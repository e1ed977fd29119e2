"""Training corpus from ``documents``: quality rules, near-dedup, secrets, mix, packing.

Each stage is a function of (spark, docs, sf_dir). All but the last return the columns
of ``documents``; what they return is written as Parquet and read again as the next
stage's ``docs``.

Cases, beside those of the operators that the stages call: a verdict belongs to a row,
so rows of one id and different texts stay or go each by its own text, and null ids are
ids like others. Rows of one id and one text get one verdict; of them near-dedup keeps
one. Null and empty texts fail the quality rules; the later stages pass them on, but
the mix, which has no words to take from them. Extra columns are carried through. An
empty table gives empty results.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from textreuse.llm import mixing, neardup, packing, quality_rules, secrets
from textreuse.llm.common import Scratch, ship_by_value, spread, table
from textreuse.llm.queries import quality_weights, trusted_ids

ship_by_value()


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep, row by row: a row goes by its own text, whatever its id."""
    return quality_rules.accepted(spread(docs), trusted_ids(spark, sf_dir))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies, and all rows without words."""
    return neardup.deduplicated(spread(docs), neardup.AT_80)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, with the values of found secrets replaced in their texts."""
    return secrets.redact_secrets(spread(docs))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it; one that it does not take goes."""
    weights, docs = quality_weights(spark, sf_dir), spread(docs)
    taken = Scratch(spark, "stage-mix").cut(mixing.sample(docs, weights), "taken")
    return mixing.apply(docs, taken, weights)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each piece of a document, with its bin."""
    return packing.pack(spread(docs))


STAGES = [("quality rules", quality), ("near-dedup", near_dedup), ("secret scan", secret_scan), ("mixing", mix), ("packing", pack)]

#: No stage before the last can be written in DuckDB's SQL (64-bit hashes of n-grams, signatures, a lexer); tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over ``documents``, one after the other."""
    scratch, docs = Scratch(spark, "pipeline"), table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = scratch.cut(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
