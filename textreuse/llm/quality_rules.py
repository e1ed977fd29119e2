"""Quality rules: base counts of a text and a hashed n-gram log-likelihood ratio.

Importance weights follow "Data Selection for Language Models via Importance
Resampling" (Xie et al., 2023): word 1-grams and 2-grams are hashed to a fixed
number of buckets, one multinomial is fitted to the trusted documents and one to
the whole corpus, and a document's score is the mean over its n-grams of the log
ratio of the two. Instead of resampling, every document meets one threshold.

Only DataFrame functions are used. Texts are never shuffled to be judged: fitting
explodes bucket numbers into a partial aggregate (if the trusted keys are too many to
broadcast, a document's bucket numbers move, two bytes each), scoring is local to a
row. What the driver holds is one number a bucket and one a bin of scores, whatever
the input.

Cases: a null or empty text has no words, all counts 0, score null, and fails the
base rule. Repeated rows are judged alike. Without trusted documents, or for an
empty table, all ratios are 0 and only the base rule rejects. Very long texts are
counted whole, in one row. A score that ties with the threshold is kept. Columns of the
input other than the id and the text do not matter, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, Scratch, let, small_or_shuffled, words

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"


@dataclass(frozen=True)
class Rules:
    """Parameters of the verdict; defaults are those of production."""

    buckets: int = 10_000
    smoothing: float = 1.0
    least_words: int = 10
    repeat_percent: int = 20
    #: The threshold is the lower end of the bin with this quantile of the trusted documents' scores.
    trusted_quantile: float = 0.01
    #: Width of the bins from which the quantile is read.
    bin_width: float = 0.01


def repeat_words(ws: Column, window: int = 5) -> Column:
    """Words that stand in a window of ``window`` words found at least twice in the array ``ws``."""

    def covered(places: Column) -> Column:
        after = F.slice(places, 2, F.size(places))
        steps = F.zip_with(places, after, lambda p, q: F.least(F.lit(window), F.coalesce(q - p, F.lit(window))))
        return F.aggregate(steps, F.lit(0), lambda a, s: a + s)

    def repeated(sorted_grams: Column) -> Column:
        same = lambda x, other: F.coalesce(other["h"] == x["h"], F.lit(False))
        found = F.filter(sorted_grams, lambda x, j: same(x, F.get(sorted_grams, j - 1)) | same(x, F.get(sorted_grams, j + 1)))
        return F.when(F.size(found) > 0, let(F.sort_array(F.transform(found, lambda x: x["i"])), covered)).otherwise(F.lit(0))

    def grams(hashes: Column) -> Column:
        placed = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) < F.size(hashes), let(placed, repeated)).otherwise(F.lit(0))

    hashed = F.transform(F.slice(ws, 1, F.size(ws) - (window - 1)), lambda w, i: F.xxhash64(w, *(F.get(ws, i + k) for k in range(1, window))))
    return F.when(F.size(ws) > window, let(hashed, grams)).otherwise(F.lit(0))


def base_counts(text: Column, ws: Column) -> dict[str, Column]:
    """The counts of the base rule, each a long."""
    whole = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(whole, "\n"), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))
    counts = {
        "n_words": F.size(ws),
        "word_chars": F.length(F.translate(whole, BLANKS, "")),
        "n_symbols": F.length(whole) - F.length(F.translate(whole, SYMBOLS, "")),
        "n_dup_lines": let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))),
        "n_repeat_words": repeat_words(ws),
    }
    return {name: c.cast("long") for name, c in counts.items()}


def gram_buckets(ws: Column, buckets: int) -> Column:
    """Bucket numbers of all 1-grams and 2-grams of the array ``ws``."""
    ones = F.transform(ws, lambda w: F.pmod(F.xxhash64(w), F.lit(buckets)).cast("int"))
    heads = F.slice(ws, 1, F.greatest(F.size(ws) - 1, F.lit(0)))
    twos = F.transform(heads, lambda w, i: F.pmod(F.xxhash64(w, F.get(ws, i + 1)), F.lit(buckets)).cast("int"))
    return F.concat(ones, twos)


def fit(docs: DataFrame, trusted: DataFrame, rules: Rules, text: str = "text", key: str = "doc_id") -> list[float]:
    """Log ratio of trusted to raw probability, by bucket. ``trusted`` has the keys of the trusted documents."""
    from math import log

    scratch = Scratch(docs.sparkSession, "quality-fit")
    ids = scratch.cut(trusted.where(F.col(key).isNotNull()).select(F.col(key).alias("_id")).distinct().withColumn("_good", F.lit(1)), "trusted")
    # Beyond the bound of a broadcast the rows of the join hold two small numbers a word, not the texts.
    number = "smallint" if rules.buckets <= 1 << 15 else "int"
    found = docs.select(F.col(key).alias("_id"), let(words(F.col(text)), lambda ws: gram_buckets(ws, rules.buckets)).cast(f"array<{number}>").alias("_bs"))
    marked = found.join(small_or_shuffled(ids), "_id", "left")
    grams = marked.select(F.coalesce("_good", F.lit(0)).alias("_good"), F.explode("_bs").alias("_b"))
    counts = {r["_b"]: (r["raw"], r["good"]) for r in grams.groupBy("_b").agg(F.count(F.lit(1)).alias("raw"), F.sum("_good").alias("good")).collect()}
    scratch.drop(ids)
    raw, good = (sum(c[i] for c in counts.values()) for i in (0, 1))
    if not good:
        return [0.0] * rules.buckets
    share = lambda n, total: log((n + rules.smoothing) / (total + rules.smoothing * rules.buckets))
    return [round(share(counts.get(b, (0, 0))[1], good) - share(counts.get(b, (0, 0))[0], raw), 6) for b in range(rules.buckets)]


def score(docs: DataFrame, ratios: list[float], rules: Rules, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Base counts and mean log ratio of every row; one row for one row."""
    table = F.split(F.lit(",".join(map(str, ratios))), ",").cast("array<double>")

    def judged(ws: Column) -> Column:
        total = lambda buckets: F.aggregate(buckets, F.lit(0.0), lambda a, b: a + F.get(table, b))
        mean = F.when(F.size(ws) > 0, F.round(let(gram_buckets(ws, rules.buckets), total) / (2 * F.size(ws) - 1), 9))
        return F.struct(*(c.alias(n) for n, c in base_counts(F.col("_text"), ws).items()), mean.alias("llr"))

    rows = docs.select(F.col(key).alias(key), F.col(text).alias("_text"))
    return rows.select(key, F.xxhash64("_text").alias("text_hash"), let(words(F.col("_text")), judged).alias("_j")).select(key, "_j.*", "text_hash")


def threshold(scored: DataFrame, trusted: DataFrame, rules: Rules, key: str = "doc_id") -> float:
    """Quantile of the trusted scores from a histogram, rounded down to a bin; the same on every run."""
    ids = trusted.where(F.col(key).isNotNull()).select(key).distinct()
    bins = scored.join(ids, key, "left_semi").where("llr is not null").groupBy(F.floor(F.col("llr") / rules.bin_width).alias("bin")).count().collect()
    wanted, seen = rules.trusted_quantile * sum(r["count"] for r in bins), 0
    for r in sorted(bins, key=lambda r: r["bin"]):
        seen += r["count"]
        if seen > wanted:
            return r["bin"] * rules.bin_width
    return float("-inf")


def judge(docs: DataFrame, trusted: DataFrame, rules: Rules = Rules(), text: str = "text", key: str = "doc_id") -> DataFrame:
    """Counts, score and verdict of every row of ``docs``: ``kept`` is false if the base rule fails or the score is under the threshold.

    ``text_hash`` is ``xxhash64`` of the text, of which alone the verdict is a function.
    """
    scratch = Scratch(docs.sparkSession, "quality")
    scored = scratch.cut(score(docs, fit(docs, trusted, rules, text, key), rules, text, key), "scored")
    least = threshold(scored, trusted, rules, key)
    failed = (F.col("n_words") < rules.least_words) | (100 * F.col("n_repeat_words") > rules.repeat_percent * F.col("n_words"))
    out = scored.withColumn("base_failed", failed)
    return out.withColumn("kept", ~F.col("base_failed") & (F.coalesce("llr", F.lit(0.0)) >= F.lit(least)))


def accepted(docs: DataFrame, trusted: DataFrame, rules: Rules = Rules(), text: str = "text", key: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` that are kept, with their columns. A row is told by its key and text hash, null keys too."""
    judged = judge(docs, trusted, rules, text, key)
    scratch = Scratch(docs.sparkSession, "accepted")
    rejected = scratch.cut(judged.where(~F.col("kept")).select(F.col(key).alias("_key"), F.col("text_hash").alias("_hash")).distinct(), "rejected")
    whole = F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row")
    rows = docs.select(whole, F.col(f"`{key}`").alias("_id"), F.xxhash64(F.col(f"`{text}`")).alias("_text"))
    rows = rows.join(small_or_shuffled(rejected), F.col("_id").eqNullSafe(F.col("_key")) & (F.col("_text") == F.col("_hash")), "left_anti")
    return rows.select(*(F.col(f"row.`{c}`").alias(c) for c in docs.columns))


__all__ = ["SPACE", "Rules", "accepted", "base_counts", "fit", "gram_buckets", "judge", "repeat_words", "score", "threshold"]
