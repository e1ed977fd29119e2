"""Mixing sources to target weights by weighted sampling without replacement.

Each document draws an exponential key scaled by its quality weight (Efraimidis
and Spirakis, 2006): ``-ln(u) / weight`` with ``u`` from a hash of its id, so that
reruns agree. A source's target is met by complete epochs first; what is left of
it is a word budget, spent on the source's documents in the order of their keys.
A prefix sum over that order finds the last document, of which only the words
that the budget still has are taken. Only DataFrame functions are used.

Targets: a source's share of all words by weight, at most ``most_epochs`` times
its own words; the excess goes to the others by weight until none is above. This
is water-filling: with sources ordered by cap over weight, those that fill up come
first, and one level holds for the rest.

Skew: a source may hold most rows. Its order is dealt by range over (source, key,
id), so no task holds a source. Sources may be many, as hosts are: their order by name
and their order by cap over weight are running totals dealt by range too, unless they
are few enough (``few_sources``) for one task; both ways give the same plan.

Cases: a null text has size 0; a null source is a source of its own, placed last;
null ids hash as one value; weights that are null, not finite or not positive
count as 1. Rows that repeat are separate documents with equal keys. Rows of one key tie
by id, then size. Very long texts count whole. A source without words has target 0. An
empty table gives an empty result. Other columns do not matter, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, Scratch, n_words, running_totals, small_or_shuffled

#: Number of values of the hash behind ``u``: 13 hexadecimal digits.
STEPS = 1 << 52


@dataclass(frozen=True)
class Mix:
    most_epochs: int = 3
    #: Weights of the sources in order, repeated as long as there are sources.
    cycle: tuple[int, ...] = (1, 2, 3)
    seed: str = "mix"
    #: Sources, one row each, up to which their running totals are taken in one task.
    few_sources: int = 100_000


def sampling_key(key: Column, weight: Column, seed: str) -> Column:
    """Exponential key of a document; the smallest are taken first."""
    digits = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("null")))), 1, 13)
    u = (F.conv(digits, 16, 10).cast("bigint") + F.lit(0.5)) / F.lit(float(STEPS))
    safe = F.when((weight > 0) & (weight < F.lit(float("inf"))), weight.cast("double")).otherwise(F.lit(1.0))
    return -F.log(u) / safe


def source_totals(rows: DataFrame, order: list[Column], values: dict[str, Column], few: bool, scratch: Scratch) -> DataFrame:
    """``rows`` with inclusive running sums of ``values``."""
    if not few:
        return running_totals(rows, order, values, scratch)
    by = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumns({name: F.sum(c).over(by) for name, c in values.items()})


def targets(sizes: DataFrame, mix: Mix, scratch: Scratch) -> DataFrame:
    """``source, source_size`` with ``target``, whole ``epochs``, the ``budget`` of words beyond them and the words of the sources ``before``."""
    sizes = scratch.cut(sizes, "source-sizes")
    few = sizes.count() <= mix.few_sources
    by_name = [F.col("source").isNull(), F.col("source")]
    ranked = source_totals(sizes, by_name, {"_i": F.lit(1).cast("long"), "_upto": F.col("source_size")}, few, scratch)
    cycle = F.array(*(F.lit(w) for w in mix.cycle))
    ranked = ranked.withColumn("before", F.col("_upto") - F.col("source_size")).withColumn("_w", F.get(cycle, (F.col("_i") - 1) % len(mix.cycle)).cast("long"))
    ranked = scratch.cut(ranked.withColumn("_cap", mix.most_epochs * F.col("source_size")), "ranked")
    whole = ranked.agg(F.sum("source_size").alias("all"), F.sum("_w").alias("weights")).first()
    every, weights = F.lit(whole["all"] or 0), F.lit(whole["weights"] or 0)
    filled = source_totals(ranked, [F.col("_cap") / F.col("_w"), F.col("_i")], {"_caps": F.col("_cap"), "_ws": F.col("_w")}, few, scratch)
    full = (every - (F.col("_caps") - F.col("_cap"))) * F.col("_w") > F.col("_cap") * (weights - (F.col("_ws") - F.col("_w")))
    filled = scratch.cut(filled.withColumn("_full", full), "filled")
    spent = filled.where("_full").agg(F.sum("_cap").alias("cap"), F.sum("_w").alias("w")).first()
    level = F.try_divide((every - F.lit(spent["cap"] or 0)).cast("double"), (weights - F.lit(spent["w"] or 0)).cast("double"))
    out = filled.withColumn("target", F.when(F.col("_full"), F.col("_cap").cast("double")).otherwise(F.coalesce(level, F.lit(0.0)) * F.col("_w")))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    out = out.withColumn("epochs", epochs).withColumn("budget", F.greatest(F.lit(0), F.floor(F.col("target") - F.col("epochs") * F.col("source_size"))).cast("long"))
    return out.select("source", "source_size", "target", "epochs", "budget", "before")


def sample(docs: DataFrame, weights: DataFrame | None = None, mix: Mix = Mix(), text: str = "text", key: str = "doc_id", source: str = "source") -> DataFrame:
    """A row for each row of ``docs``: how many of its words the mix takes.

    ``weights`` has ``key`` and ``weight``; of several rows of a key the largest weight holds.
    """
    scratch = Scratch(docs.sparkSession, "mix")
    rows = docs.select(F.col(key).alias("doc_id"), F.col(source).alias("source"), n_words(F.col(text)).alias("size"))
    if weights is None:
        rows = rows.withColumn("weight", F.lit(1.0))
    else:
        one = weights.where(F.col(key).isNotNull()).groupBy(F.col(key).alias("doc_id")).agg(F.max("weight").cast("double").alias("weight"))
        rows = rows.join(one, "doc_id", "left").withColumn("weight", F.coalesce("weight", F.lit(1.0)))
    rows = scratch.cut(rows.withColumn("sample_key", sampling_key(F.col("doc_id"), F.col("weight"), mix.seed)), "sizes")
    plan = scratch.cut(targets(rows.groupBy("source").agg(F.sum("size").alias("source_size")), mix, scratch), "targets")
    order = [F.col("source").isNull(), F.col("source"), F.col("sample_key"), F.col("doc_id"), F.col("size")]
    summed = running_totals(rows, order, {"_to": F.col("size")}, scratch)
    plan = plan.withColumnRenamed("before", "_from")
    # NULL sources join too: eqNullSafe stays an equi-join. One row a source; Spark broadcasts it if its size allows.
    joined = summed.alias("r").join(plan.withColumnRenamed("source", "_name"), F.col("r.source").eqNullSafe(F.col("_name")))
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("budget") - (F.col("_to") - F.col("_from") - F.col("size"))))
    return joined.select("doc_id", "size", "source_size", "target", (F.col("epochs") * F.col("size") + part).cast("long").alias("taken"), "source", "epochs", part.cast("long").alias("part"), "weight", "sample_key")


def apply(docs: DataFrame, taken: DataFrame, weights: DataFrame | None = None, mix: Mix = Mix(), text: str = "text", key: str = "doc_id", source: str = "source") -> DataFrame:
    """The mix itself: each document as often as the mix takes it, the last time only its first ``part`` words.

    ``taken`` is what :func:`sample` gave for the same arguments. It yields one row a source: the epochs, and the last
    document in the order of the keys of which words are taken. Each row of ``docs`` compares itself with that
    document, so texts stay where they are. Rows keep the columns of ``docs``; a document taken k times stands k
    times, one without words never. A partial copy has its words joined by single spaces.
    """
    last = F.max(F.when(F.col("part") > 0, F.struct("sample_key", F.struct("doc_id").alias("id"), "size", "part")))
    cuts = taken.groupBy(F.col("source").alias("_source")).agg(F.max("epochs").alias("_epochs"), last.alias("_last"))
    scratch = Scratch(docs.sparkSession, "mix")
    cuts = scratch.cut(cuts, "cuts")
    # The row travels as a struct, so that no column of the input can clash with those made here.
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col(key).alias("id"), F.col(source).alias("source"), n_words(F.col(text)).alias("size"))
    if weights is None:
        rows = rows.withColumn("weight", F.lit(1.0))
    else:
        one = weights.where(F.col(key).isNotNull()).groupBy(F.col(key).alias("id")).agg(F.max("weight").cast("double").alias("weight"))
        rows = rows.join(small_or_shuffled(scratch.cut(one, "weights")), "id", "left").withColumn("weight", F.coalesce("weight", F.lit(1.0)))
    rows = rows.withColumn("sample_key", sampling_key(F.col("id"), F.col("weight"), mix.seed))
    rows = rows.join(small_or_shuffled(cuts), F.col("source").eqNullSafe(F.col("_source")))
    mine = F.struct(F.col("sample_key"), F.struct(F.col("id").alias("doc_id")).alias("id"), F.col("size"))
    limit = F.struct(F.col("_last.sample_key").alias("sample_key"), F.col("_last.id").alias("id"), F.col("_last.size").alias("size"))
    part = F.when(F.col("_last").isNull() | (mine > limit), F.lit(0)).when(mine < limit, F.col("size")).otherwise(F.col("_last.part"))
    copies = F.when(F.col("size") > 0, F.col("_epochs") + F.when(F.col("part") > 0, 1).otherwise(0)).otherwise(0)
    rows = rows.withColumn("part", part).withColumn("copies", copies).where("copies > 0")
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies").cast("long"))))
    cut = (F.col("copy") > F.col("_epochs")) & (F.col("part") < F.col("size"))
    whole = F.col(f"row.`{text}`")
    short = F.array_join(F.slice(F.regexp_extract_all(whole, F.lit(WORD), F.lit(0)), F.lit(1), F.col("part").cast("int")), " ")
    rows = rows.withColumn("mixed", F.when(cut, short).otherwise(whole))
    changed = {text: F.col("mixed"), "n_chars": F.when(cut, F.length("mixed").cast("long")).otherwise(F.col("row.n_chars")) if "n_chars" in docs.columns else None}
    return rows.select(*(changed.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns))
