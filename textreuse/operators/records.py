"""Case and publication records, metadata, hydration, filters, and what the dataset tells."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.io import stored
from .normalize import begins, clean, let, two_versions, words

LANGUAGE_AREAS = {"en": 0, "de": 1, "fr": 2, "es": 3}


def unique_by_key(df: DataFrame, key: str, order: list[str]) -> DataFrame:
    """The first row of each key in a stated order; the group limit runs before the shuffle."""
    first = Window.partitionBy(key).orderBy(*order)
    return df.withColumn("_n", F.row_number().over(first)).where("_n = 1").drop("_n")


def taxonomy(spark: SparkSession) -> DataFrame:
    """Field, area, discipline: a fixed tree of 24 fields, 7 areas and 4 disciplines (a stand-in)."""
    areas = {f"src{i}": i % 7 for i in range(20)} | LANGUAGE_AREAS
    return spark.createDataFrame([(f, f"area{a}", f"disc{a % 4}") for f, a in areas.items()], "field string, area string, discipline string")


def publications(docs: DataFrame, dim: DataFrame) -> DataFrame:
    """Publication records with several granularities; arrays are sorted and distinct, an unmapped field has no area."""
    year = F.when(F.col("doc_id") % 11 == 0, F.lit(None)).otherwise(1860 + F.pmod(F.col("doc_id") * 37, F.lit(159))).cast("int")
    rows = docs.select("doc_id", F.length("text").alias("doc_chars"), year.alias("pub_year"), F.explode(F.array("source", "lang")).alias("field"))
    rows = rows.join(F.broadcast(dim), "field", "left")
    lists = (F.array_sort(F.collect_set(c)).alias(n) for c, n in (("field", "fields"), ("area", "areas"), ("discipline", "disciplines")))
    return rows.groupBy("doc_id").agg(F.first("doc_chars").alias("doc_chars"), F.first("pub_year").alias("pub_year"), *lists)


def case_id() -> Column:
    """Identifier in UUID form from the pair and its spans, the same on every run."""
    h = F.md5(F.concat_ws("|", "a_doc", "b_doc", "a_begin", "a_end", "b_begin", "b_end"))
    return F.concat_ws("-", *(F.substring(h, at, n) for at, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))))


def with_context(cases: DataFrame, pubs: DataFrame) -> DataFrame:
    """Case records: both publications' context beside the locators, without any direction."""
    side = lambda s: pubs.select(F.col("doc_id").alias(f"{s}_doc"), F.col("doc_chars").alias(f"{s}_doc_chars"), F.col("pub_year").alias(f"{s}_year"), *(F.col(c).alias(f"{s}_{c}") for c in ("fields", "areas", "disciplines")))
    return cases.withColumn("case_id", case_id()).join(side("a"), "a_doc", "left").join(side("b"), "b_doc", "left")


#: Up to so many estimated bytes a table of documents is broadcast to the cases, so that these are not shuffled for it.
BROADCAST_BYTES = 64_000_000


def _beside(rows: DataFrame, row_bytes: int) -> DataFrame:
    """``rows``, one a document, to be joined to cases. They are counted, as the size of a plan's result is not known."""
    return F.broadcast(rows) if rows.count() * row_bytes <= BROADCAST_BYTES else rows


def both_sides(cases: DataFrame, of_docs: DataFrame, row_bytes: int = 100) -> DataFrame:
    """The pairs of cases with what both documents have in ``of_docs``, one row a document; cases that it lacks a document of are left out."""
    of_docs = _beside(stored(of_docs, "of-documents"), row_bytes)
    side = lambda s: of_docs.select(*(F.col(c).alias(f"{s}_doc" if c == "doc_id" else f"{s}_{c}") for c in of_docs.columns))
    return cases.select("a_doc", "b_doc").join(side("a"), "a_doc").join(side("b"), "b_doc")


def by_both(cases: DataFrame, pubs: DataFrame) -> DataFrame:
    """``cases``, their number, for each ``a_disciplines`` and ``b_disciplines``."""
    return both_sides(cases, pubs.select("doc_id", "disciplines")).groupBy("a_disciplines", "b_disciplines").agg(F.count(F.lit(1)).alias("cases"))


def hydrate(cases: DataFrame, docs: DataFrame) -> DataFrame:
    """The text of both sides, recovered from the locators in the clean version."""
    texts = docs.select("doc_id", clean(F.col("text")).alias("clean"))
    cut = lambda s: F.substring(F.col(f"_{s}"), F.col(f"{s}_begin") + 1, F.col(f"{s}_end") - F.col(f"{s}_begin"))
    out = cases
    for s in "ab":
        out = out.join(texts.select(F.col("doc_id").alias(f"{s}_doc"), F.col("clean").alias(f"_{s}")), f"{s}_doc")
    return out.withColumns({"a_text": cut("a"), "b_text": cut("b")}).drop("_a", "_b")


def full_places(docs: DataFrame) -> DataFrame:
    """``doc_id, full_text`` with ``begins`` and ``ends`` of the words in clean coordinates, and in the full text (``full_begins``, ``full_ends``)."""
    two = two_versions(docs)
    rows = two.select("doc_id", "full_text", F.col("clean_to_full").alias("full_begins"), words(F.col("clean_text")).alias("_w"))
    rows = rows.withColumn("begins", begins(F.col("_w")))
    ends = lambda at: F.zip_with(F.col(at), "_w", lambda b, w: b + F.length(w))
    return rows.select("doc_id", "full_text", "begins", ends("begins").alias("ends"), "full_begins", ends("full_begins").alias("full_ends"))


def hydrate_full(cases: DataFrame, docs: DataFrame, margin: int = 1) -> DataFrame:
    """Cases with the passages of the uncleaned texts: ``a_full``, ``b_full`` and their places there; ``a_around`` and
    ``b_around`` have ``margin`` characters more on both ends."""
    places, out = full_places(docs), cases
    for s in "ab":
        side = places.select(F.col("doc_id").alias(f"{s}_doc"), *(F.col(c).alias(f"_{c}") for c in places.columns if c != "doc_id"))
        out = out.join(side, f"{s}_doc")
        at = lambda edges, value, full: F.get(F.col(full), (F.array_position(F.col(edges), F.col(value)) - 1).cast("int"))
        out = out.withColumns({f"{s}_full_begin": at("_begins", f"{s}_begin", "_full_begins"), f"{s}_full_end": at("_ends", f"{s}_end", "_full_ends")})
        start = F.greatest(F.lit(0), F.col(f"{s}_full_begin") - margin)
        cut = lambda a, z: F.substring(F.col("_full_text"), a + 1, z - a)
        out = out.withColumns({f"{s}_full": cut(F.col(f"{s}_full_begin"), F.col(f"{s}_full_end")), f"{s}_around": cut(start, F.col(f"{s}_full_end") + margin)})
        out = out.drop(*(f"_{c}" for c in places.columns))
    return out


#: Marks that open or close a quotation.
QUOTES = "[\"\u201c\u201d\u201e\u00ab\u00bb]"


def quoted(full: DataFrame) -> Column:
    """Whether a mark of quotation stands in or at the a side of :func:`hydrate_full`."""
    return F.col("a_around").rlike(QUOTES)


def examples(kinds: DataFrame, docs: DataFrame, many: int = 3, width: int = 40, shown: int = 80) -> DataFrame:
    """The ``many`` longest cases of each kind, with the begin of the passage and what stands around it."""
    order = [(F.col("a_end") - F.col("a_begin")).desc(), "a_doc", "b_doc", "a_begin", "b_begin"]
    top = kinds.withColumn("rank", F.row_number().over(Window.partitionBy("kind").orderBy(*order))).where(F.col("rank") <= many)
    texts = docs.select(F.col("doc_id").alias("a_doc"), clean(F.col("text")).alias("_t"))
    start = F.greatest(F.lit(0), F.col("a_begin") - width)
    passage = F.substring("_t", F.col("a_begin") + 1, F.least(F.lit(shown), F.col("a_end") - F.col("a_begin")))
    return top.join(texts, "a_doc").select("kind", "rank", "a_doc", "b_doc", "a_begin", "b_begin", F.substring("_t", start + 1, F.col("a_begin") - start).alias("before"), passage.alias("passage"), F.substring("_t", F.col("a_end") + 1, F.lit(width)).alias("after"))


def without_common_gram(hydrated: DataFrame, n: int = 8) -> DataFrame:
    """Cases of :func:`hydrate` whose recovered texts share no n-gram, whatever their length: none, if locators are right.

    The grams of both texts meet in an equi-join by case and hash; a hash that only one side has is no match.
    """
    numbered = hydrated.withColumn("_case", case_id())
    grams = lambda c: F.when(F.size(c) >= n, F.transform(F.sequence(F.lit(0), F.size(c) - n), lambda p: F.xxhash64(F.array_join(F.slice(c, p + 1, n), " "))))
    side = lambda s: numbered.select("_case", F.explode(let(words(F.col(f"{s}_text")), grams)).alias("_h")).distinct()
    shared = side("a").join(side("b"), ["_case", "_h"]).select("_case").distinct()
    return numbered.join(shared, "_case", "left_anti").drop("_case")


def context_window(cases: DataFrame, docs: DataFrame, width: int = 40) -> DataFrame:
    """What stands before and after the a side, at most ``width`` characters each."""
    texts = docs.select(F.col("doc_id").alias("a_doc"), clean(F.col("text")).alias("_t"))
    start = F.greatest(F.lit(0), F.col("a_begin") - width)
    return cases.join(texts, "a_doc").select(
        "a_doc", "b_doc", "a_begin", "a_end",
        F.substring("_t", start + 1, F.col("a_begin") - start).alias("before"), F.substring("_t", F.col("a_begin") + 1, F.col("a_end") - F.col("a_begin")).alias("passage"), F.substring("_t", F.col("a_end") + 1, F.lit(width)).alias("after"),
    )


def subset(records: DataFrame, position: tuple[float, float] | None = None, length: tuple[int, int] | None = None, years: tuple[int, int] | None = None, disciplines: list[str] | None = None) -> DataFrame:
    """Cases by place and extent of their a side, years of both, and shared discipline; a missing year is outside every range."""
    if position:
        records = records.where((F.col("a_begin") / F.col("a_doc_chars")).between(*position))
    if length:
        records = records.where((F.col("a_end") - F.col("a_begin")).between(*length))
    if years:
        records = records.where(F.col("a_year").between(*years) & F.col("b_year").between(*years))
    if disciplines:
        wanted = F.array(*map(F.lit, disciplines))
        records = records.where(F.arrays_overlap("a_disciplines", wanted) & F.arrays_overlap("b_disciplines", wanted))
    return records


def consensus(votes: DataFrame) -> DataFrame:
    """Majority of the votes on an item (ties to the smallest value), full agreement, and conflict if all differ."""
    n = votes.groupBy("item", "vote").agg(F.count(F.lit(1)).alias("n"))
    g = n.groupBy("item").agg(F.count(F.lit(1)).alias("kinds"), F.sum("n").alias("votes"), F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("n"), F.col("vote")))).alias("_all"))
    return g.select("item", F.col("_all")[0]["vote"].alias("value"), (F.col("kinds") == 1).alias("agreed"), ((F.col("kinds") == F.col("votes")) & (F.col("kinds") > 1)).alias("conflict"))


def normal_spans(cases: DataFrame, docs: DataFrame) -> DataFrame:
    """A row a side: length and start as shares of the clean document."""
    size = docs.select("doc_id", F.length(clean(F.col("text"))).alias("chars"))
    ends = F.explode(F.array(*(F.struct(F.col(f"{s}_doc").alias("doc_id"), F.col(f"{s}_begin").alias("begin"), F.col(f"{s}_end").alias("end")) for s in "ab")))
    rows = cases.select(ends.alias("_s")).select("_s.*").join(_beside(stored(size, "sizes"), 32), "doc_id")
    return rows.select("doc_id", ((F.col("end") - F.col("begin")) / F.col("chars")).alias("length"), (F.col("begin") / F.col("chars")).alias("start"))


def duplicates(cases: DataFrame, docs: DataFrame, share: float = 0.99) -> DataFrame:
    """Pairs of which one case covers more than ``share`` of both documents."""
    size = docs.select("doc_id", F.length(clean(F.col("text"))).alias("chars"))
    rows = cases
    for s in "ab":
        rows = rows.join(size.select(F.col("doc_id").alias(f"{s}_doc"), F.col("chars").alias(f"_{s}")), f"{s}_doc")
    covers = lambda s: (F.col(f"{s}_end") - F.col(f"{s}_begin")) / F.col(f"_{s}") > share
    return rows.where(covers("a") & covers("b")).select("a_doc", "b_doc").distinct()


def groups(pairs: DataFrame) -> DataFrame:
    """``doc_id, label`` of the transitive groups of pairs; a group's label is its least document.

    Every round a document takes the least label among its neighbours, a label the least that its members took, and all
    jump to the label of their label, so that steps along a chain double. Rounds end when no label moves; each is written
    to the shared folder, which also cuts its lineage.
    """
    both = stored(pairs.where("a_doc <> b_doc").select("a_doc", "b_doc").union(pairs.where("a_doc <> b_doc").select("b_doc", "a_doc")).distinct(), "pairs")
    labels = stored(both.groupBy(F.col("a_doc").alias("doc_id")).agg(F.least(F.min("b_doc"), F.first("a_doc")).alias("label")), "labels")
    moved = not labels.isEmpty()
    while moved:
        near = both.join(labels.withColumnRenamed("doc_id", "b_doc"), "b_doc").groupBy(F.col("a_doc").alias("doc_id")).agg(F.min("label").alias("_l"))
        told = labels.join(near, "doc_id").select("doc_id", "label", F.least("label", "_l").alias("_new"))
        heard = told.groupBy(F.col("label").alias("doc_id")).agg(F.min("_new").alias("_found"))
        hooked = stored(told.join(heard, "doc_id", "left").select("doc_id", F.col("label").alias("_was"), F.least("_new", "_found").alias("_up")), "hooks")
        above = hooked.select(F.col("doc_id").alias("_up"), F.col("_up").alias("label"))
        jumped = stored(hooked.join(above, "_up").select("doc_id", "_was", "label"), "labels")
        moved = not jumped.where("label <> _was").isEmpty()
        labels = jumped.drop("_was")
    return labels


def by_discipline(cases: DataFrame, pubs: DataFrame) -> DataFrame:
    """Cases and publications of each discipline with their shares of all; memberships overlap, so shares sum to more than one."""
    pubs = stored(pubs.select("doc_id", "disciplines"), "publications")
    p = pubs.select("doc_id", F.explode("disciplines").alias("discipline")).groupBy("discipline").agg(F.count_distinct("doc_id").alias("publications"))
    # Cases are counted by what both sides have, so no case is taken apart. It has each discipline of either side once, and a null for the number of all.
    each = F.explode(F.concat(F.array_union("a_disciplines", "b_disciplines"), F.array(F.lit(None).cast("string"))))
    counts = by_both(cases, pubs).select("cases", each.alias("discipline")).groupBy("discipline").agg(F.sum("cases").alias("cases"))
    counts = stored(counts, "discipline-cases")
    c = counts.where("discipline is not null")
    totals = pubs.agg(F.count(F.lit(1)).alias("_p")).join(counts.where("discipline is null").agg(F.coalesce(F.sum("cases"), F.lit(0)).alias("_c")), F.lit(True))
    rows = p.join(c, "discipline", "left").join(F.broadcast(totals), F.lit(True))
    cases_n = F.coalesce("cases", F.lit(0))
    return rows.select("discipline", cases_n.alias("cases"), "publications", F.round(cases_n / F.nullif("_c", F.lit(0)), 6).alias("case_share"), F.round(F.col("publications") / F.nullif("_p", F.lit(0)), 6).alias("publication_share"))


def example_kind(cases: DataFrame, many: int = 5, dense: float = 0.15, quotation: Column | None = None) -> DataFrame:
    """An illustrative kind: boilerplate if the a passage recurs in many documents, quotation if ``quotation`` holds, verbatim if seeds are dense, else paraphrase."""
    spread = cases.groupBy("a_doc", "a_begin", "a_end").agg(F.count_distinct("b_doc").alias("_n"))
    rows = cases.join(spread, ["a_doc", "a_begin", "a_end"])
    density = F.col("n_seeds") / (F.col("a_end") - F.col("a_begin"))
    return rows.withColumn("kind", F.when(F.col("_n") >= many, "boilerplate").when(F.lit(False) if quotation is None else quotation, "quotation").when(density >= dense / 8, "verbatim").otherwise("paraphrase")).drop("_n")
