"""Accuracy experiments on the labelled corpus, and the published scores."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import oracles as sql
from .functions import sql as sqlfn
from .operators import evaluation as ev
from .registry import query
from .sources.catalog import documents, load
from .sources.io import stored


def corpus(spark, sf_dir) -> DataFrame:
    """10,000 pairs, 2,000 a stratum; on smaller tables a pair for every two hosts."""
    return ev.hosted_corpus(documents(spark, sf_dir), load(spark, sf_dir, "benchmark"))


_F05 = "case when precision + recall > 0 then 1.25 * precision * recall / (0.25 * precision + recall) when precision + recall = 0 then 0.0::double end"
_SCORES = f"""with d0 as (select source, lang, length(text) as chars, quality = 1 as hit from documents join labels using (doc_id) where quality is not null),
e as (select field, count(*) as kept, count(*) filter (hit) as hits, sum(chars)::bigint as chars from (select unnest([source, lang]) as field, chars, hit from d0) where field is not null group by 1),
m as (select sum(kept)::bigint as n, sum(chars)::bigint as all_chars, sum(kept - hits)::bigint as wrong from e), g as (select count(*) filter (hit) as good from d0),
p0 as (select *, hits / kept as precision, hits / nullif(good, 0) as recall from e, m, g),
p as (select field, kept, hits, good, precision, recall, {_F05} as f05, case when chars * n <= all_chars * kept then 'low' else 'high' end as cost, case when (kept - hits) * n > wrong * kept then 'low' else 'high' end as specificity from p0)"""


def _scores(spark, sf_dir) -> DataFrame:
    """What the published lists were before: scored approaches to rank and select; now those of rules on the given tables."""
    return ev.field_scores(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))


@query("published_rank", f"{_SCORES} select field, rank() over (order by precision desc) as by_precision, rank() over (order by recall desc) as by_recall, rank() over (order by f05 desc) as by_f05 from p")
def published_rank(spark, sf_dir):
    by = lambda c: F.rank().over(Window.orderBy(F.col(c).desc()))
    return _scores(spark, sf_dir).select("field", by("precision").alias("by_precision"), by("recall").alias("by_recall"), by("f05").alias("by_f05"))


@query("published_fbeta_check", f"""{_SCORES}, a as (select field, ((200 * hits + kept) // (2 * kept)) / 100 as precision, ((200 * hits + good) // (2 * good)) / 100 as recall, ((1000 * hits + good + 4 * kept) // (2 * (good + 4 * kept))) / 100 as f from p where good > 0)
select field, precision, recall, f as f05, round({_F05}, 6) as recomputed, abs({_F05} - f) <= 0.01 as agrees from a""")
def published_fbeta_check(spark, sf_dir):
    """Scores as they are printed, to two digits and each from the counts: does F0.5 follow from the printed precision and recall?"""
    digits = lambda x, y: F.expr(f"(200 * ({x}) + ({y})) div (2 * ({y})) / 100")
    rows = _scores(spark, sf_dir).where("good > 0").select("field", digits("hits", "kept").alias("precision"), digits("hits", "good").alias("recall"), digits("5 * hits", "good + 4 * kept").alias("f05"))
    f = ev.f_beta(F.col("precision"), F.col("recall"))
    return rows.select("*", F.round(f, 6).alias("recomputed"), (F.abs(f - F.col("f05")) <= 0.01).alias("agrees"))


@query("published_subquadratic_low", f"{_SCORES} select field, precision, recall, f05 from p where cost = 'low' and specificity = 'low'")
def published_subquadratic_low(spark, sf_dir):
    return _scores(spark, sf_dir).where("cost = 'low' and specificity = 'low'").select("field", "precision", "recall", "f05")


_CORPUS = f"with {sql.CORPUS}"
_FOUND = f"{_CORPUS}, {sql.detected('found')}"
_SCORED = f"{_FOUND}, {sql.counted('found')}"


@query("labelled_pairs", f"{_CORPUS} select * from corp")
def labelled_pairs(spark, sf_dir):
    return corpus(spark, sf_dir).select("pair_id", "strategy", F.array_join("a_words", " ").alias("a_text"), F.array_join("b_words", " ").alias("b_text"), "a_begin", "a_end", "b_begin", "b_end")


@query("score_by_strategy", f"{_SCORED}, m as ({sql.MICRO}) select strategy, {sql.PRF} from m")
def score_by_strategy(spark, sf_dir):
    c = stored(corpus(spark, sf_dir), "corpus")
    return ev.rounded(ev.scores(ev.counts(c, ev.detect(c)), ["strategy"]))


@query("score_corpus", f"{_SCORED}, m as ({sql.MICRO}), w as (select avg(p) as p, avg(r) as r from m) select {sql.PRF} from w")
def score_corpus(spark, sf_dir):
    c = stored(corpus(spark, sf_dir), "corpus")
    return ev.rounded(ev.corpus_score(ev.scores(ev.counts(c, ev.detect(c)), ["strategy"]), []))


@query("score_micro_macro", f"{_SCORED}, m as (select 'micro' as average, * from ({sql.MICRO}) union all select 'macro', * from ({sql.MACRO})) select average, strategy, {sql.PRF} from m")
def score_micro_macro(spark, sf_dir):
    c = stored(corpus(spark, sf_dir), "corpus")
    n = ev.counts(c, ev.detect(c))
    kinds = [ev.scores(n, ["strategy"], kind).withColumn("average", F.lit(kind)) for kind in ("micro", "macro")]
    return ev.rounded(reduce(DataFrame.unionByName, kinds))


_GRANULARITY = "hit as (select f.pair_id, count(*) as n from found f join corp c on f.pair_id = c.pair_id and f.a_begin < c.a_end and f.a_end > c.a_begin group by 1), gr as (select avg(n) as granularity from hit)"


@query("score_granularity", f"{_FOUND}, {_GRANULARITY} select round(granularity, 6) as granularity from gr")
def score_granularity(spark, sf_dir):
    c = stored(corpus(spark, sf_dir), "corpus")
    return ev.granularity(c, ev.detect(c)).select(F.round("granularity", 6).alias("granularity"))


@query("score_combined", f"{_SCORED}, {_GRANULARITY}, m as ({sql.MICRO}), w as (select avg(p) as p, avg(r) as r from m) select round(p, 6) as precision, round(r, 6) as recall, round(2 * p * r / (p + r), 6) as f1, round(granularity, 6) as granularity, round(2 * p * r / (p + r) / log2(1 + granularity), 6) as combined from w, gr")
def score_combined(spark, sf_dir):
    c = stored(corpus(spark, sf_dir), "corpus")
    found = stored(ev.detect(c), "detected")
    whole = ev.corpus_score(ev.scores(ev.counts(c, found), ["strategy"]), [])
    rows = ev.combined(whole, ev.granularity(c, found))
    return rows.select(*(F.round(x, 6).alias(x) for x in rows.columns))


@query("grid_scores")
def grid_scores(spark, sf_dir):
    return ev.grid(stored(corpus(spark, sf_dir), "corpus"))


def _cell(name: str, n: int, k: int, delta: int) -> str:
    return f"{name} as (with {sql.detected('found', n, n - k, delta)}, {sql.counted('found')}, m as ({sql.MICRO}), b as (select * from m union all select 'whole corpus', avg(p), avg(r) from m) select {n}::bigint as n, {k}::bigint as k, {delta}::bigint as delta, strategy, {sql.PRF} from b)"


_CELLS = [(4, 3, 50), (8, 7, 250), (10, 5, 500)]


@query("grid_cells", f"{_CORPUS}, {', '.join(_cell(f'c{i}', *c) for i, c in enumerate(_CELLS))} select * from c0 union all select * from c1 union all select * from c2")
def grid_cells(spark, sf_dir):
    """Three cells of the grid, which SQL can compute too."""
    rows = grid_scores(spark, sf_dir)
    return rows.where(reduce(lambda a, b: a | b, ((F.col("n") == n) & (F.col("k") == k) & (F.col("delta") == d) for n, k, d in _CELLS)))


@query("grid_best")
def grid_best(spark, sf_dir):
    return ev.best(ev.grid(stored(corpus(spark, sf_dir), "corpus")))


@query("approach_comparison")
def approach_comparison(spark, sf_dir):
    return ev.compare(stored(corpus(spark, sf_dir), "corpus"))


def _approach(name: str, run, text: str | None = None) -> None:
    @query(name, text)
    def spans(spark, sf_dir):
        return run(stored(corpus(spark, sf_dir), "corpus"))


_ENSEMBLE = f"""{_CORPUS}, {sql.detected('one')}, {sql.detected('two', 6, 1, 100, order=False)},
s as (select pair_id as a_doc, 0 as b_doc, a_begin, a_end, b_begin, b_end from one union all select pair_id, 0, a_begin, a_end, b_begin, b_end from two), {sql.islands('s', 0)} select a_doc as pair_id, a_begin, a_end, b_begin, b_end from k"""
_approach("base_simple_chunks", ev.simple_chunks, f"{_CORPUS}, {sql.detected('found', 5, 5, 250)} select pair_id, a_begin, a_end, b_begin, b_end from found")
_approach("base_ensemble", ev.ensemble, _ENSEMBLE)
_approach("base_strategy_switch", ev.strategy_switch)
_approach("base_local_alignment", ev.local_alignment)


# Functions that SQL users call


@query("sqlfn_fbeta", f"{_SCORES} select field, round({_F05}, 6) as f05 from p where good > 0")
def sqlfn_fbeta(spark, sf_dir):
    sqlfn.register(spark)
    _scores(spark, sf_dir).createOrReplaceTempView("reuse_scores")
    return spark.sql("select field, round(f_beta(precision, recall, 0.5D), 6) as f05 from reuse_scores where good > 0")


@query("sqlfn_clean_text", "select doc_id, trim(regexp_replace(lower(text), '[^\\p{L}]+', ' ', 'g')) as clean from documents")
def sqlfn_clean_text(spark, sf_dir):
    sqlfn.register(spark)
    load(spark, sf_dir, "documents").createOrReplaceTempView("reuse_documents")
    return spark.sql("select doc_id, clean_text(text) as clean from reuse_documents")


@query("udtf_reuse_cases")
def udtf_reuse_cases(spark, sf_dir):
    """Cases of each benchmark item against itself, ad hoc in SQL."""
    sqlfn.register(spark)
    load(spark, sf_dir, "benchmark").createOrReplaceTempView("reuse_items")
    return spark.sql("select item_id, c.* from reuse_items, lateral reuse_cases(text, text, 8, 7, 250) c")


@query("udaf_sketch_merge", f"with {sql.signatures()} select doc_id, slot, min(hash) as hash from sig group by 1, 2")
def udaf_sketch_merge(spark, sf_dir):
    """Document sketches: the slotwise minimum of the passages' signatures."""
    from .operators import retrieval as sr

    rows = sr.sketched(documents(spark, sf_dir), family="md5").select("doc_id", F.posexplode("sig").alias("slot", "hash"))
    return rows.groupBy("doc_id", "slot").agg(F.min("hash").alias("hash"))
