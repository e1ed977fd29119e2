"""The paper's methods and experiments on the given tables, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as sql
from .operators import alignment as al
from .operators import blocks as bl
from .operators import exhaustive as ex
from .operators import normalize as nz
from .operators import records as rec
from .operators import retrieval as sr
from .operators import similarity as sim
from .registry import query
from .sources import io
from .sources.catalog import documents, load

CASES = ["a_doc", "b_doc", "a_begin", "a_end", "b_begin", "b_end", "n_seeds"]


def _full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents")


def _cases(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    return al.cases_of(documents(spark, sf_dir), store=True, **how).select(*CASES)


def _block_cases(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    docs = documents(spark, sf_dir)
    return bl.cases(docs, bl.cleaned(docs), **how)


def _runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The runs by the join that deals them by pair; the queries make them by blocks."""
    return al.runs_of_grams(al.grams(nz.worded(documents(spark, sf_dir)), context=True), store=True)


def _posts(spark: SparkSession, sf_dir: str, n: int = 50, m: int = 10, keyed: bool = True) -> DataFrame:
    return sr.postings(sr.sketched(documents(spark, sf_dir), n, m, "md5"), keyed)


# Collection and cleaning


@query("doc_unique_keys", "select doc_id, n_chars from documents")
def doc_unique_keys(spark, sf_dir):
    docs = _full(spark, sf_dir).select("doc_id", "n_chars")
    return rec.unique_by_key(docs.unionAll(docs), "doc_id", ["n_chars"])


@query("doc_word_gate", """
with n as (select doc_id, len(list_filter(string_split_regex(text, '\\x20+'), lambda w: length(w) > 0)) as n from documents),
g as (select * from (values (50, 60000), (1000, 60000)) v(lo, hi))
select lo::bigint as lo, hi::bigint as hi, count(*) as docs, count(*) filter (n between lo and hi) as kept, round(count(*) filter (n between lo and hi) / count(*), 6) as share from n, g group by 1, 2""")
def doc_word_gate(spark, sf_dir):
    docs = _full(spark, sf_dir).select("text")
    total = docs.agg(F.count(F.lit(1)).alias("docs"))
    out = None
    for lo, hi in ((50, 60_000), (1000, 60_000)):
        kept = nz.length_gate(docs, lo, hi).agg(F.count(F.lit(1)).alias("kept"))
        row = total.join(kept, F.lit(True)).select(F.lit(lo).alias("lo"), F.lit(hi).alias("hi"), "docs", "kept", F.round(F.col("kept") / F.col("docs"), 6).alias("share"))
        out = row if out is None else out.unionAll(row)
    return out


def _strip(name: str, kinds: list[str]) -> None:
    text = "text"
    for kind in kinds:
        pattern = nz.KINDS[kind].replace("'", "''")
        text = f"regexp_replace({text}, '{pattern}', ' ', 'g')"

    @query(name, f"select doc_id, {text} as text from documents")
    def strip(spark, sf_dir):
        return _full(spark, sf_dir).select("doc_id", nz.strip_spans(F.col("text"), kinds).alias("text"))


for _name, _kinds in {"doc_strip_citations": ["citation"], "doc_strip_numbers": ["number"], "doc_strip_contacts": ["contact"], "doc_strip_junk": ["junk", "table", "bibliography"]}.items():
    _strip(_name, _kinds)


@query("page_main_text", r"""
with a as (select page_id, url, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) as t,
  regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<!--.*?-->|<head.*?</head>', ' ', 'g'),
    '(?is)<div class="ad">.*?</div>', ' ', 'g'), '(?is)<[^>]*>', ' ', 'g') as h from pages)
select page_id, url, trim(t) as title, trim(regexp_replace(replace(replace(replace(replace(replace(replace(h, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '[\x20\n\r\t]+', ' ', 'g')) as body from a""")
def page_main_text(spark, sf_dir):
    return nz.html_main_text(load(spark, sf_dir, "pages"))


@query("doc_clean_text", "select doc_id, trim(regexp_replace(lower(text), '[^\\p{L}]+', ' ', 'g')) as clean from documents")
def doc_clean_text(spark, sf_dir):
    return _full(spark, sf_dir).select("doc_id", nz.clean(F.col("text")).alias("clean"))


@query("doc_token_offsets", f"with {sql.words()} select doc_id, pos, word, \"begin\", \"end\" from tok")
def doc_token_offsets(spark, sf_dir):
    return nz.tokens(documents(spark, sf_dir))


@query("doc_two_versions", r"""
with p as (select doc_id, text, string_split(regexp_replace(text, '[^\p{L}]', ' ', 'g'), ' ') as ps from documents),
u as (select doc_id, unnest(ps) as w, generate_subscripts(ps, 1) as i from p),
o as (select doc_id, i, w, coalesce(sum(length(w) + 1) over (partition by doc_id order by i rows between unbounded preceding and 1 preceding), 0)::bigint as b from u),
m as (select doc_id, string_agg(b::varchar, '|' order by i) as places from o where w <> '' group by 1)
select p.doc_id, length(text) as full_chars, length(trim(regexp_replace(lower(text), '[^\p{L}]+', ' ', 'g'))) as clean_chars, coalesce(places, '') as places from p left join m on p.doc_id = m.doc_id""")
def doc_two_versions(spark, sf_dir):
    rows = nz.two_versions(documents(spark, sf_dir))
    return rows.select("doc_id", F.length("full_text").alias("full_chars"), F.length("clean_text").alias("clean_chars"), F.array_join("clean_to_full", "|").alias("places"))


@query("doc_language", "select doc_id, lang from documents where lang = 'en'")
def doc_language(spark, sf_dir):
    """The documents of one language: a filter that reaches the scan."""
    return _full(spark, sf_dir).where("lang = 'en'").select("doc_id", "lang")


# Similarity


_PAIRS = f"""with {sql.words()}, b0 as (select item_id, trim(regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g')) as c from benchmark),
bw as (select distinct item_id, unnest(string_split(c, ' ')) as word from b0 where c <> ''), dw as (select distinct doc_id, word from tok),
nb as (select item_id, count(*) as n from bw group by 1), nd as (select doc_id, count(*) as n from dw group by 1),
s as (select item_id, doc_id, count(*) as shared from bw join dw using (word) group by 1, 2)"""


@query("sim_jaccard_pairs", f"{_PAIRS} select s.item_id, s.doc_id, shared, round(shared / (nb.n + nd.n - shared), 6) as jaccard from s join nb using (item_id) join nd using (doc_id) where shared / (nb.n + nd.n - shared) >= 0.1")
def sim_jaccard_pairs(spark, sf_dir):
    return sim.above(sim.set_overlap(load(spark, sf_dir, "benchmark"), documents(spark, sf_dir)), "jaccard", 0.1).select("item_id", "doc_id", "shared", F.round("jaccard", 6).alias("jaccard"))


@query("sim_containment_pairs", f"{_PAIRS} select s.item_id, s.doc_id, shared, round(shared / nb.n, 6) as containment from s join nb using (item_id) where shared / nb.n >= 0.8")
def sim_containment_pairs(spark, sf_dir):
    return sim.above(sim.set_overlap(load(spark, sf_dir, "benchmark"), documents(spark, sf_dir)), "containment", 0.8).select("item_id", "doc_id", "shared", F.round("containment", 6).alias("containment"))


@query("sim_bow_cosine", f"""with {sql.words()}, b0 as (select item_id, trim(regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g')) as c from benchmark),
bu as (select item_id, unnest(string_split(c, ' ')) as word from b0 where c <> ''), bt as (select item_id, word, count(*) as n from bu group by 1, 2), dt as (select doc_id, word, count(*) as n from tok group by 1, 2),
bn as (select item_id, sum(n * n) as q from bt group by 1), dn as (select doc_id, sum(n * n) as q from dt group by 1),
s as (select item_id, doc_id, sum(bt.n * dt.n) as dot from bt join dt using (word) group by 1, 2)
select item_id, doc_id, round(dot / (sqrt(bn.q) * sqrt(dn.q)), 6) as cosine from s join bn using (item_id) join dn using (doc_id) where dot / (sqrt(bn.q) * sqrt(dn.q)) >= 0.3""")
def sim_bow_cosine(spark, sf_dir):
    return sim.above(sim.bow_cosine(load(spark, sf_dir, "benchmark"), documents(spark, sf_dir)), "cosine", 0.3).select("item_id", "doc_id", F.round("cosine", 6).alias("cosine"))


@query("sim_dense_cosine_topk", """
with p as (select a.vec_id as a_id, b.vec_id as b_id, list_cosine_similarity(a.embedding::double[], b.embedding::double[]) as c from embeddings a join embeddings b on a.vec_id <> b.vec_id),
r as (select *, row_number() over (partition by a_id order by round(c, 4) desc, b_id) as rank from p) select a_id, b_id, rank, round(c, 4) as cosine from r where rank <= 3""")
def sim_dense_cosine_topk(spark, sf_dir):
    return sim.dense_top_k(load(spark, sf_dir, "embeddings"), 3)


# Source retrieval


def _passages(name: str, n: int, stride: int | None = None) -> None:
    take = f"select doc_id, pos // {n} as passage_no, string_agg(word, ' ' order by pos) as words from tok group by 1, 2"
    if stride:
        take = f""", c as (select doc_id, count(*) as n from tok group by 1), q as (select doc_id, unnest(range(0, greatest(0, ceil((n - {n}) / {stride}))::bigint + 1)) as passage_no from c)
          select q.doc_id, passage_no, string_agg(word, ' ' order by pos) as words from q join tok on tok.doc_id = q.doc_id and pos >= passage_no * {stride} and pos < passage_no * {stride} + {n} group by 1, 2"""

    @query(name, f"with {sql.words()} {take}")
    def passages(spark, sf_dir):
        rows = sr.chop(nz.worded(documents(spark, sf_dir)), n, stride)
        return rows.select("doc_id", "passage_no", F.array_join("words", " ").alias("words"))


_passages("passages_50", 50)
_passages("passages_20", 20)
_passages("passages_overlapping", 50, 25)


@query("passage_bag_counts", f"with {sql.words()} select doc_id, pos // 50 as passage_no, word, count(*) as n from tok group by 1, 2, 3")
def passage_bag_counts(spark, sf_dir):
    return sr.bag_counts(sr.chop(nz.worded(documents(spark, sf_dir)), 50))


@query("passage_minhash_md5", f"with {sql.signatures()} select doc_id, passage_no, slot, hash from sig")
def passage_minhash_md5(spark, sf_dir):
    return sr.sketched(documents(spark, sf_dir), family="md5").select("doc_id", "passage_no", F.posexplode("sig").alias("slot", "hash"))


@query("passage_minhash_xx")
def passage_minhash_xx(spark, sf_dir):
    return sr.sketched(documents(spark, sf_dir)).select("doc_id", "passage_no", F.posexplode("sig").alias("slot", "hash"))


@query("passage_minhash_affine", f"""with {sql.words()}, p as (select distinct doc_id, pos // 50 as passage_no, word from tok),
h as (select *, ('0x' || substr(md5(word), 1, 8))::bigint % 2147483647 as x from p),
c as (select i as slot, ('0x' || substr(md5('a' || i), 1, 8))::bigint % 2147483647 + 1 as a, ('0x' || substr(md5('b' || i), 1, 8))::bigint % 2147483647 as b from range(10) r(i))
select doc_id, passage_no, slot, min((a * x + b) % 2147483647) as hash from h, c group by 1, 2, 3""")
def passage_minhash_affine(spark, sf_dir):
    return sr.sketched(documents(spark, sf_dir), family="affine").select("doc_id", "passage_no", F.posexplode("sig").alias("slot", "hash"))


@query("minhash_jaccard_estimate", f"""with {sql.signatures()}, c as (select a.doc_id as a_doc, a.passage_no as a_passage, b.doc_id as b_doc, b.passage_no as b_passage, count(*) as slots
  from sig a join sig b on a.slot = b.slot and a.hash = b.hash and a.doc_id < b.doc_id group by 1, 2, 3, 4) select slots, round(slots / 10, 6) as estimate, count(*) as passage_pairs from c group by 1, 2""")
def minhash_jaccard_estimate(spark, sf_dir):
    pairs = sr.witnesses(sr.sketched(documents(spark, sf_dir), family="md5"))
    return pairs.groupBy("slots").agg(F.count(F.lit(1)).alias("passage_pairs")).withColumn("estimate", F.round(F.col("slots") / 10, 6))


_SETTINGS = [(20, 5), (50, 10), (50, 5), (50, 20), (100, 10)]


@query("minhash_bound_table", f"""with {sql.words()}, p as (select length, doc_id, pos // length as q, count(distinct word) as n from tok, (values (20), (50), (100)) l(length) group by 1, 2, 3),
z as (select length, n, count(*) as passages from p group by 1, 2)
select length::bigint as length, n::bigint as n, m::bigint as m, passages, ceil(2.0 * n / (m + 1))::bigint as words_jaccard, ceil(1.0 * n / m)::bigint as words_containment, round(1 - pow(1 - 1.0::double / m, m), 6) as collision_at_bound
from z join (values {", ".join(map(str, _SETTINGS))}) v(length, m) using (length)""")
def minhash_bound_table(spark, sf_dir):
    """The bounds by the real sizes of the passages of the collection."""
    return sr.bound_table(nz.worded(documents(spark, sf_dir)), _SETTINGS)


@query("sr_postings", f"with {sql.postings()} select doc_id, slot, hash from post")
def sr_postings(spark, sf_dir):
    return _posts(spark, sf_dir)


def _candidates(name: str, n: int, m: int, keyed: bool = True) -> None:
    @query(name, f"with {sql.candidates(n, m, keyed)} select a_doc, b_doc from cand")
    def candidates(spark, sf_dir):
        return bl.candidates(bl.fingerprints(nz.worded(documents(spark, sf_dir)), n, m))


_candidates("sr_candidates", 50, 10)
_candidates("sr_candidates_20_5", 20, 5)
_candidates("sr_candidates_unkeyed", 50, 10, False)


@query("sr_candidates_min2", f"with {sql.postings()} select a.doc_id as a_doc, b.doc_id as b_doc, count(distinct a.slot) as common from post a join post b on a.slot = b.slot and a.hash = b.hash and a.doc_id < b.doc_id group by 1, 2 having count(distinct a.slot) >= 2")
def sr_candidates_min2(spark, sf_dir):
    return sr.candidates(_posts(spark, sf_dir), 2)


_SMALL = ", small as (select * from post where (slot, hash) in (select (slot, hash) from post group by slot, hash having count(*) <= 200))"


@query("sr_candidates_capped", f"with {sql.candidates(posts='small', extra=_SMALL)} select a_doc, b_doc from cand")
def sr_candidates_capped(spark, sf_dir):
    return sr.candidates(sr.capped(_posts(spark, sf_dir), 200))


@query("sr_candidates_dropwords", f"""with {sql.words()}, n as (select count(*) as n from documents), f as (select word from (select distinct doc_id, word from tok) group by word having count(*) > 0.3 * (select n from n)),
r as (select doc_id, word, row_number() over (partition by doc_id order by pos) - 1 as pos from tok where word not in (select word from f)), p as (select distinct doc_id, pos // 50 as passage_no, word from r),
post as (select distinct doc_id, i as slot, min(md5(i::varchar || ':' || word)) over (partition by doc_id, passage_no, i) as hash from p cross join range(10) x(i))
select distinct a.doc_id as a_doc, b.doc_id as b_doc from post a join post b on a.slot = b.slot and a.hash = b.hash and a.doc_id < b.doc_id""")
def sr_candidates_dropwords(spark, sf_dir):
    rows = sr.without_frequent(nz.worded(documents(spark, sf_dir)), 0.3)
    return bl.candidates(bl.fingerprints(rows, 50, 10))


@query("sr_candidates_of_doc", f"with {sql.candidates()} select case when a_doc = 0 then b_doc else a_doc end as doc_id from cand where a_doc = 0 or b_doc = 0")
def sr_candidates_of_doc(spark, sf_dir):
    return sr.candidates_of(_posts(spark, sf_dir), 0)


@query("sr_witnesses")
def sr_witnesses(spark, sf_dir):
    """All pairs of passages that collide in a slot or more; tests check the rows."""
    return sr.witnesses(sr.sketched(documents(spark, sf_dir), family="md5"))


@query("sr_witnesses_min3", f"with {sql.signatures()} select a.doc_id as a_doc, a.passage_no as a_passage, b.doc_id as b_doc, b.passage_no as b_passage, count(*) as slots from sig a join sig b on a.slot = b.slot and a.hash = b.hash and a.doc_id < b.doc_id group by 1, 2, 3, 4 having count(*) >= 3")
def sr_witnesses_min3(spark, sf_dir):
    return sr.witnesses(sr.sketched(documents(spark, sf_dir), family="md5")).where("slots >= 3")


@query("sr_pruning", f"with {sql.candidates()}, n as (select count(*) as docs from documents), c as (select count(*) as candidates from cand) select docs, candidates, round(1 - candidates / nullif(docs * (docs - 1), 0), 6) as pruned_ordered, round(1 - 2 * candidates / nullif(docs * (docs - 1), 0), 6) as pruned_unordered from n, c")
def sr_pruning(spark, sf_dir):
    return sr.pruning(sr.count_candidates(_posts(spark, sf_dir)), documents(spark, sf_dir))


@query("sr_work_counters", f"with {sql.postings()}, b as (select count(*) as n from post group by slot, hash) select (select count(*) from tok) as words, sum(n)::bigint as postings, max(n) as largest_bucket, sum(n * (n - 1) // 2)::bigint as bucket_pairs from b")
def sr_work_counters(spark, sf_dir):
    docs = documents(spark, sf_dir)
    return sr.work_counters(nz.worded(docs), _posts(spark, sf_dir))


_TRUE = f"{sql.candidates()}, g as (select distinct doc_id, array_to_string(ws, ' ') as g from (select doc_id, pos, list(word) over (partition by doc_id order by pos rows between current row and 7 following) as ws from tok) where len(ws) = 8), tp as (select distinct a.doc_id as a_doc, b.doc_id as b_doc from g a join g b on a.g = b.g and a.doc_id < b.doc_id)"


@query("sr_recall_precision", f"with {_TRUE}, f as (select count(*) as found from tp semi join cand using (a_doc, b_doc)) select found, (select count(*) from tp) as wanted, (select count(*) from cand) as kept, round(found / nullif((select count(*) from tp), 0), 6) as recall, round(found / nullif((select count(*) from cand), 0), 6) as precision from f")
def sr_recall_precision(spark, sf_dir):
    docs = documents(spark, sf_dir)
    true_pairs = al.seeds_by_index(al.grams(nz.worded(docs)), prune=True).select("a_doc", "b_doc").distinct()
    return sr.quality(sr.candidates(_posts(spark, sf_dir)), true_pairs)


@query("sr_bucket_profile", f"with {sql.postings()}, b as (select count(*) as docs from post group by slot, hash) select docs, count(*) as buckets, (count(*) * docs * (docs - 1) // 2)::bigint as pairs from b group by 1")
def sr_bucket_profile(spark, sf_dir):
    return sr.bucket_profile(_posts(spark, sf_dir))


@query("sr_candidates_per_document", f"with {sql.candidates()}, e as (select a_doc as doc_id from cand union all select b_doc from cand), c as (select doc_id, count(*) as n from e group by 1), z as (select coalesce(n, 0) as n from documents left join c using (doc_id)), v as (select unnest([0.0, 0.25, 0.5, 0.75, 0.9, 1.0])::double as share) select share, round((select quantile_cont(n, [0.0, 0.25, 0.5, 0.75, 0.9, 1.0]) from z)[list_position([0.0, 0.25, 0.5, 0.75, 0.9, 1.0], share)], 6) as candidates from v")
def sr_candidates_per_document(spark, sf_dir):
    return sr.per_document(sr.candidates(_posts(spark, sf_dir)), documents(spark, sf_dir))


_SWEEP = [(20, 5), (20, 10), (50, 5), (50, 10), (50, 20), (100, 10)]


@query("sr_sweep", "with " + sql.words() + "".join(
    f", c{n}_{m} as (with p as (select distinct doc_id, pos // {n} as q, word from tok), s as (select distinct doc_id, i, min(md5(i::varchar || ':' || word)) over (partition by doc_id, q, i) as h from p cross join range({m}) x(i)) select {n}::bigint as n, {m}::bigint as m, count(*) as candidates from (select distinct a.doc_id, b.doc_id from s a join s b on a.i = b.i and a.h = b.h and a.doc_id < b.doc_id))" for n, m in _SWEEP)
    + " select * from (" + " union all ".join(f"select * from c{n}_{m}" for n, m in _SWEEP) + ")")
def sr_sweep(spark, sf_dir):
    rows = nz.worded(documents(spark, sf_dir))
    out = None
    for n, m in _SWEEP:
        found = sr.candidates(sr.postings(sr.minhash(sr.chop(rows, n), m, "md5")))
        row = found.agg(F.count(F.lit(1)).alias("candidates")).select(F.lit(n).alias("n"), F.lit(m).alias("m"), "candidates")
        out = row if out is None else out.unionAll(row)
    return out


@query("base_all_pairs", "select count(*) as comparisons, (count(*) * 2)::bigint as ordered from documents a join documents b on a.doc_id < b.doc_id")
def base_all_pairs(spark, sf_dir):
    """The exhaustive search space: every pair of documents is compared once (a theta join, on purpose quadratic)."""
    ids = documents(spark, sf_dir).select("doc_id")
    pairs = ids.select(F.col("doc_id").alias("a_doc")).join(ids.select(F.col("doc_id").alias("b_doc")), F.expr("a_doc < b_doc"))
    return pairs.agg(F.count(F.lit(1)).alias("comparisons"), (F.count(F.lit(1)) * 2).alias("ordered"))


_EXACT = 0.5


@query("base_passage_exact", f"""with {sql.words()}, p as (select distinct doc_id, pos // 50 as q, word from tok), z as (select doc_id, q, count(*) as n from p group by 1, 2), f as (select word, count(*) as df from p group by 1),
r as (select p.*, n, row_number() over (partition by p.doc_id, p.q order by df, word) as k from p join f using (word) join z on z.doc_id = p.doc_id and z.q = p.q),
c as (select distinct a.doc_id as a_doc, a.q as a_passage, b.doc_id as b_doc, b.q as b_passage, a.n as an, b.n as bn from r a join r b on a.word = b.word and a.doc_id < b.doc_id and a.k <= a.n - ceil({_EXACT} * a.n) + 1 and b.k <= b.n - ceil({_EXACT} * b.n) + 1),
s as (select a_doc, a_passage, b_doc, b_passage, an, bn, count(*) as shared from c join p x on x.doc_id = a_doc and x.q = a_passage join p y on y.doc_id = b_doc and y.q = b_passage and y.word = x.word group by all)
select a_doc, a_passage, b_doc, b_passage, round(shared / (an + bn - shared), 6) as jaccard from s where shared / (an + bn - shared) >= {_EXACT}""")
def base_passage_exact(spark, sf_dir):
    """Pairs of passages above a similarity without any sketch, over the whole collection."""
    rows = ex.passage_pairs_by_prefix(sr.chop(nz.worded(documents(spark, sf_dir)), 50), _EXACT)
    return rows.withColumn("jaccard", F.round("jaccard", 6))


# Text alignment


def _grams(name: str, k: int) -> None:
    @query(name, f"with {sql.grams(8, 8 - k)} select doc_id, pos, \"begin\", \"end\", g from g")
    def grams(spark, sf_dir):
        return al.grams(nz.worded(documents(spark, sf_dir)), 8, k, "text")


_grams("al_grams_8_7", 7)
_grams("al_grams_8_4", 4)
_grams("al_grams_8_0", 0)


@query("al_sentences", r"with s as (select doc_id, list_filter(string_split_regex(text, '[.!?]+[\x20\n]+'), lambda s: length(trim(s)) > 0) as ss from documents) select doc_id, unnest(ss) as sentence, (generate_subscripts(ss, 1) - 1)::bigint as pos from s")
def al_sentences(spark, sf_dir):
    return al.sentences(documents(spark, sf_dir))


def _seeds(name: str, text: str, **how) -> None:
    @query(name, text)
    def seeds(spark, sf_dir):
        docs = documents(spark, sf_dir)
        rows = nz.worded(docs)
        if how.get("candidates"):
            return bl.seeds_of_candidates(docs, rows, al.grams(rows, context=True), _posts(spark, sf_dir))
        if how.get("one_sided"):
            return bl.seeds_one_sided(docs, bl.cleaned(docs))
        gs = al.grams(rows, order=how.get("order", True))
        return al.seeds_by_index(gs, prune=how.get("prune", False))


_SEEDS = "a_doc, b_doc, a_pos, b_pos, a_begin, a_end, b_begin, b_end"
_seeds("al_seeds_index", f"with {sql.seeds()} select {_SEEDS} from s")
_seeds("al_seeds_pruned", f"with {sql.seeds()} select {_SEEDS} from s", prune=True)
_seeds("al_seeds_sorted_gram", f"with {sql.seeds(order=False)} select {_SEEDS} from s", order=False, prune=True)
_seeds("al_seeds_one_sided", f"with {sql.seeds(8, 8, step_b=1)} select {_SEEDS} from s", one_sided=True)
_seeds("al_seeds_candidates", f"""with {sql.candidates()}, g as (select * from (select doc_id, pos, "begin", lead("end", 7) over (partition by doc_id order by pos) as "end", array_to_string(list(word) over (partition by doc_id order by pos rows between current row and 7 following), ' ') as g from tok) where "end" is not null),
s as (select {sql.SEED_COLUMNS} from cand join g a on a.doc_id = a_doc join g b on b.doc_id = b_doc and a.g = b.g) select {_SEEDS} from s""", candidates=True)

_RUNS = f"{sql.seeds()}, q as (select *, a_pos - b_pos as diag, a_pos - row_number() over (partition by a_doc, b_doc, a_pos - b_pos order by a_pos) as run from s), r as (select a_doc, b_doc, min(a_begin) as a_begin, max(a_end) as a_end, min(b_begin) as b_begin, max(b_end) as b_end, count(*) as n_seeds from q group by a_doc, b_doc, diag, run)"


@query("al_runs", f"with {_RUNS} select {sql.CASE_COLUMNS} from r")
def al_runs(spark, sf_dir):
    docs = documents(spark, sf_dir)
    return bl.runs(docs, bl.cleaned(docs)).select(*CASES)


@query("al_cases", f"with {sql.cases()} select {sql.CASE_COLUMNS} from k")
def al_cases(spark, sf_dir):
    return _block_cases(spark, sf_dir)


_BY_CANDIDATES = f"""{sql.candidates()}, g as materialized (select * from (select doc_id, pos, "begin", lead("end", 7) over o as "end", concat_ws(' ', {", ".join("word" if i == 0 else f"lead(word, {i}) over o" for i in range(8))}) as g from tok window o as (partition by doc_id order by pos)) where "end" is not null),
s as (select {sql.SEED_COLUMNS} from g a join g b on a.g = b.g and a.doc_id < b.doc_id semi join cand on cand.a_doc = a.doc_id and cand.b_doc = b.doc_id),
{sql.islands()}"""


def _cases_of_candidates(spark, sf_dir) -> DataFrame:
    return _block_cases(spark, sf_dir, posts=_posts(spark, sf_dir))


@query("al_cases_candidates", f"with {_BY_CANDIDATES} select {sql.CASE_COLUMNS} from k")
def al_cases_candidates(spark, sf_dir):
    """The whole pipeline in its order: passages of 50 words with 10 fingerprints, candidates, seeds of 8 words, cases."""
    return _cases_of_candidates(spark, sf_dir)


@query("al_cases_recall", f"with c as (with {_BY_CANDIDATES} select {sql.CASE_COLUMNS} from k), e as (with {sql.cases()} select {sql.CASE_COLUMNS} from k) select (select count(*) from e) as exact, (select count(*) from c) as by_candidates, (select count(*) from e semi join c using ({sql.CASE_COLUMNS})) as found, round((select count(*) from e semi join c using ({sql.CASE_COLUMNS})) / nullif((select count(*) from e), 0), 6) as recall")
def al_cases_recall(spark, sf_dir):
    """Cases of the pipeline among those of the exact alignment of all pairs."""
    exact, some = io.stored(_cases(spark, sf_dir), "exact"), io.stored(_cases_of_candidates(spark, sf_dir), "by-candidates")
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    row = n(exact, "exact").join(n(some, "by_candidates"), F.lit(True)).join(n(exact.join(some, CASES, "left_semi"), "found"), F.lit(True))
    return row.withColumn("recall", F.round(F.col("found") / F.nullif("exact", F.lit(0)), 6))


@query("al_cases_fixpoint", f"with {sql.seeds()}, {sql.islands('s', 250, 4)} select {sql.CASE_COLUMNS} from k")
def al_cases_fixpoint(spark, sf_dir):
    """Islands split until a round splits none; the SQL makes four rounds."""
    return _block_cases(spark, sf_dir, rounds=None)


@query("al_seeds_nested_loop", f"""with t0 as (with {sql.grams(source='benchmark', key='item_id')} select * from g), t1 as (with {sql.grams()} select * from g) select {sql.SEED_COLUMNS.replace('a.doc_id as a_doc', 'a.doc_id as item_id').replace('b.doc_id as b_doc', 'b.doc_id as doc_id')} from t0 a join t1 b on a.g = b.g""")
def al_seeds_nested_loop(spark, sf_dir):
    """The reference meaning of seeding: each gram of an item is compared with each gram of a document (a product, on purpose)."""
    items = al.grams(nz.worded(load(spark, sf_dir, "benchmark"), "item_id"))
    return ex.compared(items, al.grams(nz.worded(documents(spark, sf_dir)))).withColumnsRenamed({"a_doc": "item_id", "b_doc": "doc_id"})


@query("al_cases_delta_50", f"with {sql.cases(delta=50)} select {sql.CASE_COLUMNS} from k")
def al_cases_delta_50(spark, sf_dir):
    return _block_cases(spark, sf_dir, delta=50)


@query("al_cases_min2", f"with {sql.cases()} select {sql.CASE_COLUMNS} from k where n_seeds >= 2")
def al_cases_min2(spark, sf_dir):
    return _block_cases(spark, sf_dir, min_seeds=2)


@query("al_cases_disjoint", f"with {sql.cases(8, 8)} select {sql.CASE_COLUMNS} from k")
def al_cases_disjoint(spark, sf_dir):
    return _cases(spark, sf_dir, k=0)


@query("al_cases_chain", f"""with {_RUNS}, f as (select *, case when b_begin < lag(b_begin) over o or a_begin - max(a_end) over (o rows between unbounded preceding and 1 preceding) > 250 or b_begin - lag(b_end) over o > 250 then 1 else 0 end as turn from r window o as (partition by a_doc, b_doc order by a_begin, b_begin, a_end, b_end)),
c as (select *, sum(turn) over (partition by a_doc, b_doc order by a_begin, b_begin, a_end, b_end rows unbounded preceding) as ch from f)
select a_doc, b_doc, min(a_begin) as a_begin, max(a_end) as a_end, min(b_begin) as b_begin, max(b_end) as b_end, sum(n_seeds)::bigint as n_seeds from c group by a_doc, b_doc, ch""")
def al_cases_chain(spark, sf_dir):
    return _block_cases(spark, sf_dir, how="chains")


@query("al_cases_components")
def al_cases_components(spark, sf_dir):
    return _block_cases(spark, sf_dir, how="both")


@query("al_cases_near_either")
def al_cases_near_either(spark, sf_dir):
    return _block_cases(spark, sf_dir, how="either")


# Records, metadata and analyses

_REC = f"with {sql.cases()},{sql.FIELDS}"


def _records(spark, sf_dir):
    return rec.with_context(_cases(spark, sf_dir), rec.publications(_full(spark, sf_dir), rec.taxonomy(spark)))


@query("case_records", f"""{_REC}, i as (select *, md5(concat_ws('|', a_doc, b_doc, a_begin, a_end, b_begin, b_end)) as h from k)
select concat_ws('-', substr(h, 1, 8), substr(h, 9, 4), substr(h, 13, 4), substr(h, 17, 4), substr(h, 21, 12)) as case_id, {sql.CASE_COLUMNS},
  pa.doc_chars as a_doc_chars, pa.pub_year as a_year, pa.fields as a_fields, pa.areas as a_areas, pa.disciplines as a_disciplines,
  pb.doc_chars as b_doc_chars, pb.pub_year as b_year, pb.fields as b_fields, pb.areas as b_areas, pb.disciplines as b_disciplines
from i left join pub pa on pa.doc_id = a_doc left join pub pb on pb.doc_id = b_doc""")
def case_records(spark, sf_dir):
    out = _records(spark, sf_dir)
    return out.withColumns({c: F.array_join(c, "|") for c in out.columns if c.endswith(("fields", "areas", "disciplines"))})


@query("publication_records", f"with {sql.FIELDS} select doc_id, doc_chars, pub_year, fields, areas, disciplines from pub")
def publication_records(spark, sf_dir):
    out = rec.publications(_full(spark, sf_dir), rec.taxonomy(spark))
    return out.withColumns({c: F.array_join(c, "|") for c in ("fields", "areas", "disciplines")})


@query("meta_match", "select d.doc_id, l.quality::bigint as quality, l.toxic::bigint as toxic, l.doc_id is not null as matched from documents d left join labels l on d.doc_id = l.doc_id")
def meta_match(spark, sf_dir):
    labels = load(spark, sf_dir, "labels").withColumn("matched", F.lit(True))
    return _full(spark, sf_dir).select("doc_id").join(labels, "doc_id", "left").withColumn("matched", F.coalesce("matched", F.lit(False)))


@query("meta_consensus", """with s as (select distinct source as item, substr(source, 4)::int as i from documents), v as (select item, unnest(['d' || (i % 4), 'd' || (i % 4), 'd' || (i % 3)]) as vote from s),
n as (select item, vote, count(*) as n from v group by 1, 2), r as (select *, row_number() over (partition by item order by n desc, vote) as k, count(*) over (partition by item) as kinds, sum(n) over (partition by item) as votes from n)
select item, vote as value, kinds = 1 as agreed, kinds = votes and kinds > 1 as conflict from r where k = 1""")
def meta_consensus(spark, sf_dir):
    s = _full(spark, sf_dir).select(F.col("source").alias("item")).distinct().withColumn("i", F.substring("item", 4, 10).cast("int"))
    vote = lambda k: F.concat(F.lit("d"), (F.col("i") % k).cast("string"))
    return rec.consensus(s.select("item", F.explode(F.array(vote(4), vote(4), vote(3))).alias("vote")))


@query("meta_taxonomy", f"with {sql.FIELDS} select discipline, area, p.field, count(distinct p.doc_id) as publications, grouping_id(discipline, area, p.field) as level from pub0 p join dim on dim.field = p.field group by rollup (discipline, area, p.field)")
def meta_taxonomy(spark, sf_dir):
    flat = _full(spark, sf_dir).select("doc_id", F.explode(F.array("source", "lang")).alias("field")).join(F.broadcast(rec.taxonomy(spark)), "field")
    return flat.rollup("discipline", "area", "field").agg(F.count_distinct("doc_id").alias("publications"), F.grouping_id().alias("level"))


@query("case_hydrate", f"with {sql.cases()} select {sql.CASE_COLUMNS}, substr(da.c, a_begin + 1, a_end - a_begin) as a_text, substr(db.c, b_begin + 1, b_end - b_begin) as b_text from k join d da on da.doc_id = a_doc join d db on db.doc_id = b_doc")
def case_hydrate(spark, sf_dir):
    return rec.hydrate(_cases(spark, sf_dir), documents(spark, sf_dir))


_EIGHTS = "list_transform(range(1, greatest(len({0}) - 6, 1)), lambda i: array_to_string({0}[i:i + 7], ' '))"


@query("case_hydrate_check", f"with {sql.cases()}, h as (select string_split(substr(da.c, a_begin + 1, a_end - a_begin), ' ') as x, string_split(substr(db.c, b_begin + 1, b_end - b_begin), ' ') as y from k join d da on da.doc_id = a_doc join d db on db.doc_id = b_doc) select count(*) as cases, count(*) filter (not list_has_any({_EIGHTS.format('x')}, {_EIGHTS.format('y')})) as violations from h")
def case_hydrate_check(spark, sf_dir):
    """Cases of which the recovered texts share no 8-gram: none may exist."""
    rows = io.stored(rec.hydrate(_cases(spark, sf_dir), documents(spark, sf_dir)), "hydrated")
    bad = rec.without_common_gram(rows).agg(F.count(F.lit(1)).alias("violations"))
    return rows.agg(F.count(F.lit(1)).alias("cases")).join(bad, F.lit(True))


_PLACES = r"""fp as (select doc_id, text, string_split(regexp_replace(text, '[^\p{L}]', ' ', 'g'), ' ') as ps from documents),
fu as (select doc_id, unnest(ps) as w, generate_subscripts(ps, 1) as i from fp),
fo as (select doc_id, i, w, coalesce(sum(length(w) + 1) over (partition by doc_id order by i rows between unbounded preceding and 1 preceding), 0)::bigint as fb from fu),
fw as (select doc_id, row_number() over (partition by doc_id order by i) - 1 as pos, fb, fb + length(w) as fe from fo where w <> ''),
pl as (select doc_id, "begin", "end", fb, fe from tok join fw using (doc_id, pos))"""
_FULL = f"{sql.cases()}, {_PLACES}, fk as (select k.*, a1.fb as a_full_begin, a2.fe as a_full_end, b1.fb as b_full_begin, b2.fe as b_full_end from k join pl a1 on a1.doc_id = a_doc and a1.\"begin\" = a_begin join pl a2 on a2.doc_id = a_doc and a2.\"end\" = a_end join pl b1 on b1.doc_id = b_doc and b1.\"begin\" = b_begin join pl b2 on b2.doc_id = b_doc and b2.\"end\" = b_end)"


@query("case_hydrate_full", f"with {_FULL} select {sql.CASE_COLUMNS}, a_full_begin, a_full_end, b_full_begin, b_full_end, substr(da.text, a_full_begin + 1, a_full_end - a_full_begin) as a_full, substr(db.text, b_full_begin + 1, b_full_end - b_full_begin) as b_full from fk join documents da on da.doc_id = a_doc join documents db on db.doc_id = b_doc")
def case_hydrate_full(spark, sf_dir):
    """The passages as they stand in the uncleaned texts."""
    return rec.hydrate_full(_cases(spark, sf_dir), documents(spark, sf_dir)).drop("a_around", "b_around")


@query("case_editions", f"with {sql.cases()}, h as (select a_end - a_begin + b_end - b_begin as chars from k) select 'full' as edition, count(*) as cases, sum(chars)::bigint as text_chars from h union all select 'metadata', count(*), 0 from h")
def case_editions(spark, sf_dir):
    """The records as two archives, with and without texts, written and read again."""
    rows = rec.hydrate(_cases(spark, sf_dir), documents(spark, sf_dir))
    where = f"{io.shared_folder(spark)}/textreuse-editions-{io.uuid.uuid4().hex}"
    io.write_editions(rows, where)
    full = io.read_jsonl(spark, f"{where}/full", rows.schema)
    plain = io.read_jsonl(spark, f"{where}/metadata", rows.drop("a_text", "b_text").schema)
    n = F.count(F.lit(1)).alias("cases")
    first = full.agg(n, F.sum(F.length("a_text") + F.length("b_text")).alias("text_chars")).select(F.lit("full").alias("edition"), "cases", "text_chars")
    return first.unionAll(plain.agg(n).select(F.lit("metadata").alias("edition"), "cases", F.lit(0).cast("bigint")))


@query("case_context_window", f"with {sql.cases()} select a_doc, b_doc, a_begin, a_end, substr(c, greatest(0, a_begin - 40) + 1, a_begin - greatest(0, a_begin - 40)) as before, substr(c, a_begin + 1, a_end - a_begin) as passage, substr(c, a_end + 1, 40) as after from k join d on d.doc_id = a_doc")
def case_context_window(spark, sf_dir):
    return rec.context_window(_cases(spark, sf_dir), documents(spark, sf_dir))


@query("case_subset", f"{_REC} select {sql.CASE_COLUMNS} from k join pub pa on pa.doc_id = a_doc join pub pb on pb.doc_id = b_doc where a_begin / pa.doc_chars between 0.2 and 0.8 and a_end - a_begin between 50 and 5000 and pa.pub_year between 1900 and 2000 and pb.pub_year between 1900 and 2000 and contains(pa.disciplines, 'disc0') and contains(pb.disciplines, 'disc0')")
def case_subset(spark, sf_dir):
    return rec.subset(_records(spark, sf_dir), (0.2, 0.8), (50, 5000), (1900, 2000), ["disc0"]).select(*CASES)


_DUP = f"{sql.cases()}, dup as (select distinct a_doc, b_doc from k join d da on da.doc_id = a_doc join d db on db.doc_id = b_doc where (a_end - a_begin) / length(da.c) > 0.99 and (b_end - b_begin) / length(db.c) > 0.99)"


@query("case_duplicates", f"with {_DUP} select a_doc, b_doc from dup")
def case_duplicates(spark, sf_dir):
    docs = documents(spark, sf_dir)
    return rec.duplicates(_cases(spark, sf_dir), docs)


@query("case_duplicate_groups", f"with recursive {_DUP}, e as (select a_doc as x, b_doc as y from dup union select b_doc, a_doc from dup), r as (select x, x as y from e union select r.x, e.y from r join e on r.y = e.x) select x as doc_id, min(y) as label from r group by 1")
def case_duplicate_groups(spark, sf_dir):
    return rec.groups(rec.duplicates(_cases(spark, sf_dir), documents(spark, sf_dir)))


@query("case_kinds", f"with {sql.cases()}, n as (select a_doc, a_begin, a_end, count(distinct b_doc) as n from k group by 1, 2, 3) select case when n >= 5 then 'boilerplate' when n_seeds / (a_end - a_begin) >= 0.15::double / 8 then 'verbatim' else 'paraphrase' end as kind, count(*) as cases from k join n using (a_doc, a_begin, a_end) group by 1")
def case_kinds(spark, sf_dir):
    return rec.example_kind(_cases(spark, sf_dir)).groupBy("kind").agg(F.count(F.lit(1)).alias("cases"))


_KINDS = f"""{_FULL}, kn as (select a_doc, a_begin, a_end, count(distinct b_doc) as n from k group by 1, 2, 3),
kk as (select fk.*, case when n >= 5 then 'boilerplate' when regexp_matches(substr(text, greatest(0, a_full_begin - 1) + 1, a_full_end + 1 - greatest(0, a_full_begin - 1)), '["\u201c\u201d\u201e\u00ab\u00bb]') then 'quotation' when n_seeds / (a_end - a_begin) >= 0.15::double / 8 then 'verbatim' else 'paraphrase' end as kind
  from fk join kn using (a_doc, a_begin, a_end) join documents on documents.doc_id = a_doc)"""


def _kinds(spark, sf_dir) -> DataFrame:
    full = rec.hydrate_full(_cases(spark, sf_dir), documents(spark, sf_dir))
    return rec.example_kind(full, quotation=rec.quoted(full))


@query("case_kinds_four", f"with {_KINDS} select kind, count(*) as cases from kk group by 1")
def case_kinds_four(spark, sf_dir):
    """Boilerplate, quotation, verbatim and paraphrase by yield."""
    return _kinds(spark, sf_dir).groupBy("kind").agg(F.count(F.lit(1)).alias("cases"))


@query("case_examples", f"with {_KINDS}, top as (select *, row_number() over (partition by kind order by a_end - a_begin desc, a_doc, b_doc, a_begin, b_begin) as rank from kk) select kind, rank, a_doc, b_doc, a_begin, b_begin, substr(c, greatest(0, a_begin - 40) + 1, a_begin - greatest(0, a_begin - 40)) as before, substr(c, a_begin + 1, least(80, a_end - a_begin)) as passage, substr(c, a_end + 1, 40) as after from top join d on d.doc_id = a_doc where rank <= 3")
def case_examples(spark, sf_dir):
    """The three longest cases of each kind with their context."""
    return rec.examples(_kinds(spark, sf_dir), documents(spark, sf_dir))


@query("gram_df_top", f"with {sql.grams()} select g, count(distinct doc_id) as docs from g group by 1 order by 2 desc, 1 limit 20")
def gram_df_top(spark, sf_dir):
    gs = al.grams(nz.worded(documents(spark, sf_dir)), family="text")
    return gs.groupBy("g").agg(F.count_distinct("doc_id").alias("docs")).orderBy(F.col("docs").desc(), "g").limit(20)


_DISC = f"""{_REC}, flat as (select distinct p.doc_id, discipline from pub0 p join dim on dim.field = p.field), p as (select discipline, count(distinct doc_id) as publications from flat group by 1),
ends as (select row_number() over () as id, a_doc, b_doc from k), e2 as (select id, unnest([a_doc, b_doc]) as doc_id from ends), c as (select discipline, count(distinct id) as cases from e2 join flat using (doc_id) group by 1),
disc as (select discipline, coalesce(cases, 0) as cases, publications, round(coalesce(cases, 0) / nullif((select count(*) from k), 0), 6) as case_share, round(publications / (select count(*) from pub), 6) as publication_share from p left join c using (discipline))"""


def _disciplines(spark, sf_dir):
    return rec.by_discipline(_block_cases(spark, sf_dir, columns=al.PAIR), rec.publications(_full(spark, sf_dir), rec.taxonomy(spark)))


@query("discipline_table", f"{_DISC} select * from disc")
def discipline_table(spark, sf_dir):
    return _disciplines(spark, sf_dir)


@query("discipline_shift", f"{_DISC} select discipline, round(case_share - publication_share, 5) as shift from disc")
def discipline_shift(spark, sf_dir):
    return _disciplines(spark, sf_dir).select("discipline", F.round(F.col("case_share") - F.col("publication_share"), 5).alias("shift"))


@query("discipline_matrix", f"{_DISC}, m as (select fa.discipline as a, fb.discipline as b from k join flat fa on fa.doc_id = a_doc join flat fb on fb.doc_id = b_doc) select a as discipline, " + ", ".join(f"count(*) filter (b = 'disc{i}') as disc{i}" for i in range(4)) + " from m group by 1")
def discipline_matrix(spark, sf_dir):
    pubs = rec.publications(_full(spark, sf_dir), rec.taxonomy(spark))
    records = rec.by_both(_block_cases(spark, sf_dir, columns=al.PAIR), pubs).select("cases", F.explode("a_disciplines").alias("discipline"), "b_disciplines").withColumn("b", F.explode("b_disciplines"))
    return records.groupBy("discipline").pivot("b", [f"disc{i}" for i in range(4)]).sum("cases").na.fill(0)


_NORM = f"{sql.cases()}, e as (select a_doc as doc_id, a_begin as b, a_end as e from k union all select b_doc, b_begin, b_end from k), z as (select (e.e - e.b) / length(d.c) as length, e.b / length(d.c) as start from e join d using (doc_id))"


@query("cdf_length", f"with {_NORM}, p as (select b::double as bound from (values (0.01), (0.2), (0.99), (1.0)) v(b)) select bound, round(count(*) filter (length <= bound) / count(*), 6) as share from z, p group by 1")
def cdf_length(spark, sf_dir):
    z = rec.normal_spans(_cases(spark, sf_dir), documents(spark, sf_dir))
    sums = z.agg(F.count(F.lit(1)).alias("n"), *(F.count_if(F.col("length") <= x).alias(f"c{i}") for i, x in enumerate((0.01, 0.2, 0.99, 1.0))))
    rows = sums.select(F.explode(F.array(*(F.struct(F.lit(x).alias("bound"), F.round(F.col(f"c{i}") / F.col("n"), 6).alias("share")) for i, x in enumerate((0.01, 0.2, 0.99, 1.0))))).alias("r"))
    return rows.select("r.bound", "r.share")


@query("cdf_position", f"with {_NORM}, b as (select least(19, floor(start * 20))::bigint as bin, count(*) as n from z group by 1) select bin, n, round(sum(n) over (order by bin) / sum(n) over (), 6) as cdf from b")
def cdf_position(spark, sf_dir):
    from pyspark.sql import Window

    z = rec.normal_spans(_cases(spark, sf_dir), documents(spark, sf_dir))
    b = z.groupBy(F.least(F.lit(19), F.floor(F.col("start") * 20)).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    return b.select("bin", "n", F.round(F.sum("n").over(Window.orderBy("bin")) / F.sum("n").over(Window.partitionBy()), 6).alias("cdf"))


@query("tail_share", f"with {_NORM} select count(*) as spans, round(count(*) filter (start >= 0.95) / count(*), 6) as last_5_percent from z")
def tail_share(spark, sf_dir):
    z = rec.normal_spans(_block_cases(spark, sf_dir, columns=[*al.PAIR, *al.SPAN]), documents(spark, sf_dir))
    return z.agg(F.count(F.lit(1)).alias("spans"), F.round(F.count_if(F.col("start") >= 0.95) / F.count(F.lit(1)), 6).alias("last_5_percent"))


@query("coverage_summary", f"with {sql.FIELDS} select min(pub_year) as first_year, max(pub_year) as last_year, (select count(distinct field) from pub0) as fields, (select count(distinct area) from dim join pub0 using (field)) as areas, (select count(distinct discipline) from dim join pub0 using (field)) as disciplines from pub")
def coverage_summary(spark, sf_dir):
    pubs = rec.publications(_full(spark, sf_dir), rec.taxonomy(spark))
    kinds = [F.size(F.collect_set(c)).alias(c) for c in ("fields", "areas", "disciplines")]
    flat = pubs.select(F.explode("fields").alias("fields"), "areas", "disciplines").withColumn("areas", F.explode("areas")).withColumn("disciplines", F.explode("disciplines"))
    return pubs.agg(F.min("pub_year").alias("first_year"), F.max("pub_year").alias("last_year")).join(flat.agg(*kinds), F.lit(True))


@query("yield_summary", f"with {sql.cases()}, u as (select a_doc as x from k union select b_doc from k) select (select count(*) from k) as cases, (select count(*) from documents) as publications, (select count(*) from u) as with_case, (select count(*) from documents) - (select count(*) from u) as without_case, round((select count(*) from k) / (select count(*) from documents), 6) as cases_per_publication")
def yield_summary(spark, sf_dir):
    docs = documents(spark, sf_dir)
    used = _block_cases(spark, sf_dir, columns=al.PAIR).select(F.explode(F.array("a_doc", "b_doc")).alias("x")).groupBy("x").agg(F.count(F.lit(1)).alias("n"))
    # A case is counted at both of its ends, so the cases are made once for both numbers.
    used = used.agg(F.count(F.lit(1)).alias("with_case"), (F.coalesce(F.sum("n"), F.lit(0)) / 2).cast("bigint").alias("cases"))
    row = used.join(docs.agg(F.count(F.lit(1)).alias("publications")), F.lit(True))
    return row.select("cases", "publications", "with_case", (F.col("publications") - F.col("with_case")).alias("without_case"), F.round(F.col("cases") / F.col("publications"), 6).alias("cases_per_publication"))


@query("year_gap", f"{_REC} select abs(pa.pub_year - pb.pub_year) // 10 as decades, count(*) as cases from k join pub pa on pa.doc_id = a_doc join pub pb on pb.doc_id = b_doc where pa.pub_year is not null and pb.pub_year is not null group by 1")
def year_gap(spark, sf_dir):
    gap = F.floor(F.abs(F.col("a_year") - F.col("b_year")) / 10)
    pubs = rec.publications(_full(spark, sf_dir), rec.taxonomy(spark)).select("doc_id", F.col("pub_year").alias("year"))
    return rec.both_sides(_block_cases(spark, sf_dir, columns=al.PAIR), pubs.where("year is not null")).groupBy(gap.alias("decades")).agg(F.count(F.lit(1)).alias("cases"))


@query("base_contains", f"with {sql.words()}, b as (select item_id, trim(regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g')) as t from benchmark) select item_id, doc_id from b join d on contains(d.c, b.t) where t <> ''")
def base_contains(spark, sf_dir):
    return sim.contained(load(spark, sf_dir, "benchmark"), documents(spark, sf_dir))


@query("bench_passage_recall", f"""with it as (with {sql.grams(source='benchmark', key='item_id')} select * from g), dg as (with {sql.grams()} select * from g),
b as (select item_id, trim(regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g')) as t from benchmark), dd as (select doc_id, trim(regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g')) as c from documents),
wanted as (select item_id, doc_id, length(t) as n from b join dd on contains(c, t) where len(string_split(t, ' ')) >= 8),
s as (select i.doc_id as a_doc, dg.doc_id as b_doc, i.pos as a_pos, dg.pos as b_pos, i."begin" as a_begin, i."end" as a_end, dg."begin" as b_begin, dg."end" as b_end from it i join dg on i.g = dg.g), {sql.islands()},
whole as (select distinct a_doc as item_id, b_doc as doc_id from k join wanted on a_doc = item_id and b_doc = wanted.doc_id where a_begin = 0 and a_end = n)
select (select count(*) from wanted) as planted, (select count(*) from whole) as found, round((select count(*) from whole) / nullif((select count(*) from wanted), 0), 6) as recall""")
def bench_passage_recall(spark, sf_dir):
    """Of the items that a document contains whole, those that one case of alignment covers from end to end."""
    items, docs = load(spark, sf_dir, "benchmark"), documents(spark, sf_dir)
    texts = items.select("item_id", F.length(nz.clean(F.col("text"))).alias("_n"))
    wanted = io.stored(sim.contained(items, docs, 8), "wanted")
    cases = al.merge(al.runs(al.seeds_between(al.grams(nz.worded(items, "item_id")), al.grams(nz.worded(docs)))))
    whole = cases.join(texts, F.col("a_doc") == F.col("item_id")).where("a_begin = 0 and a_end = _n").select("item_id", F.col("b_doc").alias("doc_id")).distinct()
    hits = wanted.join(whole.withColumn("hit", F.lit(1)), ["item_id", "doc_id"], "left")
    return hits.agg(F.count(F.lit(1)).alias("planted"), F.count("hit").alias("found"), F.round(F.count("hit") / F.nullif(F.count(F.lit(1)), F.lit(0)), 6).alias("recall"))


_CONV = "(select conv_id, string_agg(text, chr(10) order by turn) as text from conversations group by conv_id)"


@query("conv_cases", f"with {sql.cases(source=_CONV, key='conv_id')} select {sql.CASE_COLUMNS} from k")
def conv_cases(spark, sf_dir):
    turns = load(spark, sf_dir, "conversations")
    whole = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda t: t["text"]), "\n")
    return al.cases_of(turns.groupBy(F.col("conv_id").alias("doc_id")).agg(whole.alias("text"))).select(*CASES)


_PAGES = r"""(with a as (select page_id, regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<!--.*?-->|<head.*?</head>', ' ', 'g'),
    '(?is)<div class="ad">.*?</div>', ' ', 'g'), '(?is)<[^>]*>', ' ', 'g') as h from pages)
select page_id, trim(regexp_replace(replace(replace(replace(replace(replace(replace(h, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '[\x20\n\r\t]+', ' ', 'g')) as text from a)"""


@query("page_cases", f"with {sql.cases(source=_PAGES, key='page_id')} select {sql.CASE_COLUMNS} from k")
def page_cases(spark, sf_dir):
    pages = nz.html_main_text(load(spark, sf_dir, "pages"))
    return al.cases_of(pages.select(F.col("page_id").alias("doc_id"), F.col("body").alias("text"))).select(*CASES)


#: The text that each profile hands on, and whether all but letters goes then.
_PROFILES = {
    "none": ("documents", False),
    "special characters": ("documents", True),
    "full": ("(select doc_id, regexp_replace(regexp_replace(text, '" + nz.KINDS["contact"] + "', ' ', 'g'), '" + nz.KINDS["number"] + "', ' ', 'g') as text from documents)", True),
}


@query("cleaning_ablation", "with " + ", ".join(f"p{i} as (with {sql.cases(source=src, letters=letters)} select '{name}' as profile, (select count(*) from s) as seeds, count(*) as cases from k)" for i, (name, (src, letters)) in enumerate(_PROFILES.items())) + " select * from p0 union all select * from p1 union all select * from p2")
def cleaning_ablation(spark, sf_dir):
    """Seeds and cases without cleaning, with letters only, and with contacts and numbers cut out before."""
    docs, out = documents(spark, sf_dir), None
    for name, kinds in (("none", None), ("special characters", []), ("full", ["contact", "number"])):
        rows = nz.worded(docs, letters=False) if kinds is None else nz.worded(docs.withColumn("text", nz.strip_spans(F.col("text"), kinds)))
        cases = al.merge(al.runs_of_grams(al.grams(rows, context=True))).agg(F.count(F.lit(1)).alias("cases"), F.sum("n_seeds").alias("seeds"))
        row = cases.select(F.lit(name).alias("profile"), "seeds", "cases")
        out = row if out is None else out.unionAll(row)
    return out
