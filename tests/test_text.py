"""Worked examples, invariants and brute force for cleaning, retrieval and alignment."""

import re
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from textreuse.operators import alignment as al
from textreuse.operators import evaluation as ev
from textreuse.operators import normalize as nz
from textreuse.operators import records as rec
from textreuse.operators import retrieval as sr
from textreuse.sources import io
from textreuse.sources.catalog import documents


def frame(spark, *texts):
    return spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")


def words(prefix, n):
    """n different words of letters only."""
    return [prefix + "".join(chr(97 + int(c)) for c in str(i)) for i in range(n)]


def cases(spark, *texts, **how):
    return sorted(tuple(r) for r in al.cases_of(frame(spark, *texts), **how).collect())


# Grams and seeds


@pytest.mark.parametrize(("n", "k", "count"), [(4, 3, 6), (4, 0, 2), (10, 9, 0)])
def test_nine_word_sentence(spark, n, k, count):
    docs = frame(spark, "one two three four five six seven eight nine.")
    assert al.grams(nz.worded(docs), n, k).count() == count


def test_eight_shared_words_are_a_case_and_seven_are_none(spark):
    shared = " ".join(words("s", 8))
    got = cases(spark, f"aa {shared} bb", f"{shared} cc")
    assert len(got) == 1 and got[0][6] == 1 and got[0][2:6] == (3, 3 + len(shared), 0, len(shared))
    assert cases(spark, f"aa {' '.join(words('s', 7))} bb", " ".join(words("s", 7)) + " cc") == []


@pytest.mark.parametrize(("gap", "count"), [(250, 1), (251, 2)])
def test_gap_at_the_limit(spark, gap, count):
    one, two = " ".join(words("p", 9)), " ".join(words("q", 9))
    # The gap runs from the end of one block to the begin of the next: two spaces and the foreign text.
    a, b = f"{one} {'x' * (gap - 2)} {two}", f"{one} {'y' * (gap - 2)} {two}"
    assert len(cases(spark, a, b)) == count
    assert len(cases(spark, a, f"{one} {two}")) == count


def test_blocks_far_apart_in_the_source(spark):
    one, two, foreign = " ".join(words("p", 9)), " ".join(words("q", 9)), " ".join(words("f", 80))
    docs = frame(spark, f"{one} {foreign} {two}", f"{one} {two}")
    runs = al.runs(al.seeds_by_index(al.grams(nz.worded(docs))))
    assert al.components(runs, near="both").count() == 2 and al.components(runs, near="either").count() == 1


def test_swapped_blocks(spark):
    one, two = " ".join(words("p", 9)), " ".join(words("q", 9))
    docs = frame(spark, f"{one} zz {two}", f"{two} yy {one}")
    runs = al.runs(al.seeds_by_index(al.grams(nz.worded(docs))))
    assert al.merge(runs).count() == 1 and al.chains(runs).count() == 2


def test_known_limits(spark):
    text = words("w", 64)
    changed = [w if i % 8 else f"new{w}" for i, w in enumerate(text)]
    assert cases(spark, " ".join(text), " ".join(changed)) == []
    assert cases(spark, "alpha misspeling beta", "gamma misspeling delta") == []


def test_seed_plans_agree(spark, sf):
    gs = al.grams(nz.worded(documents(spark, sf)))
    plain, pruned = (sorted(map(tuple, al.seeds_by_index(gs, prune=p).collect())) for p in (False, True))
    assert plain == pruned
    rows = [(r["doc_id"], r["pos"], r["g"]) for r in gs.collect()]
    where = defaultdict(list)
    for d, p, g in rows:
        where[g].append((d, p))
    brute = sorted((a, b, p, q) for v in where.values() for a, p in v for b, q in v if a < b)
    assert [s[:4] for s in plain] == brute


def test_runs_give_the_same_cases_and_merging_ends(spark, sf):
    seeds = al.seeds_by_index(al.grams(nz.worded(documents(spark, sf))), prune=True).cache()
    by_run, by_seed = (sorted(map(tuple, al.merge(x).collect())) for x in (al.runs(seeds), seeds))
    assert by_run == by_seed
    assert sum(c[6] for c in by_run) == seeds.count()
    assert sorted(map(tuple, al.merge(al.runs(seeds), rounds=3).collect())) == by_run
    assert al.components(al.runs(seeds)).count() >= len(by_run)


def test_a_document_never_meets_itself_and_offsets_recover_the_text(spark):
    text = "Straße, É déjà-vu — naïve ÑANDÚ und noch mehr Wörter hier"
    docs = frame(spark, text, text)
    got = rec.hydrate(al.cases_of(docs), docs).collect()
    assert len(got) == 1 and got[0]["a_doc"] == 0 and got[0]["a_text"] == got[0]["b_text"] == "straße é déjà vu naïve ñandú und noch mehr wörter hier"


# Cleaning


def test_tokens_of_odd_texts(spark):
    docs = frame(spark, "", None, "123 456", "###", "word", "İstanbul ﬁn éte 😀 x")
    rows = nz.tokens(docs).collect()
    assert {r["doc_id"] for r in rows} == {4, 5}
    clean = {r["doc_id"]: r["c"] for r in docs.select("doc_id", nz.clean(F.col("text")).alias("c")).collect()}
    for r in rows:
        assert clean[r["doc_id"]][r["begin"] : r["end"]] == r["word"]


def test_begins_over_many_chunks(spark):
    text = " ".join(words("w", 1500))
    rows = sorted((r["pos"], r["begin"], r["end"]) for r in nz.tokens(frame(spark, text)).collect())
    assert [(m.start(), m.end()) for m in re.finditer(r"\S+", text)] == [(b, e) for _, b, e in rows]


def test_strip_spans(spark):
    text = "As shown [1, 2-4] and (Smith et al., 1999a), mail a.b@c.org or http://x.y/z from 10.0.0.1 costs 1,234.5 ##%% end\na | b | c\nReferences\nrest"
    strip = lambda *kinds: frame(spark, text).select(nz.strip_spans(F.col("text"), list(kinds)).alias("t")).first()["t"]
    assert "[1" not in strip("citation") and "Smith" not in strip("citation")
    assert "@" not in strip("contact") and "http" not in strip("contact") and "10.0.0.1" not in strip("contact")
    assert "1,234" not in strip("number") and "##" not in strip("junk") and "a | b" not in strip("table") and "rest" not in strip("bibliography")


def test_two_versions_map(spark):
    text = "One (2) Two—three! É"
    r = nz.two_versions(frame(spark, text)).first()
    ws = r["clean_text"].split(" ")
    assert [text[b : b + len(w)].lower() for w, b in zip(ws, r["clean_to_full"], strict=True)] == ws


# Retrieval


def test_bounds():
    assert [sr.min_shared_words(*a) for a in ((20, 5), (50, 10))] == [7, 10]
    assert [sr.min_shared_words(*a, model="containment") for a in ((20, 5), (50, 10))] == [4, 5]
    assert sr.choose_m(0.1) == 10 and sr.choose_m(0.1, 0.99) == 44 and abs(sr.collision_probability(0.1, 10) - 0.6513) < 1e-4


@pytest.mark.parametrize("family", ["xx", "md5"])
def test_candidates(spark, family):
    a, b = " ".join(words("a", 30)), " ".join(words("b", 30))
    docs = frame(spark, a, a, b, "", "lone")
    pairs = sr.candidates(sr.postings(sr.sketched(docs, 50, 5, family))).collect()
    assert [tuple(p) for p in pairs] == [(0, 1)]


def test_more_hashes_lose_nothing_and_caps_add_nothing(spark, sf):
    docs = documents(spark, sf)
    few, many = (set(map(tuple, sr.candidates(sr.postings(sr.sketched(docs, 50, m))).collect())) for m in (5, 10))
    assert few <= many
    posts = sr.postings(sr.sketched(docs))
    assert set(map(tuple, sr.candidates(sr.capped(posts, 20)).collect())) <= many
    assert set(tuple(r)[:2] for r in sr.candidates(posts, 2).collect()) <= many


def test_collision_rate_follows_the_real_formula(spark):
    texts = []
    for i in range(300):
        tag = f"{chr(97 + i % 26)}{chr(97 + i // 26)}"
        base = words(f"w{tag}", 40)
        texts += [" ".join(base), " ".join(base[:10] + words(f"z{tag}", 30))]
    pairs = {tuple(r) for r in sr.candidates(sr.postings(sr.sketched(frame(spark, *texts), 50, 5))).collect()}
    rate = sum((2 * i, 2 * i + 1) in pairs for i in range(300)) / 300
    assert abs(rate - sr.collision_probability(10 / 70, 5)) < 0.1


# Measures


def spans(spark, rows):
    return spark.createDataFrame(rows, "pair_id long, a_begin int, a_end int, b_begin int, b_end int")


def test_interval_scoring(spark):
    truth = spark.createDataFrame([(1, "x", 10, 30, None, None), (2, "x", None, None, None, None)], "pair_id long, strategy string, a_begin int, a_end int, b_begin int, b_end int")
    found = spans(spark, [(1, 0, 20, None, None), (1, 15, 25, None, None)])
    got = {r["pair_id"]: r for r in ev.counts(truth, found).collect()}
    assert (got[1]["both"], got[1]["detected"], got[1]["wanted"]) == (15, 25, 20) and got[2]["detected"] == 0
    s = ev.scores(ev.counts(truth, found), ["strategy"]).first()
    assert (s["precision"], s["recall"]) == (15 / 25, 15 / 20)
    nothing = ev.scores(ev.counts(truth.where("pair_id = 2"), found.limit(0)), ["strategy"]).first()
    assert (nothing["precision"], nothing["recall"], nothing["f05"]) == (1, 1, 1)
    wrong = ev.scores(ev.counts(truth.where("pair_id = 2"), spans(spark, [(2, 1, 5, 1, 5)])), ["strategy"]).first()
    assert wrong["precision"] == 0 and wrong["f05"] == 0


def test_printed_scores_recompute(spark):
    rows = [(p, r, f) for _, _, p, r, f, _, _ in ev.PUBLISHED] + [row[2:] for row in ev.PUBLISHED_STRATA]
    assert len(rows) == 37
    for p, r, f in rows:
        assert abs(1.25 * p * r / (0.25 * p + r) - f) <= 0.01


def test_strata_order(spark, sf):
    items = spark.read.parquet(f"{sf}/benchmark.parquet")
    corpus = ev.labelled_corpus(documents(spark, sf), items, pairs=100).cache()
    for r in corpus.where("a_begin is not null and strategy = 'verbatim'").collect():
        assert " ".join(r["a_words"])[r["a_begin"] : r["a_end"]] == " ".join(r["b_words"])
    s = {r["strategy"]: r for r in ev.scores(ev.counts(corpus, ev.detect(corpus)), ["strategy"]).collect()}
    assert s["verbatim"]["recall"] == 1 and s["none"]["f05"] == 1
    assert all(s[k]["recall"] < 0.9 for k in ("random", "translation", "summary"))
    local = ev.scores(ev.counts(corpus, ev.local_alignment(corpus)), ["strategy"]).where("strategy = 'verbatim'").first()
    assert local["recall"] > 0.99 and local["precision"] > 0.95


# Records


def test_no_verdict_and_null_years(spark, sf):
    full = spark.read.parquet(f"{sf}/documents.parquet")
    records = rec.with_context(al.cases_of(documents(spark, sf)), rec.publications(full, rec.taxonomy(spark)))
    assert not {c for c in records.columns if re.search("direction|verdict|source_of|plagiar", c)}
    old, rest = rec.subset(records, years=(1800, 1900)), rec.subset(records, years=(1901, 2100))
    assert old.where("a_year is null").count() == 0 and old.count() + rest.count() < records.count()


def test_consensus(spark):
    votes = [("i", v) for v in "aaa"] + [("j", v) for v in "aab"] + [("k", v) for v in "abc"]
    got = {r["item"]: (r["value"], r["agreed"], r["conflict"]) for r in rec.consensus(spark.createDataFrame(votes, "item string, vote string")).collect()}
    assert got == {"i": ("a", True, False), "j": ("a", False, False), "k": ("a", False, True)}


def test_groups_of_long_chains(spark):
    chain = [(i, i + 1) for i in range(1, 60)]
    zigzag = [(100 + (7 * i) % 50, 100 + (7 * (i + 1)) % 50) for i in range(49)]
    pairs = [*chain, *zigzag, (300, 301), (301, 300), (400, 400)]
    got = {r["doc_id"]: r["label"] for r in rec.groups(spark.createDataFrame(pairs, "a_doc long, b_doc long")).collect()}
    assert got == {i: 1 for i in range(1, 61)} | {i: 100 for i in range(100, 150)} | {300: 300, 301: 300}
    assert rec.groups(spark.createDataFrame([], "a_doc long, b_doc long")).count() == 0


def test_jsonl_with_a_corrupt_line_and_a_missing_key(spark, tmp_path):
    (tmp_path / "x.json").write_text('{"doc_id": 1, "lang": "en"}\nnot json\n{"doc_id": 2}\n')
    schema = spark.createDataFrame([], "doc_id long, lang string").schema
    rows = io.read_jsonl(spark, f"file://{tmp_path}", schema).collect()
    assert sorted((r["doc_id"] or 0, r["lang"] or "", r[io.CORRUPT] or "") for r in rows) == [(0, "", "not json"), (1, "en", ""), (2, "", "")]


# Plans


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plan_of_the_flagship(spark, sf):
    text = plan(al.cases_of(documents(spark, sf)))
    assert "Python" not in text and "Pandas" not in text and "CartesianProduct" not in text and "BroadcastNestedLoop" not in text
    assert re.search(r"ReadSchema: struct<doc_id:bigint,text:string>", text)
