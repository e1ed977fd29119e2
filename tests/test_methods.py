"""Retrieval by blocks, orders of joins, fixpoints, exact baselines, full-text locators and the hosted corpus."""

from collections import Counter
from types import SimpleNamespace

import numpy as np
import pytest
from pyspark.sql import functions as F

from textreuse import experiments, workloads  # noqa: F401  they register their queries
from textreuse.operators import alignment as al
from textreuse.operators import evaluation as ev
from textreuse.operators import exhaustive as ex
from textreuse.operators import normalize as nz
from textreuse.operators import records as rec
from textreuse.operators import retrieval as sr
from textreuse.plans import choose
from textreuse.registry import ORACLES, QUERIES
from textreuse.sources import io
from textreuse.sources.catalog import documents


def rows_of(df):
    return Counter(map(tuple, df.collect()))


@pytest.mark.parametrize("blocks", [1, 2, 7])
def test_candidates_by_blocks_equal_those_by_join(spark, blocks):
    rng = np.random.default_rng(1)
    posts = [(int(d) * 31 - 400, int(s), int(h)) for d in range(150) for s in range(4) for h in {rng.integers(0, 60), 7 if d % 2 else 8}]
    posts += [(99_999, 0, 123_456)]
    df = spark.createDataFrame(posts, "doc_id long, slot int, hash long").distinct()
    by_join, by_blocks = rows_of(sr.candidates_by_join(df)), rows_of(sr.candidates_by_blocks(df, blocks))
    assert by_blocks == by_join and max(by_blocks.values()) == 1 and rows_of(sr.candidates(df)) == by_join
    assert sr.candidates_by_blocks(df.limit(0), blocks).count() == 0 and sr.candidates(df.limit(0)).count() == 0


@pytest.mark.parametrize("how", [{}, {"block_docs": 60}, {"block_postings": 150, "bitmap_bytes": 64}])
def test_candidates_are_counted_without_a_row_for_a_pair(spark, how):
    rng = np.random.default_rng(3)
    posts = [(int(d) * 31 - 400, int(s), int(h)) for d in range(200) for s in range(4) for h in {rng.integers(0, 60), 7 if d % 2 else 8}]
    posts += [(99_999, 0, 123_456), (None, 0, 7), (None, 1, 8)]
    df = spark.createDataFrame(posts, "doc_id long, slot int, hash long").distinct()
    rare = df.where("hash not in (7, 8)")
    for some in (df, rare, df.limit(0)):
        found = sr.count_candidates(some, **how)
        assert [r["candidates"] for r in found.collect()] == [sr.candidates_by_join(some).count()]
        assert found.columns == ["candidates"] and "a_doc" not in found._jdf.queryExecution().toString()


def test_pruning_lists_no_pair(spark, sf, monkeypatch):
    monkeypatch.setattr(sr, "candidates", lambda *_: pytest.fail("pairs are listed"))
    row = workloads.sr_pruning(spark, sf).first()
    monkeypatch.undo()
    assert row["docs"] == 200 and row["candidates"] == QUERIES["sr_candidates"](spark, sf).count()


def read_tables(df):
    return {f.rsplit("/", 2)[-1] if f.endswith(".parquet") else f.rsplit("/", 2)[-2] for f in df.inputFiles()}


def equal_to_sql(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    db = duckdb.connect()
    for t in ("documents", "labels"):
        db.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = QUERIES[name](spark, sf)
    got = db.execute(ORACLES[name])
    names = [d[0] for d in got.description]
    assert sorted(names) == sorted(df.columns)
    want = Counter(got.fetchall())
    assert rows_of(df.select(*names)) == want and want
    return df


def test_bounds_are_those_of_the_passages_of_a_table(spark, sf):
    df = equal_to_sql(spark, sf, "minhash_bound_table")
    assert read_tables(df) == {"documents.parquet"}


@pytest.mark.parametrize("name", ["published_fbeta_check", "published_rank", "published_subquadratic_low", "sqlfn_fbeta"])
def test_scores_are_those_of_rules_on_given_tables(spark, sf, name):
    assert {"documents.parquet", "labels.parquet"} <= read_tables(equal_to_sql(spark, sf, name))


def test_candidates_of_a_document_list_no_other_pair(spark, sf, monkeypatch):
    pairs = [tuple(r) for r in QUERIES["sr_candidates"](spark, sf).collect()]
    monkeypatch.setattr(sr, "candidates", lambda *_: pytest.fail("all pairs are listed"))
    got = workloads.sr_candidates_of_doc(spark, sf)
    want = Counter((b,) if a == 0 else (a,) for a, b in pairs if 0 in (a, b))
    assert want and rows_of(got) == want
    posts = workloads._posts(spark, sf)
    assert rows_of(sr.candidates_of(posts, 117)) == Counter((b,) if a == 117 else (a,) for a, b in pairs if 117 in (a, b))
    assert sr.candidates_of(posts, -1).count() == 0


def test_listing_takes_the_way_that_moves_less(spark):
    hot = spark.range(2000).select(F.col("id").alias("doc_id"), F.lit(0).alias("slot"), F.lit(5).cast("long").alias("hash"))
    rare = spark.range(2000).select(F.col("id").alias("doc_id"), F.lit(0).alias("slot"), F.expr("id div 2").alias("hash"))
    assert sr.listing(hot)["blocks"] > 0 and sr.listing(rare)["blocks"] == 0


def test_affine_family_estimates_similarity(spark):
    rng = np.random.default_rng(2)
    word = lambda k: f"w{k}"
    rows = []
    for p in range(60):
        shared = [word(x) for x in rng.integers(0, 10**6, 30)]
        rows += [(2 * p + s, 0, shared + [word(x) for x in rng.integers(0, 10**6, 10)]) for s in (0, 1)]
    sig = {r["doc_id"]: r["sig"] for r in sr.minhash(spark.createDataFrame(rows, "doc_id long, passage_no int, words array<string>"), 40, "affine").collect()}
    agree = np.mean([np.mean(np.array(sig[2 * p]) == np.array(sig[2 * p + 1])) for p in range(60)])
    assert abs(agree - 0.6) < 0.06


def test_sketch_of_numbers_is_the_minimum_of_each_function(spark):
    passages = spark.createDataFrame([(1, 0, ["a", "b", "a"]), (1, 1, ["c"]), (2, 0, ["b"])], "doc_id long, passage_no int, words array<string>")
    want = {(d, p): [min(spark.range(1).select(F.xxhash64(F.lit(i), F.lit(w))).first()[0] for w in ws) for i in range(3)] for d, p, ws in passages.collect()}
    assert {(r["doc_id"], r["passage_no"]): r["sig"] for r in sr.minhash(passages, 3).collect()} == want


def test_frequent_words_leave_the_bags(spark):
    rows = spark.createDataFrame([(i, ["common", f"w{i}", "half" if i % 2 else "x"]) for i in range(10)], "doc_id long, words array<string>")
    assert all("common" not in r["words"] and f"w{r['doc_id']}" in r["words"] for r in sr.without_frequent(rows, 0.6).collect())
    assert rows_of(sr.without_frequent(rows, 1.0).select("doc_id")) == rows_of(rows.select("doc_id"))


def test_both_orders_of_joins_find_the_same_seeds(spark, sf):
    docs = documents(spark, sf)
    gs, posts = al.grams(nz.worded(docs)), sr.postings(sr.sketched(docs))
    pairs = sr.candidates(posts)
    by = {plan: rows_of(al.seeds_by_candidates(pairs, gs, plan)) for plan in ("index", "candidates")}
    assert by["index"] == by["candidates"] == rows_of(choose.planned_seeds(posts, gs)) and by["index"]


@pytest.mark.parametrize("prune", [True, False])
def test_runs_of_grams_equal_runs_of_seeds(spark, prune):
    rng = np.random.default_rng(8)
    texts = [" ".join(rng.choice(["a", "b", "c"], rng.integers(0, 60))) for _ in range(8)] + ["x " * 40, "y x x x x x x x x x x z " * 3, "", "one two"]
    rows = nz.worded(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    for n in (3, 8):
        pick = lambda df: rows_of(df.select("a_doc", "b_doc", *al.SPAN, "n_seeds"))
        want = pick(al.runs(al.seeds_by_index(al.grams(rows, n))))
        assert want and pick(al.runs_of_grams(al.grams(rows, n, context=True), prune)) == want


def brute_islands(spans, delta, rounds=None):
    def split(group, s):
        out, far = [], None
        for x in sorted(group, key=lambda x: (x[s], x[s + 1])):
            if far is None or x[s] - far > delta:
                out.append([])
                far = x[s + 1]
            out[-1].append(x)
            far = max(far, x[s + 1])
        return out

    groups, done = [spans], 0
    while rounds is None or done < rounds:
        now = [part for g in groups for half in split(g, 0) for part in split(half, 2)]
        done += 1
        if len(now) == len(groups) and rounds is None:
            break
        groups = now
    return Counter((min(x[0] for x in g), max(x[1] for x in g), min(x[2] for x in g), max(x[3] for x in g), len(g)) for g in groups)


def test_islands_to_a_fixpoint(spark):
    rng = np.random.default_rng(3)
    differs = False
    for _ in range(4):
        spans = [(int(a), int(a) + 5, int(b), int(b) + 5) for a, b in rng.integers(0, 900, (60, 2))]
        df = spark.createDataFrame([(1, 2, *s) for s in spans], "a_doc long, b_doc long, a_begin int, a_end int, b_begin int, b_end int")
        got = Counter(tuple(r) for r in al.merge(df, 25, rounds=None).select("a_begin", "a_end", "b_begin", "b_end", "n_seeds").collect())
        assert got == brute_islands(spans, 25)
        differs |= got != brute_islands(spans, 25, 1)
    assert differs


@pytest.mark.parametrize("near", ["both", "either"])
def test_components_treat_many_pairs_at_once(spark, near):
    rng = np.random.default_rng(8)
    pairs = [(int(a), int(a) + 1 + int(b), n) for a in range(40) for b, n in ((0, 1), (1, int(rng.integers(1, 9))))] + [(7, 70, 60)]
    rows = [(a, b, x, x + int(rng.integers(3, 9)), y, y + int(rng.integers(3, 9)), 1 + x % 4) for a, b, n in pairs for x, y in rng.integers(0, 90, (n, 2)).tolist()]
    df = spark.createDataFrame(rows, "a_doc long, b_doc long, a_begin int, a_end int, b_begin int, b_end int, n_seeds long")
    # One pair at a time is the plain meaning, which brute force checks below.
    want = Counter()
    for a, b, _ in pairs:
        alone = df.where((F.col("a_doc") == a) & (F.col("b_doc") == b)).coalesce(1) if (a, b) in {(7, 70), (7, 8), (7, 9), (3, 5)} else None
        want += rows_of(al.components(alone, 6, near)) if alone is not None else Counter()
    for size in (1, 17, 200_000):
        made = al.components(df, 6, near, batch_rows=size)
        got = rows_of(made)
        assert sum(r[6] * k for r, k in got.items()) == sum(r[6] for r in rows)
        assert Counter({r: k for r, k in got.items() if r[:2] in {(7, 70), (7, 8), (7, 9), (3, 5)}}) == want
        assert "FlatMapGroupsInPandas" not in choose.describe(made)


def test_runs_are_dealt_by_pair_once(spark, sf):
    runs = workloads._runs(spark, sf)
    exchanges = choose.describe(runs).get("Exchange", 0)
    for made in (al.merge(runs), al.chains(runs), al.components(runs)):
        assert choose.describe(made).get("Exchange", 0) == exchanges


@pytest.mark.parametrize("near", ["both", "either"])
def test_components_match_brute_force(spark, near):
    rng = np.random.default_rng(4)
    spans = [(int(a), int(a) + int(n), int(b), int(b) + int(n)) for a, b, n in rng.integers(1, 400, (50, 3)) // [1, 1, 10]]
    root = list(range(50))
    gap = lambda x, y, s: max(x[s], y[s]) - min(x[s + 1], y[s + 1])
    test = all if near == "both" else any
    for i in range(50):
        for j in range(i):
            if test(gap(spans[i], spans[j], s) <= 6 for s in (0, 2)):
                root = [root[j] if r == root[i] else r for r in root]
    want = Counter()
    for c in set(root):
        g = [x for x, r in zip(spans, root, strict=True) if r == c]
        want[min(x[0] for x in g), max(x[1] for x in g), min(x[2] for x in g), max(x[3] for x in g), len(g)] += 1
    df = spark.createDataFrame([(1, 2, *s, 1) for s in spans], al.CASE)
    assert Counter(tuple(r) for r in al.components(df, 6, near).select("a_begin", "a_end", "b_begin", "b_end", "n_seeds").collect()) == want


def test_passages_by_prefix_equal_exact_ones(spark):
    rng = np.random.default_rng(5)
    rows = [(d, p, [f"w{int(x)}" for x in rng.zipf(1.6, rng.integers(1, 30)) % 60]) for d in range(25) for p in range(2)]
    df = spark.createDataFrame(rows, "doc_id long, passage_no int, words array<string>")
    for j in (0.3, 0.5, 0.8, 1.0):
        pick = lambda out: Counter((*tuple(r)[:4], round(r["jaccard"], 9)) for r in out.collect())
        assert pick(ex.passage_pairs_by_prefix(df, j)) == pick(ex.passage_pairs_exact(df, j))


def test_full_locators_recover_the_uncleaned_passage(spark):
    a = 'Intro 12! "The quick-brown FOX, jumps (over) the lazy dog — twice" he said; more here.'
    b = "Before that: the quick brown fox jumps over the lazy dog twice."
    docs = spark.createDataFrame([(1, a), (2, b)], "doc_id long, text string")
    row = rec.hydrate_full(al.cases_of(docs), docs).first()
    assert row["a_full"] == "The quick-brown FOX, jumps (over) the lazy dog — twice" and row["b_full"] == "the quick brown fox jumps over the lazy dog twice"
    assert row["a_around"] == f'"{row["a_full"]}"' and a[row["a_full_begin"] : row["a_full_end"]] == row["a_full"]
    full = rec.hydrate_full(al.cases_of(docs), docs)
    kinds = rec.example_kind(full, quotation=rec.quoted(full))
    assert [r["kind"] for r in kinds.collect()] == ["quotation"]
    shown = rec.examples(kinds, docs).first()
    assert shown["passage"] == "the quick brown fox jumps over the lazy dog twice" and shown["before"] == "intro " and shown["after"] == " he said more here"


def test_wrong_locators_are_found_whatever_the_length(spark):
    rng = np.random.default_rng(6)
    ws = lambda n: " ".join("w" + "".join(chr(97 + int(c)) for c in rng.integers(0, 26, 5)) for _ in range(n))
    shared = ws(1500)
    cases = [(1, 2, 0, 10, 0, 10, 1, shared, f"{ws(900)} {shared}"), (1, 3, 0, 10, 0, 10, 1, ws(1500), ws(1500)), (1, 4, 0, 5, 0, 5, 1, "one two", "one two")]
    df = spark.createDataFrame(cases, al.CASE + ", a_text string, b_text string")
    assert {r["b_doc"] for r in rec.without_common_gram(df).collect()} == {3, 4}


def test_local_alignment_is_the_best_one(spark):
    rng = np.random.default_rng(7)
    rows, want = [], {}
    for k in range(25):
        a, b = ([f"w{int(x)}" for x in rng.integers(0, 12, n)] for n in rng.integers(5, 60, 2))
        table = np.zeros((len(a) + 1, len(b) + 1), int)
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1, j + 1] = max(0, table[i, j] + (2 if x == y else -1), table[i, j + 1] - 1, table[i + 1, j] - 1)
        rows.append((k, a, b))
        want[k] = int(table.max())

    def score(a, b):  # of a global alignment
        table = np.zeros((len(a) + 1, len(b) + 1), int)
        table[0], table[:, 0] = -np.arange(len(b) + 1), -np.arange(len(a) + 1)
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1, j + 1] = max(table[i, j] + (2 if x == y else -1), table[i, j + 1] - 1, table[i + 1, j] - 1)
        return int(table[-1, -1])

    corpus = spark.createDataFrame(rows, "pair_id long, a_words array<string>, b_words array<string>")
    got = {r["pair_id"]: r for r in ev.local_alignment(corpus, least=1).collect()}
    assert set(got) == {k for k, v in want.items() if v}
    for k, a, b in rows:
        if k in got:
            cut = lambda ws, s: " ".join(ws)[got[k][f"{s}_begin"] : got[k][f"{s}_end"]].split(" ")  # noqa: B023, E731
            assert score(cut(a, "a"), cut(b, "b")) == want[k]


def test_hosted_corpus(spark, sf):
    corpus = ev.hosted_corpus(documents(spark, sf), spark.read.parquet(f"{sf}/benchmark.parquet")).cache()
    kinds = Counter(r["strategy"] for r in corpus.collect())
    assert set(kinds) == set(ev.STRATEGIES) and max(kinds.values()) - min(kinds.values()) <= 6
    for r in corpus.collect():
        a, b = (" ".join(r[f"{s}_words"]) for s in "ab")
        assert (r["a_begin"] is None) == (r["strategy"] == "none")
        if r["strategy"] == "verbatim":
            assert a[r["a_begin"] : r["a_end"]] == b[r["b_begin"] : r["b_end"]]
    s = {r["strategy"]: r for r in ev.scores(ev.counts(corpus, ev.detect(corpus)), ["strategy"]).collect()}
    assert s["none"]["f05"] == 1 and s["verbatim"]["recall"] == 1 and s["verbatim"]["precision"] < 1
    assert all(s[k]["recall"] < s["verbatim"]["recall"] for k in ("random", "translation", "summary"))
    short = {r["strategy"]: r for r in ev.scores(ev.counts(corpus, ev.detect(corpus, 4)), ["strategy"]).collect()}
    assert all(short[k]["precision"] < s[k]["precision"] for k in ev.STRATEGIES)


def test_only_one_machine_may_leave_the_shared_folder_unset():
    def session(master, named=None):
        conf = SimpleNamespace(get=lambda key, default=None: named)
        return SimpleNamespace(sparkContext=SimpleNamespace(getConf=lambda: conf, master=master), conf=conf)

    assert io.shared_folder(session("local")).startswith("file:") and io.shared_folder(session("yarn", "hdfs:///x")) == "hdfs:///x"
    with pytest.raises(RuntimeError):
        io.shared_folder(session("spark://h:7077"))
