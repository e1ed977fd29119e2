"""Runs, components and one-sided seeds by blocks: equal to the plans that shuffle rows of pairs, with only the ends of runs made."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from textreuse import workloads  # noqa: F401  it registers its queries
from textreuse.operators import alignment as al
from textreuse.operators import blocks as bl
from textreuse.operators import normalize as nz
from textreuse.operators import retrieval as sr
from textreuse.registry import QUERIES
from textreuse.sources.catalog import documents


def rows_of(df, names=None):
    return Counter(map(tuple, df.select(*(names or df.columns)).collect()))


@pytest.fixture(scope="module")
def texts(spark):
    own = lambda d, n: " ".join(f"w{chr(97 + d)}{chr(97 + k)}" for k in range(n))
    line, other = "é b c d e f g h i j k l", "m n o p q r s t u v ß x y z"
    rows = [(d, f"{own(d, 3 * d)} {line} {own(d + 9, 2 * d)} {other} {line}") for d in range(7)]
    rows += [(20, line), (21, f"{line} {line} {other}"), (22, "la " * 40), (23, "La-" * 30 + line), (24, ""), (25, None), (None, line), (-3, f"{other} {line}"), (2**53 + 1, other)]
    return spark.createDataFrame(rows, "doc_id long, text string").repartition(3).cache()


@pytest.mark.parametrize("blocks, cells", [(1, 7), (4, 1_000_000)])
def test_runs_components_and_seeds_by_blocks(spark, texts, blocks, cells, monkeypatch):
    monkeypatch.setattr(bl, "CELLS", cells)
    grams = al.grams(nz.worded(texts), context=True)
    runs = al.runs_of_grams(grams).cache()
    assert rows_of(bl.runs(texts, bl.cleaned(texts), blocks), runs.columns) == rows_of(runs) and runs.count()
    for near in ("both", "either"):
        for delta in (0, 30):
            want = al.components(runs, delta, near)
            assert rows_of(bl.cases(texts, bl.cleaned(texts), delta, how=near, blocks=blocks), want.columns) == rows_of(want)
    plain = al.grams(nz.worded(texts))
    want = al.seeds_by_index(plain.where("pos % 8 = 0"), plain)
    assert rows_of(bl.seeds_one_sided(texts, bl.cleaned(texts), blocks=blocks), want.columns) == rows_of(want) and want.count()
    twice = texts.unionAll(spark.createDataFrame([(3, "é b c d e f g h i j k"), (5, "x n o p q r s t u v")], texts.schema))
    plain = al.grams(nz.worded(twice))
    want = al.seeds_by_index(plain.where("pos % 8 = 0"), plain)
    assert rows_of(bl.seeds_one_sided(twice, bl.cleaned(twice), blocks=blocks), want.columns) == rows_of(want)
    assert bl.runs(texts.limit(0), bl.cleaned(texts.limit(0))).count() == bl.seeds_one_sided(texts.limit(0), bl.cleaned(texts.limit(0))).count() == 0


@pytest.mark.parametrize("name, plain", [("al_runs", None), ("al_cases", None), ("al_cases_components", "both"), ("al_cases_near_either", "either")])
def test_queries_of_runs_shuffle_no_row_of_a_pair(spark, sf, name, plain, monkeypatch):
    runs = al.runs_of_grams(al.grams(nz.worded(documents(spark, sf)), context=True))
    want = rows_of(al.components(runs, near=plain) if plain else runs if name == "al_runs" else al.merge(runs), workloads.CASES)
    for made in ("runs_of_grams", "seeds_by_index", "shared_grams"):
        monkeypatch.setattr(al, made, lambda *_, **__: pytest.fail("rows of pairs are shuffled"))
    df = QUERIES[name](spark, sf)
    assert "Exchange" not in df._jdf.queryExecution().executedPlan().toString()
    assert rows_of(df, workloads.CASES) == want and want


def test_seeds_within_runs_are_not_made():
    """A line of two contexts in many documents: what is enumerated are ends of runs, not pairs of equal grams."""
    docs, n = 200, 8
    h = np.arange(1, 13, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    own = np.random.default_rng(1).integers(1, 2**63, (docs, 2)).astype(np.uint64)
    words = np.stack([np.concatenate([own[d, :1], h, own[d, 1:]]) if d < 3 else np.concatenate([h[:1], h, h[:1]]) for d in range(docs)])
    at = np.tile(np.arange(words.shape[1]), docs)
    a = bl._grams(np.arange(docs), np.full(docs, words.shape[1]), words.reshape(-1), 2 * at, 2 * at + 1, n, None, False)
    more = {"doc": a["doc_id"], "gram": np.unique(a["g"], return_inverse=True)[1], "met": np.ones(len(a["g"]), bool)}
    ends = bl._Ends(a | more, a | more, "before", 1, "begin").size.sum()
    grams = np.unique(a["g"], return_counts=True)[1]
    assert ends < 0.4 * (grams**2).sum()
    runs = [r for r in bl._runs(a, a, True)]
    assert sum(len(r["a_doc"]) for r in runs) >= docs * (docs - 1) // 2


def test_words_are_told_apart_wherever_they_stand():
    places, words = bl._Places(), ["a", "b", "ab", "ba", "abc", "cba", "aab", "aba", "é", "è", "aaaaaaaa", "aaaaaaa"] + [f"{a}{b}{a}{b}" for a in "abcdef" for b in "uvwxyz"]
    rng = np.random.default_rng(1)
    seen = {}
    for _ in range(50):
        some = [words[k] for k in rng.integers(0, len(words), 40)]
        data = np.frombuffer(" ".join(some).encode(), np.uint8)
        ends = np.append(np.flatnonzero(data == 32), len(data))
        for w, h in zip(some, places.words(data, np.append(0, ends[:-1] + 1), ends).tolist(), strict=True):
            assert seen.setdefault(w, h) == h
    assert len(set(seen.values())) == len(seen) == len(words)


def test_sketches_without_frequent_words_need_no_postings(spark, sf, monkeypatch):
    rows = sr.without_frequent(nz.worded(documents(spark, sf)), 0.3)
    want = rows_of(sr.candidates_by_join(sr.postings(sr.minhash(sr.chop(rows, 50), 10, "md5"))))
    monkeypatch.setattr(sr, "postings", lambda *_, **__: pytest.fail("postings are shuffled to be made distinct"))
    assert rows_of(QUERIES["sr_candidates_dropwords"](spark, sf), ["a_doc", "b_doc"]) == want and want


@pytest.mark.parametrize("name, more", [("discipline_table", 0), ("discipline_shift", 0), ("discipline_matrix", 0), ("year_gap", 0), ("yield_summary", 0), ("tail_share", 4)])
def test_only_what_is_counted_leaves_a_task_of_cases(spark, sf, name, more, monkeypatch):
    made, by_blocks = [], bl.by_blocks
    monkeypatch.setattr(bl, "by_blocks", lambda *args, **how: made.append(by_blocks(*args, **how)) or made[-1])
    assert QUERIES[name](spark, sf).count()
    assert [df.columns for df in made] == [[*al.PAIR, *al.SPAN[:more]]]
