"""Pairs by blocks of documents: equal to the plans with a shuffled row for a pair, and to SQL, without such rows."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from textreuse import workloads
from textreuse.operators import alignment as al
from textreuse.operators import blocks as bl
from textreuse.operators import normalize as nz
from textreuse.operators import retrieval as sr
from textreuse.registry import ORACLES, QUERIES
from textreuse.sources.catalog import documents

#: Queries that make pairs by blocks, by finding.
BY_BLOCKS = [
    "al_seeds_candidates",
    "al_cases_chain",
    "al_cases_delta_50",
    "al_cases_min2",
    "al_seeds_one_sided",
    "discipline_matrix",
    "discipline_table",
    "discipline_shift",
    "sr_candidates",
    "sr_candidates_20_5",
    "sr_candidates_unkeyed",
    "sr_candidates_dropwords",
    "tail_share",
    "year_gap",
    "yield_summary",
    "al_cases_candidates",
    "al_cases_fixpoint",
]


def rows_of(df, names=None):
    return Counter(map(tuple, df.select(*(names or df.columns)).collect()))


@pytest.mark.parametrize("name", BY_BLOCKS)
def test_no_row_of_a_pair_is_shuffled(spark, sf, name, monkeypatch):
    duckdb = pytest.importorskip("duckdb")
    for module, made in ((al, "runs_of_grams"), (al, "seeds_by_candidates"), (al, "shared_grams"), (sr, "candidates")):
        monkeypatch.setattr(module, made, lambda *_, **__: pytest.fail("rows of pairs are shuffled"))
    db = duckdb.connect()
    db.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    df, got = QUERIES[name](spark, sf), db.execute(ORACLES[name])
    names = [d[0] for d in got.description]
    flat = lambda rows: Counter(tuple(float(v) if isinstance(v, float) else int(v) if isinstance(v, int) else str(v) for v in r) for r in rows)
    want = flat(got.fetchall())
    assert sorted(names) == sorted(df.columns) and flat(df.select(*names).collect()) == want and want


@pytest.fixture(scope="module")
def texts(spark):
    """Copied passages with gaps, a passage repeated in its document, copies that begin or end a text, and texts without words."""
    word = lambda k: "".join(chr(97 + int(d)) for d in str(k))
    own = lambda d, n: " ".join(word(10_000 + 1_000 * d + k) for k in range(n))
    line, other = " ".join(word(k) for k in range(12)), " ".join(word(100 + k) for k in range(20))
    rows = [(d, f"{own(d, 5 * d)} {line} {own(d + 50, 12 * d)} {other} {line}") for d in range(9)]
    rows += [(20, line), (21, f"{line} {line}"), (22, "la " * 40), (23, "la " * 30 + line), (24, ""), (25, None), (2**53 + 1, other), (2**53 + 2, f"{other} {own(3, 9)} {line}")]
    return spark.createDataFrame(rows, "doc_id long, text string").repartition(3).cache()


@pytest.mark.parametrize("blocks", [1, 4])
@pytest.mark.parametrize("cells", [7, 1_000_000])
def test_cases_by_blocks_equal_those_of_shuffled_runs(spark, texts, blocks, cells, monkeypatch):
    monkeypatch.setattr(bl, "CELLS", cells)
    grams = al.grams(nz.worded(texts), context=True)
    runs = al.runs_of_grams(grams).cache()
    for delta, rounds, least in ((20, 2, 1), (60, None, 1), (250, 2, 3)):
        want = al.merge(runs, delta, rounds, least)
        assert rows_of(bl.cases(texts, grams, delta, rounds, least, blocks=blocks), want.columns) == rows_of(want)
    want = al.chains(runs, 20)
    assert rows_of(bl.cases(texts, grams, 20, how="chains", blocks=blocks), want.columns) == rows_of(want)
    assert bl.cases(texts.limit(0), grams.limit(0)).count() == 0


@pytest.mark.parametrize("blocks", [1, 4])
def test_candidates_and_their_seeds_by_blocks(spark, texts, blocks, monkeypatch):
    rows, posts = nz.worded(texts), sr.postings(sr.sketched(texts, 10, 3)).cache()
    pairs = sr.candidates_by_join(posts).cache()
    assert 0 < pairs.count() and rows_of(bl.candidates(posts, blocks)) == rows_of(pairs)
    assert bl.candidates(posts.limit(0)).count() == 0
    grams = al.grams(rows, context=True)
    want = al.seeds_by_candidates(pairs, grams)
    found = bl.seeds_of_candidates(texts, rows, grams, posts, blocks=blocks)
    assert rows_of(found, want.columns) == rows_of(want) and want.count()
    cases = al.merge(al.runs(want))
    assert rows_of(bl.cases(texts, grams, posts=posts, blocks=blocks), cases.columns) == rows_of(cases)


def test_grams_that_only_stand_within_runs_leave_before_the_join(spark, sf):
    docs = documents(spark, sf)
    grams = al.grams(nz.worded(docs), context=True)
    kept, shared = bl.turning(grams, 10_000), grams.join(al.shared_grams(grams), "g", "left_semi")
    assert kept.join(shared, ["doc_id", "pos"], "left_anti").count() == 0 and 0 < 2 * kept.count() < shared.count()
    assert shared.join(bl.shared(grams, 10_000), ["doc_id", "pos"], "left_anti").count() == 0
