"""Exact passage pairs by a prefix filter: equal to the join on words, and no row of a word or of a pair is shuffled."""

from collections import Counter

import numpy as np
import pytest

from textreuse.operators import exhaustive as ex
from textreuse.operators import prefix
from textreuse.registry import ORACLES, QUERIES


def picked(out):
    return Counter((*tuple(r)[:4], round(r["jaccard"], 9)) for r in out.collect())


@pytest.mark.parametrize("j", [0.3, 0.5, 0.7, 1.0])
def test_blocks_of_passages_equal_the_join_on_words(spark, monkeypatch, j):
    """Copies, near copies, passages without words, long ones, and blocks and parts of a few rows."""
    for name, value in (("BLOCK", 16), ("CELLS", 50), ("WHOLE", 7), ("SLOT_BITS", 3)):
        monkeypatch.setattr(prefix, name, value)
    rng = np.random.default_rng(11)
    rows = [(d, p, [f"w{int(x)}" for x in rng.zipf(1.5, rng.integers(0, 40)) % 80]) for d in range(30) for p in range(3)]
    rows += [(100 + d, 0, rows[d % 5 + 3][2]) for d in range(25)] + [(200 + d, 0, rows[7][2][d:]) for d in range(8)]
    df = spark.createDataFrame(rows, "doc_id long, passage_no int, words array<string>").repartition(5)
    got = ex.passage_pairs_by_prefix(df, j)
    assert picked(got) == picked(ex.passage_pairs_exact(df, j)) and got.count() > 25
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan


def test_fewest_shared_words_are_the_fewest():
    for j in (0.1, 1 / 3, 0.5, 0.8, 1.0):
        o = prefix.least_shared(60, j)
        for t in range(2, 121):
            assert o[t] == next(s for s in range(1, t + 1) if s == t or s / (t - s) >= j)


def test_query_equals_sql(spark, sf):
    duckdb = pytest.importorskip("duckdb")
    db = duckdb.connect()
    db.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    want = Counter(db.execute(ORACLES["base_passage_exact"]).fetchall())
    assert Counter(map(tuple, QUERIES["base_passage_exact"](spark, sf).collect())) == want and want
