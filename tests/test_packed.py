"""Rows that tasks pack before they are shuffled: the same arrays come out, and fewer rows and bytes are shuffled."""

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


def shuffled(spark, run):
    """Records that the stages of ``run`` write to shuffles."""
    sc = spark.sparkContext
    seen = lambda: {s.stageId(): s.shuffleWriteRecords() for s in (lambda x: [x.apply(i) for i in range(x.size())])(sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None))}
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    before = seen()
    run()
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    return sum(n for k, n in seen().items() if k not in before)


def test_no_row_of_a_gram_is_shuffled(spark, sf):
    docs = documents(spark, sf)
    grams = al.grams(nz.worded(docs), context=True)
    n = grams.count()
    assert 0 < shuffled(spark, lambda: QUERIES["discipline_shift"](spark, sf).collect()) < 0.1 * n


@pytest.mark.parametrize("step", [3, 400_000])
def test_grams_made_in_tasks_equal_those_of_rows(spark, step):
    texts = ["", None, "a b c", "a b c d e f g h", "é b c d e f g h i " * 3, "A b-c d e f g h i"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows, table = nz.worded(docs), bl.hashed_words(nz.worded(docs)).toArrow()
    made = list(bl._made(table.to_batches(), 1_000_000, step=step))
    got = {c: np.concatenate([m[c] for m in made]) for c in made[0]}
    want = al.grams(rows, context=True).orderBy("doc_id", "pos").collect()
    names = ["doc_id", "pos", "begin", "end"]
    assert [tuple(r[c] for c in names) for r in want] == list(zip(*(got[c].tolist() for c in names), strict=True))
    # Equal grams, before and after, and only those, have equal numbers.
    for c in ("g", "before", "after"):
        pairs = {(r[c], g) for r, g in zip(want, got[c].tolist(), strict=True) if r[c] is not None}
        assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})
    assert [(r["before"] is None) + 2 * (r["after"] is None) for r in want] == got["edge"].tolist()


def test_packed_columns_come_back(spark):
    some = np.random.default_rng(1)
    for n in (0, 1, 1000):
        wide = some.integers(-(2**63), 2**63 - 1, n)
        columns = {"wide": wide, "rising": np.sort(wide), "runs": np.sort(some.integers(0, 9, n)), "small": some.integers(0, 99, n).astype(np.int32), "data": np.array([b"x"] * n, object)}
        back = bl.unpack(bl.pack(columns))
        assert all(v.dtype == back[c].dtype and Counter(v.tolist()) == Counter(back[c].tolist()) and (v == back[c]).all() for c, v in columns.items())


@pytest.mark.parametrize("n, m", [(50, 10), (3, 4)])
def test_fingerprints_made_in_tasks_are_the_postings(spark, sf, n, m, monkeypatch):
    """A bucket is a bucket of SQL's sketches, keyed by slot or not; no digest is taken by row."""
    docs = documents(spark, sf).unionAll(spark.createDataFrame([(10_000, None), (10_001, ""), (10_002, "é ß É"), (None, "a b")], "doc_id long, text string"))
    posts = sr.occurrences(sr.sketched(docs, n, m, "md5")).where("doc_id is not null").select("doc_id", F.conv(F.substring("hash", 1, 16), 16, -10).cast("bigint").alias("g"))
    want = set(map(tuple, posts.collect()))
    got = [tuple(r) for r in bl.fingerprints(nz.worded(docs), n, m).select("doc_id", "g").collect()]
    assert set(got) == want and len(got) < 1.2 * len(want) and want
    hashes = sr.occurrences(sr.sketched(docs, n, m, "md5")).groupBy("hash").agg(F.count_distinct("slot").alias("k"))
    assert hashes.where("k > 1").count() == 0  # so slots need not be told apart by a key
    monkeypatch.setattr(sr, "hashed", lambda *_, **__: pytest.fail("a digest is taken for each word of each passage"))
    assert QUERIES["sr_candidates_unkeyed"](spark, sf).count()
