"""What blocks of documents bring is shuffled and written once: pairs of blocks read files, and no plan of pairs has an exchange."""

from collections import Counter

import pytest

from textreuse import workloads  # noqa: F401  it registers its queries
from textreuse.operators import alignment as al
from textreuse.operators import blocks as bl
from textreuse.operators import normalize as nz
from textreuse.operators import retrieval as sr
from textreuse.registry import QUERIES
from textreuse.sources.catalog import documents


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name, keyed", [("sr_candidates_20_5", True), ("sr_candidates_unkeyed", False)])
def test_candidates_read_files_and_need_no_distinct_postings(spark, sf, name, keyed, monkeypatch):
    n, m = (20, 5) if keyed else (50, 10)
    posts = sr.postings(sr.sketched(documents(spark, sf), n, m, "md5"), keyed)
    want = Counter(map(tuple, sr.candidates_by_join(posts).collect()))
    monkeypatch.setattr(sr, "postings", lambda *_, **__: pytest.fail("postings are shuffled to be made distinct"))
    df = QUERIES[name](spark, sf)
    assert "Exchange" not in plan(df) and Counter(map(tuple, df.select("a_doc", "b_doc").collect())) == want and want


def test_cases_read_files(spark, sf):
    """Blocks of any number give the same cases, and what was stored for them is deleted."""
    docs = documents(spark, sf)
    grams = al.grams(nz.worded(docs), context=True)
    stored = []
    keep = bl.stored
    bl.stored = lambda df, name: stored.append(keep(df, name)) or stored[-1]
    try:
        one, many = bl.cases(docs, grams, blocks=1), bl.cases(docs, grams, blocks=5)
    finally:
        bl.stored = keep
    assert "Exchange" not in plan(many) and Counter(map(tuple, one.collect())) == Counter(map(tuple, many.collect())) and one.count()
    hadoop = spark._jvm.org.apache.hadoop.fs.Path
    for df in stored:
        for f in df.inputFiles():
            path = hadoop(f)
            assert not path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path)
