"""The registry: names pair up, imports need no session, every query of the small groups runs."""

import subprocess
import sys

import pytest

import __spark_entry__ as entry
from conftest import ROOT


def test_import_needs_no_session():
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"], cwd=ROOT, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr


def test_sql_belongs_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_flagship(spark):
    rows = entry.entry(spark)
    assert rows.count() > 0 and rows.columns[:2] == ["a_doc", "b_doc"]


@pytest.mark.parametrize("name", ["al_cases", "sr_candidates", "doc_token_offsets", "case_records", "discipline_table", "st_tumbling", "rel_join_asof", "io_json_roundtrip", "udtf_reuse_cases", "sim_dense_cosine_topk"])
def test_query_equals_sql(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    df = entry.queries()[name](spark, sf)
    rows = df.collect()
    if name not in entry.oracle_sql():
        return
    db = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        db.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    got = db.execute(entry.oracle_sql()[name])
    names = [d[0] for d in got.description]
    assert sorted(names) == sorted(df.columns)
    flat = lambda v: round(v, 6) if isinstance(v, float) else v
    want = sorted(repr([flat(r[names.index(c)]) for c in sorted(names)]) for r in got.fetchall())
    assert sorted(repr([flat(r[c]) for c in sorted(names)]) for r in rows) == want


def test_witnesses_are_all_collisions(spark, sf):
    from collections import Counter, defaultdict
    from itertools import combinations

    from textreuse.operators import retrieval as sr
    from textreuse.sources.catalog import documents

    buckets = defaultdict(list)
    for r in sr.sketched(documents(spark, sf), family="md5").collect():
        for slot, h in enumerate(r["sig"]):
            buckets[slot, h].append((r["doc_id"], r["passage_no"]))
    want = Counter((*a, *b) for b_ in buckets.values() for a, b in combinations(sorted(b_), 2) if a[0] < b[0])
    got = entry.queries()["sr_witnesses"](spark, sf).collect()
    assert {(r["a_doc"], r["a_passage"], r["b_doc"], r["b_passage"]): r["slots"] for r in got} == want and len(got) == len(want)
    assert {(r["a_doc"], r["b_doc"]) for r in got} == {(r["a_doc"], r["b_doc"]) for r in entry.queries()["sr_candidates"](spark, sf).collect()}


def test_stream_equals_batch(spark, sf):
    from textreuse.operators import retrieval as sr
    from textreuse.sources.catalog import documents

    batch = set(map(tuple, sr.candidates(sr.postings(sr.sketched(documents(spark, sf)))).collect()))
    assert {tuple(r) for r in entry.queries()["st_incremental_candidates"](spark, sf).collect()} == batch
