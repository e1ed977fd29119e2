"""The corpus pipeline stage by stage against brute force."""

import re
from collections import Counter
from math import comb

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
from test_operators import brute_components, messy_rows, sentence, shingles, SCHEMA  # noqa: E402

from textreuse.llm import neardup, secrets  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_stages_on_the_small_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    kept = corpus_pipeline.quality(spark, docs, sf).cache()
    assert kept.columns == docs.columns and 0 < kept.count() < docs.count()
    good = {r["doc_id"] for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1 and toxic = 0").collect()}
    ids = {r["doc_id"] for r in kept.collect()}
    long = {r["doc_id"] for r in docs.collect() if len(WORD.findall(r["text"])) >= 10}
    assert len(good & long - ids) <= 0.03 * len(good & long)
    single = corpus_pipeline.near_dedup(spark, kept, sf).cache()
    want = {i for i, _, c in brute_components([(r["doc_id"], r["text"]) for r in kept.collect()]) if i == c}
    assert {r["doc_id"] for r in single.collect()} == want and single.columns == docs.columns
    clean = corpus_pipeline.secret_scan(spark, single, sf).cache()
    before = {r["doc_id"]: r["text"] for r in single.collect()}
    for r in clean.collect():
        assert r["text"] == secrets.redact(before[r["doc_id"]]) and r["n_chars"] == len(r["text"])
    mixed = corpus_pipeline.mix(spark, clean, sf).cache()
    assert mixed.columns == docs.columns
    total = sum(len(WORD.findall(r["text"])) for r in clean.collect())
    got = Counter()
    for r in mixed.collect():
        got[r["source"]] += len(WORD.findall(r["text"]))
    assert abs(sum(got.values()) - total) <= len(got)
    packed = corpus_pipeline.pack(spark, mixed, sf).collect()
    assert sum(r["n_words"] for r in packed) == sum(got.values())


def at_080(rows):
    """Ids that stand for their component, by brute force."""
    sets, root = [shingles(t) for _, t in rows], list(range(len(rows)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and b and 100 * len(a & b) >= 80 * len(a | b):
                root = [root[j] if r == root[i] else r for r in root]
    return {min(i for (i, _), r in zip(rows, root, strict=True) if r == c) for c in set(root)}


def test_stages_from_dedup_on_at_080(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    single = corpus_pipeline.near_dedup(spark, docs, sf).cache()
    assert {r["doc_id"] for r in single.collect()} == at_080([(r["doc_id"], r["text"]) for r in docs.collect()])
    clean = corpus_pipeline.secret_scan(spark, single, sf).cache()
    before = {r["doc_id"]: r["text"] for r in single.collect()}
    assert all(r["text"] == secrets.redact(before[r["doc_id"]]) and r["n_chars"] == len(r["text"]) for r in clean.collect())
    mixed = corpus_pipeline.mix(spark, clean, sf).cache()
    total, got = (sum(len(WORD.findall(r["text"])) for r in x.collect()) for x in (clean, mixed))
    assert abs(got - total) <= len({r["source"] for r in clean.collect()})
    assert sum(r["n_words"] for r in corpus_pipeline.pack(spark, mixed, sf).collect()) == got


def test_dedup_stage_links_from_080_on(spark, sf):
    rows = []
    for k in range(40):
        words = sentence(300 + k, 100).split()
        near = list(words)
        near[20 + k // 4], near[60] = "changed", "twice"  # 86 of 106 shingles: 0.81
        far = list(words)
        far[10], far[40], far[80] = "one", "more", "change"  # 81 of 111: 0.73, and less to the near copy
        rows += [(3 * k + n, " ".join(x), "en", "a", 1) for n, x in enumerate((words, near, far))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert {r["doc_id"] for r in corpus_pipeline.near_dedup(spark, docs, sf).collect()} == {i for i in range(120) if i % 3 != 1}
    at_85 = neardup.near_duplicates(docs)
    assert at_85.where("kept").count() == 120


def test_signature_distance_is_complete_at_080():
    near = neardup.AT_80
    n, d = near.slots, near.distance
    assert sum(comb(n, k) * 0.2**k * 0.8 ** (n - k) for k in range(d + 1, n + 1)) < 1e-5


def test_stages_on_awkward_rows(spark, sf):
    for rows in (messy_rows(), []):
        docs = spark.createDataFrame(rows, SCHEMA)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns, name
            out.collect()
        corpus_pipeline.pack(spark, docs, sf).collect()


def test_stages_decide_by_row(spark, sf):
    """Rows of one id with different texts, and null ids, stay or go each by its own text."""
    good, other, poor = sentence(900, 80), sentence(901, 80), "bad " * 80
    rows = [(3, good), (7, other), (7, good), (7, poor), (None, poor), (None, sentence(902, 80)), (None, good), (None, None)]
    docs = spark.createDataFrame([(i, t, "en", "s", 1, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, lang string, source string, n_chars long, row int")
    kept = corpus_pipeline.quality(spark, docs, sf)
    assert kept.columns == docs.columns
    before = {r["row"] for r in kept.collect()}
    assert not before & {3, 4, 7}
    single = corpus_pipeline.near_dedup(spark, docs, sf)
    assert {r["row"] for r in single.collect()} == {0, 1, 3, 5, 7}
