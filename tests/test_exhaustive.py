"""Exhaustive baselines on small fixtures, and the choice of plan."""

from textreuse.operators import alignment as al
from textreuse.operators import exhaustive as ex
from textreuse.operators import normalize as nz
from textreuse.operators import retrieval as sr
from textreuse.plans import choose


def fixture(spark):
    shared = " ".join(f"s{chr(97 + i)}" for i in range(20))
    texts = [f"aa bb {shared}", f"{shared} cc dd", "nothing of this kind is found here at all today", shared]
    return nz.worded(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))


def test_nested_loop_equals_the_index(spark):
    gs = al.grams(fixture(spark))
    assert sorted(map(tuple, ex.seeds_nested_loop(gs).collect())) == sorted(map(tuple, al.seeds_by_index(gs, prune=True).collect())) != []


def test_exact_passages_and_second_opinion(spark):
    passages = sr.chop(fixture(spark), 50)
    sets = {r["doc_id"]: set(r["words"]) for r in passages.collect()}
    want = {(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.5}
    assert {(r["a_doc"], r["b_doc"]) for r in ex.passage_pairs_exact(passages, 0.5).collect()} == want
    assert {(r["a_doc"], r["b_doc"]) for r in ex.ml_minhash(passages, 0.5).collect()} <= want


def test_choice_of_plan(spark):
    rows = fixture(spark)
    v = choose.volumes(al.grams(rows), sr.postings(sr.minhash(sr.chop(rows, 50))))
    assert v.grams == 15 + 15 + 3 + 13 and choose.choose_seed_plan(v) == "candidates"
    assert choose.choose_seed_plan(choose.Volumes(10, 5, 50)) == "index"
    assert choose.describe(al.seeds_by_index(al.grams(rows))).get("CartesianProduct", 0) == 0
