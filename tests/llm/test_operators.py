"""The ten operators against brute force and on awkward input: nulls, empty and long texts, ties, repeats, clashing names."""

import hashlib
import re
import struct
from collections import Counter, defaultdict

import numpy as np
import pytest

pytest.importorskip("textreuse.llm")
from textreuse.llm import langid, mixing, neardup, packing, quality_rules, secrets, sharding, site_quality, topk, warc  # noqa: E402
from textreuse.llm.common import Scratch, running_totals, ship_by_value  # noqa: E402
from textreuse.llm.components import components  # noqa: E402

ship_by_value()
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _id long, size string, node string, weight double"


def sentence(seed: int, n: int) -> str:
    rng = np.random.default_rng(seed)
    return " ".join("w" + "".join(chr(97 + c) for c in rng.integers(0, 26, 5)) for _ in range(n))


def messy_rows() -> list[tuple]:
    long = sentence(1, 30_000)
    base = sentence(2, 120)
    near = base.split()
    near[60] = "changed"
    rows = [(0, None, None, None), (1, "", "en", "a"), (2, "   \n\t", "en", "a"), (3, long, "en", "a"), (4, base, "fr", "b"), (5, " ".join(near), "fr", None), (6, base.upper(), "fr", "b"), (7, base, None, "b"), (7, base, None, "b"), (8, "one two", "en", "a"), (9, "One TWO", "en", "c"), (10, "1234 5678", "en", "c"), (None, base, "en", "a"), (None, None, None, None), (11, 'password = "hunter2hunter2" x', "en", "c"), (12, (sentence(5, 8) + " ") * 6, "de", "c")]
    return [(i, t, lang, s, len(t) if t else None, 1, "x", "y", 0.5) for i, t, lang, s in rows]


@pytest.fixture(scope="module")
def messy(spark):
    return spark.createDataFrame(messy_rows(), SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def shingles(text):
    w = WORD.findall((text or "").translate({c: c + 32 for c in range(65, 91)}))
    return frozenset([tuple(w)] if 0 < len(w) < 5 else (tuple(w[k : k + 5]) for k in range(len(w) - 4)))


# 1 WARC


def test_warc_round_trip_and_revisits(spark):
    body = "<p>é</p>" * 200
    rows = [(i, f"http://h/{i}", body, 1) for i in (1, 5, 9)] + [(2, None, None, 1), (3, "u v", "", 1), (4, "x", "short", 1), (6, "x", "short", 1), (None, "x", "n", 1), (4, "x", "short", 1)]
    back = warc.round_trip(spark.createDataFrame(rows, "page_id long, url string, html string, size int")).collect()
    assert len(back) == len(rows) and not [r for r in back if r["error"]]
    by = {r["page_id"]: r for r in back}
    assert [(by[i]["record_type"], by[i]["refers_to"]) for i in (1, 5, 9)] == [("revisit", 9), ("revisit", 9), ("response", None)]
    assert by[1]["payload_bytes"] == len(body.encode()) and by[1]["payload_digest"] == hashlib.sha1(body.encode()).hexdigest()
    assert by[2]["payload_bytes"] == 0 and by[6]["record_type"] == "response"
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc.round_trip(none).count() == 0


def test_warc_dictionary_frame_and_damage():
    made = [warc.record(i, "http://x", (f"page {i} " * 50).encode(), warc.base32_sha1((f"page {i} " * 50).encode()), None) for i in range(300)]
    data = warc.archive(made, dictionary_bytes=4096)
    assert struct.unpack_from("<I", data)[0] == warc.DICTIONARY_MAGIC
    assert list(warc.frames(data)) == made and all(warc.parse(r)["error"] is None for r in made)
    with pytest.raises(warc.Damaged):
        list(warc.frames(data[:-3]))
    with pytest.raises(warc.Damaged):
        list(warc.frames(data + b"xyz"))
    assert "Content-Length" in warc.parse(made[0].replace(b"\r\n\r\n", b"\r\n\r\n!", 1))["error"]
    assert warc.parse(b"nonsense")["error"] and warc.parse(made[0].replace(b"WARC-Date", b"X-Date"))["error"]
    assert list(warc.frames(warc.archive(made[:2]))) == made[:2]  # too little for a dictionary


# 2 quality rules


def counts(text):
    w = WORD.findall(text or "")
    grams = [tuple(w[k : k + 5]) for k in range(len(w) - 4)]
    n = Counter(grams)
    covered = {p for k, g in enumerate(grams) if n[g] > 1 for p in range(k, k + 5)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_quality_counts_and_verdicts(spark, messy, empty):
    trusted = messy.where("doc_id in (4, 5)").select("doc_id")
    out = quality_rules.judge(messy, trusted).collect()
    assert len(out) == len(messy_rows())
    texts = {r[0]: r[1] for r in messy_rows() if r[0] is not None}
    for r in out:
        if r["doc_id"] is not None:
            assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == counts(texts[r["doc_id"]])
        assert r["base_failed"] == (r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"])
        assert not (r["kept"] and r["base_failed"])
    assert quality_rules.judge(empty, trusted).count() == 0
    untrusted = quality_rules.judge(messy, trusted.limit(0)).collect()
    assert all(r["kept"] != r["base_failed"] for r in untrusted)


def test_quality_ratio_by_hand(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, "a a"), (3, "c")], "doc_id long, text string")
    rules = quality_rules.Rules(buckets=7)
    bucket = {r["t"]: r["b"] for r in spark.sql("select t, cast(pmod(xxhash64(t), 7) as int) b from values ('a'), ('b'), ('c') v(t)").collect()}
    pairs = spark.sql("select cast(pmod(xxhash64('a', 'b'), 7) as int) ab, cast(pmod(xxhash64('a', 'a'), 7) as int) aa").first()
    raw, good = Counter([bucket["a"]] * 3 + [bucket["b"], bucket["c"], pairs["ab"], pairs["aa"]]), Counter([bucket["a"], bucket["b"], pairs["ab"]])
    want = [np.log((good[b] + 1) / (3 + 7)) - np.log((raw[b] + 1) / (7 + 7)) for b in range(7)]
    got = quality_rules.fit(docs, docs.where("doc_id = 1").select("doc_id"), rules)
    assert np.allclose(got, want, atol=1e-6)
    score = {r["doc_id"]: r["llr"] for r in quality_rules.score(docs, got, rules).collect()}
    assert abs(score[3] - got[bucket["c"]]) < 1e-8 and abs(score[1] - (got[bucket["a"]] + got[bucket["b"]] + got[pairs["ab"]]) / 3) < 1e-8


def test_quality_threshold_is_not_set_by_an_outlier(spark):
    scored = spark.createDataFrame([(i, 0.001 * (i % 50)) for i in range(500)] + [(500, -0.3), (501, -0.28)], "doc_id long, llr double")
    assert -0.01 <= quality_rules.threshold(scored, scored.select("doc_id"), quality_rules.Rules()) <= 0


def test_quality_rejects_poor_and_keeps_trusted(spark):
    from textreuse.llm.queries import op2_quality_rules

    sf = "/root/testdata/sf0.01"
    label = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").where("quality is not null and coalesce(toxic, 0) = 0").collect()}
    out = [r for r in op2_quality_rules(spark, sf).collect() if r["doc_id"] in label and not r["base_failed"]]
    kept = {q: sum(r["kept"] for r in out if label[r["doc_id"]] == q) for q in (0, 1)}
    assert kept[0] == 0 and kept[1] >= 0.98 * sum(label[r["doc_id"]] == 1 for r in out)


# 3 language identification


def test_language_held_out_accuracy_and_cases(spark, sf, messy, empty):
    from textreuse.llm.queries import op3_language_id

    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    out = [r for r in op3_language_id(spark, sf).collect() if r["held_out"]]
    assert len(out) > 30 and sum(truth[r["doc_id"]] == r["lang_pred"] for r in out) >= 0.95 * len(out)
    model = langid.learn(messy)
    got = {r["doc_id"]: r for r in langid.identify(messy, model).collect()}
    assert got[0]["lang_pred"] == got[1]["lang_pred"] == got[10]["lang_pred"] == "und" and got[10]["score"] == 0
    assert all(0 <= r["score"] <= 1 for r in got.values())
    nothing = langid.learn(empty)
    assert langid.identify(empty, nothing).count() == 0
    assert {r["lang_pred"] for r in langid.identify(messy, nothing).collect()} == {"und"}


def test_temperature_lowers_the_loss():
    rng = np.random.default_rng(0)
    y = rng.integers(0, 3, 400)
    logits = rng.normal(size=(400, 3)) + 1.0 * np.eye(3)[y]
    t = langid.temperature(logits * 8, y)
    loss = lambda s: -np.log(langid.softmax(logits * 8 / s)[np.arange(400), y]).mean()
    assert t > 2 and loss(t) <= min(loss(s) for s in (1, t * 0.8, t * 1.25)) + 1e-9


def test_l1_makes_weights_sparse():
    rng = np.random.default_rng(1)
    rows = [(np.array([y, *rng.integers(10, 500, 5)]), np.ones(6) / 6**0.5, y) for y in rng.integers(0, 3, 300)]
    dense, sparse = (langid.train(rows, 3, langid.Fit(features=512, l1=l1)) for l1 in (0.0, 2.0))
    assert (sparse != 0).sum() < 0.5 * (dense != 0).sum() and (sparse[:3].argmax(axis=1) == [0, 1, 2]).all()


# 4 secrets


def base(text):
    a = re.compile(r"""(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
    found = [(m.start(), 0, "assign", m.end()) for m in a.finditer(text) if len(m[1]) >= 6]
    found += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    found += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return ",".join(f"{k}:{s}:{e}" for s, _, k, e in sorted(found))


TEXTS = [
    "secret:token:abcdefg", "toKen = abcdefgh", "TOKEN='abcdef' é API-key=zzzzzz apikey: zzzzzz", "AKIA" + "Z9" * 10 + " AKIAAKIA123", "0123456789abcdef01234567g" * 2,
    "password = x\npassword: \"longer-than-six\" passwd==abc", "token=secret=abcdef", "x" * 50_000 + "=" + "y" * 50_000, "a:" * 20_000,
]


def test_secret_base_matches_brute_force(spark, messy, empty):
    for text in TEXTS:
        assert secrets.spans_text(secrets.scan(text)[0]) == base(text), text[:60]
    for r in secrets.scan_secrets(messy).collect():
        if r["doc_id"] == 0:
            assert r["base_sha256"] == hashlib.sha256(b"").hexdigest() and r["spans"] == ""
        if r["doc_id"] == 11:
            assert r["n_assign"] == 1 and r["spans"] == "assign:0:26"
    assert secrets.scan_secrets(empty).count() == 0


def test_secret_assignments_and_propagation():
    literal = lambda t: [t[s:e] for s, e, k, _ in secrets.scan(t)[1] if k == "literal"]
    assert literal('db_credentials = "Zq8-Lm2!vT94xR"') == ["Zq8-Lm2!vT94xR"]
    assert literal('part = "Zq8Lm2vT94xRpp"\nclient_pwd = part') == ["Zq8Lm2vT94xRpp"]
    assert literal('client_pwd = part\npart = "Zq8Lm2vT94xRpp"') == ["Zq8Lm2vT94xRpp"]
    assert literal('a = "Zq8Lm2vT"\nb = a + "94xRppQw"\nauth_passphrase = b') == ["Zq8Lm2vT", "94xRppQw"]
    assert literal('{"privateKey": "Zq8Lm2vT94xRpp"}') == ["Zq8Lm2vT94xRpp"]
    assert not literal('title = "Zq8Lm2vT94xRpp"') and not literal('user_pwd = "changeme-please"') and not literal("He said: nothing here")
    assert secrets.redact('token = "abcdef123456" and more') == 'token = "[REDACTED]" and more'
    assert secrets.redact(None) is None and secrets.redact("plain: text") == "plain: text"


def test_secret_with_symbols_goes_whole():
    text = 'password = "abcdef7$Gh1!kLmN2pQ" # x'
    base, every = secrets.scan(text)
    assert secrets.spans_text(base) == "assign:0:19" and secrets.spans_text(every) == "assign:0:19,literal:12:31"
    assert secrets.redact(text) == 'password = "[REDACTED]" # x'
    assert secrets.redact('api_key = "$Gh1!kLmN2pQ:token=abcdef7$Gh1!"; a = 1') == 'api_key = "[REDACTED]"; a = 1'
    key = "AKIA" + "Z9" * 10
    assert secrets.spans_text(secrets.scan(f'api_key: "{key}"')[1]) == "assign:0:34,access:10:34"


# 5 near-duplicates


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows]
    root = list(range(len(sets)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            a, b = sets[i][1], sets[j][1]
            if a and b and 100 * len(a & b) >= 85 * len(a | b):
                root[top(i)] = top(j)
    least = {}
    for k, (i, _) in enumerate(sets):
        least[top(k)] = min(least.get(top(k), i), i)
    return [(i, len(s), least[top(k)]) for k, (i, s) in enumerate(sets)]


@pytest.mark.parametrize("block, pivots", [(1_000_000, 8), (500, 8), (500, 1)])
def test_near_duplicates_match_brute_force(spark, block, pivots):
    rng = np.random.default_rng(3)
    rows = []
    for family in range(6):
        words = sentence(100 + family, 130).split()
        for _ in range(12):
            copy = list(words)
            for p in rng.choice(130, rng.integers(0, 4), replace=False):
                copy[p] = f"x{rng.integers(1e6)}"
            rows.append((len(rows), " ".join(copy)))
    rows += [(500 + k, sentence(k, 40)) for k in range(20)] + [(600, "a b"), (601, "A b"), (602, ""), (603, None)]
    rng.shuffle(rows)
    rows = [(int(i), t) for i, t in rows]
    near = neardup.Near(block_shingles=block, pivots=pivots)
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), near).collect()
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == sorted(brute_components(rows))
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_near_duplicates_awkward(messy, empty):
    got = neardup.near_duplicates(messy).collect()
    assert len(got) == len(messy_rows())
    by = defaultdict(set)
    for r in got:
        by[r["doc_id"]].add((r["component_id"], r["kept"]))
    assert by[4] == {(4, True)} and by[5] == {(4, False)} and by[6] == {(4, False)} and by[7] == {(4, False)}
    assert by[9] == {(8, False)} and by[1] == {(1, True)} and by[0] == {(0, True)} and by[None] == {(4, False), (None, True)}
    assert neardup.near_duplicates(empty).count() == 0


def test_pigeonhole_keys_find_every_pair_within_the_distance():
    near, rng = neardup.Near(), np.random.default_rng(5)
    a = rng.integers(0, 1 << 16, (200, near.slots)).astype(np.uint16)
    b = a.copy()
    for row in b:
        row[rng.choice(near.slots, near.distance, replace=False)] ^= 1
    ka, kb = neardup.all_keys(a, near), neardup.all_keys(b, near)
    assert all(set(x) & set(y) for x, y in zip(ka.tolist(), kb.tolist(), strict=True))


def test_components_on_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 1000 + k) for k in range(1, 40)] + [(5000, 5000)]
    got = components(spark.createDataFrame(edges, "a long, b long"), Scratch(spark, "test")).collect()
    groups = defaultdict(set)
    for r in got:
        groups[r["label"]].add(r["node"])
    assert sorted(map(len, groups.values())) == [40, 61]


# 6 sharding


def minimax(sizes, k):
    low, high = max(sizes, default=1), sum(sizes) or 1

    def need(c):
        n, cur = 1, 0
        for s in sizes:
            n, cur = (n + 1, s) if cur + s > c else (n, cur + s)
        return n

    while low < high:
        mid = (low + high) // 2
        low, high = (low, mid) if need(mid) <= k else (mid + 1, high)
    return low


def test_sharding_is_minimax_and_gapless(spark, messy, empty):
    rng = np.random.default_rng(6)
    rows = [(i, "t" * int(rng.integers(0, 60)) if i % 3 else "same text") for i in range(300)]
    out = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    groups = defaultdict(lambda: [1 << 60, 0])
    for i, t in rows:
        groups[t][0], groups[t][1] = min(groups[t][0], i), groups[t][1] + len(t) + 1
    want = minimax([b for _, b in sorted(groups.values())], 8)
    total, slots, of = Counter(), defaultdict(list), {}
    for r in out:
        total[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        assert of.setdefault(dict(rows)[r["doc_id"]], r["shard"]) == r["shard"]
    assert max(total.values()) == want and all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert sharding.shard(messy).count() == len(messy_rows()) and sharding.shard(empty).count() == 0


def test_block_search_equals_plain_search():
    rng = np.random.default_rng(8)
    for _ in range(50):
        sizes = [int(x) for x in rng.integers(1, 50, rng.integers(1, 200))]
        ends = np.cumsum(sizes).tolist()
        parts = [ends[i : i + 7] for i in range(0, len(ends), 7)]
        e = sharding.Ends([(k, p[0], p[-1]) for k, p in enumerate(parts)], lambda k: parts[k])  # noqa: B023
        assert sharding.minimax_cuts(e, max(sizes), 8)[0] == minimax(sizes, 8)


# 7 packing


def naive_best_fit(lengths, sources, clusters, capacity):
    bins, out = [], []
    for n, s, c in zip(lengths, sources, clusters, strict=True):
        fit = [(b["left"], k) for k, b in enumerate(bins) if b["left"] >= n and (s is None or s not in b["s"]) and c not in b["c"]]
        if not fit:
            bins.append({"left": capacity, "s": set(), "c": set()})
            fit = [(capacity, len(bins) - 1)]
        left, k = min(fit)
        out.append((k, capacity - left))
        bins[k]["left"] -= n
        bins[k]["s"].add(s)
        bins[k]["c"].add(c)
    return out


def test_packing_equals_naive_best_fit():
    rng = np.random.default_rng(9)
    lengths = sorted((int(x) for x in rng.integers(1, 90, 400)), reverse=True)
    sources = [None if x == 0 else f"s{x}" for x in rng.integers(0, 12, 400)]
    clusters = rng.integers(0, 300, 400).tolist()
    assert packing.best_fit(lengths, sources, clusters, 100) == naive_best_fit(lengths, sources, clusters, 100)


def test_packing_covers_every_word_once(messy, empty):
    out = packing.pack(messy, packing.Bins(capacity=100, pack_rows=4)).collect()
    words = Counter()
    bins = defaultdict(list)
    for r in out:
        words[r["doc_id"]] += r["n_words"]
        if r["bin_id"] is not None:
            bins[r["bin_id"]].append(r)
    want = Counter()
    for i, t, *_ in messy_rows():
        want[i] += len(WORD.findall(t or ""))
    assert +words == +want and all(sum(r["n_words"] for r in b) <= 100 for b in bins.values())
    for b in bins.values():
        named = [r["source"] for r in b if r["source"] is not None]
        assert len(set(named)) == len(named)
    assert packing.pack(empty).count() == 0


# 8 mixing


def test_mixing_meets_targets(spark, messy, empty):
    rows = [(i, " ".join(["w"] * (1 + i % 13)), ["a", "b", "c", None][i % 4] if i > 40 else "a") for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = mixing.sample(docs).collect()
    size = Counter()
    for _, t, s in rows:
        size[s] += len(t.split())
    target, taken = {r["source"]: r["target"] for r in out}, Counter()
    order = sorted(size, key=lambda s: (s is None, s or ""))
    weight, fixed, total = {s: 1 + k % 3 for k, s in enumerate(order)}, {}, sum(size.values())
    while True:  # reshare the excess until none is above its cap
        free = [s for s in order if s not in fixed]
        level = (total - sum(fixed.values())) / sum(weight[s] for s in free)
        over = [s for s in free if level * weight[s] > 3 * size[s]]
        if not over:
            break
        fixed |= {s: 3 * size[s] for s in over}
    for s in order:
        assert abs(target[s] - fixed.get(s, level * weight[s])) < 1e-6
    for r in out:
        taken[r["source"]] += r["taken"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    assert all(abs(taken[s] - target[s]) <= 1 for s in order)
    whole = mixing.apply(docs, mixing.sample(docs)).collect()
    mixed = Counter()
    for r in whole:
        mixed[r["source"]] += len(r["text"].split())
    assert mixed == taken
    assert mixing.sample(messy).count() == len(messy_rows()) and mixing.sample(empty).count() == 0
    assert mixing.apply(messy, mixing.sample(messy)).columns == messy.columns and mixing.apply(empty, mixing.sample(empty)).count() == 0


def test_heavier_documents_come_first(spark):
    docs = spark.createDataFrame([(i, "w w w w", "a") for i in range(400)] + [(1000 + i, "w " * 300, "b") for i in range(10)], "doc_id long, text string, source string")
    weights = spark.createDataFrame([(i, 20.0) for i in range(200)], "doc_id long, weight double")
    got = {r["doc_id"]: r["sample_key"] for r in mixing.sample(docs, weights).collect()}
    assert np.median([got[i] for i in range(200)]) < 0.2 * np.median([got[i] for i in range(200, 400)])


# 9 top-k


@pytest.mark.parametrize("unit", [True, False])
def test_top_k_is_exact(spark, unit):
    rng = np.random.default_rng(10)
    x = rng.normal(size=(300, 8)) * (1 if unit else rng.lognormal(0, 2, (300, 1)))
    x = x / np.linalg.norm(x, axis=1, keepdims=True) if unit else x
    x[20:30] = x[0]
    rows = [(i, [float(v) for v in r], 1) for i, r in enumerate(x)] + [(400, None, 1), (450, [1.0, None] + [0.0] * 6, 1), (500, [float("nan")] * 8, 1), (550, [float("inf")] + [0.0] * 7, 1), (600, [1.0, 2.0], 1), (None, [0.0] * 8, 1), (650, [0.0] * 8, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, norm int")
    got = defaultdict(list)
    for r in topk.search(df, topk.TopK(candidate_block=64, query_block=3, bucket=16)).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    ints = {i: np.floor(np.array(v) * 256).astype(np.int64) for i, v, _ in rows if i is not None and v and len(v) == 8 and all(e is not None and np.isfinite(e) for e in v)}
    for q in [i for i in ints if i % 50 == 0]:
        want = sorted((-int(ints[q] @ v), i) for i, v in ints.items() if i != q)[:5]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(want)]
    assert set(got) == {i for i in ints if i % 50 == 0}
    assert topk.search(df.limit(0)).count() == 0


# 10 site quality


def test_site_posteriors_shrink(spark, messy, empty):
    rng = np.random.default_rng(11)
    good = lambda k: sentence(k, 60).capitalize() + "."
    bad = lambda k: " ".join(w + "###" for w in sentence(k, 60).upper().split())
    rows = [(i, good(i) if (g := rng.random() < (0.9 if i % 2 else 0.3)) else bad(i), f"host{i % 2}", "p", int(g)) for i in range(200)] + [(999, good(9), "lonely", "p", 1)]
    docs = spark.createDataFrame([r[:4] for r in rows], "doc_id long, text string, source string, lang string")
    labels = spark.createDataFrame([(r[0], r[4]) for r in rows if r[0] % 3], "doc_id long, quality int")
    out = {r["doc_id"]: r for r in site_quality.assess(docs, labels).collect()}
    assert len(out) == 201
    assert out[1]["host_posterior"] > out[999]["host_posterior"] * 0.8 and out[0]["host_posterior"] < out[999]["host_posterior"] < 1
    assert sum(out[r[0]]["kept"] == bool(r[4]) for r in rows) >= 0.97 * len(rows)
    assert site_quality.assess(messy, messy.select("doc_id", (messy["n_chars"] > 100).cast("int").alias("quality"))).count() == len(messy_rows())
    assert site_quality.assess(empty, labels.limit(0)).count() == 0


def test_running_totals(spark):
    df = spark.createDataFrame([(i * 37 % 101, i) for i in range(101)], "k long, v long")
    from pyspark.sql import functions as F

    out = {r["k"]: r["t"] for r in running_totals(df, ["k"], {"t": F.col("v")}, Scratch(spark, "test"), 7).collect()}
    total = 0
    for k, v in sorted((i * 37 % 101, i) for i in range(101)):
        total += v
        assert out[k] == total


# Rows of one id, null ids, hot groups, depth and length


def test_warc_revisits_are_a_matter_of_the_row(spark):
    a, b = "a" * 1200, "b" * 1200
    rows = [(5, "u", a), (5, "v", b), (7, "u", a), (9, "u", b), (None, "u", a), (9, "w", b), (7, "x", "short")]
    back = warc.round_trip(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    digest = lambda t: hashlib.sha1(t.encode()).hexdigest()
    got = Counter((r["page_id"], r["payload_digest"], r["record_type"], r["refers_to"], r["payload_bytes"]) for r in back)
    assert got == Counter([(5, digest(a), "revisit", 7, 1200), (5, digest(b), "revisit", 9, 1200), (7, digest(a), "response", None, 1200), (9, digest(b), "response", None, 1200), (9, digest(b), "response", None, 1200), (None, digest(a), "response", None, 1200), (7, digest("short"), "response", None, 5)])


def test_warc_damage_fails_the_job(spark, tmp_path):
    made = [warc.record(i, "http://x", b"page" * 400, warc.base32_sha1(b"page" * 400), None) for i in range(3)]
    (tmp_path / "part.warc.zst").write_bytes(warc.archive(made)[:-5])
    back = warc.read_archives(spark, f"file://{tmp_path}", payloads=False)
    assert back.where("error is not null").count() == 1
    with pytest.raises(Exception, match="damaged archive"):
        warc.sound(back).select("record_type").collect()


def test_warc_columns_of_clashing_names(spark):
    rows = [(1, "u", "x" * 2000, "d", 3), (2, "u", "x" * 2000, "d", 4)]
    back = warc.round_trip(spark.createDataFrame(rows, "page_id long, url string, html string, _digest string, _at int")).collect()
    assert {(r["page_id"], r["refers_to"]) for r in back} == {(1, 2), (2, None)}


@pytest.mark.parametrize("block", [7, 64])
def test_top_k_of_repeated_ids(spark, block):
    rng = np.random.default_rng(20)
    x = rng.normal(size=(120, 6)) * rng.lognormal(0, 1.5, (120, 1))
    ids = [50 if i % 3 == 0 else i for i in range(120)]
    rows = [(i, [float(v) for v in r]) for i, r in zip(ids, x, strict=True)]
    got = Counter(tuple(r) for r in topk.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), topk.TopK(candidate_block=block, query_block=8, bucket=4)).select("query_id", "rank", "vec_id", "score").collect())
    ints, want = [np.floor(np.array(v) * 256).astype(np.int64) for _, v in rows], Counter()
    for q, i in enumerate(ids):
        if i % 50 == 0:
            best = sorted((-int(ints[q] @ v), ids[c]) for c, v in enumerate(ints) if c != q)[:5]
            want.update((i, k + 1, c, -s) for k, (s, c) in enumerate(best))
    assert got == want


def test_top_k_of_very_long_vectors(spark):
    rng = np.random.default_rng(21)
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(rng.normal(size=(101, 4)) * 2.0**22)]
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in topk.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), topk.TopK(candidate_block=16)).collect()}
    ints = [[int(np.floor(x * 256)) for x in v] for _, v in rows]
    for q in (0, 50, 100):
        want = sorted((-sum(a * b for a, b in zip(ints[q], v, strict=True)), i) for i, v in enumerate(ints) if i != q)[:5]
        assert [got[q, k + 1] for k in range(5)] == [(i, -s) for s, i in want]


def test_secrets_at_any_depth_and_length():
    chain = 'a0 = "Zq8Lm2vT94xRpp"\n' + "".join(f"a{k} = a{k - 1}\n" for k in range(1, 3000)) + "client_pwd = a2999\n"
    assert [chain[s:e] for s, e, k, _ in secrets.scan(chain)[1] if k == "literal"] == ["Zq8Lm2vT94xRpp"]
    double = 'a0 = "Zq8Lm2vT"\n' + "".join(f"a{k} = a{k - 1} + a{k - 1}\n" for k in range(1, 300)) + "client_pwd = a299\n"
    assert [double[s:e] for s, e, k, _ in secrets.scan(double)[1] if k == "literal"] == ["Zq8Lm2vT"]
    long = "Zq8-Lm2!vT94xR" * 2000
    text = f'part = "{long}"\nclient_pwd = part'
    assert [text[s:e] for s, e, k, _ in secrets.scan(text)[1] if k == "literal"] == [long]
    loop = 'a = b\nb = a + "Zq8Lm2vT94xRpp"\nclient_pwd = b'
    assert [loop[s:e] for s, e, k, _ in secrets.scan(loop)[1] if k == "literal"] == ["Zq8Lm2vT94xRpp"]


def test_secret_names_stand_for_their_last_assignment():
    literal = lambda t: [t[s:e] for s, e, k, _ in secrets.scan(t)[1] if k == "literal"]
    assert literal('x = "plain words"\nx = "Zq8Lm2vT94xRpp"\nuser_pwd = x') == ["Zq8Lm2vT94xRpp"]
    assert literal('x = "Zq8Lm2vT94xRpp"\nuser_pwd = x\nx = "Xw9Kp3uS85yQoo"\ntitle = x') == ["Zq8Lm2vT94xRpp"]


def test_secret_scan_is_linear_in_blanks():
    from time import process_time

    def seconds(text):
        at = process_time()
        secrets.scan(text)
        return process_time() - at

    for make in (lambda n: "a: b" + " " * n, lambda n: "a = 'x'" + " " * n + "1", lambda n: "a: " + "b " * (n // 2), lambda n: "a : b " * (n // 6)):
        seconds(make(50_000))
        assert seconds(make(1_000_000)) < 40 * max(seconds(make(50_000)), 0.01)


def test_value_of_parts_equals_value_of_the_whole():
    rng = np.random.default_rng(22)
    words = ["true", "x", "xx", "exam", "ple", "change", "me", "Zq8", "<", "null", "$", "{", "placeholder", "placehol", "der", "aaaaaaaaaaaaaaaaaaaa", "a"]
    for _ in range(3000):
        parts = [words[i] for i in rng.integers(0, len(words), rng.integers(0, 6))]
        value, whole = secrets.Value(), secrets.Value("".join(parts))
        for p in parts:
            value = value + secrets.Value(p)
        assert all(getattr(value, k) == getattr(whole, k) for k in secrets.Value.__slots__), parts


def half_shared(n):
    common = sentence(700, 100)
    rows = [(i, f"{common} {sentence(800 + i, 100)}") for i in range(n)]
    near = rows[0][1].split()
    near[150] = "changed"
    return [*rows, (n, " ".join(near))]


@pytest.mark.parametrize("bucket_members", [4096, 20])
def test_template_pages_are_no_family(spark, bucket_members):
    near, rows = neardup.Near(bucket_members=bucket_members, pivots=2), half_shared(200)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    scratch = Scratch(spark, "test")
    classes = scratch.cut(neardup.sketch(docs, near, "text", "doc_id"), "classes")
    found = neardup.families(scratch.cut(neardup.postings(classes, near), "postings"), classes, near, scratch).join(classes, "node").collect()
    assert {r["doc_id"] for r in found} == {0, 200} and len({r["label"] for r in found}) == 1
    got = neardup.near_duplicates(docs, near).collect()
    assert {r["doc_id"]: r["component_id"] for r in got} == {i: 0 if i == 200 else i for i, _ in rows}


@pytest.mark.parametrize("bucket_members, pivots", [(4096, 8), (16, 1)])
def test_families_hold_all_pairs_within_the_distance(spark, bucket_members, pivots):
    near, rng = neardup.Near(bucket_members=bucket_members, pivots=pivots), np.random.default_rng(23)
    sigs = []
    for _ in range(12):  # groups whose members differ from one base in up to 12 slots, so that some pairs are near and some not
        base = rng.integers(0, 1 << 16, near.slots)
        for _ in range(10):
            one = base.copy()
            one[rng.choice(near.slots, rng.integers(0, 13), replace=False)] = rng.integers(0, 1 << 16)
            sigs.append(one.astype(np.uint16))
    root = list(range(len(sigs)))
    for i in range(len(sigs)):
        for j in range(i):
            if (sigs[i] != sigs[j]).sum() <= near.distance:
                root = [root[j] if r == root[i] else r for r in root]
    want = {frozenset(i for i, r in enumerate(root) if r == c) for c in set(root)}
    scratch = Scratch(spark, "test")
    classes = scratch.cut(spark.createDataFrame([(i * 7919 - 300, bytearray(s.tobytes())) for i, s in enumerate(sigs)], "node long, sig binary"), "classes")
    got = defaultdict(set)
    for r in neardup.families(scratch.cut(neardup.postings(classes, near), "postings"), classes, near, scratch).collect():
        got[r["label"]].add((r["node"] + 300) // 7919)
    assert {frozenset(v) for v in got.values()} == {w for w in want if len(w) > 1}


def test_near_duplicates_of_the_given_table_match_brute_force(spark):
    from textreuse.llm.queries import op5_near_duplicates

    sf = "/root/testdata/sf0.01"
    sets = {r["doc_id"]: shingles(r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    holders, root = defaultdict(list), {i: i for i in sets}
    for i, s in sets.items():
        for g in s:
            holders[g].append(i)
    shared = Counter((a, b) for ids in holders.values() for k, a in enumerate(ids) for b in ids[k + 1 :])
    linked = [(a, b) for (a, b), n in shared.items() if 100 * n >= 85 * (len(sets[a]) + len(sets[b]) - n)]
    assert len(linked) > 50

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in linked:
        a, b = top(a), top(b)
        root[max(a, b)] = min(a, b)
    out = op5_near_duplicates(spark, sf).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in out} == {i: (len(s), top(i)) for i, s in sets.items()}


def test_dedup_keeps_one_row_of_a_group_whatever_its_id(spark):
    a, alone = sentence(40, 60), sentence(41, 60)
    rows = [(3, a), (7, alone), (7, a), (3, a), (None, a), (None, sentence(42, 60)), (None, sentence(42, 60)), (None, None), (None, None), (9, "")]
    docs = spark.createDataFrame([(i, t, k, "x") for k, (i, t) in enumerate(rows)], "doc_id long, text string, _hash int, row string")
    out = neardup.deduplicated(docs)
    assert out.columns == docs.columns
    assert Counter((r["doc_id"], r["text"]) for r in out.collect()) == Counter([(3, a), (7, alone), (None, sentence(42, 60)), (None, None), (None, None), (9, "")])


def test_quality_verdicts_match_brute_force(spark):
    import xxhash
    from textreuse.llm.queries import trusted_ids

    sf, rules = "/root/testdata/sf0.001", quality_rules.Rules()
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    good = {r["doc_id"] for r in trusted_ids(spark, sf).collect()}
    h = lambda w, seed=42: xxhash.xxh64_intdigest(w.encode(), seed)
    bucket = lambda x: (x - (1 << 64) if x >> 63 else x) % rules.buckets
    grams = {i: [bucket(h(w)) for w in ws] + [bucket(h(w, h(v))) for v, w in zip(ws, ws[1:], strict=False)] for i, t in texts.items() for ws in [WORD.findall(t or "")]}
    raw, sure = Counter(b for g in grams.values() for b in g), Counter(b for i, g in grams.items() if i in good for b in g)
    share = lambda n, c: np.log((n + 1) / (sum(c.values()) + rules.buckets))
    ratio = [round(share(sure[b], sure) - share(raw[b], raw), 6) for b in range(rules.buckets)]
    score = {i: round(sum(ratio[b] for b in g) / len(g), 9) if g else None for i, g in grams.items()}
    known = sorted(score[i] for i in good if i in score and score[i] is not None)
    least = np.floor(known[int(rules.trusted_quantile * len(known))] / rules.bin_width) * rules.bin_width
    for r in quality_rules.judge(docs, trusted_ids(spark, sf)).collect():
        want = score[r["doc_id"]]
        assert (r["llr"] is None) == (want is None) and (want is None or abs(r["llr"] - want) < 1e-7)
        if want is None or abs(want - least) > 1e-6:
            assert r["kept"] == (not r["base_failed"] and (0.0 if want is None else want) >= least)


def test_quality_accepts_rows_by_their_own_text(spark):
    good, poor = sentence(50, 60), "bad " * 60
    docs = spark.createDataFrame([(7, good, 1), (7, poor, 2), (None, poor, 3), (None, good, 4), (None, None, 5), (8, poor, 6)], "doc_id long, text string, _key int")
    out = quality_rules.accepted(docs, docs.select("doc_id").limit(0))
    assert out.columns == docs.columns and {r["_key"] for r in out.collect()} == {1, 4}


def test_quality_fit_is_the_same_beyond_a_broadcast(spark, sf, monkeypatch):
    from textreuse.llm.queries import trusted_ids

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    near = quality_rules.fit(docs, trusted_ids(spark, sf), quality_rules.Rules())
    monkeypatch.setattr(quality_rules, "small_or_shuffled", lambda side: side)
    assert quality_rules.fit(docs, trusted_ids(spark, sf), quality_rules.Rules()) == near


def test_sharding_output_columns(spark):
    import zlib

    rows = [(i, ["x", "éß", "", None][i % 4] if i % 3 else "t" * i) for i in range(80)]
    out = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    for r in out:
        raw = (dict(rows)[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 1, zlib.crc32(raw), "bytes", None) and 0 <= r["shard"] < 8


def test_packing_keeps_clusters_apart(spark):
    rng = np.random.default_rng(24)
    rows = [(i, " ".join(["w"] * int(rng.integers(1, 30))) + f" {i}", f"s{i}", int(i % 9) if i % 9 else None) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, near long")
    one = packing.pack(docs, packing.Bins(capacity=100, pack_rows=10_000), cluster="near").collect()
    bins = defaultdict(list)
    for r in one:
        bins[r["bin_id"]].append(r["cluster"])
    named = [[c for c in b if c is not None] for b in bins.values()]
    assert all(len(set(b)) == len(b) for b in named) and sum(map(len, named)) == sum(1 for r in rows if r[3] is not None)
    order = sorted(((r["n_words"], r["doc_id"], r["source"], r["cluster"], r["bin_id"], r["bin_offset"]) for r in one), key=lambda r: (-r[0], r[1]))
    want = naive_best_fit([r[0] for r in order], [r[2] for r in order], [r[3] if r[3] is not None else f"none {k}" for k, r in enumerate(order)], 100)
    assert [(r[4], r[5]) for r in order] == want


def test_packing_splits_rows_of_one_id(spark):
    docs = spark.createDataFrame([(None if i % 2 else 5, f"text {i}", f"s{i}") for i in range(400)], "doc_id long, text string, source string")
    out = packing.pack(docs, packing.Bins(pack_rows=50)).collect()
    packs = Counter(r["bin_id"] >> 32 for r in out)
    assert len(out) == 400 and len(packs) >= 6 and max(packs.values()) < 150


def test_mixing_of_many_sources_equals_that_of_few(spark):
    rows = [(i, " ".join(["w"] * (1 + i % 7)), None if i % 41 == 0 else f"h{i % 40}") for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    few, many = (sorted(map(tuple, mixing.sample(docs, mix=mixing.Mix(few_sources=n)).select("doc_id", "target", "taken").collect())) for n in (100_000, 0))
    assert few == many


def test_language_predictions_match_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.learn(docs)
    rows = {r["doc_id"]: r["text"] for r in docs.limit(40).collect()}
    mask, mul, fin = (1 << 64) - 1, 0x1F123BB5, 0xBF58476D1CE4E5B9

    def number(x):
        x = ((x ^ (x >> 29)) * fin) & mask
        return x >> (64 - langid.Fit().features.bit_length() + 1)

    for r in langid.identify(docs.where(docs["doc_id"].isin(list(rows))), model).collect():
        text = "".join(c if c.isalpha() else " " for c in rows[r["doc_id"]].lower())
        kept = [ord(c) for k, c in enumerate(text) if k == 0 or c != " " or text[k - 1] != " "]
        cp = [32, *kept, 32]
        two = [(a * mul + b) & mask for a, b in zip(cp, cp[1:], strict=False)]
        three = [(a * mul + b) & mask for a, b in zip(two, cp[2:], strict=False)]
        tf = Counter(number(x) for x in [*cp, *two, *three])
        x = {f: (1 + np.log(n)) * model.idf[f] for f, n in tf.items()}
        norm = np.sqrt(sum(v * v for v in x.values()))
        logits = sum(v / norm * model.weights[f] for f, v in x.items()) / model.temperature
        p = np.exp(logits - logits.max()) / np.exp(logits - logits.max()).sum()
        assert r["lang_pred"] == model.languages[int(p.argmax())] and abs(r["score"] - p.max()) < 1e-9


def test_rare_languages_are_learned(spark):
    rare = [(10_000 + i, "zzyx qquv zzyx wqxv " * 5, "xx") for i in range(3)]
    rows = [(i, sentence(i, 20), "en" if i % 2 else "de") for i in range(600)] + rare
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.learn(docs, langid.Fit(fit_rows=60))
    assert model.languages == ["de", "en", "xx"]
    assert langid.quotas({"a": 3, "b": 1000, "c": 1000}, 60) == {"a": 3, "b": 28, "c": 29} and langid.quotas({"a": 5, "b": 5}, 1) == {"a": 1, "b": 1}
    assert langid.quotas({}, 10) == {}


def test_frequencies_are_those_of_labelled_documents(spark):
    with_lang = spark.createDataFrame([(1, "aaaa bbbb", "en"), (2, "aaaa", "de")], "doc_id long, text string, lang string")
    more = with_lang.unionAll(spark.createDataFrame([(3, "cccc", None)], "doc_id long, text string, lang string"))
    assert np.array_equal(langid.learn(with_lang).idf, langid.learn(more).idf)


def test_site_quality_matches_brute_force(spark):
    rng = np.random.default_rng(25)
    rows = [(i, sentence(i, 30) if i % 4 else " ".join(w + "###" for w in sentence(i, 30).split()), f"h{int(rng.integers(0, 5))}" if i % 11 else None, f"p{i % 3}") for i in range(240)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string")
    label = {i: int(i % 4 > 0) for i in range(0, 240, 2)}
    out = {r["doc_id"]: r for r in site_quality.assess(docs, spark.createDataFrame(list(label.items()), "doc_id long, quality int")).collect()}
    good = {i: label.get(i, out[i]["p_doc"]) for i in out}
    hosts, paths = defaultdict(list), defaultdict(list)
    for i, _, h, p in rows:
        hosts[h].append(good[i])
        paths[h, p].append(good[i])
    mean = min(max(sum(good.values()) / len(good), 0.01), 0.99)

    def strength(groups):  # of (good, total, prior)
        m = np.mean([q * (1 - q) for *_, q in groups])
        v = np.mean([(g / n - q) ** 2 - q * (1 - q) / n for g, n, q in groups])
        return max(1.0, min(1e6, m / max(v, 1e-6) - 1))

    k = strength([(sum(v), len(v), mean) for v in hosts.values()])
    m = strength([(sum(v), len(v), (sum(hosts[h]) + k * mean) / (len(hosts[h]) + k)) for (h, _), v in paths.items()])
    logit = lambda x: np.log(x / (1 - x))
    for i, _, h, p in rows:
        host = (sum(hosts[h]) - good[i] + k * mean) / (len(hosts[h]) - 1 + k)
        path = (sum(paths[h, p]) - good[i] + m * host) / (len(paths[h, p]) - 1 + m)
        quality = 1 / (1 + np.exp(-(logit(min(max(out[i]["p_doc"], 1e-6), 1 - 1e-6)) + logit(path) - logit(mean))))
        assert abs(out[i]["host_posterior"] - host) < 2e-6 and abs(out[i]["path_posterior"] - path) < 2e-6 and abs(out[i]["quality"] - quality) < 2e-6
        assert out[i]["kept"] == (out[i]["quality"] >= 0.5)


def test_site_quality_of_labels_that_it_was_not_told(spark):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet").where("coalesce(toxic, 0) = 0").select("doc_id", "quality")
    truth = {r["doc_id"]: r["quality"] for r in labels.where("doc_id % 2 = 1").collect()}
    out = {r["doc_id"]: r["kept"] for r in site_quality.assess(spark.read.parquet(f"{sf}/documents.parquet"), labels.where("doc_id % 2 = 0")).collect()}
    poor = [i for i, q in truth.items() if q == 0]
    fine = [i for i, q in truth.items() if q == 1]
    assert sum(out[i] for i in poor) <= 0.1 * len(poor) and sum(out[i] for i in fine) >= 0.98 * len(fine)


def test_tables_without_splits_are_dealt(spark, tmp_path):
    from textreuse.llm.common import spread

    path = f"file://{tmp_path}/one"
    spark.range(1000).withColumnRenamed("id", "_place").coalesce(1).write.parquet(path)
    dealt = spread(spark.read.parquet(path))
    sizes = [n for n in dealt.rdd.mapPartitions(lambda rows: [sum(1 for _ in rows)]).collect() if n]
    assert dealt.columns == ["_place"] and len(sizes) == spark.sparkContext.defaultParallelism and sum(sizes) == 1000


def test_broadcasts_are_bound_by_bytes(spark, tmp_path):
    from textreuse.llm.common import estimated_bytes, small_or_shuffled

    path = f"file://{tmp_path}/wide"
    spark.range(100).selectExpr("id", "repeat('x', 1000) as text", "named_struct('a', 1) as s").write.parquet(path)
    side = spark.read.parquet(path)
    assert 100_000 < estimated_bytes(side) < 200_000
    hinted = lambda df: "hint" in df._jdf.queryExecution().logical().toString().lower()
    assert hinted(small_or_shuffled(side)) and not hinted(small_or_shuffled(side, 1000))


def test_only_one_machine_may_leave_the_shared_folder_unset():
    from types import SimpleNamespace

    from textreuse.llm.common import shared_folder

    def session(master, named=None):
        conf = SimpleNamespace(get=lambda key, default=None: named)
        return SimpleNamespace(sparkContext=SimpleNamespace(getConf=lambda: conf, master=master), conf=conf)

    assert shared_folder(session("local[4]")).startswith("file:") and shared_folder(session("yarn", "hdfs:///x/")) == "hdfs:///x"
    for master in ("yarn", "spark://h:7077", "local-cluster[3,2,1024]"):
        with pytest.raises(RuntimeError):
            shared_folder(session(master))
