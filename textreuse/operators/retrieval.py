"""Source retrieval: passages, MinHash sketches, postings, candidate pairs and their measures.

Two documents are candidates if any passage of one shares a MinHash value with any
passage of the other. Sketching is a map and a partial aggregate; postings are made
distinct in a document before they meet. Pairs are listed by whichever way moves less:
a self-join on (slot, hash), whose rows grow with the squares of the buckets, or blocks
of documents that meet one another, whose rows are the postings times the blocks.
"""

from __future__ import annotations

from math import ceil, isqrt, log

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.io import stored
from .normalize import let, worded


def chop(rows: DataFrame, n: int = 50, stride: int | None = None) -> DataFrame:
    """Passages of n words, the last may be short; with a stride below n they overlap."""
    step = stride or n
    last = F.greatest(F.lit(0), F.ceil((F.size("words") - n) / step)).cast("int") if step < n else ((F.size("words") - 1) / step).cast("int")
    starts = F.when(F.size("words") > 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
    cut = let(F.col("words"), lambda ws: F.transform(starts, lambda p: F.struct(p.alias("passage_no"), F.slice(ws, p * step + 1, n).alias("words"))))
    out = rows.select("doc_id", F.explode(cut).alias("p"))
    return out.select("doc_id", "p.passage_no", "p.words")


def bag_counts(passages: DataFrame) -> DataFrame:
    """Occurrence view: a row for each word of a passage with its count."""
    distinct = passages.select("doc_id", "passage_no", F.explode("words").alias("word"))
    return distinct.groupBy("doc_id", "passage_no", "word").agg(F.count(F.lit(1)).alias("n"))


#: The modulus of the affine family, a prime of 31 bits.
AFFINE_PRIME = (1 << 31) - 1


def _short_number(text: Column) -> Column:
    """A number below the prime from a text, by its digest; SQL can compute it too."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint") % AFFINE_PRIME


def hashed(slot: Column, word: Column, family: str) -> Column:
    """Value of one hash function of a family: 64 bits (``xx``), hexadecimal text (``md5``), or a multiple of one number a word (``affine``)."""
    if family == "xx":
        return F.xxhash64(slot, word)
    name = slot.cast("string")
    if family == "affine":
        return ((_short_number(F.concat(F.lit("a"), name)) + 1) * _short_number(word) + _short_number(F.concat(F.lit("b"), name))) % AFFINE_PRIME
    return F.md5(F.concat(name, F.lit(":"), word))


def minhash(passages: DataFrame, m: int = 10, family: str = "xx") -> DataFrame:
    """``sig``: the minimum of each of m hash functions over a passage's set of words.

    Numbers are minima of a hash aggregate over the words, which stays in generated code; a passage's words are in
    one task, so a row a passage moves. Texts as minima would not, and are taken within the row.
    """
    if family == "md5":
        bag = F.array_distinct("words")
        sig = let(bag, lambda ws: F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.array_min(F.transform(ws, lambda w: hashed(i, w, family)))))
        return passages.select("doc_id", "passage_no", sig.alias("sig"))
    each = passages.select("doc_id", "passage_no", F.explode("words").alias("_w"))
    least = each.groupBy("doc_id", "passage_no").agg(*(F.min(hashed(F.lit(i), F.col("_w"), family)).alias(f"_{i}") for i in range(m)))
    return least.select("doc_id", "passage_no", F.array(*(f"_{i}" for i in range(m))).alias("sig"))


def occurrences(signatures: DataFrame, keyed: bool = True) -> DataFrame:
    """One row for each passage and fingerprint, without a shuffle: postings that may be there more than once."""
    rows = signatures.select("doc_id", F.posexplode("sig").alias("slot", "hash"))
    return rows if keyed else rows.withColumn("slot", F.lit(0))


def postings(signatures: DataFrame, keyed: bool = True) -> DataFrame:
    """One row for each document and fingerprint; without ``keyed`` slots count as one."""
    return occurrences(signatures, keyed).distinct()


def capped(posts: DataFrame, cap: int) -> DataFrame:
    """A named lossy variant: buckets of more than ``cap`` documents are left out."""
    small = posts.groupBy("slot", "hash").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") <= cap)
    return posts.join(small.select("slot", "hash"), ["slot", "hash"], "left_semi")


def without_frequent(rows: DataFrame, share: float) -> DataFrame:
    """A named lossy variant: words that more than ``share`` of the documents have do not enter the bags.

    The list of frequent words has at most average-distinct-words / share entries, whatever the number of documents.
    """
    n = rows.count()
    df = rows.select("doc_id", F.explode(F.array_distinct("words")).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    # The list is that short, so it may come to the driver; a list of literals is looked up by hash.
    stop = [r["word"] for r in df.where(F.col("n") > share * n).select("word").collect()]
    return rows.select("doc_id", F.filter("words", lambda w: ~w.isin(stop)).alias("words"))


def candidates(posts: DataFrame, min_common: int = 1) -> DataFrame:
    """Distinct pairs (a_doc < b_doc) that share at least ``min_common`` fingerprints."""
    if min_common == 1:
        posts = stored(posts, "postings")
        plan = listing(posts)
        return candidates_by_blocks(posts, plan["blocks"]) if plan["blocks"] else candidates_by_join(posts)
    a = posts.select("slot", "hash", F.col("doc_id").alias("a_doc"))
    b = posts.select("slot", "hash", F.col("doc_id").alias("b_doc"))
    pairs = a.join(b, ["slot", "hash"]).where("a_doc < b_doc")
    return pairs.groupBy("a_doc", "b_doc").agg(F.count_distinct("slot").alias("common")).where(F.col("common") >= min_common)


def candidates_by_join(posts: DataFrame) -> DataFrame:
    """Pairs by a self-join of the buckets: best where these are small."""
    a = posts.select("slot", "hash", F.col("doc_id").alias("a_doc"))
    b = posts.select("slot", "hash", F.col("doc_id").alias("b_doc"))
    return a.join(b, ["slot", "hash"]).where("a_doc < b_doc").select("a_doc", "b_doc").distinct()


def listing(posts: DataFrame, block_docs: int = 2048, block_postings: int = 2_000_000) -> dict[str, int]:
    """Rows that either way of listing the pairs moves, and the number of blocks, 0 if the join moves less.

    A block has at most about ``block_docs`` documents, so that a pair of blocks fits a matrix of bits, and about
    ``block_postings`` postings. There are enough pairs of blocks for the cores.
    """
    sizes = posts.groupBy("slot", "hash").agg(F.count(F.lit(1)).alias("n"))
    b = sizes.agg(F.sum("n").alias("postings"), F.sum((F.col("n") * (F.col("n") - 1) / 2).cast("bigint")).alias("pairs")).first()
    postings, pairs = b["postings"] or 0, b["pairs"] or 0
    docs = posts.agg(F.count_distinct("doc_id").alias("n")).first()["n"]
    enough = min(isqrt(4 * posts.sparkSession.sparkContext.defaultParallelism) + 1, docs // 256)
    blocks = max(1, -(-docs // block_docs), -(-postings // block_postings), enough)
    return {"postings": postings, "bucket_pairs": pairs, "blocks": blocks if pairs > postings * blocks else 0}


def candidates_by_blocks(posts: DataFrame, blocks: int) -> DataFrame:
    """Pairs by blocks of documents: each pair of blocks is a task, which marks the pairs of each bucket in a matrix and so
    lists a pair once. No pair is made twice or shuffled, and a hot bucket is spread over all pairs of blocks."""
    rows = posts.select("doc_id", F.xxhash64("slot", "hash").alias("key"), F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int").alias("_b"))
    rows = rows.withColumn("_o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = rows.select("doc_id", "key", F.least("_b", "_o").alias("_i"), F.greatest("_b", "_o").alias("_j"), (F.col("_b") > F.col("_o")).alias("side"))
    cells = 4_000_000

    def run(pair: pd.DataFrame) -> pd.DataFrame:
        one, key, doc, side = pair["_i"].iloc[0] == pair["_j"].iloc[0], *(pair[c].to_numpy() for c in ("key", "doc_id", "side"))

        def group(mine):  # documents, and by key the place of each
            names, at = np.unique(doc[mine], return_inverse=True)
            order = np.argsort(key[mine], kind="stable")
            keys, starts, counts = np.unique(key[mine][order], return_index=True, return_counts=True)
            return names, at[order], keys, starts, counts

        a = group(np.ones(len(key), bool) if one else ~side)
        b = a if one else group(side)
        seen = np.zeros((len(a[0]), len(b[0])), bool)
        _, x, y = np.intersect1d(a[2], b[2], assume_unique=True, return_indices=True)
        xs, xn, ys, yn = a[3][x], a[4][x], b[3][y], b[4][y]
        if one:
            keep = xn > 1
            xs, xn, ys, yn = xs[keep], xn[keep], ys[keep], yn[keep]
        size = xn * yn
        for k in np.flatnonzero(size > 4096):
            seen[np.ix_(a[1][xs[k] : xs[k] + xn[k]], b[1][ys[k] : ys[k] + yn[k]])] = True
        rest = np.flatnonzero(size <= 4096)
        ends = np.cumsum(size[rest])
        for at in range(0, int(ends[-1]) if len(rest) else 0, cells):
            part = rest[np.searchsorted(ends, at, side="right") : np.searchsorted(ends, at + cells, side="right") + 1]
            n = size[part]
            k = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            wide = np.repeat(yn[part], n)
            seen[a[1][np.repeat(xs[part], n) + k // wide], b[1][np.repeat(ys[part], n) + k % wide]] = True
        if one:
            seen = np.triu(seen, 1)
        i, j = np.nonzero(seen)
        left, right = a[0][i], b[0][j]
        return pd.DataFrame({"a_doc": np.minimum(left, right), "b_doc": np.maximum(left, right)})

    return rows.groupBy("_i", "_j").applyInPandas(run, "a_doc long, b_doc long")


def count_candidates(posts: DataFrame, block_postings: int = 8_000_000, block_docs: int = 1 << 17, bitmap_bytes: int = 64_000_000) -> DataFrame:
    """``candidates``: the number of pairs that :func:`candidates` lists, in one row, without listing them.

    Each pair of blocks is a task. A large bucket is a row of bits over the documents of one block; the candidates of a
    document of the other are the union of its buckets. What is shuffled is the postings times the blocks, which are few,
    as no matrix of pairs is kept; no row is made for a pair.
    """
    posts = posts.where(F.col("doc_id").isNotNull()).select("doc_id", F.xxhash64("slot", "hash").alias("key"))
    posts = stored(posts.groupBy("doc_id").agg(F.collect_set("key").alias("keys")), "document-postings")
    n = posts.agg(F.count(F.lit(1)).alias("docs"), F.sum(F.size("keys")).alias("postings")).first()
    enough = min(isqrt(2 * posts.sparkSession.sparkContext.defaultParallelism) + 1, n["docs"] // 256)
    blocks = max(1, -(-n["docs"] // block_docs), -(-(n["postings"] or 0) // block_postings), enough)
    rows = posts.select("keys", F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int").alias("_b"))
    rows = rows.withColumn("_o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = rows.select("keys", F.least("_b", "_o").alias("_i"), F.greatest("_b", "_o").alias("_j"), (F.col("_b") > F.col("_o")).alias("side"))
    cells = 4_000_000

    def run(pair: pd.DataFrame) -> pd.DataFrame:
        one, side, keys = pair["_i"].iloc[0] == pair["_j"].iloc[0], pair["side"].to_numpy(), pair["keys"].to_numpy()

        def flat(mine):  # places of documents and their keys, one after the other
            sizes = np.fromiter(map(len, mine), np.int64, len(mine))
            return np.repeat(np.arange(len(mine)), sizes), np.concatenate(mine) if len(mine) else np.empty(0, np.int64)

        b_side = ~side if one else side
        n_a, n_b = int((~side).sum()), int(b_side.sum())
        (a_doc, a_key), (b_doc, b_key) = flat(keys[~side]), flat(keys[b_side])
        if not n_a or not n_b:
            return pd.DataFrame({"n": [0]})
        order = np.argsort(b_key, kind="stable")
        members = b_doc[order]
        names, starts, counts = np.unique(b_key[order], return_index=True, return_counts=True)
        at = np.minimum(np.searchsorted(names, a_key), len(names) - 1)
        met = names[at] == a_key
        a_doc, at = a_doc[met], at[met]
        width = -(-n_b // 64)
        large = np.argsort(-counts, kind="stable")[: max(1, bitmap_bytes // (8 * width))]
        large = large[counts[large] >= 32]
        place = np.full(len(names), -1)
        place[large] = np.arange(len(large))
        bits = np.zeros((len(large), width), np.uint64)
        for k, g in enumerate(large):
            row = np.zeros(width * 64, np.uint8)
            row[members[starts[g] : starts[g] + counts[g]]] = 1
            bits[k] = np.packbits(row, bitorder="little").view(np.uint64)
        hot = place[at] >= 0
        hot_row, cold_doc, cold = place[at[hot]], a_doc[~hot], at[~hot]
        hot_ends = np.searchsorted(a_doc[hot], np.arange(n_a + 1))
        work = np.concatenate([[0], np.cumsum(np.bincount(cold_doc, weights=counts[cold], minlength=n_a))])
        cold_ends = np.searchsorted(cold_doc, np.arange(n_a + 1))
        total, first = 0, 0
        while first < n_a:
            last = int(min(first + 256, n_a, max(first + 1, np.searchsorted(work, work[first] + cells, side="right") - 1)))
            seen = np.zeros((last - first, width), np.uint64)
            for r in range(first, last):
                row = seen[r - first]
                for h in hot_row[hot_ends[r] : hot_ends[r + 1]]:
                    np.bitwise_or(row, bits[h], out=row)
            part = slice(cold_ends[first], cold_ends[last])
            size = counts[cold[part]]
            if size.sum():
                k = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
                r, m = np.repeat(cold_doc[part] - first, size), members[np.repeat(starts[cold[part]], size) + k]
                new = (seen[r, m >> 6] >> (m & 63).astype(np.uint64)) & np.uint64(1) == 0
                total += len(np.unique(r[new] * n_b + m[new]))
            total += int(np.bitwise_count(seen).sum(dtype=np.int64))
            first = last
        # In a block with itself a document meets itself once and each other one from both sides.
        return pd.DataFrame({"n": [(total - len(np.unique(a_doc))) // 2 if one else total]})

    found = rows.groupBy("_i", "_j").applyInPandas(run, "n long")
    return found.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("candidates"))


def per_document(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """How many candidates a document has: least, quartiles, ninth decile and most, over all documents."""
    ends = pairs.select(F.explode(F.array("a_doc", "b_doc")).alias("doc_id")).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    n = docs.select("doc_id").join(ends, "doc_id", "left").select(F.coalesce("n", F.lit(0)).alias("n"))
    at = [0.0, 0.25, 0.5, 0.75, 0.9, 1.0]
    values = n.agg(F.percentile("n", F.array(*map(F.lit, at))).alias("v"))
    rows = values.select(F.explode(F.arrays_zip(F.array(*map(F.lit, at)).alias("share"), F.col("v").alias("candidates"))).alias("r"))
    return rows.select("r.share", F.round("r.candidates", 6).alias("candidates"))


def candidates_of(posts: DataFrame, doc_id: int) -> DataFrame:
    """The candidate set of one document: the other documents of its buckets. The buckets of one document are few and are broadcast."""
    mine = posts.where(F.col("doc_id") == doc_id).select("slot", "hash").distinct()
    return posts.where(F.col("doc_id") != doc_id).join(F.broadcast(mine), ["slot", "hash"], "left_semi").select("doc_id").distinct()


def witnesses(signatures: DataFrame) -> DataFrame:
    """Pairs of passages that collide, with the number of slots they share."""
    rows = signatures.select("doc_id", "passage_no", F.posexplode("sig").alias("slot", "hash"))
    a = rows.select("slot", "hash", F.col("doc_id").alias("a_doc"), F.col("passage_no").alias("a_passage"))
    b = rows.select("slot", "hash", F.col("doc_id").alias("b_doc"), F.col("passage_no").alias("b_passage"))
    return a.join(b, ["slot", "hash"]).where("a_doc < b_doc").groupBy("a_doc", "a_passage", "b_doc", "b_passage").agg(F.count(F.lit(1)).alias("slots"))


def pruning(c: DataFrame, docs: DataFrame) -> DataFrame:
    """Candidate pairs, of which ``c`` has the number, and the share of the search space left out, by ordered and by unordered pairs."""
    n = docs.agg(F.count(F.lit(1)).alias("docs"))
    both = F.col("docs") * (F.col("docs") - 1)
    share = lambda k: F.round(1 - k * F.col("candidates") / F.nullif(both, F.lit(0)), 6)
    return n.join(c, F.lit(True)).select("docs", "candidates", share(1).alias("pruned_ordered"), share(2).alias("pruned_unordered"))


def quality(pairs: DataFrame, true_pairs: DataFrame) -> DataFrame:
    """Retrieval recall and precision against the pairs that truly share a gram."""
    found = true_pairs.join(pairs, ["a_doc", "b_doc"], "left_semi").agg(F.count(F.lit(1)).alias("found"))
    wanted = true_pairs.agg(F.count(F.lit(1)).alias("wanted"))
    kept = pairs.agg(F.count(F.lit(1)).alias("kept"))
    row = found.join(wanted, F.lit(True)).join(kept, F.lit(True))
    return row.select("found", "wanted", "kept", F.round(F.col("found") / F.nullif("wanted", F.lit(0)), 6).alias("recall"), F.round(F.col("found") / F.nullif("kept", F.lit(0)), 6).alias("precision"))


def bucket_profile(posts: DataFrame) -> DataFrame:
    """How many buckets have how many documents, and the pairs that they emit."""
    sizes = posts.groupBy("slot", "hash").agg(F.count(F.lit(1)).alias("docs"))
    out = sizes.groupBy("docs").agg(F.count(F.lit(1)).alias("buckets"))
    return out.withColumn("pairs", (F.col("buckets") * F.col("docs") * (F.col("docs") - 1) / 2).cast("bigint"))


def work_counters(rows: DataFrame, posts: DataFrame) -> DataFrame:
    """Counts of work instead of seconds: words, postings, largest bucket, pairs before distinct."""
    ws = rows.agg(F.sum(F.size("words")).cast("bigint").alias("words"))
    sizes = posts.groupBy("slot", "hash").agg(F.count(F.lit(1)).alias("n"))
    b = sizes.agg(F.sum("n").cast("bigint").alias("postings"), F.max("n").alias("largest_bucket"), F.sum((F.col("n") * (F.col("n") - 1) / 2).cast("bigint")).alias("bucket_pairs"))
    return ws.join(b, F.lit(True))


def min_shared_words(n: int, m: int, model: str = "jaccard") -> int:
    """Words that two n-word passages must share to reach the bound 1/m: of the union, or of a passage."""
    return ceil(2 * n / (m + 1)) if model == "jaccard" else ceil(n / m)


def collision_probability(j: float, m: int) -> float:
    """Chance that at least one of m independent MinHash values agrees."""
    return 1 - (1 - j) ** m


def choose_m(min_jaccard: float, target_recall: float | None = None) -> int:
    """Hashes so that the bound 1/m lies under a threshold, or so that a recall is reached there."""
    return ceil(1 / min_jaccard) if target_recall is None else ceil(log(1 - target_recall) / log(1 - min_jaccard))


def bound_table(rows: DataFrame, settings: list[tuple[int, int]]) -> DataFrame:
    """Both formulas of the minimal overlap, and the real chance of a collision at the bound, for the passages of a
    collection: by setting (words of a passage, hashes) and by n, the distinct words that a passage really has."""
    out = None
    for length in sorted({length for length, _ in settings}):
        sizes = chop(rows.select("doc_id", "words"), length).select(F.size(F.array_distinct("words")).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("passages"))
        each = sizes.select(F.lit(length).alias("length"), "n", F.explode(F.array(*(F.lit(m) for words, m in settings if words == length))).alias("m"), "passages")
        out = each if out is None else out.unionAll(each)
    n, m = F.col("n"), F.col("m")
    return out.select(
        "length", n.cast("bigint").alias("n"), m.cast("bigint").alias("m"), "passages",
        F.ceil(2 * n / (m + 1)).cast("bigint").alias("words_jaccard"), F.ceil(n / m).cast("bigint").alias("words_containment"),
        F.round(1 - F.pow(1 - 1 / m, m), 6).alias("collision_at_bound"),
    )


def estimate_jaccard(a: Column, b: Column) -> Column:
    """Share of slots in which two signatures agree."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x) / F.size(a)


def sketched(docs: DataFrame, n: int = 50, m: int = 10, family: str = "xx") -> DataFrame:
    """Signatures of all passages of ``docs``."""
    return minhash(chop(worded(docs).select("doc_id", "words"), n), m, family)
