"""MinHash near-dedup by a multi-index Hamming join.

1. A document is the set of its distinct word shingles, hashed to 64 bits. Equal
   sets form a class; from here on only one member of a class is looked at.
2. A class has a signature: ``slots`` minima of as many hash functions, each cut to
   ``bits`` bits. The distance of two signatures is the number of differing slots.
3. The slots are split into ``chunks`` equal chunks. If two signatures differ in at
   most ``errors * chunks + chunks - 1`` slots, some chunk differs in at most
   ``errors`` (pigeonhole). All ways to leave out ``errors`` slots of a chunk are
   enumerated, and what remains is a key: every pair under the threshold shares one.
4. Of the members of a key's bucket, pairs within the signature distance become edges;
   connected edges are families. Members that only share a key, as pages of one template
   do, are not brought together. A large bucket is dealt into blocks as a family is (5, 6).
5. A family is dealt into blocks of bounded size. Each block, joined by a few pivots of
   its family, goes to one task, which finds the pairs within the distance and confirms
   them on the full sets. It returns a spanning forest of the links, at most a row a
   member. The data that this moves grows with the family, not with its square.
6. Only classes of different components can still be linked. The largest component of
   a family is its core. Blocks of the rest meet each other and those of the core, in a
   task a pair; blocks of the core never meet again. A family of true copies has no rest.
7. Components of all links, over classes, then give every row its label.

With 9 chunks of 5 slots and one error, all pairs within 17 of 45 differing slots are
found; a pair of similarity 0.85 differs in 6.75 slots on average and is outside with
a chance of about 4e-5, and misses every chunk with one below 1e-7. For ``percent=80``
``AT_80`` has 12 chunks of 4 slots: all pairs within 23 of 48 are found, and a pair of
similarity 0.80, which differs in 9.6 slots on average, is outside with a chance of 3e-6.

Cases: null, empty and blank texts have no shingles and link with nothing. Texts
shorter than a shingle are one shingle. Rows that repeat link as equal sets. A null
id is never the smallest: a component has a null id only if all its ids are null. Ties,
as rows of one id, are told apart by ``text_hash``, and rows of one id and text not at
all: ``chosen`` marks the rows of the smallest id of a component and, of these, of the
smallest hash, so that a component's chosen rows have one id and one text. Very long
texts are one row of one block. An empty table gives an empty result. Other columns of
the input are passed by, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, small_or_shuffled
from .components import components
from .hashing import mixed, shingle_set


@dataclass(frozen=True)
class Near:
    words: int = 5
    #: Link if 100 * intersection >= percent * union.
    percent: int = 85
    chunks: int = 9
    chunk_slots: int = 5
    errors: int = 1
    bits: int = 16
    #: Most shingles of a block; a single longer document is a block of its own.
    block_shingles: int = 1_000_000
    #: A family is spread over up to ``spread`` blocks, so long as they hold ``block_least`` shingles.
    block_least: int = 65_536
    spread: int = 8
    #: Most members of a block of a key's bucket.
    bucket_members: int = 4096
    #: Members of a bucket or family that meet all its blocks at once.
    pivots: int = 8
    seed: int = 11

    @property
    def slots(self) -> int:
        return self.chunks * self.chunk_slots

    @property
    def distance(self) -> int:
        """Largest signature distance at which the join is complete."""
        return self.errors * self.chunks + self.chunks - 1


#: Complete from a similarity of 0.80 on.
AT_80 = Near(percent=80, chunks=12, chunk_slots=4)


def signature(hashes: np.ndarray, near: Near) -> np.ndarray:
    """Minima of ``slots`` hash functions over the shingle hashes, cut to ``bits`` bits."""
    rng = np.random.default_rng(near.seed)
    odd = rng.integers(1, 1 << 63, near.slots, dtype=np.uint64) | np.uint64(1)
    out = np.empty(near.slots, np.uint64)
    for k in range(near.slots):
        z = hashes * odd[k]
        z ^= z >> np.uint64(32)
        out[k] = (z * odd[k]).min()
    return (mixed(out) >> np.uint64(64 - near.bits)).astype(np.uint32)


def all_keys(sigs: np.ndarray, near: Near) -> np.ndarray:
    """A key for every chunk and every choice of slots left out, for each signature; the place of the slots is part of the key."""
    columns = []
    for c in range(near.chunks):
        part = sigs[:, c * near.chunk_slots : (c + 1) * near.chunk_slots].astype(np.uint64)
        for v, left in enumerate(combinations(range(near.chunk_slots), near.chunk_slots - near.errors)):
            z = np.full(len(sigs), c * 1000 + v + 1, np.uint64)
            for i in left:
                z = mixed(z * np.uint64(0x9E3779B97F4A7C15) + part[:, i])
            columns.append(z)
    return np.stack(columns, axis=1).view(np.int64) if len(sigs) else np.empty((0, 0), np.int64)


LINKS = "a long, b long"
BUCKET = ["family", "node", "label", "sig"]
MEMBER = [*BUCKET, "shingles"]
SKETCH = "doc_id string, text_hash long, n_shingles long, node long, check long, sig binary"


def sketch(docs: DataFrame, near: Near, text: str, key: str) -> DataFrame:
    """Size, 128-bit fingerprint of the set (``node``, ``check``) and signature of every row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sizes, nodes, checks, sigs = [], [], [], []
            for whole in batch["_text"]:
                h = shingle_set(whole, near.words)
                sizes.append(len(h))
                if not len(h):
                    nodes.append(None), checks.append(None), sigs.append(None)
                    continue
                node = int(mixed(h).sum(dtype=np.uint64).view(np.int64))
                check = int((mixed(h ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64) + np.uint64(len(h))).view(np.int64))
                nodes.append(node), checks.append(check), sigs.append(signature(h, near).astype(np.uint16 if near.bits <= 16 else np.uint32).tobytes())
            # Columns with nulls are built as nullable integers: 64-bit hashes do not survive a float.
            yield pd.DataFrame({"doc_id": batch["_id"], "text_hash": batch["_hash"], "n_shingles": sizes, "node": pd.array(nodes, "Int64"), "check": pd.array(checks, "Int64"), "sig": sigs})

    drawn = docs.select(F.col(key).cast("string").alias("_id"), F.xxhash64(F.col(text)).alias("_hash"), F.col(text).alias("_text")).mapInPandas(run, SKETCH)
    return drawn.withColumn("doc_id", F.col("doc_id").cast("long"))


def postings(classes: DataFrame, near: Near) -> DataFrame:
    """``key, node`` for every class and key."""
    kind = np.uint16 if near.bits <= 16 else np.uint32

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for at in range(0, len(batch), 2000):
                part = batch.iloc[at : at + 2000]
                keys = all_keys(np.stack([np.frombuffer(s, kind) for s in part["sig"]]), near)
                yield pd.DataFrame({"key": keys.ravel(), "node": np.repeat(part["node"].to_numpy(np.int64), keys.shape[1])})

    return classes.select("node", "sig").mapInPandas(run, "key long, node long")


def near_in_buckets(block: pd.DataFrame, near: Near) -> pd.DataFrame:
    """Edges that connect the members of each bucket (``family``) of a block that are within the signature distance.

    Small buckets are compared pair by pair, all of them at once; a large one skips pairs that are connected already.
    """
    kind = np.uint16 if near.bits <= 16 else np.uint32
    block = block.drop_duplicates(["family", "node"]).sort_values(["family", "node"])
    family, nodes = block["family"].to_numpy(np.int64), block["node"].to_numpy(np.int64)
    sigs = np.frombuffer(b"".join(block["sig"]), kind).reshape(len(block), near.slots) if len(block) else np.empty((0, near.slots), kind)
    starts = np.flatnonzero(np.concatenate([[True], family[1:] != family[:-1]])) if len(block) else np.empty(0, int)
    sizes = np.diff(np.append(starts, len(block)))
    size = np.repeat(sizes, sizes)
    ends = np.repeat(starts + sizes, sizes)
    found: list[np.ndarray] = []
    small = 32
    for shift in range(1, small):
        left = np.flatnonzero((size <= small) & (np.arange(len(block)) + shift < ends))
        if not len(left):
            break
        left = left[(sigs[left] != sigs[left + shift]).sum(axis=1) <= near.distance]
        found.append(np.stack([nodes[left], nodes[left + shift]], axis=1))
    _, label = np.unique(block["label"].to_numpy(np.int64), return_inverse=True)
    side = block["side"].to_numpy()
    for at, n in zip(starts[sizes > small], sizes[sizes > small], strict=True):
        root, part, own = label[at : at + n].copy(), sigs[at : at + n], side[at : at + n]
        between = (own != own[0]).any()
        for i in range(n - 1):
            todo = root[i + 1 :] != root[i]
            if between:
                todo &= own[i + 1 :] != own[i]
            todo = np.flatnonzero(todo) + i + 1
            todo = todo[(part[todo] != part[i]).sum(axis=1) <= near.distance]
            if len(todo):
                _, one = np.unique(root[todo], return_index=True)
                found.append(np.stack([np.full(len(one), nodes[at + i]), nodes[at + todo[one]]], axis=1))
                root[np.isin(root, root[todo])] = root[i]
    return pd.DataFrame(np.concatenate(found) if found else np.empty((0, 2), np.int64), columns=["a", "b"])


def within(pairs: DataFrame, near: Near) -> DataFrame:
    """Rows of ``a, b`` whose signatures (``a_sig``, ``b_sig``) are within the distance."""
    kind = np.uint16 if near.bits <= 16 else np.uint32

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            one, other = (np.frombuffer(b"".join(batch[c]), kind).reshape(len(batch), near.slots) for c in ("a_sig", "b_sig"))
            yield batch.loc[(one != other).sum(axis=1) <= near.distance, ["a", "b"]]

    return pairs.mapInPandas(run, LINKS)


def families(posted: DataFrame, classes: DataFrame, near: Near, scratch: Scratch) -> DataFrame:
    """``node, label`` for every class that is within the signature distance of another, or connected to it by such.

    First each member of a bucket meets the bucket's least class: one row a member. What this leaves in several
    components, in buckets of more than two, is compared within the bucket.
    """
    shared = posted.groupBy("key").agg(F.count(F.lit(1)).alias("members"), F.min("node").alias("least"), F.max("node").alias("most")).where("least <> most").drop("most")
    rows = scratch.cut(posted.join(shared, "key").select(F.col("key").alias("family"), "node", "members", "least"), "shared")
    sigs = classes.select("node", "sig")
    side = lambda s: sigs.select(F.col("node").alias(s), F.col("sig").alias(f"{s}_sig"))
    stars = rows.where("node <> least").select(F.col("least").alias("a"), F.col("node").alias("b")).distinct()
    edges = scratch.cut(within(stars.join(side("a"), "a").join(side("b"), "b"), near), "stars")
    labels = components(edges, scratch)
    some = rows.where("members > 2").drop("least").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    unsettled = some.groupBy("family").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("family")
    blocks = lambda members: F.ceil(members / near.bucket_members).cast("int")
    left = scratch.cut(some.join(unsettled, "family", "left_semi").join(sigs, "node").withColumn("_n", blocks(F.col("members"))), "buckets")
    scratch.drop(rows)
    counted = left.agg(F.count_if(F.col("_n") == 1).alias("small"), F.count_if(F.col("_n") > 1).alias("large")).first()
    if not counted["small"] and not counted["large"]:
        return labels
    how = lambda block: near_in_buckets(block, near)
    dealt = F.pmod(F.xxhash64("family"), F.lit(max(1, counted["small"] // 20_000))).cast("long")
    edges = edges.union(left.where("_n = 1").select(*BUCKET, F.lit(0).alias("side"), dealt.alias("_g")).groupBy("_g").applyInPandas(how, LINKS))
    if counted["large"]:
        by, many = ["_g", "_i", "_j"], left.where("_n > 1").drop("members")
        edges = scratch.cut(edges.union(one_by_one(many, near, BUCKET).groupBy(*by).applyInPandas(how, LINKS)), "edges")
        again = across(many.withColumn("weight", F.lit(1)), components(edges, scratch), blocks, scratch, BUCKET)
        edges = edges.union(again.groupBy(*by).applyInPandas(how, LINKS))
    return components(edges, scratch)


def shingles_of(docs: DataFrame, wanted: DataFrame, near: Near, text: str, key: str) -> DataFrame:
    """``node, shingles`` of the representatives in ``wanted`` (``rep``, ``node``), from their whole texts."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sets = [np.sort(shingle_set(x, near.words)) for x in batch["_text"]]
            node = [int(mixed(h).sum(dtype=np.uint64).view(np.int64)) for h in sets]
            yield pd.DataFrame({"node": node, "shingles": [h.tobytes() for h in sets]})

    reps = small_or_shuffled(wanted.select(F.col("rep.doc_id").alias("_i"), F.col("rep.text_hash").alias("_h")))
    found = docs.select(F.col(key).cast("long").alias("_id"), F.col(text).alias("_text"))
    found = found.join(reps, F.col("_id").eqNullSafe(F.col("_i")) & (F.xxhash64("_text") == F.col("_h")), "left_semi")
    return found.where("_text is not null").mapInPandas(run, "node long, shingles binary")


def confirm(block: pd.DataFrame, near: Near) -> pd.DataFrame:
    """Spanning forest of the confirmed links between classes of different ``label`` in a block, or between two blocks of a family."""
    kind = np.uint16 if near.bits <= 16 else np.uint32
    links: list[tuple[int, int]] = []
    for _, family in block.drop_duplicates(["family", "node"]).groupby("family", sort=False):
        family = family.sort_values("node")
        nodes, sides = family["node"].to_numpy(np.int64), family["side"].to_numpy()
        sigs = np.stack([np.frombuffer(s, kind) for s in family["sig"]])
        sets = [np.frombuffer(s, np.uint64) for s in family["shingles"]]
        sizes = np.array([len(s) for s in sets])
        starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        _, ids = np.unique(np.concatenate(sets), return_inverse=True)
        mark = np.zeros(ids.max() + 1, bool)
        _, root = np.unique(family["label"].to_numpy(np.int64), return_inverse=True)
        between = len(set(sides)) > 1
        for i in range(len(nodes) - 1):
            todo = root[i + 1 :] != root[i]
            if between:
                todo &= sides[i + 1 :] != sides[i]
            todo = np.flatnonzero(todo) + i + 1
            small, large = np.minimum(sizes[todo], sizes[i]), np.maximum(sizes[todo], sizes[i])
            todo = todo[100 * small >= near.percent * large]
            todo = todo[(sigs[todo] != sigs[i]).sum(axis=1) <= near.distance]
            if not len(todo):
                continue
            mine = ids[starts[i] : starts[i] + sizes[i]]
            mark[mine] = True
            for j in todo:
                if root[j] != root[i]:
                    both = int(mark[ids[starts[j] : starts[j] + sizes[j]]].sum())
                    if 100 * both >= near.percent * (sizes[i] + sizes[j] - both):
                        links.append((int(nodes[i]), int(nodes[j])))
                        root[root == root[j]] = root[i]
            mark[mine] = False
    return pd.DataFrame(links, columns=["a", "b"], dtype="int64")


def confirmed(rows: DataFrame, near: Near) -> DataFrame:
    """Links found in each group of ``_g, _i, _j``."""
    return rows.groupBy("_g", "_i", "_j").applyInPandas(lambda block: confirm(block, near), LINKS)


def n_blocks(shingles: Column, near: Near) -> Column:
    """Blocks that so many shingles are dealt into."""
    spread = F.least(F.lit(near.spread), F.ceil(shingles / near.block_least))
    return F.greatest(spread, F.ceil(shingles / near.block_shingles)).cast("int")


def own_block() -> Column:
    return F.pmod(F.xxhash64("node"), F.col("_n")).cast("int")


def alone(placed: DataFrame, families: int) -> DataFrame:
    """Families of one block, about a hundred to a group."""
    groups = F.lit(max(1, families // 100))
    return placed.where("_n = 1").select(*MEMBER, F.lit(0).alias("side"), F.pmod(F.xxhash64("family"), groups).cast("long").alias("_g"), F.lit(-1).alias("_i"), F.lit(-1).alias("_j"))


def one_by_one(many: DataFrame, near: Near, pick: list[str]) -> DataFrame:
    """Each block of the families of several (``_n``), with the pivots of its family."""
    chosen = many.groupBy("family", F.pmod(F.xxhash64("node", F.lit(1)), F.lit(near.pivots))).agg(F.min("node").alias("node")).select("family", "node")
    pivots = many.join(chosen, ["family", "node"], "left_semi").withColumn("_i", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    both = many.withColumn("_i", own_block()).unionByName(pivots.where(F.col("_i") != own_block()))
    return both.select(*pick, F.lit(0).alias("side"), F.col("family").alias("_g"), "_i", F.col("_i").alias("_j"))


def across(many: DataFrame, labels: DataFrame, blocks: Callable[[Column], Column], scratch: Scratch, pick: list[str]) -> DataFrame:
    """Pairs of blocks of the families of several that are not one component of ``labels`` (``node``, ``label``).

    ``blocks`` tells into how many a sum of ``weight`` is dealt.
    """
    many = many.drop("label", "_n").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    parts = many.groupBy("family", "label").agg(F.sum("weight").alias("_part"))
    cores = parts.groupBy("family").agg(F.max(F.struct("_part", "label")).alias("_core"), F.sum("_part").alias("_all")).where("_all > _core._part")
    rest = F.col("_all") - F.col("_core._part")
    cores = cores.select("family", F.col("_core.label").alias("_core"), blocks(F.col("_core._part")).alias("_c"), blocks(rest).alias("_r"))
    cores = scratch.cut(cores, "cores")
    # Blocks of the core come first, then those of the rest; a core block meets only the latter.
    rows, own = many.join(small_or_shuffled(cores), "family"), F.xxhash64("node")
    in_core = F.col("label") == F.col("_core")
    rows = rows.withColumn("side", F.when(in_core, F.pmod(own, F.col("_c"))).otherwise(F.col("_c") + F.pmod(own, F.col("_r"))).cast("int"))
    rows = rows.withColumn("_o", F.explode(F.sequence(F.when(in_core, F.col("_c")).otherwise(F.lit(0)), F.col("_c") + F.col("_r") - 1)))
    return rows.select(*pick, "side", F.col("family").alias("_g"), F.least("side", "_o").alias("_i"), F.greatest("side", "_o").alias("_j"))


def links(classes: DataFrame, docs: DataFrame, near: Near, scratch: Scratch, text: str, key: str) -> DataFrame:
    """Confirmed links that connect the classes (``node``, ``rep``, ``n_shingles``, ``sig``)."""
    posted = scratch.cut(postings(classes, near), "postings")
    members = families(posted, classes, near, scratch).withColumnRenamed("label", "family")
    members = scratch.cut(members.join(classes, "node"), "families")
    scratch.drop(posted)
    sets = shingles_of(docs, members, near, text, key)
    sizes = scratch.cut(members.groupBy("family").agg(n_blocks(F.sum("n_shingles"), near).alias("_n")), "sizes")
    n = sizes.count()
    placed = members.join(small_or_shuffled(sizes), "family").join(sets.dropDuplicates(["node"]), "node").withColumn("label", F.col("node"))
    placed = scratch.cut(placed.withColumnRenamed("n_shingles", "weight"), "sets")
    found = confirmed(alone(placed, n), near)
    if not sizes.where("_n > 1").isEmpty():
        many = placed.where("_n > 1")
        first = scratch.cut(confirmed(one_by_one(many, near, MEMBER), near), "first-links")
        again = across(many, components(first, scratch), lambda weight: n_blocks(weight, near), scratch, MEMBER)
        found = found.union(first).union(confirmed(again, near))
    found = scratch.cut(found, "links")
    scratch.drop(placed, members, sizes)
    return found


KEY = ("doc_id", "text_hash")


def near_duplicates(docs: DataFrame, near: Near = Near(), text: str = "text", key: str = "doc_id") -> DataFrame:
    """``doc_id, n_shingles, component_id, kept, text_hash, chosen`` for every row of ``docs``.

    ``component_id`` is the smallest id that links reach, ``kept`` is true for rows of that id. ``text_hash`` is
    ``xxhash64`` of the text; ``chosen`` rows of a component have one id and one hash.
    """
    scratch = Scratch(docs.sparkSession, "neardup")
    drawn = scratch.cut(sketch(docs, near, text, key), "sketch")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), *KEY)).alias("rep")
    classes = drawn.where("n_shingles > 0").groupBy("node", "check").agg(least, F.first("n_shingles").alias("n_shingles"), F.first("sig").alias("sig"))
    classes = scratch.cut(classes, "classes")
    found = links(classes, docs, near, scratch, text, key)
    named = components(found, scratch).join(classes.select("node", "rep"), "node")
    linked = named.join(named.groupBy("label").agg(F.min("rep").alias("_linked")), "label").select("node", "_linked")
    labels = classes.select("node", "check", F.col("rep").alias("_own")).join(linked, "node", "left")
    out = drawn.select("doc_id", "text_hash", "n_shingles", "node", "check").join(labels.select("node", "check", F.coalesce("_linked", "_own").alias("_rep")), ["node", "check"], "left")
    some = F.col("n_shingles") > 0
    out = out.select(*KEY, "n_shingles", F.when(some, F.col("_rep.doc_id")).otherwise(F.col("doc_id")).alias("component_id"), "_rep")
    chosen = ~some | (F.col("doc_id").eqNullSafe(F.col("_rep.doc_id")) & (F.col("text_hash") == F.col("_rep.text_hash")))
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"), "text_hash", chosen.alias("chosen"))


def deduplicated(docs: DataFrame, near: Near = Near(), text: str = "text", key: str = "doc_id") -> DataFrame:
    """``docs`` with one row of each component, and all rows without words; columns as they are.

    Rows are told by id and text hash, null ids too, so a row goes only if its own text links. Of rows of one id and
    text one stays: only those, if any, are brought together. Texts stay where they are if the rejected keys are few.
    """
    scratch = Scratch(docs.sparkSession, "dedup")
    found = scratch.cut(near_duplicates(docs, near, text, key), "found")
    rejected = scratch.cut(found.where("not chosen").select(*(F.col(c).alias(f"_{c}") for c in KEY)).distinct(), "rejected")
    again = scratch.cut(found.where("chosen and n_shingles > 0").groupBy(*KEY).count().where("count > 1").select(*(F.col(c).alias(f"_{c}") for c in KEY)), "repeated")
    whole = F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row")
    rows = docs.select(whole, F.col(f"`{key}`").cast("long").alias("_key"), F.xxhash64(F.col(f"`{text}`")).alias("_text"))
    same = F.col("_key").eqNullSafe(F.col("_doc_id")) & (F.col("_text") == F.col("_text_hash"))
    rows = rows.join(small_or_shuffled(rejected), same, "left_anti")
    if not again.isEmpty():
        again = small_or_shuffled(again)
        once = rows.join(again, same, "left_semi").groupBy("_key", "_text").agg(F.first("row").alias("row"))
        rows = rows.join(again, same, "left_anti").select("row").unionByName(once.select("row"))
    return rows.select(*(F.col(f"row.`{c}`").alias(c) for c in docs.columns))
