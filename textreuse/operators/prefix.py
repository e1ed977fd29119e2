"""Exact pairs of similar passages by a prefix filter, in blocks of passages that meet in tasks.

With the words of each passage in one order, rarest first, two passages whose shared words must number ``o`` share one
among the first n - o + 1 of each. Blocks of passages are files below the shared folder, each written once; a task reads
the two blocks of its pair. So what is on disk grows with the collection, and neither a word nor a pair is shuffled.
Words are told by 64-bit hashes; a passage is told by ``doc_id`` and ``passage_no``.
"""

from __future__ import annotations

import sys
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.io import delete, get, put, shared_folder, stored

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need no installed copy of this package

#: Passages of a block, matches that a task holds at once, pairs that are compared whole at once.
BLOCK, CELLS, WHOLE = 1 << 16, 1_000_000, 1 << 12
#: Words are counted by so many bits of their hashes; words that fall together only count as more frequent.
SLOT_BITS = 22


def least_shared(most: int, j: float) -> np.ndarray:
    """By the sum of two sizes, the fewest shared words that reach the similarity."""
    t = np.arange(2 * most + 1)
    s = np.maximum(1, (j * t / (1 + j)).astype(np.int64) - 1)
    with np.errstate(divide="ignore"):
        for _ in range(4):
            s = s + ((t > s) & (s / np.maximum(t - s, 1) < j))
    return s


def _least_partner(most: int, j: float) -> np.ndarray:
    """By size, the size of the smallest passage that can be that similar."""
    n = np.maximum(np.arange(most + 1), 1)
    s = np.maximum(1, (j * n).astype(np.int64) - 1)
    for _ in range(3):
        s = s + (s / n < j)
    return s


def _signatures(tokens: np.ndarray, of: np.ndarray, n: int) -> np.ndarray:
    """256 bits a passage: of how many words the last byte is odd. Two differ in no more bits than their passages in words."""
    counts = np.bincount(of * 256 + (tokens & 255), minlength=n * 256).astype(np.uint8) & 1
    return np.packbits(counts.reshape(n, 256), axis=1, bitorder="little").view(np.uint64)


def _ordered(parts: list[dict], rank: np.ndarray, j: float) -> dict:
    """A block: words of each passage by rank, and the order of those of its prefixes by word.

    ``core`` are the words that count if the other passage is not smaller; they come first in the order.
    """
    doc, no, size, tokens = (np.concatenate([p[c] for p in parts]) for c in ("doc", "no", "size", "tokens"))
    of = np.repeat(np.arange(len(size)), size)
    tokens = tokens[np.lexsort((tokens, rank[tokens & (len(rank) - 1)], of))]
    starts = np.cumsum(size) - size
    place, n, most = np.arange(len(tokens)) - starts[of], size[of], int(size.max())
    shared = least_shared(most, j)
    head = np.flatnonzero(place <= n - shared[n + np.minimum(_least_partner(most, j)[n], n)])
    core = place[head] <= n[head] - shared[2 * n[head]]
    order = np.lexsort((~core, tokens[head]))
    return {"doc": doc, "no": no, "size": size, "tokens": tokens, "signature": _signatures(tokens, of, len(size)), "order": head[order].astype(np.uint32), "core": core[order]}


def _candidates(a: dict, b: dict, one: bool, shared: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of passages that share a word where they must, and may be similar by their signatures; by whole passages of a."""
    a_at, b_at = a["order"].astype(np.int64), b["order"].astype(np.int64)
    if not len(a_at) or not len(b_at):
        return
    place = lambda s, at, of: (at - (np.cumsum(s["size"]) - s["size"])[of]).astype(np.int32)
    passage = lambda s, at: np.repeat(np.arange(len(s["size"]), dtype=np.int32), s["size"])[at]
    b_of = passage(b, b_at)
    b_place = place(b, b_at, b_of)
    names, starts, counts = np.unique(b["tokens"][b_at], return_index=True, return_counts=True)
    cores = np.add.reduceat(b["core"].astype(np.int64), starts)
    wanted = a["tokens"][a_at]
    at = np.minimum(np.searchsorted(names, wanted), len(names) - 1)
    n = np.where(names[at] == wanted, np.where(a["core"], counts[at], cores[at]), 0)
    met = np.flatnonzero(n)
    met = met[np.argsort(a_at[met], kind="stable")]  # by passage
    at, n, a_of = starts[at[met]], n[met], passage(a, a_at[met])
    a_place = place(a, a_at[met], a_of)
    begins = np.flatnonzero(np.diff(a_of, prepend=-1))
    ends, work = np.append(begins, len(n)), np.append(0, np.cumsum(n))
    first = 0
    while first < len(begins):
        last = int(np.searchsorted(work[ends], work[ends[first]] + CELLS, side="right")) - 1
        last = min(len(begins), max(first + 1, last))
        i, k = ends[first], ends[last]
        lengths = n[i:k]
        e = np.repeat(np.arange(i, k), lengths)
        y = np.arange(len(e)) + np.repeat(at[i:k] - (work[i:k] - work[i]), lengths)
        p, q = a_of[e], b_of[y]
        keep = np.flatnonzero(p < q) if one else slice(None)
        e, y, p, q = e[keep], y[keep], p[keep], q[keep]
        a_n, b_n = a["size"][p], b["size"][q]
        o = shared[a_n + b_n]
        some = np.flatnonzero((a_place[e] <= a_n - o) & (b_place[y] <= b_n - o) & (a["doc"][p] != b["doc"][q]))
        p, q, spare = p[some], q[some], (a_n + b_n - 2 * o)[some]
        some = np.bitwise_count(a["signature"][p] ^ b["signature"][q]).sum(axis=1, dtype=np.int64) <= spare
        code = np.unique(p[some].astype(np.int64) * len(b["size"]) + q[some])
        yield code // len(b["size"]), code % len(b["size"])
        first = last


def _shared_words(a: dict, b: dict, p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """How many words two passages share, whole."""

    def table(s, of):
        size, first = s["size"][of], (np.cumsum(s["size"]) - s["size"])[of]
        at = np.arange(size.max())
        inside = at < size[:, None]
        return np.where(inside, s["tokens"][np.minimum(first[:, None] + at, len(s["tokens"]) - 1)], 0), inside

    (x, x_in), (y, y_in) = table(a, p), table(b, q)
    found = np.zeros(len(p), np.int64)
    for c in range(y.shape[1]):
        found += ((x == y[:, c : c + 1]) & x_in).any(axis=1) & y_in[:, c]
    return found


def _similar(a: dict, b: dict, one: bool, j: float) -> Iterator[dict]:
    shared = least_shared(int(max(a["size"].max(), b["size"].max())), j)
    for p, q in _candidates(a, b, one, shared):
        for i in range(0, len(p), WHOLE):
            x, y = p[i : i + WHOLE], q[i : i + WHOLE]
            n = _shared_words(a, b, x, y)
            value = n / (a["size"][x] + b["size"][y] - n)
            keep = value >= j
            x, y, value = x[keep], y[keep], value[keep]
            turned = a["doc"][x] > b["doc"][y]
            ends = {f"{s}_{c}": np.where(turned, other, mine) for c, k in (("doc", "doc"), ("passage", "no")) for s, mine, other in (("a", a[k][x], b[k][y]), ("b", b[k][y], a[k][x]))}
            yield {c: ends[c] for c in ("a_doc", "a_passage", "b_doc", "b_passage")} | {"jaccard": value}


def passage_pairs(passages: DataFrame, min_jaccard: float) -> DataFrame:
    """``a_doc, a_passage, b_doc, b_passage, jaccard`` of passages of different documents (a_doc < b_doc)."""
    spark, j, block = passages.sparkSession, float(min_jaccard), BLOCK
    root = f"{shared_folder(spark)}/textreuse-passages-{uuid.uuid4().hex}"
    given, blocks_at, low = f"{root}/given", f"{root}/blocks", (1 << SLOT_BITS) - 1
    hashes = F.transform(F.array_distinct(F.filter("words", lambda w: w.isNotNull())), lambda w: F.xxhash64(w))
    rows = passages.where("doc_id is not null and passage_no is not null").select(F.col("doc_id").cast("bigint"), F.col("passage_no").cast("bigint"), hashes.alias("h")).where(F.size("h") > 0)
    names = ["file", "n", "slot", "count"]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def packed_rows() -> pa.RecordBatch:
            got = {c: np.concatenate([h[c] for h in held]) for c in held[0]}
            file = put(given, got)
            slots, counts = np.unique(got["tokens"] & low, return_counts=True)
            first = lambda v, kind: pa.concat_arrays([pa.array([v], kind), pa.nulls(len(slots) - 1, kind)])
            return pa.RecordBatch.from_arrays([first(file, pa.string()), first(len(got["doc"]), pa.int64()), pa.array(slots.astype(np.int32)), pa.array(counts.astype(np.int64))], names=names)

        for b in batches:
            if b.num_rows:
                h = b.column(2)
                size = h.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
                held.append({"doc": b.column(0).to_numpy(), "no": b.column(1).to_numpy(), "size": size, "tokens": h.flatten().to_numpy()})
                n += b.num_rows
            if n >= block:
                yield packed_rows()
                held, n = [], 0
        if n:
            yield packed_rows()

    packed = stored(rows.mapInArrow(pack, "file string, n long, slot int, count long"), "passage-words")
    files = [(r["file"], r["n"]) for r in packed.where("file is not null").select("file", "n").collect()]
    often = packed.groupBy("slot").agg(F.sum("count").alias("n")).where("n > 1").select("slot", F.least(F.lit(255), F.floor(8 * F.log2("n"))).cast("short").alias("rank")).toArrow()
    rank = np.zeros(1 << SLOT_BITS, np.uint8)
    rank[often.column(0).to_numpy()] = often.column(1).to_numpy()
    groups: list[list[str]] = []
    room = 0
    for file, n in sorted(files, key=lambda f: (-f[1], f[0])):
        if not groups or room < n:
            groups, room = [*groups, []], max(block, n)
        groups[-1].append(file)
        room -= n
    sent = spark.sparkContext.broadcast(rank)

    def arrange(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in b.column(0).to_pylist():
                yield pa.RecordBatch.from_pydict({"file": [put(blocks_at, _ordered([get(given, f) for f in groups[k]], sent.value, j))]})

    made = [r["file"] for r in spark.range(0, len(groups), 1, max(1, len(groups))).mapInArrow(arrange, "file string").collect()]
    delete(spark, given)
    tasks = [(x, y) for y in range(len(made)) for x in range(y + 1)]

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in b.column(0).to_pylist():
                x, y = tasks[k]
                one = get(blocks_at, made[x])
                for out in _similar(one, one if x == y else get(blocks_at, made[y]), x == y, j):
                    yield pa.RecordBatch.from_pydict(out)

    return spark.range(0, len(tasks), 1, max(1, len(tasks))).mapInArrow(meet, "a_doc long, a_passage long, b_doc long, b_passage long, jaccard double")
