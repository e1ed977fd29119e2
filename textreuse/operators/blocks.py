"""Pairs by blocks of documents: candidates, runs, seeds and cases of a collection without a shuffled row for a pair.

Blocks are ranges of document ids, and each pair of blocks is a task. What the documents bring (grams at which a run can
begin or end, buckets, lengths of words) is shuffled once and written once, a file for each block; rows of pairs
are made in a task, a part of its documents at a time, and leave it as they are made. A pair is whole within one part.
"""

from __future__ import annotations

import hashlib
import pickle
import sys
import uuid
from collections.abc import Callable, Iterator
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.io import discard, get, put, release, shared_folder, stored
from .alignment import CASE, SPAN, single_links
from .normalize import clean

cloudpickle.register_pickle_by_value(sys.modules[__name__])  # executors need no installed copy of this package

#: Matches that a task holds at once.
CELLS = 1_000_000


#: Numbers that are packed together, and rows of grams or postings.
PACKED_NUMBERS, PACKED_ROWS = 4_000_000, 1_000_000


def pack(columns: dict) -> dict:
    """Columns in fewer bytes, as they are: repeats of the row before as bits, differences where a column rises, and bytes of one weight compressed together."""
    codec, out = pa.Codec("zstd", 1), {}
    for c, v in columns.items():
        if v.dtype == object:
            out[c] = v
            continue
        new = np.append(True, v[1:] != v[:-1])[: len(v)]
        few = 4 * int(new.sum()) < 3 * len(v)
        w = v[new] if few else v
        rises = bool((w[1:] >= w[:-1]).all())
        planes = np.ascontiguousarray((np.diff(w, prepend=w.dtype.type(0)) if rises else w).view(np.uint8).reshape(len(w), v.itemsize).T)
        parts = [codec.compress(x, asbytes=True) if x.any() else None for x in planes]
        out[c] = (v.dtype.str, len(w), rises, np.packbits(new) if few else None, len(v), parts)
    return out


def unpack(packed: dict) -> dict:
    """What :func:`pack` was given."""
    codec, out = pa.Codec("zstd", 1), {}
    for c, x in packed.items():
        if isinstance(x, np.ndarray):
            out[c] = x
            continue
        kind, n, rises, new, rows, parts = x
        planes = np.zeros((len(parts), n), np.uint8)
        for k, part in enumerate(parts):
            if part is not None:
                planes[k] = np.frombuffer(codec.decompress(part, n), np.uint8)
        w = np.ascontiguousarray(planes.T).reshape(-1).view(kind)
        w = np.cumsum(w, dtype=kind) if rises else w
        out[c] = w if new is None else w[np.cumsum(np.unpackbits(new, count=rows)) - 1]
    return out


def _held(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[dict]:
    """The columns of the batches of a task, about ``rows`` of them at a time."""
    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held, n = [*held, batch], n + batch.num_rows
        if n >= rows:
            yield _columns(pa.Table.from_batches(held))
            held, n = [], 0
    if n:
        yield _columns(pa.Table.from_batches(held))


def _columns(table: pa.Table) -> dict:
    return {c: table.column(c).to_numpy() for c in table.column_names}


def _joined(packed: pa.ChunkedArray) -> dict:
    """Columns that were packed in parts."""
    parts = [unpack(pickle.loads(x.as_py())) for x in packed]
    return {c: np.concatenate([p[c] for p in parts]) for c in parts[0]}


def _sent(key: int, columns: dict) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"at": pa.array([int(key)], pa.int32()), "data": pa.array([pickle.dumps(pack(columns), protocol=5)], pa.binary())})


def cleaned(docs: DataFrame) -> DataFrame:
    """``doc_id, clean`` of documents: what a task makes grams with context from, so that no row of a word or of a gram leaves it before it is packed."""
    return docs.select("doc_id", clean(F.col("text")).alias("clean"))


def hashed_words(rows: DataFrame) -> DataFrame:
    """:func:`cleaned`, of worded rows."""
    return rows.select("doc_id", F.array_join("words", " ").alias("clean"))


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return h ^ (h >> np.uint64(32))


class _Places:
    """Sums over the bytes of a text, by which any part of it is hashed in one step: of a number for each byte, times a power for its place."""

    def __init__(self):
        self.values = _mixed(_mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
        self.powers = self.inverse = np.empty(0, np.uint64)

    def words(self, data: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        """A hash of each range of bytes, the same wherever it stands."""
        if len(data) >= len(self.powers):
            p, n = 0xD1342543DE82EF9B, len(data) + 1
            ones = lambda x: np.cumprod(np.append(np.ones(1, np.uint64), np.full(n, x, np.uint64)))
            self.powers, self.inverse = ones(p), ones(pow(p, -1, 1 << 64))
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.values[data] * self.powers[: len(data)], out=sums[1:])
        return _mixed((sums[end] - sums[begin]) * self.inverse[begin])


def _grams(doc: np.ndarray, sizes: np.ndarray, h: np.ndarray, begin: np.ndarray, end: np.ndarray, n: int, keep: Callable[[np.ndarray], np.ndarray] | None, bare: bool) -> dict:
    """Grams of n words with context, as :func:`alignment.grams` has them, by another hash. ``h``, ``begin`` and ``end`` are of the words of all documents."""
    first = np.cumsum(sizes) - sizes
    pos = np.arange(len(h)) - np.repeat(first, sizes)
    last = np.repeat(sizes, sizes) - n
    at = np.flatnonzero(pos <= last)
    g = np.zeros(max(0, len(h) - n + 1), np.uint64)
    for k in range(n):
        g = (g ^ (g >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) + h[k : k + len(g)]
    g = ((g ^ (g >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)).view(np.int64)
    if keep:
        at = at[keep(g[at])]
    if bare:
        return {"g": g[at]}
    head, tail = pos[at] == 0, pos[at] == last[at]
    out = {"doc_id": np.repeat(doc, sizes)[at], "g": g[at], "pos": pos[at].astype(np.int32), "begin": begin[at].astype(np.int32), "end": end[at + n - 1].astype(np.int32)}
    out |= {"before": np.where(head, 0, g[at - 1]), "after": np.where(tail, 0, g[np.minimum(at + 1, max(0, len(g) - 1))])} if len(at) else {c: g[:0] for c in ("before", "after")}
    return out | {"edge": (head + 2 * tail).astype(np.int32)}


def _made(batches: Iterator[pa.RecordBatch], rows: int, n: int = 8, step: int = 1_000_000, keep: Callable[[np.ndarray], np.ndarray] | None = None, bare: bool = False) -> Iterator[dict]:
    """The grams of documents of :func:`cleaned`, of about ``step`` bytes at a time and fewer than ``rows``; those that ``keep`` tells, and with ``bare`` their hashes only."""
    places = _Places()
    for batch in batches:
        docs, texts = batch.column("doc_id").to_numpy(zero_copy_only=False), batch.column("clean").cast(pa.large_string()).fill_null("")
        if not len(texts):
            continue
        upto = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        data, i = np.frombuffer(texts.buffers()[2] or b"", np.uint8), 0
        while i < len(docs):
            j = min(len(docs), max(i + 1, int(np.searchsorted(upto, upto[i] + min(rows, step), side="right")) - 1))
            part, at = data[upto[i] : upto[j]], upto[i : j + 1] - upto[i]
            # A word begins with a text or after a blank, and ends with a text or at a blank.
            blank, worded = part == 32, at[1:] > at[:-1]
            begins, ends = np.zeros(len(part) + 1, bool), np.zeros(len(part) + 1, bool)
            begins[1:] = ends[:-1] = blank
            begins[at[:-1][worded]] = ends[at[1:][worded]] = True
            begin, end = np.flatnonzero(begins), np.flatnonzero(ends)
            sizes = np.diff(np.searchsorted(begin, at))
            letters = np.append(0, np.cumsum((part & 0xC0) != 0x80))  # a letter may have several bytes
            of = np.repeat(letters[at[:-1]], sizes)
            yield _grams(docs[i:j], sizes, places.words(part, begin, end), letters[begin] - of, letters[end] - of, n, keep, bare)
            i = j


def _by_rows(parts: Iterator[dict], rows: int) -> Iterator[dict]:
    held, n = [], 0
    for part in parts:
        size = len(next(iter(part.values())))
        held, n = [*held, part], n + size
        if n >= rows:
            yield {c: np.concatenate([p[c] for p in held]) for c in part}
            held, n = [], 0
    if n:
        yield {c: np.concatenate([p[c] for p in held]) for c in held[0]}


def repeated(gs: DataFrame, grams: int) -> tuple[int, np.ndarray]:
    """A bitmap, and the mask of a place in it, of the grams that occur more than once; of others a few may be in it.

    Grams are told by their place and 7 bits more, which a task sorts and packs: that is all that is shuffled. The bitmap has 4 to 8 bits a gram, 64 MB
    at most, as each executor stores a copy.
    """
    width, more = min(29, max(20, (4 * grams).bit_length())), 7
    mask, low = (1 << width) - 1, (1 << more) - 1
    worded = "clean" in gs.columns

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = _made(batches, PACKED_NUMBERS, bare=True) if worded else _held(batches, PACKED_NUMBERS)
        for held in _by_rows(made, PACKED_NUMBERS):
            g = held["g"]
            v = np.sort((g & mask) << more | (g >> width) & low)
            v = v[np.append([True, True], v[2:] != v[:-2])[: len(v)]]  # that it is there twice is enough
            begins = np.flatnonzero(np.diff(v >> (20 + more), prepend=-1))
            for i, j in zip(begins, np.append(begins[1:], len(v)), strict=True):
                yield _sent(v[i] >> (20 + more), {"v": v[i:j]})

    def count(table: pa.Table) -> pa.Table:
        v = np.sort(_joined(table.column("data"))["v"])
        bits = np.zeros(1 << 20, np.uint8)
        bits[(v[1:][v[1:] == v[:-1]] >> more) & ((1 << 20) - 1)] = 1
        return pa.table({"s": table.column("at")[:1], "bits": pa.array([np.packbits(bits, bitorder="little").tobytes()], pa.binary())})

    bitmap = np.zeros(1 << (width - 3), np.uint8)
    for r in (gs if worded else gs.select("g")).mapInArrow(send, "at int, data binary").groupBy("at").applyInArrow(count, "s int, bits binary").collect():
        bitmap[r["s"] << 17 : (r["s"] + 1) << 17] = np.frombuffer(r["bits"], np.uint8)
    return mask, bitmap


def _marks(g: np.ndarray, mask: int, bitmap: np.ndarray) -> np.ndarray:
    at = g & mask
    return (bitmap[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1


def _marked(batches: Iterator[pa.RecordBatch], rows: int, mask: int, bitmap: np.ndarray, worded: bool) -> Iterator[dict]:
    """The grams of a task whose place in the bitmap is set."""
    if worded:
        yield from _made(batches, rows, keep=lambda g: _marks(g, mask, bitmap))
        return
    for held in _held(batches, rows):
        keep = _marks(held["g"], mask, bitmap)
        yield {c: v[keep] for c, v in held.items()}


def marked(gs: DataFrame, mask: int, bitmap: np.ndarray) -> DataFrame:
    """The grams whose place in the bitmap is set."""
    sent = gs.sparkSession.sparkContext.broadcast(bitmap)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = sent.value
        for b in batches:
            yield b.filter(pa.array(_marks(b.column("g").to_numpy(), mask, bits)))

    return gs.mapInArrow(run, gs.schema)


def shared(gs: DataFrame, grams: int) -> DataFrame:
    """The grams that occur more than once, and a few others: what :func:`alignment.shared_grams` keeps is in it."""
    found = repeated(gs, grams)
    release(gs.sparkSession)
    return marked(gs, *found)


def turning(gs: DataFrame, grams: int) -> DataFrame:
    """Of grams with context, or of those of :func:`cleaned`, those at which a run of some pair can begin or end, stored.

    They are in more than one document, and not all that are equal have equal grams before and equal grams after.
    """
    worded = "clean" in gs.columns
    rows = gs.where(F.col("doc_id").isNotNull()).withColumn("doc_id", F.col("doc_id").cast("bigint"))
    if not worded:
        edge = F.col("before").isNull().cast("int") + 2 * F.col("after").isNull().cast("int")
        rows = rows.select("doc_id", "g", "pos", "begin", "end", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("before", "after")), edge.alias("edge"))
    mask, bitmap = repeated(rows, grams)
    release(gs.sparkSession)
    sent = gs.sparkSession.sparkContext.broadcast(bitmap)
    bins = max(gs.sparkSession.sparkContext.defaultParallelism, -(-grams // 1_000_000))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for held in _by_rows(_marked(batches, PACKED_ROWS, mask, sent.value, worded), PACKED_ROWS):
            order = np.lexsort((held["after"], held["before"], held["g"]))
            held = {c: v[order] for c, v in held.items()}
            to = (((held["g"] >> 32) + (1 << 31)) * bins) >> 32
            held["end"] -= held["begin"]
            begins = np.flatnonzero(np.diff(to, prepend=-1))
            for i, j in zip(begins, np.append(begins[1:], len(to)), strict=True):
                yield _sent(to[i], {c: v[i:j] for c, v in held.items()})

    def turn(table: pa.Table) -> pa.Table:
        held = _joined(table.column("data"))
        order = np.argsort(held["g"], kind="stable")
        held = {c: v[order] for c, v in held.items()}
        held["end"] += held["begin"]
        starts = np.flatnonzero(np.append(True, held["g"][1:] != held["g"][:-1]))
        differs = lambda v: np.minimum.reduceat(v, starts) != np.maximum.reduceat(v, starts)
        turns = differs(held["doc_id"]) & (differs(held["before"]) | differs(held["after"]) | (np.maximum.reduceat(held["edge"], starts) > 0))
        keep = np.repeat(turns, np.diff(np.append(starts, len(order))))
        return pa.table({c: v[keep] for c, v in held.items()})

    schema = ", ".join(f"{c} {_COLUMNS[c]}" for c in ("doc_id", "g", "pos", "begin", "end", "before", "after", "edge"))
    found = stored(rows.mapInArrow(send, "at int, data binary").groupBy("at").applyInArrow(turn, schema), "turning-grams")
    del rows
    sent.unpersist()
    release(found.sparkSession)
    return found


def number_of_grams(docs: DataFrame) -> int:
    """About as many as a collection has words."""
    return (docs.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0) // 6


# What a task does with the rows of two blocks


def _cut(size: np.ndarray, begins: np.ndarray, cells: int) -> Iterator[tuple[int, int]]:
    """Ranges of groups (that start at ``begins``) with at most ``cells`` in all, or one group."""
    work = np.append(0, np.cumsum(size))[np.append(begins, len(size))]
    first, n = 0, len(begins)
    while first < n:
        last = max(first + 1, int(np.searchsorted(work, work[first] + cells, side="right")) - 1)
        yield first, min(last, n)
        first = last


def _order(*keys: np.ndarray) -> np.ndarray:
    """The order of rows by columns of numbers from 0 on, as one number where they fit in it."""
    if not len(keys[0]):
        return np.empty(0, np.int64)
    bits = [int(k.max()).bit_length() for k in keys]
    if sum(bits) > 63:
        return np.lexsort(keys[::-1])
    value = keys[0].astype(np.int64)
    for k, n in zip(keys[1:], bits[1:], strict=True):
        value = value << n | k
    return np.argsort(value)


class _Ends:
    """The rows of b where runs of rows of a begin (``around`` is ``before``, ``bit`` 1) or end (``after``, 2): those of its gram without its gram around.

    The rows of b of a gram stand together, and of them those of one gram around, so what a row of a meets are two ranges, and seeds within a run are not made.
    """

    def __init__(self, a: dict, b: dict, around: str, bit: int, edge: str):
        beside, by = np.unique(b[around], return_inverse=True)
        wide = len(beside) + 1
        of = b["gram"] * wide + np.where(b["edge"] & bit > 0, len(beside), by)
        order = np.argsort(of, kind="stable")
        of = of[order]
        self.b = {"doc": b["doc"][order], "pos": b["pos"][order], "place": b[edge][order]}
        some = np.flatnonzero(np.diff(of, prepend=-1))
        groups, starts = of[some], np.append(some, len(of))
        grams = np.searchsorted(of, np.arange(int(b["gram"].max()) + 2) * wide)
        met, at = a["met"], a["gram"]
        near = np.minimum(np.searchsorted(beside, a[around]), len(beside) - 1)
        own = np.minimum(np.searchsorted(groups, at * wide + near), len(groups) - 1)
        same = met & (beside[near] == a[around]) & (groups[own] == at * wide + near) & (a["edge"] & bit == 0)
        begin = grams[at]
        end = np.where(met, grams[at + 1], begin)
        out, again = np.where(same, starts[own], end), np.where(same, starts[own + 1], end)
        # Two ranges a row: before what has the same gram around, and after it.
        self.begins, self.sizes = np.stack([begin, again], 1), np.stack([out - begin, end - again], 1)
        self.size = self.sizes.sum(1)

    def of(self, a: dict, lo: int, hi: int, one: bool) -> tuple[np.ndarray, ...]:
        """Of rows ``lo`` to ``hi`` of a, ordered by pair and diagonal: rows of a, documents of b, and of the rows of b words and places."""
        n = self.sizes[lo:hi].reshape(-1)
        x = np.repeat(np.arange(lo, hi), self.size[lo:hi])
        y = np.repeat(self.begins[lo:hi].reshape(-1) - np.cumsum(n) + n, n) + np.arange(len(x))
        if one:
            ordered = a["doc"][x] < self.b["doc"][y]
            x, y = x[ordered], y[ordered]
        doc, pos = self.b["doc"][y], a["pos"][x].astype(np.int64)
        diagonal = pos - self.b["pos"][y]
        least = int(diagonal.min()) if len(x) else 0
        order = _order(a["doc"][x] - a["doc"][lo], doc, diagonal - least, pos)
        y = y[order]
        return x[order], doc[order], self.b["pos"][y], self.b["place"][y]


def _runs(a: dict, b: dict, one: bool) -> Iterator[dict]:
    """The runs of all pairs of two blocks, those of a pair together: documents, places and spans."""
    if not len(a["g"]) or not len(b["g"]):
        return
    a_docs, a_doc = np.unique(a["doc_id"], return_inverse=True)
    b_docs, b_doc = np.unique(b["doc_id"], return_inverse=True)
    grams, gram = np.unique(b["g"], return_inverse=True)
    at = np.minimum(np.searchsorted(grams, a["g"]), len(grams) - 1)
    a, b = a | {"doc": a_doc, "gram": at, "met": grams[at] == a["g"]}, b | {"doc": b_doc, "gram": gram}
    heads, tails = _Ends(a, b, "before", 1, "begin"), _Ends(a, b, "after", 2, "end")
    begins = np.flatnonzero(np.diff(a_doc, prepend=-1))
    ends = np.append(begins, len(a_doc))
    for first, last in _cut(heads.size + tails.size, begins, CELLS):
        # On a diagonal runs follow one another, so the first of its heads has the first of its tails.
        x, doc, b_pos, b_begin = heads.of(a, ends[first], ends[last], one)
        t, _, _, b_end = tails.of(a, ends[first], ends[last], one)
        if not len(x):
            continue
        out = {"a_doc": a_docs[a_doc[x]], "b_doc": b_docs[doc], "a_pos": a["pos"][x], "b_pos": b_pos, "a_begin": a["begin"][x], "a_end": a["end"][t], "b_begin": b_begin, "b_end": b_end}
        out["n_seeds"] = a["pos"][t] - out["a_pos"] + 1
        yield {k: v.astype(np.int64) for k, v in out.items()}


def _pair_numbers(r: dict) -> np.ndarray:
    return np.cumsum((np.diff(r["a_doc"], prepend=r["a_doc"][0]) != 0) | (np.diff(r["b_doc"], prepend=r["b_doc"][0]) != 0))


def _before(value: np.ndarray, group: np.ndarray) -> np.ndarray:
    """For all but the first of ordered rows the greatest value before, if of its group; smaller values stand for others."""
    base = group * (int(value.max()) - int(value.min()) + 1)
    return np.maximum.accumulate(value + base)[:-1] - base[1:]


def _split(group: np.ndarray, begin: np.ndarray, end: np.ndarray, delta: int) -> tuple[np.ndarray, np.ndarray]:
    """Groups split at gaps, and which rows are of a group that was."""
    order = _order(group, begin, end)
    g = group[order]
    change = g[1:] != g[:-1]
    gap = ~change & (begin[order][1:] - _before(end[order], g) > delta)
    was, out, broken = np.append(0, np.cumsum(change)), np.empty_like(group), np.empty(len(group), bool)
    out[order] = np.append(0, np.cumsum(change | gap))
    broken[order] = (np.bincount(was[1:][gap], minlength=was[-1] + 1) > 0)[was]
    return out, broken


def _islands(r: dict, delta: int, rounds: int | None) -> np.ndarray:
    group, made = _pair_numbers(r), 0
    rows = np.arange(len(group))
    while len(rows) and (rounds is None or made < rounds):
        for s in "ab":
            if len(rows):
                part, broken = _split(group[rows], r[f"{s}_begin"][rows], r[f"{s}_end"][rows], delta)
                group[rows] = part + int(group.max()) + 1
                rows = rows[broken] if made or s == "b" else rows  # a group that is split along neither side stays as it is
        made += 1
    return group


def _chains(r: dict, delta: int) -> np.ndarray:
    pair = _pair_numbers(r)
    order = _order(pair, r["a_begin"], r["b_begin"], r["a_end"], r["b_end"])
    p, b0, b1 = pair[order], r["b_begin"][order], r["b_end"][order]
    new = (p[1:] != p[:-1]) | (b0[1:] < b0[:-1]) | (b0[1:] - b1[:-1] > delta)
    new |= r["a_begin"][order][1:] - _before(r["a_end"][order], p) > delta
    out = np.empty_like(pair)
    out[order] = np.append(0, np.cumsum(new))
    return out


def _components(r: dict, delta: int, near: str) -> np.ndarray:
    pair = _pair_numbers(r)
    order = _order(pair, *(r[c] for c in SPAN))
    out = np.empty_like(pair)
    out[order] = single_links(pair[order], *(r[c][order] for c in SPAN), delta, near)
    return out


def _spans(r: dict, group: np.ndarray) -> dict:
    order = np.argsort(group, kind="stable")
    starts = np.flatnonzero(np.diff(group[order], prepend=-1))
    out = {k: r[k][order][starts] for k in ("a_doc", "b_doc")}
    out |= {k: (np.minimum if k.endswith("begin") else np.maximum).reduceat(r[k][order], starts) for k in SPAN}
    out["n_seeds"] = np.add.reduceat(r["n_seeds"][order], starts)
    return out


def _merged(r: dict, group: Callable[[dict], np.ndarray], min_seeds: int) -> dict:
    """The cases of runs that stand by pair. The only run of a pair is a case; the runs of others are put in groups."""
    first = np.append(True, (r["a_doc"][1:] != r["a_doc"][:-1]) | (r["b_doc"][1:] != r["b_doc"][:-1]))
    alone = first & np.append(first[1:], True)
    names, more = ("a_doc", "b_doc", *SPAN, "n_seeds"), np.flatnonzero(~alone)
    at = np.flatnonzero(alone)
    out, rest = {k: r[k][at] for k in names}, {k: r[k][more] for k in names}
    if len(rest["a_doc"]):
        some = _spans(rest, group(rest))
        out = {k: np.concatenate([v, some[k]]) for k, v in out.items()}
    return out if min_seeds <= 1 else {k: v[out["n_seeds"] >= min_seeds] for k, v in out.items()}


class _Buckets:
    """Rows of bits over the documents of b: whom the documents of a meet in a bucket."""

    def __init__(self, a: dict, b: dict, bitmap_bytes: int = 64_000_000):
        self.a_docs, a_doc = np.unique(a["doc_id"], return_inverse=True)
        self.b_docs, b_doc = np.unique(b["doc_id"], return_inverse=True)
        order = np.argsort(b["g"], kind="stable")
        self.members = b_doc[order]
        names, self.starts, self.counts = np.unique(b["g"][order], return_index=True, return_counts=True)
        self.width = -(-len(self.b_docs) // 64)
        if not len(names) or not len(a_doc):
            self.at, self.begins = np.empty(0, np.int64), np.zeros(len(self.a_docs) + 1, np.int64)
            return
        at = np.minimum(np.searchsorted(names, a["g"]), len(names) - 1)
        met = names[at] == a["g"]
        by_doc = np.argsort(a_doc[met], kind="stable")
        self.at = at[met][by_doc]
        self.begins = np.searchsorted(a_doc[met][by_doc], np.arange(len(self.a_docs) + 1))
        large = np.argsort(-self.counts, kind="stable")[: max(1, bitmap_bytes // (8 * self.width))]
        large = large[self.counts[large] >= 32]
        self.place = np.full(len(names), -1)
        self.place[large] = np.arange(len(large))
        self.bits = np.zeros((len(large), self.width), np.uint64)
        for k, g in enumerate(large):
            row = np.zeros(self.width * 64, np.uint8)
            row[self.members[self.starts[g] : self.starts[g] + self.counts[g]]] = 1
            self.bits[k] = np.packbits(row, bitorder="little").view(np.uint64)

    def row(self, i: int) -> np.ndarray:
        """Whether each document of b meets document i of a."""
        mine = self.at[self.begins[i] : self.begins[i + 1]]
        if not len(mine):
            return np.zeros(len(self.b_docs), bool)
        seen, hot = np.zeros(self.width, np.uint64), self.place[mine]
        for h in hot[hot >= 0]:
            np.bitwise_or(seen, self.bits[h], out=seen)
        row = np.unpackbits(seen.view(np.uint8), count=len(self.b_docs), bitorder="little").view(bool)
        cold = mine[hot < 0]
        n = self.counts[cold]
        row[self.members[np.repeat(self.starts[cold], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]] = True
        return row

    def listed(self, one: bool) -> Iterator[dict]:
        held, n = [], 0
        for i, doc in enumerate(self.a_docs):
            mates = self.b_docs[self.row(i)]
            if one:
                mates = mates[mates > doc]
            held, n = [*held, (doc, mates)], n + len(mates)
            if n >= CELLS:
                yield self._pairs(held)
                held, n = [], 0
        if n:
            yield self._pairs(held)

    @staticmethod
    def _pairs(held: list) -> dict:
        return {"a_doc": np.repeat([d for d, _ in held], [len(m) for _, m in held]), "b_doc": np.concatenate([m for _, m in held])}

    def holds(self, a_doc: np.ndarray, b_doc: np.ndarray) -> np.ndarray:
        """Which of some pairs, those of a document of a together, are candidates."""
        out, starts = np.zeros(len(a_doc), bool), np.flatnonzero(np.diff(a_doc, prepend=a_doc[0] - 1))
        for lo, hi in zip(starts, np.append(starts[1:], len(a_doc)), strict=True):
            i = int(np.searchsorted(self.a_docs, a_doc[lo]))
            if i < len(self.a_docs) and self.a_docs[i] == a_doc[lo] and len(self.b_docs):
                j = np.minimum(np.searchsorted(self.b_docs, b_doc[lo:hi]), len(self.b_docs) - 1)
                out[lo:hi] = (self.b_docs[j] == b_doc[lo:hi]) & self.row(i)[j]
        return out


class _Words:
    """Where each word of a document begins and ends, from the lengths of its words."""

    def __init__(self, rows: dict):
        self.docs = rows["doc_id"]
        sizes = [np.frombuffer(x, ">i4").astype(np.int64) for x in rows["data"]]
        self.first = np.append(0, np.cumsum([len(x) for x in sizes]))[:-1]
        self.ends = np.concatenate([np.cumsum(x + 1) - 1 for x in sizes]) if sizes else np.empty(0, np.int64)
        self.begins = self.ends - np.concatenate(sizes) if sizes else self.ends

    def at(self, doc: np.ndarray, pos: np.ndarray) -> np.ndarray:
        return self.first[np.searchsorted(self.docs, doc)] + pos


def _seeds(r: dict, a: _Words, b: _Words, n: int) -> Iterator[dict]:
    """The seeds of runs, one by one."""
    for i, j in _cut(r["n_seeds"], np.arange(len(r["n_seeds"])), CELLS):
        size = r["n_seeds"][i:j]
        k = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        out = {c: np.repeat(r[c][i:j], size) for c in ("a_doc", "b_doc")}
        for s, w in (("a", a), ("b", b)):
            out[f"{s}_pos"] = np.repeat(r[f"{s}_pos"][i:j], size) + k
            at = np.repeat(w.at(r[f"{s}_doc"][i:j], r[f"{s}_pos"][i:j]), size) + k
            out |= {f"{s}_begin": w.begins[at], f"{s}_end": w.ends[at + n - 1]}
        yield out


# Tasks


GRAM, BUCKET, WORDS = 0, 1, 2
_COLUMNS = {"doc_id": "bigint", "g": "bigint", "pos": "int", "begin": "int", "end": "int", "before": "bigint", "after": "bigint", "edge": "int", "data": "binary"}


def number_of_blocks(rows: DataFrame, block_rows: int = 700_000, n: int | None = None) -> int:
    """Enough pairs of blocks for the cores, and blocks of about ``block_rows``."""
    n = rows.count() if n is None else n
    return max(1, -(-n // block_rows), min(isqrt(2 * rows.sparkSession.sparkContext.defaultParallelism) + 1, n // 2000))


def by_blocks(parts: dict[int, DataFrame], make: Callable[[dict, dict, bool], Iterator[dict]], schema: str, blocks: int, ids: DataFrame | None = None) -> DataFrame:
    """What ``make`` finds in each pair of blocks. ``parts`` are rows of documents by kind, stored for this call; the first kind decides where blocks end.
    With ``ids`` these decide that, and ``parts`` are read once and need not be stored.

    Each block is shuffled once and written as a file below the shared folder; the task of a pair of blocks reads two.
    """
    spark = next(iter(parts.values())).sparkSession
    own = {k: [c for c in _COLUMNS if c in p.columns] for k, p in parts.items()}
    ends = np.array((next(iter(parts.values())) if ids is None else ids).approxQuantile("doc_id", [k / blocks for k in range(1, blocks)], 0.01) if blocks > 1 else [], float)
    folder = f"{shared_folder(spark)}/textreuse-blocks-{uuid.uuid4().hex}"

    def ordered(kind: int, rows: dict) -> dict:
        by = ("doc_id", "pos") if kind == GRAM and "pos" in rows else ("g", "doc_id") if kind == BUCKET else ("doc_id",)
        order = np.lexsort([rows[c] for c in reversed(by)])
        if kind == BUCKET:  # a document is in a bucket once
            first = np.append(True, np.logical_or.reduce([np.diff(rows[c][order]) != 0 for c in by]))
            order = order[first[: len(order)]]
        return {c: v[order] for c, v in rows.items()}

    def send(kind: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for held in _held(batches, PACKED_ROWS):
                to = np.searchsorted(ends, held["doc_id"])
                for b in np.unique(to):
                    yield _sent(b, ordered(kind, {c: v[to == b] for c, v in held.items()})).append_column("kind", pa.array([kind], pa.int32()))

        return run

    def write(table: pa.Table) -> pa.Table:
        kinds, out = table.column("kind").to_numpy(), {}
        for k in np.unique(kinds):
            out[int(k)] = pack(ordered(k, _joined(table.column("data").filter(pa.array(kinds == k)))))
        return pa.table({"b": table.column("at")[:1], "file": [put(folder, out)]})

    rows = None
    for kind, part in parts.items():
        typed = part.where(F.col("doc_id").isNotNull()).select(*(F.col(c).cast(_COLUMNS[c]).alias(c) for c in own[kind]))
        one = typed.mapInArrow(send(kind), "at int, data binary, kind int")
        rows = one if rows is None else rows.unionAll(one)
    made = {r["b"]: r["file"] for r in rows.groupBy("at").applyInArrow(write, "b int, file string").collect()}
    for part in parts.values() if ids is None else ():
        discard(part)
    del rows, one, typed
    release(spark)
    pairs = [(made[i], made[j]) for j in sorted(made) for i in sorted(made) if i <= j]
    kinds = {f.name: "int32" if f.dataType == T.IntegerType() else "int64" for f in T._parse_datatype_string(schema)}
    none = {k: {c: np.empty(0, np.int64) for c in own.get(k, _COLUMNS)} for k in (GRAM, BUCKET, WORDS)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column(0).to_pylist():
                x, y = pairs[k]
                a = none | {kind: unpack(v) for kind, v in get(folder, x).items()}
                for out in make(a, a if x == y else none | {kind: unpack(v) for kind, v in get(folder, y).items()}, x == y):
                    yield pa.RecordBatch.from_pydict({c: pa.array(out[c].astype(kind)) for c, kind in kinds.items()})

    return spark.range(0, len(pairs), 1, max(1, len(pairs))).mapInArrow(run, schema)


def fingerprints(rows: DataFrame, n: int = 50, m: int = 10) -> DataFrame:
    """``doc_id, g``: the buckets of documents of words, by the ``md5`` family of :func:`retrieval.minhash` over passages of n words.

    A task digests each word of its documents once for each hash function, not once for each passage, and ``g`` is the first half of the
    least digest. A digest is of a word with its slot, so those of two slots are equal for neither keyed nor unkeyed buckets.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}
        values = np.empty((1 << 12, m), np.uint64)
        for batch in batches:
            doc, lists = batch.column("doc_id").to_numpy(), batch.column("words")
            sizes = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
            upto, i = np.cumsum(sizes), 0
            while i < len(sizes):
                j = max(i + 1, int(np.searchsorted(upto, (upto[i - 1] if i else 0) + 200_000, side="right")))
                words, size = lists[i:j].flatten().dictionary_encode(), sizes[i:j]
                if len(known) > 1_000_000:
                    known = {}
                places = np.empty(len(words.dictionary), np.int64)
                for k, w in enumerate(words.dictionary.to_pylist()):
                    at = known.get(w)
                    if at is None:
                        at = known[w] = len(known)
                        if at >= len(values):
                            values = np.concatenate([values, np.empty_like(values)])
                        values[at] = [int.from_bytes(hashlib.md5(f"{s}:{w}".encode(), usedforsecurity=False).digest()[:8], "big") for s in range(m)]
                    places[k] = at
                pos = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
                starts = np.flatnonzero(pos % n == 0)
                if len(starts):
                    g = np.minimum.reduceat(values[places[words.indices.to_numpy()]], starts, axis=0).view(np.int64).reshape(-1)
                    of = np.repeat(np.repeat(doc[i:j], size)[starts], m)
                    order = np.lexsort((g, of))
                    g, of = g[order], of[order]
                    new = np.append(True, (g[1:] != g[:-1]) | (of[1:] != of[:-1]))
                    yield pa.RecordBatch.from_pydict({"doc_id": pa.array(of[new].astype(np.int64)), "g": pa.array(g[new])})
                i = j

    return rows.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("bigint").alias("doc_id"), "words").mapInArrow(run, "doc_id bigint, g bigint")


def buckets(posts: DataFrame) -> DataFrame:
    """Postings, or :func:`fingerprints`, with a bucket as one number ``g``, stored."""
    rows = posts if "g" in posts.columns else posts.select("doc_id", F.xxhash64("slot", "hash").alias("g")).where(F.col("doc_id").isNotNull())
    return stored(rows, "buckets")


def candidates(posts: DataFrame, blocks: int | None = None) -> DataFrame:
    """The pairs of :func:`retrieval.candidates`. They leave a task a part at a time, so none are shuffled and no matrix is held.

    A posting may be there more than once, so ``posts`` need not be made distinct.
    """
    posts = buckets(posts)
    return by_blocks({BUCKET: posts}, lambda a, b, one: _Buckets(a[BUCKET], b[BUCKET]).listed(one), "a_doc long, b_doc long", blocks or number_of_blocks(posts, 4_000_000))


def cases(docs: DataFrame, grams: DataFrame, delta: int = 250, rounds: int | None = 2, min_seeds: int = 1, how: str = "islands", posts: DataFrame | None = None, blocks: int | None = None, columns: list[str] | None = None) -> DataFrame:
    """Cases by ``islands``, by ``chains``, or by components linked if near in ``both`` documents or in ``either``, of the runs of
    ``grams`` with context; with ``posts`` of candidate pairs only. All are made, and ``columns`` are what leaves a task of them.

    Equal to :func:`alignment.merge`, :func:`alignment.chains` and :func:`alignment.components` of :func:`alignment.runs_of_grams`.
    """
    found = turning(grams, number_of_grams(docs))
    parts = {GRAM: found} if posts is None else {GRAM: found, BUCKET: buckets(posts)}
    met_only = posts is not None

    def group(r: dict) -> np.ndarray:
        if how in ("both", "either"):
            return _components(r, delta, how)
        return _chains(r, delta) if how == "chains" else _islands(r, delta, rounds)

    def make(a: dict, b: dict, one: bool) -> Iterator[dict]:
        met = _Buckets(a[BUCKET], b[BUCKET]) if met_only else None
        for r in _runs(a[GRAM], b[GRAM], one):
            r = _kept(r, met)
            if len(r["a_doc"]):
                yield _merged(r, group, min_seeds)

    schema = ", ".join(c for c in CASE.split(", ") if columns is None or c.split(" ")[0] in columns)
    return by_blocks(parts, make, schema, blocks or number_of_blocks(found))


def runs(docs: DataFrame, grams: DataFrame, blocks: int | None = None) -> DataFrame:
    """The runs of ``grams`` with context. Equal to :func:`alignment.runs_of_grams`."""
    found = turning(grams, number_of_grams(docs))
    return by_blocks({GRAM: found}, lambda a, b, one: _runs(a[GRAM], b[GRAM], one), CASE, blocks or number_of_blocks(found))


def _equal(a: dict, b: dict, one: bool) -> Iterator[dict]:
    """Equal grams of two blocks."""
    order = np.argsort(b["g"], kind="stable")
    b = {c: v[order] for c, v in b.items()}
    starts, ends = (np.searchsorted(b["g"], a["g"], side=s) for s in ("left", "right"))
    size = ends - starts
    for i, j in _cut(size, np.arange(len(size)), CELLS):
        n = size[i:j]
        x = np.repeat(np.arange(i, j), n)
        y = np.repeat(starts[i:j] - np.cumsum(n) + n, n) + np.arange(len(x))
        if one:
            ordered = a["doc_id"][x] < b["doc_id"][y]
            x, y = x[ordered], y[ordered]
        yield {f"{s}_{c.removesuffix('_id')}": rows[c][at] for s, rows, at in (("a", a, x), ("b", b, y)) for c in ("doc_id", "pos", "begin", "end")}


def seeds_one_sided(docs: DataFrame, grams: DataFrame, step: int = 8, blocks: int | None = None) -> DataFrame:
    """The seeds of each ``step``-th gram of a document, with all grams of those after it, of :func:`cleaned` documents.

    Equal to :func:`alignment.seeds_by_index` of them; grams that occur once do not leave the task that makes them.
    """
    spark, total = docs.sparkSession, number_of_grams(docs)
    mask, bitmap = repeated(grams, total)
    release(spark)
    sent = spark.sparkContext.broadcast(bitmap)
    names = ["doc_id", "g", "pos", "begin", "end"]
    rows = grams.where(F.col("doc_id").isNotNull()).withColumn("doc_id", F.col("doc_id").cast("bigint"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in _made(batches, PACKED_ROWS, keep=lambda g: _marks(g, mask, sent.value), bare=True):
            yield pa.RecordBatch.from_pydict({"n": pa.array([len(x["g"])], pa.int64())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in _marked(batches, PACKED_ROWS, mask, sent.value, True):
            yield pa.RecordBatch.from_pydict({c: pa.array(x[c]) for c in names})

    def make(a: dict, b: dict, one: bool) -> Iterator[dict]:
        first = a[GRAM]["pos"] % step == 0
        yield from _equal({c: v[first] for c, v in a[GRAM].items()}, b[GRAM], one)

    if blocks is None:
        blocks = number_of_blocks(rows, n=rows.mapInArrow(count, "n long").agg(F.sum("n").alias("n")).first()["n"] or 0)
    found = rows.mapInArrow(run, ", ".join(f"{c} {_COLUMNS[c]}" for c in names))
    return by_blocks({GRAM: found}, make, "a_doc long, b_doc long, a_pos int, b_pos int, a_begin int, a_end int, b_begin int, b_end int", blocks, docs.where(F.col("doc_id").isNotNull()).select("doc_id"))


def _kept(r: dict, met: _Buckets | None) -> dict:
    if met is None or not len(r["a_doc"]):
        return r
    pair = _pair_numbers(r)
    first = np.flatnonzero(np.diff(pair, prepend=-1))
    keep = met.holds(r["a_doc"][first], r["b_doc"][first])[pair]
    return {k: v[keep] for k, v in r.items()}


def seeds_of_candidates(docs: DataFrame, rows: DataFrame, grams: DataFrame, posts: DataFrame, n: int = 8, blocks: int | None = None) -> DataFrame:
    """The seeds of :func:`alignment.seeds_by_candidates`: runs of candidate pairs, each taken apart at the words of its documents, ``rows``."""
    found = turning(grams, number_of_grams(docs))
    lengths = F.to_binary(F.array_join(F.transform("words", lambda w: F.lpad(F.hex(F.length(w)), 8, "0")), ""), F.lit("hex"))
    parts = {GRAM: found, BUCKET: buckets(posts), WORDS: stored(rows.select("doc_id", lengths.alias("data")), "word-lengths")}

    def make(a: dict, b: dict, one: bool) -> Iterator[dict]:
        met, aw, bw = _Buckets(a[BUCKET], b[BUCKET]), _Words(a[WORDS]), _Words(b[WORDS])
        for r in _runs(a[GRAM], b[GRAM], one):
            r = _kept(r, met)
            if len(r["a_doc"]):
                yield from _seeds(r, aw, bw, n)

    return by_blocks(parts, make, "a_doc long, b_doc long, a_pos int, b_pos int, a_begin int, a_end int, b_begin int, b_end int", blocks or number_of_blocks(found))
