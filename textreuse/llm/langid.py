"""Language identification by sparse multinomial logistic regression.

Features are TF-IDF weights of hashed character 1- to 3-grams of the whole,
lower-cased text, letters kept and everything else one space. Document frequencies
are counted over all documents that may be learned from: those with a language. Weights are trained with
the follow-the-regularised-leader (proximal) rule and elastic-net penalties on a
bounded sample, and a temperature is then fitted on a part of the sample that training
did not see.

Bounds: the sample has ``fit_rows`` documents, or one of each language if these are
more. Every language has an equal quota of rows, the smallest by a hash of id and text,
so a rare language is learned too; those that have fewer leave the rest to the others.
The driver holds their sparse features and a ``features`` x languages matrix. Everything
else is a map over all rows; partial frequencies are summed by feature.

Cases: texts that are null or have no letters are ``und`` with score 0. Rows without a
language are not learned from, but predicted. With nothing to learn from, everything
is ``und``. Repeated rows are predicted alike, and count once each in the sample's
quota. Very long texts are read whole. Of languages that tie the first by name is
predicted. An empty table gives an empty result. Other columns are passed by, whatever
their names.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch

UNKNOWN = "und"


@dataclass(frozen=True)
class Fit:
    features: int = 1 << 14
    #: Bound on the sample of labelled documents.
    fit_rows: int = 3000
    epochs: int = 3
    alpha: float = 2.0
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.001
    #: Every so many rows of the sample are left for calibration.
    calibrate_every: int = 5


#: Filled once a process by :func:`letters`. A plain list, as a cached function would travel by name and need an installed copy.
_LETTERS: list[np.ndarray] = []


def letters() -> np.ndarray:
    """Whether a code point is a letter."""
    if not _LETTERS:
        _LETTERS.append(np.fromiter((chr(c).isalpha() for c in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1))
    return _LETTERS[0]


def gram_numbers(text: str | None, features: int) -> np.ndarray | None:
    """Feature numbers of all grams; None without a letter."""
    if not text:
        return None
    cp = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    real = letters()[cp]
    if not real.any():
        return None
    cp = np.where(real, cp, 32)
    keep = np.ones(len(cp), bool)
    keep[1:] = real[1:] | real[:-1]
    a = np.concatenate([[32], cp[keep], [32]]).astype(np.uint64)
    two = a[:-1] * np.uint64(0x1F123BB5) + a[1:]
    three = two[:-1] * np.uint64(0x1F123BB5) + a[2:]
    z = np.concatenate([a, two, three])
    z = (z ^ (z >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return (z >> np.uint64(64 - features.bit_length() + 1)).astype(np.int64)


def tf(text: str | None, features: int) -> tuple[np.ndarray, np.ndarray] | None:
    """Numbers of the features in a text, and 1 + log of their counts."""
    numbers = gram_numbers(text, features)
    if numbers is None:
        return None
    counts = np.bincount(numbers, minlength=features)
    at = np.flatnonzero(counts)
    return at, 1 + np.log(counts[at])


def weighted(at: np.ndarray, x: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = x * idf[at]
    return x / max(np.sqrt(x @ x), 1e-12)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def train(rows: list[tuple[np.ndarray, np.ndarray, int]], classes: int, fit: Fit) -> np.ndarray:
    """Weights by follow-the-regularised-leader, one pass over ``rows`` an epoch."""
    z = np.zeros((fit.features, classes))
    n = np.zeros((fit.features, classes))

    def weights(at=slice(None)) -> np.ndarray:
        zz = z[at]
        return np.where(np.abs(zz) <= fit.l1, 0, -(zz - np.sign(zz) * fit.l1) / ((fit.beta + np.sqrt(n[at])) / fit.alpha + fit.l2))

    for _ in range(fit.epochs):
        for at, x, y in rows:
            w = weights(at)
            g = softmax(x @ w)
            g[y] -= 1
            g = x[:, None] * g[None, :]
            old = n[at]
            z[at] += g - (np.sqrt(old + g * g) - np.sqrt(old)) / fit.alpha * w
            n[at] = old + g * g
    return weights()


def temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The temperature of least log loss, by golden-section search over its logarithm."""
    loss = lambda t: -np.log(np.maximum(softmax(logits / np.exp(t))[np.arange(len(y)), y], 1e-12)).mean()
    low, high, ratio = -4.0, 4.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = high - ratio * (high - low), low + ratio * (high - low)
        low, high = (low, b) if loss(a) <= loss(b) else (a, high)
    return float(np.exp((low + high) / 2))


@dataclass
class Model:
    languages: list[str]
    idf: np.ndarray
    weights: np.ndarray
    temperature: float

    def predict(self, text: str | None) -> tuple[str, float]:
        found = tf(text, len(self.idf)) if self.languages else None
        if found is None:
            return UNKNOWN, 0.0
        at, x = found
        p = softmax(weighted(at, x, self.idf) @ self.weights[at] / self.temperature)
        best = int(p.argmax())
        return self.languages[best], float(min(1.0, max(0.0, p[best])))


def document_frequencies(docs: DataFrame, features: int, text: str) -> tuple[int, np.ndarray]:
    """Documents with letters, and documents that have each feature."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = np.zeros(features + 1, np.int64)
        for batch in batches:
            for whole in batch["_text"]:
                numbers = gram_numbers(whole, features)
                if numbers is not None:
                    seen = np.zeros(features, bool)
                    seen[numbers] = True
                    held[:-1] += seen
                    held[-1] += 1
        at = np.flatnonzero(held)
        yield pd.DataFrame({"f": at, "n": held[at]})

    counted = docs.select(F.col(text).alias("_text")).mapInPandas(run, "f long, n long").groupBy("f").agg(F.sum("n").alias("n"))
    out = np.zeros(features + 1)
    for r in counted.collect():  # a row a feature at most
        out[r["f"]] = r["n"]
    return int(out[-1]), out[:-1]


def quotas(counts: dict[str, int], rows: int) -> dict[str, int]:
    """Rows of each language in the sample: equal shares, what one language lacks goes to the others, at least one each."""
    out, left = {}, rows
    for k, lang in enumerate(sorted(counts, key=lambda x: (counts[x], x))):
        out[lang] = max(1, min(counts[lang], left // (len(counts) - k)))
        left = max(0, left - out[lang])
    return out


def learn(docs: DataFrame, fit: Fit = Fit(), text: str = "text", lang: str = "lang", key: str = "doc_id") -> Model:
    """A model from the rows of ``docs`` that have a language."""
    labelled = docs.select(F.col(key).alias("_id"), F.col(text).alias("_text"), F.col(lang).cast("string").alias("_lang")).where("_lang is not null and _text is not null")
    total, df = document_frequencies(labelled, fit.features, "_text")
    idf = np.log((1 + total) / (1 + df)) + 1
    counts = {r["_lang"]: r["count"] for r in labelled.groupBy("_lang").count().collect()}  # a row a language
    wanted = quotas(counts, fit.fit_rows)
    # A hash below a share of its range leaves about twice the quota and some, of which the smallest are taken.
    limits = labelled.sparkSession.createDataFrame([(x, n, min(1.0, (2 * n + 50) / counts[x])) for x, n in wanted.items()], "_lang string, _quota int, _share double")
    place = F.xxhash64("_id", "_text")
    near = labelled.withColumn("_place", place).join(F.broadcast(limits), "_lang").where((F.shiftrightunsigned("_place", 11) / F.lit(float(1 << 53))) < F.col("_share"))
    first = Window.partitionBy("_lang").orderBy("_place", "_id")
    sample = near.withColumn("_rank", F.row_number().over(first)).where(F.col("_rank") <= F.col("_quota"))
    features = fit.features

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = [(i, x, tf(t, features)) for i, t, x in zip(batch["_place"], batch["_text"], batch["_lang"], strict=True)]
            yield pd.DataFrame([(i, x, f[0].astype(np.int32).tobytes(), f[1].astype(np.float32).tobytes()) for i, x, f in found if f], columns=["place", "lang", "at", "x"])

    got = sample.select("_place", "_text", "_lang").mapInPandas(run, "place long, lang string, at binary, x binary").collect()
    got.sort(key=lambda r: (r["place"] & 0xFFFFFFFF, r["place"], r["lang"], bytes(r["x"])))  # mixes the languages
    languages = sorted({r["lang"] for r in got})
    rows = []
    for r in got:
        at = np.frombuffer(r["at"], np.int32).astype(np.int64)
        rows.append((at, weighted(at, np.frombuffer(r["x"], np.float32).astype(float), idf), languages.index(r["lang"])))
    if not rows:
        return Model([], idf, np.zeros((fit.features, 0)), 1.0)
    held = rows[:: fit.calibrate_every] if len(rows) > 10 else []
    weights = train([r for k, r in enumerate(rows) if not held or k % fit.calibrate_every], len(languages), fit)
    heat = temperature(np.stack([x @ weights[at] for at, x, _ in held]), np.array([y for *_, y in held])) if held else 1.0
    return Model(languages, idf, weights, heat)


def identify(docs: DataFrame, model: Model, scratch: Scratch | None = None, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``lang_pred`` and ``score`` beside the key of every row."""
    # Features x languages, whatever the input. Arrays travel, not the class: broadcasts name classes, and executors need not have ours.
    sent = docs.sparkSession.sparkContext.broadcast((model.languages, model.idf, model.weights, model.temperature))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = Model(*sent.value)
        for batch in batches:
            found = [own.predict(t) for t in batch["_text"]]
            yield pd.DataFrame({"doc_id": batch["_id"], "lang_pred": [f[0] for f in found], "score": [f[1] for f in found]})

    # Ids travel as text: a null among them would make pandas hold them as floats.
    found = docs.select(F.col(key).cast("string").alias("_id"), F.col(text).alias("_text")).mapInPandas(run, "doc_id string, lang_pred string, score double")
    return found.withColumn("doc_id", F.col("doc_id").cast("long"))
