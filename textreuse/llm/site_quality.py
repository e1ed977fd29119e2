"""Quality by hierarchical empirical Bayes: document evidence, host and path posteriors.

1. A logistic regression on hashed character n-grams and a few shares (marks, capitals, digits, repetition) gives
   each document a probability of good quality. It is trained by the follow-the-leader
   rule of :mod:`langid` on a bounded sample of labelled rows and calibrated by a
   temperature on a part of them that training did not see.
2. Hosts and paths are sites. Every document counts: a labelled one by its label, any
   other by its probability. Grouped sums give the good and the total count of a site.
3. Between-site variance (method of moments) gives the strength of the prior, for
   hosts around the global mean and for paths around their host. A site's posterior
   mean is its own rate shrunk by that strength, so sparse sites stay near the prior.
4. A document's quality adds the log odds of its own evidence and of its path, less
   those of the global mean, which both contain. The posteriors that a document meets
   leave it out, so neither its label nor its evidence counts twice.

Sums are partial aggregates; the site table joins back by its key, and a hot site is
split by the engine. Texts are never shuffled.

Cases: a null text is an empty one, whose features are those of no words; null hosts and
paths are a site of their own. A row repeated counts again, and each leaves out itself
only. Labels that are null do not count; of several for an id the smallest holds. Of
rows of one labelled id one is fitted on. Very long texts are read whole. A quality that
ties with ``least`` is kept. Without labels of both kinds all evidence is the share of
good labels, 0.5 without any. An empty table gives an empty result. Other columns do not
matter, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, small_or_shuffled
from .langid import Fit, softmax, temperature, train

EXTRAS = 7
#: Marks of code and layout among the first 128 characters.
_MARKS = np.isin(np.arange(128), [ord(c) for c in "#*$%&|<>!{}[]@_=+~^\\/"])


@dataclass(frozen=True)
class Evidence:
    #: Bound on the labelled rows that the classifier is fitted on.
    fit_rows: int = 4000
    #: Buckets of hashed n-grams of 1 to 3 characters.
    buckets: int = 1 << 12
    epochs: int = 4
    l1: float = 0.02
    l2: float = 0.01
    calibrate_every: int = 5
    #: Documents keep if their quality is at least this.
    least: float = 0.5
    #: Weight of the site beside the document's own evidence.
    site_weight: float = 1.0


def features(text: str | None, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers and values of the features: n-grams as they stand, digits alike, of length 1 together; then shares of marks, capitals, digits and repetition."""
    whole = text or ""
    raw = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32)
    cp = np.where((raw >= 48) & (raw <= 57), 48, raw)
    a = np.concatenate([[32], cp, [32]]).astype(np.uint64)
    two = a[:-1] * np.uint64(0x1F123BB5) + a[1:]
    three = two[:-1] * np.uint64(0x1F123BB5) + a[2:]
    z = np.concatenate([a, two, three])
    z = (z ^ (z >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    counts = np.bincount((z >> np.uint64(64 - buckets.bit_length() + 1)).astype(np.int64), minlength=buckets)
    at = np.flatnonzero(counts)
    x = 1 + np.log(counts[at])
    words, lines = whole.split(), [line for line in whole.split("\n") if line.strip()]
    small = np.frombuffer(whole.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    n = max(len(raw), 1)
    marks = _MARKS[raw[raw < 128]].sum() / n
    shape = [marks, (raw != small).sum() / n if len(raw) == len(small) else sum(map(str.isupper, whole)) / n, (cp == 48).sum() / n]
    extras = [*shape, 1 - len(set(words)) / max(len(words), 1), 1 - len(set(lines)) / max(len(lines), 1), np.log1p(len(words)) / 10, float(not words)]
    return np.concatenate([at, buckets + np.arange(EXTRAS)]), np.concatenate([x / np.sqrt(x @ x), extras])


def _strength(groups: DataFrame, good: str, total: str, prior: str) -> float:
    """Prior strength by moments: mean(1 - mean) / between-site variance - 1, at least 1."""
    rate = F.col(good) / F.col(total)
    spread = (rate - F.col(prior)) ** 2
    noise = F.col(prior) * (1 - F.col(prior)) / F.col(total)
    r = groups.where(F.col(total) > 0).agg(F.avg(F.col(prior) * (1 - F.col(prior))).alias("m"), F.avg(spread - noise).alias("v")).first()
    if r is None or r["m"] is None:
        return 1.0
    return float(max(1.0, min(1e6, r["m"] / max(r["v"], 1e-6) - 1)))


def fit_evidence(docs: DataFrame, labels: DataFrame, how: Evidence, text: str, key: str) -> tuple[np.ndarray | None, float]:
    """Weights of the features for "good" over "poor" with the temperature in them, or None; and the share of good labels."""
    share = labels.agg(F.avg("label")).first()[0]
    if share is None:
        return None, 0.5
    chosen = labels.orderBy(F.xxhash64("_id"), "_id").limit(how.fit_rows)
    rows = docs.select(F.col(key).alias("_id"), F.col(text).alias("_text")).join(F.broadcast(chosen), "_id")  # fit_rows rows at most
    # Of rows of one id that of the smallest hash, so that the sample stays within its bound.
    one = rows.groupBy("_id", "label").agg(F.min_by("_text", F.xxhash64("_text")).alias("_text"))
    buckets = how.buckets

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            found = [features(t, buckets) for t in batch["_text"]]
            yield pd.DataFrame({"place": batch["_place"], "label": batch["label"], "at": [f[0].astype(np.int32).tobytes() for f in found], "x": [f[1].astype(np.float32).tobytes() for f in found]})

    got = one.select(F.xxhash64("_id").alias("_place"), "label", "_text").mapInPandas(run, "place long, label double, at binary, x binary").collect()
    got.sort(key=lambda r: (r["place"] & 0xFFFFFFFF, r["place"]))  # in no order of labels
    data = [(np.frombuffer(r["at"], np.int32).astype(np.int64), np.frombuffer(r["x"], np.float32).astype(float), int(r["label"] > 0.5)) for r in got]
    if len({y for *_, y in data}) < 2:
        return None, float(share)
    held = data[:: how.calibrate_every] if len(data) >= 50 else []
    rule = Fit(features=buckets + EXTRAS, epochs=how.epochs, l1=how.l1, l2=how.l2)
    weights = train([r for k, r in enumerate(data) if not held or k % how.calibrate_every], 2, rule)
    heat = temperature(np.stack([x @ weights[at] for at, x, _ in held]), np.array([y for *_, y in held])) if held else 1.0
    return np.round((weights[:, 1] - weights[:, 0]) / max(heat, 1.0), 9), float(share)


def evidence(docs: DataFrame, weights: np.ndarray | None, share: float, how: Evidence, text: str, columns: list[Column]) -> DataFrame:
    """``columns`` (strings) of every row, and ``p_doc``."""
    names = [f"_{k}" for k in range(len(columns))]
    rows = docs.select(*(c.alias(n) for c, n in zip(columns, names, strict=True)), F.col(text).alias("_text"))
    if weights is None:
        return rows.select(*names, F.lit(share).alias("p_doc"))
    # As many numbers as features, whatever the input.
    sent, buckets = docs.sparkSession.sparkContext.broadcast(weights), how.buckets

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        w = sent.value
        for batch in batches:
            odds = [x @ w[at] for at, x in (features(t, buckets) for t in batch["_text"])]
            yield batch[names].assign(p_doc=1 / (1 + np.exp(-np.clip(np.array(odds, float), -15, 15))))

    return rows.mapInPandas(run, ", ".join(f"{n} string" for n in names) + ", p_doc double")


def assess(docs: DataFrame, labelled: DataFrame, how: Evidence = Evidence(), text: str = "text", key: str = "doc_id", host: Column | None = None, path: Column | None = None) -> DataFrame:
    """Evidence, site posteriors without the row itself, ``quality`` and ``kept`` for every row. ``labelled`` has the key and ``quality`` 0 or 1."""
    scratch = Scratch(docs.sparkSession, "site-quality")
    labels = labelled.where(F.col("quality").isNotNull() & F.col(key).isNotNull()).groupBy(F.col(key).alias("_id")).agg(F.min("quality").cast("double").alias("label"))
    labels = scratch.cut(labels, "labels")
    weights, share = fit_evidence(docs, labels, how, text, key)
    share = min(max(share, 0.01), 0.99)
    logit = lambda p: F.log(p / (1 - p))
    host = F.col("source") if host is None else host
    path = F.col("lang") if path is None else path
    rows = evidence(docs, weights, share, how, text, [F.col(key).cast("string"), host.cast("string"), path.cast("string")])
    rows = rows.select(F.col("_0").cast("long").alias("doc_id"), F.col("_1").alias("host"), F.col("_2").alias("path"), F.round("p_doc", 9).alias("p_doc"))
    rows = scratch.cut(rows, "evidence").join(small_or_shuffled(labels.withColumnRenamed("_id", "doc_id")), "doc_id", "left")
    rows = rows.withColumn("good", F.coalesce("label", "p_doc"))
    paths = scratch.cut(rows.groupBy("host", "path").agg(F.sum("good").alias("path_good"), F.count(F.lit(1)).alias("path_n")), "paths")
    hosts = paths.groupBy("host").agg(F.sum("path_good").alias("host_good"), F.sum("path_n").alias("host_n"))
    hosts = scratch.cut(hosts, "hosts")
    whole = hosts.agg(F.sum("host_good").alias("g"), F.sum("host_n").alias("n")).first()
    mean = min(max((whole["g"] or 0.0) / (whole["n"] or 1), 0.01), 0.99) if whole["n"] else share
    k = _strength(hosts.withColumn("mean", F.lit(mean)), "host_good", "host_n", "mean")
    paths = paths.join(hosts.withColumnRenamed("host", "_h"), F.col("host").eqNullSafe(F.col("_h"))).drop("_h")
    m = _strength(paths.withColumn("around", (F.col("host_good") + k * mean) / (F.col("host_n") + k)), "path_good", "path_n", "around")
    paths = scratch.cut(paths, "sites").withColumnsRenamed({"host": "_h", "path": "_p"})
    joined = rows.join(paths, rows["host"].eqNullSafe(paths["_h"]) & rows["path"].eqNullSafe(paths["_p"]))
    less = lambda name: (F.col(f"{name}_good") - F.col("good"), F.col(f"{name}_n") - 1)
    (host_good, host_n), (path_good, path_n) = less("host"), less("path")
    joined = joined.withColumn("host_posterior", (host_good + k * mean) / (host_n + k))
    joined = joined.withColumn("path_posterior", (path_good + m * F.col("host_posterior")) / (path_n + m))
    safe = lambda c: F.greatest(F.lit(1e-6), F.least(F.lit(1 - 1e-6), c))
    odds = logit(safe(F.col("p_doc"))) + how.site_weight * (logit(safe(F.col("path_posterior"))) - logit(F.lit(mean)))
    out = joined.withColumn("quality", F.round(1 / (1 + F.exp(-odds)), 6))
    return out.select("doc_id", "host", "path", "p_doc", F.col("path_n").cast("long").alias("path_n"), F.round("host_posterior", 6).alias("host_posterior"), F.round("path_posterior", 6).alias("path_posterior"), "quality", (F.col("quality") >= how.least).alias("kept"))
