"""Toxicity by non-negative positive-unlabelled learning.

Positives are confirmed toxic documents, the rest is unlabelled text, and the class prior is the toxic share of labelled rows. Features are
the presence of character n-grams of words (with marks at word ends); those that set positives most apart from unlabelled text are
selected. A linear classifier is trained in NumPy on the risk  prior * E_P[l(+)] + max(0, E_U[l(-)] - prior * E_P[l(-)])  with the
logistic loss: where the bracket falls below zero, a step climbs out of it instead of descending.

Both samples of the fit are bounded, by `most_positive` and `most_unlabelled` documents drawn by a hash of their ids; everything else sees all
rows, and so does the count of unlabelled documents with a feature, by which features are selected. Words are cached in a worker, so a text costs a lookup per distinct word.

Defined results: null or empty text scores the classifier's value for no feature; without positives every score is 0.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Kept, table
from .language_id import WORD, grams

ORDERS = (4, 5)


class Features:
    """Sorted feature numbers of texts, by way of a cache of words; known: the selected n-grams (sorted), or None for all, hashed to 2^bits."""

    def __init__(self, bits: int, known: np.ndarray | None = None):
        self.bits, self.known, self.cache = bits, known, {}

    def of(self, texts: list[str | None]) -> list[np.ndarray]:
        sets = [set(WORD.findall(t.lower())) if t else set() for t in texts]
        new = [w for w in set().union(*sets) if w not in self.cache] if sets else []
        if new:
            h, owner = grams(new, ORDERS)
            h = (h >> np.uint64(64 - self.bits)).astype(np.int64)
            if self.known is not None:
                at = np.minimum(np.searchsorted(self.known, h), max(len(self.known) - 1, 0))
                hit = self.known[at] == h if len(self.known) else np.zeros(len(h), bool)
                h, owner = at[hit], owner[hit]
            order = np.argsort(owner, kind="stable")
            h, owner = h[order], owner[order]
            ends = np.searchsorted(owner, np.arange(len(new) + 1))
            self.cache.update((w, tuple(h[a:b].tolist())) for w, a, b in zip(new, ends, ends[1:], strict=False))
        out = [np.array(sorted(set().union(*(x for w in s if (x := self.cache[w])))), np.int64) for s in sets]
        if len(self.cache) > 300_000:
            self.cache.clear()
        return out


@dataclass
class Classifier:
    bits: int
    known: np.ndarray
    weights: np.ndarray
    bias: float

    def score(self, features: list[np.ndarray]) -> np.ndarray:
        if not len(self.known):
            return np.zeros(len(features))
        z = np.array([self.weights[f].sum() for f in features]) + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def gains(in_p: np.ndarray, in_u: np.ndarray, positives: int, unlabelled: int, prior: float, purity: float) -> np.ndarray:
    """How far each feature, in so many documents of either sample, sets positives apart; 0 for those in fewer than 4 positives."""
    gain = in_p * np.abs(np.log((in_p + 0.5) / (positives + 1)) - np.log((in_u + 0.5) / (unlabelled + 1)))
    # The toxic share among documents with a feature, as the prior and both samples tell it, with a deviation's benefit to the doubt against it.
    pure = prior * (in_p / max(positives, 1)) / ((in_u + np.sqrt(in_u + 1)) / max(unlabelled, 1))
    return np.where((in_p < 4) | (pure < purity), 0.0, gain)


def best(features: np.ndarray, gain: np.ndarray, select: int) -> np.ndarray:
    order = np.lexsort((features, -gain))[:select]
    return np.sort(features[order[gain[order] > 0]])


def fit(positive: list[np.ndarray], unlabelled: list[np.ndarray], known: np.ndarray, prior: float, bits: int, rounds: int = 200, rate: float = 0.1, decay: float = 1e-4, slack: float = 0.0) -> Classifier:
    """Non-negative risk, by Adam over all rows in each round. Rows hold places in `known`."""
    if not positive or not unlabelled:
        return Classifier(bits, np.zeros(0, np.int64), np.zeros(0), 0.0)

    def rows(x: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return np.repeat(np.arange(len(x)), [len(f) for f in x]), np.concatenate([*x, np.zeros(0, np.int64)])

    (pr, pc), (ur, uc) = rows(positive), rows(unlabelled)
    w, b = np.zeros(len(known)), float(np.log(prior / (1 - prior)))
    m, v = np.zeros(len(known) + 1), np.zeros(len(known) + 1)
    sig = lambda z: 1 / (1 + np.exp(-np.clip(z, -60, 60)))
    for t in range(1, rounds + 1):
        sp = sig(np.bincount(pr, w[pc], len(positive)) + b)
        su = sig(np.bincount(ur, w[uc], len(unlabelled)) + b)
        negative = -np.log1p(-np.minimum(su, 1 - 1e-12)).mean() + prior * np.log1p(-np.minimum(sp, 1 - 1e-12)).mean()
        gp, gu = -prior * (1 - sp) / len(positive), su / len(unlabelled)
        gn = -prior * sp / len(positive)
        if negative >= -slack:
            gp = gp + gn
        else:
            gp, gu = -gn, -gu
        g = np.append(np.bincount(pc, gp[pr], len(known)) + np.bincount(uc, gu[ur], len(known)) + decay * w, gp.sum() + gu.sum())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    return Classifier(bits, known, w, b)


def train(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float, bits: int, select: int = 1024, purity: float = 0.0) -> Classifier:
    """Selection and fit of rows that hold feature numbers below 2^bits."""
    count = lambda x: np.bincount(np.concatenate([*x, np.zeros(0, np.int64)]), minlength=1 << bits)
    known = best(np.arange(1 << bits), gains(count(positive), count(unlabelled), len(positive), len(unlabelled), prior, purity), select)
    place = lambda x: [np.searchsorted(known, f[np.isin(f, known)]) for f in x]
    return fit(place(positive), place(unlabelled), known, prior, bits)


def learn(docs: DataFrame, labels: DataFrame, most_positive: int = 4000, most_unlabelled: int = 8000, bits: int = 20, select: int = 1024, purity: float = 0.2) -> Classifier:
    """docs(doc_id, text) and labels(doc_id, toxic) of training rows only. Features are counted and selected where the documents are; the
    driver sees the samples' selected features only."""
    order = F.xxhash64("doc_id", F.lit(7))
    toxic = labels.filter("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    prior = min(max(toxic.agg(F.avg(F.col("toxic").cast("double"))).first()[0] or 0.0, 1e-3), 0.5)
    pick = lambda df, n: df.select("doc_id").filter("doc_id is not null").distinct().orderBy(order, "doc_id").limit(n)
    chosen = pick(toxic.filter("toxic = 1"), most_positive).withColumn("p", F.lit(1)).union(pick(docs, most_unlabelled).withColumn("p", F.lit(0)))
    sample = Kept(docs.sparkSession).keep(docs.join(F.broadcast(chosen), "doc_id").select("p", "text"))

    def count(texts: DataFrame, among: np.ndarray | None = None) -> DataFrame:
        """(feature, n): documents with each feature; with `among`, features are places in it."""

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            f, n = Features(bits, among), np.zeros(1 << bits if among is None else len(among), np.int64)
            for pdf in batches:
                for k in range(0, len(pdf), 256):
                    for row in f.of(pdf["text"].tolist()[k : k + 256]):
                        n[row] += 1
            at = np.flatnonzero(n)
            yield pd.DataFrame({"feature": at, "n": n[at]})

        return texts.select("text").mapInPandas(run, "feature long, n long").groupBy("feature").agg(F.sum("n").alias("n"))

    # Only features of 4 positives can be selected; how many unlabelled documents have them is told by all training text.
    in_p = count(sample.filter("p = 1")).filter("n >= 4").orderBy("feature").toPandas()  # at most 2^bits rows
    among = in_p["feature"].to_numpy(np.int64)
    in_u = np.zeros(len(among), np.int64)
    if len(among):
        found = count(docs, among).toPandas()
        in_u[found["feature"].to_numpy(np.int64)] = found["n"].to_numpy()
    known = best(among, gains(in_p["n"].to_numpy(), in_u, sample.filter("p = 1").count(), docs.count(), prior, purity), select)

    def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        f = Features(bits, known)
        for pdf in batches:
            for k in range(0, len(pdf), 256):
                yield pd.DataFrame({"p": pdf["p"].to_numpy()[k : k + 256], "f": [x.astype(np.int32) for x in f.of(pdf["text"].tolist()[k : k + 256])]})

    got = sample.mapInPandas(rows, "p int, f array<int>").toPandas()  # at most both bounds
    split = [[np.asarray(x, np.int64) for x in got["f"][got["p"] == k]] for k in (1, 0)]
    return fit(*split, known, prior, bits)


def predict(docs: DataFrame, model: Classifier, threshold: float = 0.7) -> DataFrame:
    """All columns of docs but text, with score and predicted; columns of these names are replaced."""
    others = [c for c in docs.columns if c not in ("text", "score", "predicted")]
    sent = docs.sparkSession.sparkContext.broadcast(model)  # as many weights as were selected
    schema = ", ".join([*(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in others), "score double", "predicted int"])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m: Classifier = sent.value
        f = Features(m.bits, m.known)
        for pdf in batches:
            for k in range(0, len(pdf), 512):
                part = pdf.iloc[k : k + 512]
                s = m.score(f.of(part["text"].tolist()))
                yield part[others].assign(score=s, predicted=(s >= threshold).astype(np.int32))

    return docs.mapInPandas(run, schema)


def op4_positive_unlabelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic")
    return predict(docs.withColumn("held_out", held), learn(docs.filter(~held), labels.filter(~held)))
