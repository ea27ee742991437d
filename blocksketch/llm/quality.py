"""Quality rules: the log-likelihood ratio of hashed word n-grams between trusted text and the raw corpus, by length.

Two multinomials over 2^bits buckets of hashed words and word pairs are counted, with `smooth` added to each bucket: one over the
trusted documents (labels.quality is 1), one over all documents. A document's score is the mean over its n-grams of the log ratio.
It is kept if the base rules pass and its score is at least mean - `spread` * deviation of the trusted documents' scores, taken over all of
them, so every document is decided by a fixed threshold.

Base rules fail a document of fewer than 20 words, or with over 30 % of its words inside 8-word windows that repeat within it.

Defined results: null, empty or blank text has no words, score 0, and fails; without trusted documents the score is 0 for all and only
the base rules decide. Repeated rows each get their row; a document is trusted if any of its label rows says so.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, Kept, table
from .shingles import SPACE, Words, chunks

SYMBOLS = b"#*$%&|<>"
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(SYMBOLS)] = True


def buckets(w: Words, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The bucket of each word and word pair, and its text."""
    pair, at = w.runs(2)
    shift = U64(64 - bits)
    return np.concatenate([w.hash >> shift, pair >> shift]).astype(np.int64), np.concatenate([w.doc, w.doc[at]])


def base_counts(w: Words, window: int = 8) -> dict[str, np.ndarray]:
    """word_chars, n_symbols, n_dup_lines and n_repeat_words of each text."""
    data, n = w.data, w.n
    space = SPACE[data]

    def summed(x: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(x, dtype=np.int64)])
        return total[w.offset[1:]] - total[w.offset[:-1]]

    chars = summed(~space & ((data & 0xC0) != 0x80))
    line = data == 10
    line[w.offset[1:] - 1] = True
    ends = np.flatnonzero(line)
    starts = np.concatenate([[0], ends[:-1] + 1])
    ink = np.concatenate([[0], np.cumsum(~space, dtype=np.int64)])
    has = ink[ends] > ink[starts]
    starts, ends = starts[has], ends[has]
    h, doc = w.windows.hash(starts, ends), np.searchsorted(w.offset, starts, "right") - 1
    order = np.lexsort((h, doc))
    again = (h[order][1:] == h[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    dup = np.bincount(doc[order][1:][again], minlength=n)
    runs, at = w.runs(window)
    repeat = np.zeros(n, np.int64)
    if len(runs):
        order = np.argsort(runs, kind="stable")
        same = (runs[order][1:] == runs[order][:-1]) & (w.doc[at[order][1:]] == w.doc[at[order][:-1]])
        twice = np.zeros(len(runs), bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        cover = np.zeros(len(w.hash) + 1, np.int64)
        cover[at[twice]] += 1
        np.subtract.at(cover, at[twice] + window, 1)
        repeat = np.bincount(w.doc[np.cumsum(cover)[:-1] > 0], minlength=n)
    return {"word_chars": chars, "n_symbols": summed(_SYMBOL[data]), "n_dup_lines": dup, "n_repeat_words": repeat}


def trusted_flag(docs: DataFrame, labels: DataFrame, most: int = 2_000_000) -> DataFrame:
    """Adds the column trusted. The ids are broadcast if there are at most `most`, else the tables are joined by a shuffle."""
    good = labels.filter("quality = 1 and doc_id is not null").select(F.col("doc_id").alias("__good")).distinct()
    few = good.count() <= most
    out = docs.join(F.broadcast(good) if few else good, docs["doc_id"] == F.col("__good"), "left")
    return out.withColumn("trusted", F.col("__good").isNotNull()).drop("__good")


def counts(flagged: DataFrame, bits: int) -> np.ndarray:
    """n-grams of all and of trusted texts in each bucket, from flagged(text, trusted)."""
    size = 1 << bits

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n = np.zeros((2, size), np.int64)
        for pdf in batches:
            good = pdf["trusted"].to_numpy(bool)
            for first, texts in chunks(pdf["text"]):
                b, doc = buckets(Words(texts, lower=False), bits)
                n[0] += np.bincount(b, minlength=size)
                n[1] += np.bincount(b[good[first + doc]], minlength=size)
        at = np.flatnonzero(n[0])
        yield pd.DataFrame({"bucket": at, "raw": n[0][at], "target": n[1][at]})

    got = flagged.select("text", "trusted").mapInPandas(run, "bucket long, raw long, target long").groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("target").alias("target")).toPandas()
    out = np.zeros((2, size))
    out[0, got["bucket"]], out[1, got["bucket"]] = got["raw"], got["target"]  # at most 2^bits rows
    return out


def scored(flagged: DataFrame, counted: np.ndarray, smooth: float = 1.0) -> DataFrame:
    """flagged(doc_id, text, trusted) to base counts and score. A document's own n-grams are taken out of both multinomials, so a
    trusted document scores as an unseen one would."""
    size = counted.shape[1]
    bits = size.bit_length() - 1
    sent = flagged.sparkSession.sparkContext.broadcast(counted)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        raw, target = sent.value + smooth
        sums = raw.sum(), target.sum()
        for pdf in batches:
            for first, texts in chunks(pdf["text"]):
                part = pdf.iloc[first : first + len(texts)]
                w = Words(texts, lower=False)
                b, doc = buckets(w, bits)
                number = np.bincount(doc, minlength=w.n)
                key, own = np.unique(doc * size + b, return_counts=True)
                at, of = key % size, key // size
                good = part["trusted"].to_numpy(bool)[of]
                ratio = np.log((target[at] - own * good) / (sums[1] - number[of] * good)) - np.log((raw[at] - own) / (sums[0] - number[of])) if sums[1] > smooth * size else np.zeros(len(at))
                score = np.bincount(of, own * ratio, w.n) / np.maximum(number, 1)
                yield pd.DataFrame({"doc_id": part["doc_id"].to_numpy(), "trusted": part["trusted"].to_numpy(), "n_words": w.count} | base_counts(w) | {"score": score})

    return flagged.select("doc_id", "text", "trusted").mapInPandas(run, "doc_id long, trusted boolean, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, score double")


def decided(scores: DataFrame, spread: float = 4.0) -> DataFrame:
    """Adds base_failed and kept."""
    m, d = scores.filter("trusted and n_words > 0").agg(F.avg("score"), F.stddev_pop("score")).first()
    least = float("-inf") if m is None else m - spread * d - 1e-9
    failed = (F.col("n_words") < 20) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 30)
    return scores.withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("score") >= least))


def op3_likelihood_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    flagged = trusted_flag(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"))
    out = decided(Kept(spark).keep(scored(flagged, counts(flagged, bits=16))))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "score")
