"""Language identification by bit-sliced Bloom filters over character n-grams.

Learning counts each character n-gram of each language over all training documents. An n-gram belongs to a language if its
relative frequency there is at least `min_count` occurrences and at least `share` of its highest relative frequency in any
language, so words quoted from another language do not blur the filters. All languages share one Bloom filter: a cell holds a
bit per language (bit slices), so `hashes` lookups and an AND return the set of all languages holding an n-gram. A document's
count for a language is the number of its n-grams with that bit; as a Bloom filter also says yes by chance, each count is
corrected by that language's measured false-positive rate. The highest corrected count decides.

Defined results: null text, empty text and text without a letter give `und` and score 0; letters of which no n-gram is known
give the most frequent learned language with score 0; ties go to the more frequent language in training. With no training
rows every document is `und`. The filter's size is a parameter and does not grow with the corpus.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, Kept, mix, released, seeds, table

WORD = re.compile(r"[^\W\d_]+")
ORDERS = (3, 4)
_MUL = seeds("ngram", 8)
KNOWN, LETTERS = 100_000, 4_000_000  # words that a task holds at a time, and their letters
TEXTS = 256  # texts at a time


def grams(words: list[str], orders: tuple[int, ...] = ORDERS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the n-grams of each word with a mark at either end, and the index of the word each belongs to."""
    text = "\0" + "\0".join(words) + "\0"
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    sep = code == 0
    word = np.cumsum(sep) - 1
    found, owner = [], []
    for n in orders:
        m = len(code) - n + 1
        if m <= 0:
            continue
        inner = np.zeros(m, bool)
        h = np.full(m, n, np.uint64)
        for k in range(n):
            if 0 < k < n - 1:
                inner |= sep[k : k + m]
            h = (h ^ code[k : k + m]) * _MUL[k]
            h ^= h >> U64(29)
        at = np.flatnonzero(~inner)
        found.append(mix(h[at]))
        owner.append(word[at])
    if not found:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(found), np.concatenate(owner)


def cells(h: np.ndarray, bits: int, hashes: int) -> list[np.ndarray]:
    a, b = h & U64(0xFFFFFFFF), (h >> U64(32)) | U64(1)
    return [((a + U64(k) * b) & U64((1 << bits) - 1)).astype(np.int64) for k in range(hashes)]


@dataclass
class Filters:
    """languages: most frequent in training first; words: one uint64 array of cells for each 64 languages."""

    languages: list[str]
    words: list[np.ndarray]
    bits: int
    hashes: int

    def __post_init__(self):
        n = len(self.languages)
        fill = np.array([np.count_nonzero(self.words[i // 64] >> U64(i % 64) & U64(1)) / (1 << self.bits) for i in range(n)])
        self.false = fill**self.hashes

    def member(self, h: np.ndarray) -> np.ndarray:
        """Per language, whether each n-gram is in its filter."""
        at = cells(h, self.bits, self.hashes)
        out = []
        for w in self.words:
            m = w[at[0]]
            for x in at[1:]:
                m &= w[x]
            out.append(m)
        return np.stack([(out[i // 64] >> U64(i % 64) & U64(1)).astype(bool) for i in range(len(self.languages))]) if self.languages else np.zeros((0, len(h)), bool)


@released
def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Language, n-gram and number, summed within bounded memory. Words are counted first, as they repeat often."""
    counts: dict[str, Counter] = {}
    seen = 0  # letters since the last flush, repeated ones too

    def flush():
        for lang, words in counts.items():
            h, owner = grams(list(words))
            n = np.fromiter(words.values(), np.int64, len(words))
            u, inverse = np.unique(h, return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.repeat(pa.scalar(lang, pa.string()), len(u)), pa.array(u.view(np.int64)), pa.array(np.bincount(inverse, n[owner], len(u)).astype(np.int64))], ["lang", "gram", "n"])
        counts.clear()

    for batch in batches:
        for k in range(0, len(batch), TEXTS):
            part = batch.slice(k, TEXTS)
            for lang, text in zip(part["lang"].to_pylist(), part["text"].to_pylist(), strict=True):
                counts.setdefault(lang, Counter()).update(WORD.findall(text.lower()))
                seen += len(text)
            if sum(map(len, counts.values())) > KNOWN or seen > LETTERS and sum(len(w) for words in counts.values() for w in words) > LETTERS:
                yield from flush()
                seen = 0
    yield from flush()


def learn(train: DataFrame, bits: int = 20, hashes: int = 3, min_count: int = 2, share: float = 0.2, max_languages: int = 1024) -> Filters:
    """Filters from `train(text, lang)`; rows without text or lang are left out. Raises beyond max_languages, which bounds what is sent."""
    spark = train.sparkSession
    counted = Kept(spark)
    rows = train.select(F.col("text"), F.col("lang")).filter("text is not null and lang is not null")
    totals_df = counted.keep(rows.mapInArrow(_count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")))
    totals = totals_df.groupBy("lang").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "lang").limit(max_languages + 1).collect()
    if len(totals) > max_languages:
        raise ValueError(f"more than {max_languages} languages")
    languages = [r.lang for r in totals]
    size = 1 << bits
    words = [np.zeros(size, np.uint64) for _ in range(max(1, -(-len(languages) // 64)))]
    if languages:
        ids = pa.table({"lang": languages, "id": pa.array(range(len(totals)), pa.int32()), "total": [float(r.n) for r in totals]})
        ids = spark.createDataFrame(ids)  # by Arrow: rows would go through Python workers of their own
        rated = totals_df.join(F.broadcast(ids), "lang").withColumn("rate", F.col("n") / F.col("total"))
        top = rated.groupBy("gram").agg(F.max("rate").alias("top"), F.collect_list(F.struct("id", "n", "rate")).alias("of"))
        one = top.select("gram", "top", F.explode("of").alias("x")).filter((F.col("x.n") >= min_count) & (F.col("x.rate") >= share * F.col("top")))
        one = one.groupBy("gram", (F.col("x.id") / 64).cast("int").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(x.id % 64 as int))")).alias("mask"))
        low, step = F.col("gram").bitwiseAND(0xFFFFFFFF), F.shiftrightunsigned("gram", 32).bitwiseOR(F.lit(1).cast("long"))
        at = F.array(*[(low + F.lit(k).cast("long") * step).bitwiseAND(size - 1) for k in range(hashes)])
        sets = one.select("word", "mask", F.explode(at).alias("cell")).groupBy("word", "cell").agg(F.bit_or("mask").alias("mask"))
        got = sets.toPandas()  # at most 2^bits rows for each 64 languages
        for w in range(len(words)):
            x = got[got["word"] == w]
            words[w][x["cell"].to_numpy(np.int64)] = x["mask"].to_numpy(np.int64).view(np.uint64)
    counted.drop(totals_df)
    return Filters(languages, words, bits, hashes)


class Verdicts:
    """Language and score of texts, with a cache of words that belongs to one task."""

    def __init__(self, filters: Filters):
        self.f, self.known, self.letters = filters, {}, 0
        self.votes = np.zeros((0, len(filters.languages) + 2), np.int32)  # per word: counts by language, number of n-grams, whether it has a letter

    def of(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        f, langs, n = self.f, len(self.f.languages), len(texts)
        ids, owner, new = [], [], []
        for i, t in enumerate(texts):
            words = WORD.findall(t.lower()) if t else ()
            owner.append(np.full(len(words), i))
            for w in words:
                k = self.known.get(w)
                if k is None:
                    k = self.known[w] = len(self.known)
                    new.append(w)
                ids.append(k)
        if new:
            h, of = grams(new)
            more = np.zeros((len(new), langs + 2), np.int32)
            for j, m in enumerate(f.member(h)):
                more[:, j] = np.bincount(of, m, len(new))
            more[:, langs] = np.bincount(of, minlength=len(new))
            more[:, langs + 1] = [any(map(str.isalpha, w)) for w in new]
            self.votes = np.concatenate([self.votes, more])
            self.letters += sum(map(len, new))
        owner = np.concatenate(owner) if owner else np.zeros(0, np.int64)
        got = np.stack([np.bincount(owner, self.votes[ids, j], n) for j in range(langs + 2)]) if ids else np.zeros((langs + 2, n))
        if len(self.known) > KNOWN or self.letters > LETTERS:
            self.known, self.letters, self.votes = {}, 0, self.votes[:0].copy()
        if not langs:
            return np.full(n, "und", object), np.zeros(n)
        total, letters = np.maximum(got[langs], 1), got[langs + 1] > 0
        share = np.clip((got[:langs] / total - f.false[:, None]) / (1 - np.minimum(f.false, 0.999))[:, None], 0, 1)
        best = share.argmax(0)  # the first of equals: the more frequent language
        return np.where(letters, np.array(f.languages, object)[best], "und"), np.where(letters, share.max(0), 0.0)


def predict(docs: DataFrame, filters: Filters) -> DataFrame:
    """All columns of docs but the text, with lang_pred string and score double for every row; columns of these names are replaced."""
    others = [c for c in docs.columns if c not in ("text", "lang_pred", "score")]
    sent = docs.sparkSession.sparkContext.broadcast(filters)  # 2^bits cells of 8 bytes for each 64 languages
    schema = ", ".join([*(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in others), "lang_pred string", "score double"])

    @released
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        v = Verdicts(sent.value)
        for pdf in batches:
            for k in range(0, len(pdf), TEXTS):
                part = pdf.iloc[k : k + TEXTS]
                pred, score = v.of(part["text"].tolist())
                yield part[others].assign(lang_pred=pred, score=score)

    return docs.select(*others, "text").mapInPandas(run, schema)


def held_out() -> F.Column:
    """crc32(doc_id as text) mod 4 is 2; false for a null id."""
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))


def op8_language_bitmask(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    filters = learn(docs.filter(~held_out()).select("text", "lang"))
    return predict(docs.select("doc_id", held_out().alias("held_out"), "text"), filters)


def reject_unknown(spark: SparkSession, docs: DataFrame, sf_dir: str | None = None, least: float = 0.2) -> DataFrame:
    """Pipeline stage: keeps documents in which some language holds at least the share `least` of n-grams; und goes. All columns stay."""
    filters = learn(docs.filter(~held_out()).select("text", "lang"))
    names = docs.columns
    sent = spark.sparkContext.broadcast(filters)

    @F.arrow_udf("lang_pred string, score double")
    @released
    def verdict(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        v = Verdicts(sent.value)
        for texts in batches:
            got = [v.of(texts.slice(k, TEXTS).to_pylist()) for k in range(0, len(texts), TEXTS)] or [v.of([])]
            yield pa.StructArray.from_arrays([pa.array(np.concatenate([x[0] for x in got]), pa.string()), pa.array(np.concatenate([x[1] for x in got]))], ["lang_pred", "score"])

    scored = docs.withColumn("__verdict", verdict("text"))
    return scored.filter((F.col("__verdict.lang_pred") != "und") & (F.col("__verdict.score") >= least)).select(*names)
