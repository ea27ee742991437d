"""Whole queries over the smallest tables, against plain versions without Spark or arrays."""

import collections
import math
import re
import statistics
import struct
import zlib

import numpy as np
import pytest
import xxhash

from blocksketch.llm import language_id, mixing, quality, toxicity
from blocksketch.llm.common import table
from blocksketch.llm.shingles import Words

DATA = "/root/testdata/sf0.001"
SPACE = r"[\x20\x09-\x0D]+"


def words(t):
    return [w for w in re.split(SPACE, t or "") if w]


@pytest.fixture(scope="module")
def documents(spark):
    return table(spark, DATA, "documents").collect()


def hashed(data: bytes, seed: int = 42) -> int:
    return xxhash.xxh64_intdigest(data, seed)


def topic(text):
    n = [0] * 8
    for w in words(text):
        if len(w) >= 4:
            h = hashed(w.lower().encode())
            n[(h - (1 << 64) if h >> 63 else h) % 8] += 1
    return n.index(max(n))


def test_raked_mixture(spark, documents):
    cell = {d.doc_id: (d.source or "(none)", d.lang or "(none)", topic(d.text)) for d in documents}
    tokens = {d.doc_id: max(1, len(words(d.text))) for d in documents}
    mass = collections.Counter()
    for k, c in cell.items():
        mass[c] += tokens[k]
    total = sum(mass.values())
    goals = []
    for d in range(3):
        share = collections.Counter()
        for c, n in mass.items():
            share[c[d]] += n
        raised = {g: math.sqrt(n / total) for g, n in share.items()}
        goals.append({g: v / sum(raised.values()) for g, v in raised.items()})
    factor = dict.fromkeys(mass, 1.0)
    for _ in range(100):
        for d in range(3):
            now = collections.Counter()
            for c, n in mass.items():
                now[c[d]] += factor[c] * n / total
            for c in factor:
                factor[c] *= goals[d][c[d]] / now[c[d]]
    got = {r.doc_id: r for r in mixing.op1_raked_mixture(spark, DATA).collect()}
    assert got.keys() == cell.keys()
    scale = max(r.prob / r.weight for r in got.values())
    for k, r in got.items():
        assert (r.source, r.lang, r.topic, r.n_tokens) == (*cell[k], tokens[k])
        assert r.weight == pytest.approx(factor[cell[k]], rel=1e-5) and r.prob == pytest.approx(min(1, scale * factor[cell[k]]), rel=1e-5)
        uniform = (hashed(struct.pack("<i", 1), hashed(struct.pack("<q", k))) >> 11) / 2**53
        assert r.sampled == (uniform < r.prob)
    assert sum(tokens[k] * r.prob for k, r in got.items()) == pytest.approx(total / 2, rel=1e-6)


def test_likelihood_ratio(spark, documents):
    trusted = {r.doc_id for r in table(spark, DATA, "labels").filter("quality = 1").collect()}
    grams = {d.doc_id: [*(w := words(d.text)), *(f"{a} {b}" for a, b in zip(w, w[1:], strict=False))] for d in documents}
    every = sorted({g for x in grams.values() for g in x})
    single = Words([g.encode() for g in every], lower=False)
    found, of = quality.buckets(single, 16)
    bucket = dict(zip((every[k] for k in of), found, strict=True))  # of a pair, the last is the pair's own
    raw, target = collections.Counter(), collections.Counter()
    for k, x in grams.items():
        for g in x:
            raw[bucket[g]] += 1
            target[bucket[g]] += k in trusted
    size, score = 1 << 16, {}
    for k, x in grams.items():
        own, good = collections.Counter(bucket[g] for g in x), k in trusted
        sums = sum(raw.values()) + size - len(x), sum(target.values()) + size - len(x) * good
        logs = (n * (math.log((target[b] + 1 - n * good) / sums[1]) - math.log((raw[b] + 1 - n) / sums[0])) for b, n in own.items())
        score[k] = sum(logs) / max(1, len(x))
    seen = [score[k] for k in score if k in trusted and grams[k]]
    least = statistics.fmean(seen) - 4 * statistics.pstdev(seen)
    for r in quality.op3_likelihood_ratio(spark, DATA).collect():
        assert r.score == pytest.approx(score[r.doc_id], abs=1e-9)
        assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words)
        assert r.kept == (not r.base_failed and score[r.doc_id] >= least - 1e-9)


def test_language_bitmask(spark, documents):
    def grams(text):
        for w in language_id.WORD.findall((text or "").lower()):
            marked = f"\0{w}\0"
            for n in (3, 4):
                yield from (marked[i : i + n] for i in range(len(marked) - n + 1))

    held = {d.doc_id: zlib.crc32(str(d.doc_id).encode()) % 4 == 2 for d in documents}
    count = collections.defaultdict(collections.Counter)
    for d in documents:
        if not held[d.doc_id] and d.lang is not None:
            count[d.lang].update(grams(d.text))
    rate = {lang: {g: n / sum(c.values()) for g, n in c.items()} for lang, c in count.items()}
    top = collections.Counter()
    for r in rate.values():
        for g, x in r.items():
            top[g] = max(top[g], x)
    members = {lang: {g for g, n in c.items() if n >= 2 and rate[lang][g] >= 0.2 * top[g]} for lang, c in count.items()}
    clear = 0
    text = {d.doc_id: d.text for d in documents}
    for r in language_id.op8_language_bitmask(spark, DATA).collect():
        x = list(grams(text[r.doc_id]))
        assert r.held_out == held[r.doc_id]
        if not x:
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        share = sorted(((sum(g in m for g in x) / len(x), lang) for lang, m in members.items()), reverse=True)
        assert r.score == pytest.approx(share[0][0], abs=0.02)
        if share[0][0] > share[1][0] + 0.04:
            clear += 1
            assert r.lang_pred == share[0][1]
    assert clear > 0.9 * len(documents)


def test_positive_unlabelled_fit(spark, documents):
    """The distributed selection and fit equal those over all rows in memory, where the samples hold every row."""
    toxic = {k for k, d in enumerate(documents) if k % 9 == 0}
    texts = [(d.text or "") + (" vile rotten scum" if k in toxic else "") for k, d in enumerate(documents)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(k in toxic)) for k in range(0, len(texts), 3)], "doc_id long, toxic int")
    got = toxicity.learn(docs, labels)
    rows = [np.asarray(f) for f in toxicity.Features(20, None).of(texts)]
    prior = len(toxic) / len(range(0, len(texts), 3))
    want = toxicity.train([rows[k] for k in sorted(toxic)], rows, min(prior, 0.5), 20, purity=0.2)
    assert np.array_equal(got.known, want.known) and len(got.known)
    assert np.allclose(got.weights, want.weights, atol=1e-6) and got.bias == pytest.approx(want.bias, abs=1e-6)
    score = {r.doc_id: r.score for r in toxicity.predict(docs, got).collect()}
    memory = want.score([np.searchsorted(want.known, f[np.isin(f, want.known)]) for f in rows])
    assert all(score[k] == pytest.approx(memory[k], abs=1e-6) for k in score)
