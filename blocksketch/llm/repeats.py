"""Removal of repeated byte strings, and the finding of repeated passages of words, by a column-wise suffix order over a collection.

A byte goes if a string of `width` bytes that covers it starts anywhere else in the corpus too. A word lies in a repeated passage if a run of
`passage` words that covers it starts anywhere else; passages are counted, not removed. Both are one algorithm over symbols: bytes, or hashes of words.
Inserting one symbol of every whole document per round over a whole corpus would take as many rounds as the longest document
has symbols, each over all data. So candidates are cut out first, without loss:

1. Every window of `width` symbols is named by its anchor, the least hashed `gram`-symbol string within it. Equal windows have equal
   anchors at equal offsets. Windows of one anchor are put into blocks of neighbouring offsets (64 for bytes); all windows of a block share a core of
   width - 63 symbols. A block is described by a hash of its core, so only blocks whose core occurs twice can hold repeats.
2. Blocks that agree in everything (core, up to 63 symbols before and after) and occur twice are repeated altogether; that is decided by the 124 bits of
   two hashes.
3. Of other blocks with a repeated core, one per distinct content goes into a collection of short documents: up to 63 symbols, the core as one symbol,
   up to 63 symbols. The collection's suffix order is built column by column from the right: each round inserts one symbol per document, read through the
   present order (the transform's column), by a stable distribution on it, and updates the common prefixes of neighbours. After the round
   of a window's first symbol, it is repeated if its common prefix with a neighbour spans it.
4. Cores in over `most` contents are cut into two blocks of half the offsets, whose cores are longer by what their windows share; so hot groups spread over
   tasks and are decided by the same rounds. Halves that agree in everything and occur twice are repeated altogether; one of each goes on. All blocks of
   one size are cut together, so the number of jobs grows with the logarithm of `block`.

A collection holds up to `most` contents and those of one core more, so the columns of its rounds stay in a task's memory; nothing is written to a
machine's own disk. Hashes have 62 bits and more and are taken modulo primes.
Defined results: null text counts as empty; texts shorter than width keep all; repeated rows are documents of
their own, so both lose what they share. Anchors of very long texts are found part by part.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, Kept, Windows, fingerprints, mix, seeds, table
from .shingles import Words, chunks

PART = 4_000_000
_POSITION = U64((1 << 24) - 1)
_GRAM = seeds("symbols", 64)


@dataclass(frozen=True)
class Scheme:
    """Windows of `width` symbols, anchors of `gram`, blocks of up to `block` (64 at most) offsets; symbols are bytes or words."""

    width: int
    gram: int
    block: int
    words: bool = False

    def __post_init__(self):
        if not self.gram <= self.width - self.block + 1 or not 1 < self.block <= 64:
            raise ValueError("an anchor must fit into the core of a block of 2 to 64 windows")

    @property
    def side(self) -> int:
        return self.block - 1

    @property
    def least_bytes(self) -> int:
        return 2 * self.width - 1 if self.words else self.width

    def sequences(self, texts: pd.Series) -> Iterator[np.ndarray]:
        """The symbols of each text."""
        if not self.words:
            for t in texts:
                yield np.frombuffer(t.encode("utf-8", "surrogatepass"), np.uint8) if t else np.zeros(0, np.uint8)
            return
        for _, held in chunks(texts):
            w = Words(held, lower=False)
            ends = np.searchsorted(w.doc, np.arange(len(held) + 1))
            for a, b in zip(ends, ends[1:], strict=False):
                yield w.hash[a:b]


def sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    """The least value of each window of `width` neighbours, from prefix and suffix minima of blocks."""
    n = len(x) - width + 1
    pad = -len(x) % width
    y = np.concatenate([x, np.full(pad, x.dtype.type(np.iinfo(x.dtype).max))]).reshape(-1, width)
    ahead = np.minimum.accumulate(y, axis=1).ravel()
    back = np.minimum.accumulate(y[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[width - 1 : width - 1 + n])


def _anchors(data: np.ndarray, gram: int) -> np.ndarray:
    """A pseudo-random number for each string of `gram` symbols."""
    if data.dtype == np.uint8:
        return fingerprints(data, gram)
    m = len(data) - gram + 1
    h = np.zeros(m, np.uint64)
    for k in range(gram):
        h += data[k : k + m] * _GRAM[k]
    return mix(h)


def blocks(data: np.ndarray, s: Scheme) -> dict[str, np.ndarray]:
    """The blocks of one text: key (core), x (all content), core (start of the core), p0 and cnt (its windows)."""
    width, block = s.width, s.block
    m = len(data) - width + 1
    if m <= 0:
        return {c: np.zeros(0, np.int64) for c in ("key", "x", "core", "p0", "cnt")}
    w = Windows(data)
    anchor = np.empty(m, np.int64)
    for begin in range(0, m, PART):
        end = min(begin + PART, m)
        g = _anchors(data[begin : end + width - 1], s.gram)
        g = (g & ~_POSITION) | np.arange(len(g), dtype=np.uint64)
        anchor[begin:end] = begin + (sliding_least(g, width - s.gram + 1) & _POSITION).astype(np.int64)
    q = (anchor - np.arange(m)) // block
    p0 = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (q[1:] != q[:-1])]))
    cnt, q = np.diff(np.append(p0, m)), q[p0]
    core = anchor[p0] - block * q
    end = core + width - block + 1
    key = mix(w.hash(core, end) + q.astype(np.uint64) + U64(1))
    lo, hi = np.maximum(core - block + 1, 0), np.minimum(end + block - 1, len(data))
    place = (core - lo) + 64 * (hi - end) + 4096 * (p0 - core + block) + (1 << 20) * cnt
    x = mix(w.hash(lo, hi) ^ mix(place.astype(np.uint64)))
    return {"key": key.view(np.int64), "x": x.view(np.int64), "core": core, "p0": p0, "cnt": cnt}


def _blocks(s: Scheme):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            held, size = [], 0
            for rid, data in zip(pdf["rid"], s.sequences(pdf["text"]), strict=True):
                b = blocks(data, s)
                if not len(b["key"]):
                    continue
                held.append({"rid": np.full(len(b["key"]), rid)} | b)
                size += len(b["key"])
                if size > 100_000:
                    yield pd.DataFrame({c: np.concatenate([h[c] for h in held]) for c in held[0]})
                    held, size = [], 0
            if held:
                yield pd.DataFrame({c: np.concatenate([h[c] for h in held]) for c in held[0]})

    return run


class Collection:
    """Short documents of equal number of columns, whose suffixes are ordered column by column, from the last to the first.

    Symbol 0 ends a document: it equals nothing. `transform` has the inserted symbols of each round in the order before it."""

    def __init__(self, m: int, traced: bool = False):
        self.order, self.common = np.arange(m), np.zeros(m, np.int32)
        self.transform: list[np.ndarray] | None = [] if traced else None

    def insert(self, symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One symbol in front of each document: the new order, and each suffix's common prefix with the one before it."""
        column = symbols[self.order]
        if self.transform is not None:
            self.transform.append(column)
        at = np.argsort(column, kind="stable")
        told = column[at]
        i = np.flatnonzero((told[1:] == told[:-1]) & (told[1:] != 0)) + 1
        lcp = np.zeros(len(at), np.int32)
        if len(i):
            ends = np.append(self.common, np.int32(0))  # so that an end behind the last is allowed
            lcp[i] = 1 + np.minimum.reduceat(ends, np.stack([at[i - 1] + 1, at[i] + 1], 1).ravel())[::2]
        self.order, self.common = self.order[at], lcp
        return self.order, lcp


def repeated_windows(group: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """For each content (its core's group, `side` symbols before and after, 0: none), side + 1 bits: bit j says that the window that
    starts j places after the first possible one is found in another content too."""
    m, side = left.shape
    mask = np.zeros(m, np.uint64)
    if m < 2:
        return mask
    c = Collection(m)
    for k in range(side - 1, -1, -1):
        c.insert(right[:, k])
    for j in range(side, -1, -1):
        order, lcp = c.insert(group + 1 if j == side else left[:, j])
        long = lcp > side
        hit = long.copy()
        hit[:-1] |= long[1:]
        mask[order[hit]] |= U64(1 << j)
    return mask


def _sides(rows: list[bytes], side: int, before: bool, words: bool) -> np.ndarray:
    """The symbols, numbered from 1, in `side` columns: at the right end (before) or the left (after), 0 where there are none."""
    size = 8 if words else 1
    n = np.array([len(b) // size for b in rows], np.int64)
    flat = np.frombuffer(b"".join(rows), np.int64 if words else np.uint8)
    flat = np.unique(flat, return_inverse=True)[1].astype(np.int32) + 1 if words else flat.astype(np.uint16) + 1
    place = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(side - n if before else np.zeros(len(n), np.int64), n)
    out = np.zeros((len(rows), side), flat.dtype)
    out[np.repeat(np.arange(len(rows)), n), place] = flat
    return np.asfortranarray(out)


def _settle(s: Scheme, most: int):
    """Rows (key, lo, hi, first, x, before, after), sorted by key within a task, to (first, x, mask), for the windows lo to hi - 1 of each content."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: pd.DataFrame | None = None

        def done(pdf: pd.DataFrame) -> Iterator[pd.DataFrame]:
            for windows, part in pdf.groupby(pdf["hi"] - pdf["lo"]):
                sides = [_sides(part[c].to_list(), windows - 1, c == "before", s.words) for c in ("before", "after")]
                mask = repeated_windows(part["key"].factorize()[0], *sides) << part["lo"].to_numpy(np.uint64)
                yield pd.DataFrame({"first": part["first"], "x": part["x"], "mask": mask.view(np.int64)})

        for pdf in batches:
            pdf = pdf if held is None else pd.concat([held, pdf], ignore_index=True)
            if len(pdf) < most:
                held = pdf
                continue
            open_ = pdf["key"] == pdf["key"].iloc[-1]  # this key may go on
            yield from done(pdf[~open_])
            held = pdf[open_].reset_index(drop=True)
        if held is not None and len(held):
            yield from done(held)

    return run


def _content(s: Scheme):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        size = s.width - s.block + 1
        for pdf in batches:
            key, x, before, after = [], [], [], []
            for data, k, v, core in zip(s.sequences(pdf["text"]), pdf["key"], pdf["x"], pdf["core"], strict=True):
                key.append(k)
                x.append(v)
                before += [data[max(0, c - s.side) : c].tobytes() for c in core]
                after += [data[c + size : c + size + s.side].tobytes() for c in core]
            yield pd.DataFrame({"key": np.concatenate(key), "x": np.concatenate(x), "before": before, "after": after})

    return run


def _halves(split: DataFrame, size: int) -> DataFrame:
    """Each content twice, for either half of its windows. What all windows of the half share, before and after the core, goes into the key and only what
    varies is left; a text that lacks the shared part holds none of these windows."""
    mid = F.floor((F.col("lo") + F.col("hi")) / 2).cast("int")
    half = F.explode(F.array(F.struct(F.col("lo").alias("a"), mid.alias("b")), F.struct(mid.alias("a"), F.col("hi").alias("b"))))
    back, ahead, left = "(hi - b) * {0}", "(a - lo) * {0}", "(b - 1 - a) * {0}"
    back, ahead, left = (x.format(size) for x in (back, ahead, left))
    has = split.withColumn("half", half).select("*", "half.a", "half.b").filter(f"octet_length(before) >= {back} and octet_length(after) >= {ahead}")
    rest = f"octet_length(before) - {back}"
    return has.selectExpr(
        f"xxhash64(key, a, b, substring(before, {rest} + 1, {back}), substring(after, 1, {ahead})) as key", "a as lo", "b as hi", "first", "x",
        f"substring(before, greatest({rest} - {left}, 0) + 1, least({rest}, {left})) as before", f"substring(after, {ahead} + 1, {left}) as after",
    )


def _settled(content: DataFrame, s: Scheme, most: int, keep: Kept) -> DataFrame:
    """content(key, x, before, after) to (key, x, mask): the column-wise rounds on every block, hot cores in halves, all of one size in the same jobs."""
    wide = content.select("key", F.lit(0).alias("lo"), F.lit(s.block).alias("hi"), F.col("key").alias("first"), "x", "before", "after")
    done = []
    while True:
        hot = keep.keep(wide.groupBy("key").agg(F.count("*").alias("c")).filter(F.col("c") > most).select("key"))
        n = hot.count()
        side = F.broadcast(hot) if n <= 100_000 else hot
        cool = wide.join(side, "key", "left_anti") if n else wide
        done.append(cool.repartition("key").sortWithinPartitions("key").mapInPandas(_settle(s, most), "first long, x long, mask long"))
        if not n:
            break
        halves = keep.keep(_halves(wide.join(side, "key", "left_semi"), 8 if s.words else 1))
        # Halves that agree in everything are repeated altogether; one of them stands for them against the others.
        same = ["key", "lo", "hi", "before", "after"]
        kinds = keep.keep(halves.groupBy(*same).agg(F.count("*").alias("n"), F.min(F.struct("first", "x")).alias("one")))
        full = F.expr("shiftleft(shiftrightunsigned(-1L, 64 - (hi - lo)), lo)")
        done.append(halves.join(kinds.filter("n > 1").select(*same), same, "left_semi").select("first", "x", full.alias("mask")))
        wide = kinds.filter("hi - lo > 1").select("key", "lo", "hi", "one.first", "one.x", "before", "after")
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    if len(done) > 1:
        out = out.groupBy("first", "x").agg(F.bit_or("mask").alias("mask"))
    return out.withColumnRenamed("first", "key")


def repeated(docs: DataFrame, s: Scheme, keep: Kept, most: int = 5_000, few: int = 2_000_000) -> DataFrame:
    """docs(rid, text) to (rid, core, p0, cnt, mask), arrays of equal length: the blocks of each text with windows that start elsewhere too."""
    long = docs.filter(F.octet_length("text") >= s.least_bytes).select("rid", "text")
    every = keep.keep(long.mapInPandas(_blocks(s), "rid long, key long, x long, core int, p0 int, cnt int"))
    # Both sides of a join on a hot key are read from files, so that adaptive execution may split them.
    keys = keep.keep(every.groupBy("key").agg(F.count("*").alias("c")).filter("c > 1").select("key"))
    found = keep.keep(every.join(keys, "key", "left_semi"))
    keep.drop(every)
    kinds = keep.keep(found.groupBy("key", "x").agg(F.count("*").alias("n"), F.min(F.struct("rid", "core")).alias("one")))
    open_ = keep.keep(kinds.groupBy("key").agg(F.count("*").alias("kinds")).filter("kinds > 1").select("key"))
    reps = kinds.join(open_, "key", "left_semi").select("one.rid", "key", "x", "one.core")
    lists = reps.groupBy("rid").agg(F.collect_list(F.struct("key", "x", "core")).alias("of")).select("rid", "of.key", "of.x", "of.core")
    lists = keep.keep(lists)
    ids = lists.select("rid")
    some = docs.join(F.broadcast(ids) if lists.count() <= few else ids, "rid", "left_semi")
    texts = some.join(lists, "rid").dropDuplicates(["rid"]).select("text", "key", "x", "core")
    content = keep.keep(texts.mapInPandas(_content(s), "key long, x long, before binary, after binary"))
    masks = _settled(content, s, most, keep)
    all_ = F.lit(-1).cast("long")
    judged = kinds.join(masks, ["key", "x"], "left").select("key", "x", F.when(F.col("n") > 1, all_).otherwise(F.coalesce("mask", F.lit(0).cast("long"))).alias("mask"))
    judged = keep.keep(judged.filter("mask <> 0"))
    hits = found.join(judged, ["key", "x"]).groupBy("rid").agg(F.collect_set(F.struct("core", "p0", "cnt", "mask")).alias("of"))
    return keep.keep(hits.select("rid", "of.core", "of.p0", "of.cnt", "of.mask"))


def covered(n: int, s: Scheme, core: np.ndarray, p0: np.ndarray, cnt: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """Which of n symbols lie in a repeated window."""
    step = np.arange(s.block)
    p = (core.astype(np.int64) - s.side)[:, None] + step
    on = (mask.view(np.uint64)[:, None] >> step.astype(np.uint64) & U64(1)).astype(bool)
    first, number = p0.astype(np.int64)[:, None], cnt.astype(np.int64)[:, None]
    at = p[on & (p >= first) & (p < first + number)]
    edge = np.bincount(at, minlength=n + 1) - np.bincount(at + s.width, minlength=n + 1)
    return np.cumsum(edge)[:n] > 0


def _spans(gone: np.ndarray) -> int:
    return int(np.count_nonzero(gone[1:] & ~gone[:-1]) + (gone[0] if len(gone) else 0))


def _cut(by_bytes: Scheme, by_words: Scheme):
    fields = ("core", "p0", "cnt", "mask")

    def hidden(row: dict, prefix: str, n: int, s: Scheme) -> np.ndarray:
        got = [row[f"{prefix}_{f}"] for f in fields]
        if got[0] is None:
            return np.zeros(n, bool)
        # A text of very many blocks is marked part by part, as each block has `block` places.
        out = np.zeros(n, bool)
        for k in range(0, len(got[0]), 100_000):
            out |= covered(n, s, *(np.asarray(x[k : k + 100_000]) for x in got))
        return out

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for row, data, words in zip(pdf.to_dict("records"), by_bytes.sequences(pdf["text"]), by_words.sequences(pdf["text"]), strict=True):
                gone, said = hidden(row, "b", len(data), by_bytes), hidden(row, "w", len(words), by_words)
                left = data[~gone].tobytes()
                out.append((row["doc_id"], len(data), int(gone.sum()), _spans(gone), hashlib.sha256(left).hexdigest(), int(said.sum()), _spans(said), left.decode("utf-8", "replace") if gone.any() else None))
            yield pd.DataFrame(out, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "n_passage_words", "n_passages", "kept_text"])

    return run


def remove_repeats(docs: DataFrame, width: int = 400, gram: int = 32, block: int = 64, passage: int = 50, word_gram: int = 8, most: int = 5_000, few: int = 2_000_000) -> DataFrame:
    """docs(doc_id, text) to doc_id, n_bytes, n_removed, n_spans, kept_sha256, n_passage_words (words in runs of `passage` words that start elsewhere too),
    n_passages (runs of such words) and, where bytes were removed, kept_text (broken characters replaced)."""
    keep = Kept(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    docs = docs.withColumn("rid", F.xxhash64("doc_id", "text"))
    by_bytes = Scheme(width, gram, block)
    by_words = Scheme(passage, word_gram, min(64, passage - word_gram + 1), words=True)
    of = []
    for name, s in (("b", by_bytes), ("w", by_words)):
        got = repeated(docs.select("rid", "text"), s, keep, most, few)
        of.append(got.withColumnsRenamed({c: f"{name}_{c}" for c in got.columns if c != "rid"}))
    per = keep.keep(of[0].join(of[1], "rid", "full"))
    ids = F.broadcast(per.select("rid")) if per.count() <= few else per.select("rid")
    cut = docs.join(ids, "rid", "left_semi").join(per, "rid").drop("rid")
    cut = cut.mapInPandas(_cut(by_bytes, by_words), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, n_passage_words long, n_passages long, kept_text string")
    none = F.lit(0).cast("long")
    whole = docs.join(ids, "rid", "left_anti").select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), none.alias("n_removed"), none.alias("n_spans"), F.sha2("text", 256).alias("kept_sha256"), none.alias("n_passage_words"), none.alias("n_passages"), F.lit(None).cast("string").alias("kept_text"))
    return cut.unionByName(whole)


def op5_columnwise_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents")).drop("kept_text")
