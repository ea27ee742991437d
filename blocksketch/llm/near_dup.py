"""Near-duplicate documents by fast similarity sketching, banding and exact verification.

Texts with the same set of 5-word shingles form a class, told by a 128-bit sum over the set; one class member goes on, and its doc_id names
the class. Should two classes have the same least doc_id (rows that share an id but not a text), the others get a name of their own beyond 2^62. Its
sketch of `size` coordinates comes from rounds of hashed bin placement (see shingles.sketches); the first `bands * rows` of them
give buckets. At similarity 0.75 a pair shares no bucket with probability (1 - 0.75^4)^32 = 5e-6.

A bucket of n classes is not expanded into all its pairs. Each class is first compared with a few pivots of its buckets, drawn by
hash, and the links found are merged into components. While that pays, further pivots are drawn from the buckets that hold more than
one component. Then the pairs left over, those in one bucket but in different components, are all compared. So pairs that
could change no component are skipped, and no other: nothing is capped. A bucket of more than TILE members is dealt over tiles by hash, and each
pair of tiles is a join key of its own, so that no task compares a large bucket alone.

Before its full sets are fetched, a pair is tested on packed sketches of 2 bits a coordinate: at most 253 of 1024 may differ, where a pair at
0.75 expects 192 with deviation 12.5. Of the buckets that a pair shares, only the first yields it. Links are confirmed on full sets of
64-bit shingle hashes, whose words are hashed modulo two primes, so no structure of a text makes its hashes collide.

Defined results: null, empty or blank text has an empty set (n_shingles 0), is linked with nothing and kept; a text of fewer than
five words has one shingle. Rows that share a doc_id and a text count once; with unlike texts each row follows its own text, and a component
has the least doc_id of its rows. A null doc_id keeps its row but names no component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, Kept, mix, released, seeds, table
from .components import components
from .shingles import Words, chunks, set_hash, sketches


EVEN = 0x5555555555555555  # the lower bit of each pair of bits
TEXTS = 512  # sketched at a time, so a worker holds a few MB of sketches whatever the lengths
NAMED = 1 << 62
SMALL = 100_000  # rows that may be broadcast
FEW = 2_000_000  # ids that may be broadcast, so that texts need no shuffle
TILE = 2048  # members of a bucket that are compared in one task


def _features(size: int, width: int, bands: int, rows: int):
    @released
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        salt = seeds("band", bands)
        for pdf in batches:
            for first, texts in chunks(pdf["text"], rows=TEXTS):
                h, doc = Words(texts).sets(width)
                n = np.bincount(doc, minlength=len(texts))
                c1, c2 = set_hash(h, doc, len(texts))
                s = sketches(h, doc, len(texts), size).view(np.uint32).astype(np.uint64)
                keys = np.zeros((len(texts), bands), np.uint64)
                for k in range(rows):
                    keys = mix(keys + s[:, k * bands : (k + 1) * bands] + U64(1)) * salt
                bits = np.zeros((len(texts), size // 32), np.uint64)
                for k in range(32):
                    bits |= (s[:, k :: 32] & U64(3)) << U64(2 * k)
                prints = (keys[:, 0::2] >> U64(32)) | (keys[:, 1::2] & U64(0xFFFFFFFF00000000))
                out = {"doc_id": pdf["doc_id"].to_numpy()[first : first + len(texts)], "n": n, "c1": c1, "c2": c2, "bands": list(keys.view(np.int64)), "prints": list(prints.view(np.int64))}
                yield pd.DataFrame(out | {f"p{k}": bits[:, k].view(np.int64) for k in range(size // 32)})

    return run


def _sets(width: int):
    @released
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for first, texts in chunks(pdf["text"]):
                h, doc = Words(texts).sets(width)
                ends = np.searchsorted(doc, np.arange(len(texts) + 1))
                c1, c2 = set_hash(h, doc, len(texts))
                yield pd.DataFrame({"doc_id": pdf["doc_id"].to_numpy()[first : first + len(texts)], "c1": c1, "c2": c2, "members": [h[a:b].view(np.int64) for a, b in zip(ends, ends[1:], strict=False)]})

    return run


def near_duplicates(docs: DataFrame, percent: int = 75, width: int = 5, size: int = 1024, bands: int = 32, rows: int = 4, rounds: int = 4) -> DataFrame:
    """docs(doc_id, text) to (doc_id, n_shingles, component_id, kept), one row per row of docs."""
    keep = Kept(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ps = [f"p{k}" for k in range(size // 32)]
    schema = "doc_id long, n long, c1 long, c2 long, bands array<long>, prints array<long>, " + ", ".join(f"{p} long" for p in ps)
    feats = keep.keep(docs.mapInPandas(_features(size, width, bands, rows), schema))
    classes = keep.keep(feats.filter("n > 0").groupBy("c1", "c2").agg(F.min("doc_id").alias("first")))
    again = classes.filter("first is not null").groupBy("first").agg(F.count("*").alias("c"), F.min(F.struct("c1", "c2")).alias("lead")).filter("c > 1").select(F.col("first").alias("f"), "lead")
    again = keep.keep(again)
    clash = again.count()
    named = classes.join(F.broadcast(again) if clash <= SMALL else again, F.col("first") == F.col("f"), "left")
    own = F.lit(NAMED) + F.xxhash64("c1", "c2").bitwiseAND(NAMED - 1)
    classes = keep.keep(named.select("c1", "c2", "first", F.when(F.col("lead").isNull() | (F.struct("c1", "c2") == F.col("lead")), F.col("first")).otherwise(own).alias("node")))
    known_classes = classes.filter("node is not null").withColumnsRenamed({"c1": "d1", "c2": "d2"})
    reps = feats.join(known_classes, (F.col("doc_id") == F.col("first")) & (F.col("c1") == F.col("d1")) & (F.col("c2") == F.col("d2")))
    reps = keep.keep(reps.dropDuplicates(["node"]).select("node", "n", *ps, "bands", "prints"))
    slim = keep.keep(feats.select("doc_id", "n", "c1", "c2"))
    keep.drop(feats)
    each = reps.select("node", F.posexplode("bands").alias("band", "key"))
    shared = each.groupBy("band", "key").agg(F.count("*").alias("c")).filter("c > 1").drop("c")
    cand = keep.keep(each.join(shared, ["band", "key"]).withColumn("key", F.xxhash64("band", "key")))
    nodes = cand.select("node").distinct()
    known = keep.keep(reps.join(nodes, "node", "left_semi").drop("bands"))
    keep.drop(reps)

    differ = " + ".join(f"bit_count(((a.{p} ^ b.{p}) | shiftrightunsigned(a.{p} ^ b.{p}, 1)) & {EVEN}L)" for p in ps)
    alike = F.expr(f"least(a.n, b.n) * 100 >= greatest(a.n, b.n) * {percent} and {differ} <= {int(size * 0.248)}")
    pair = [F.least("a.node", "b.node").alias("a"), F.greatest("a.node", "b.node").alias("b")]

    def plausible(pairs: DataFrame) -> DataFrame:
        """Of pairs(a, b), those whose sketches are alike."""
        side = lambda x: known.select(F.struct("node", "n", *ps).alias(x))
        pairs = pairs.select(F.col("a").alias("__a"), F.col("b").alias("__b")).distinct()
        return pairs.join(side("a"), F.col("__a") == F.col("a.node")).join(side("b"), F.col("__b") == F.col("b.node")).filter(alike).select(*pair)

    wanted = keep.keep(known_classes.join(nodes, "node", "left_semi"))
    ids = wanted.select(F.col("first").alias("doc_id")).distinct()
    sets = docs.join(F.broadcast(ids) if ids.count() <= FEW else ids, "doc_id", "left_semi").mapInPandas(_sets(width), "doc_id long, c1 long, c2 long, members array<long>")
    sets = sets.dropDuplicates(["doc_id", "c1", "c2"]).join(wanted, (F.col("doc_id") == F.col("first")) & (F.col("c1") == F.col("d1")) & (F.col("c2") == F.col("d2")))
    sets = keep.keep(sets.select("node", "members"))

    def links(pairs: DataFrame) -> DataFrame:
        """Of pairs(a, b), those whose full sets are alike."""
        with_a = pairs.join(sets.select(F.col("node").alias("a"), F.col("members").alias("ma")), "a")
        both = with_a.join(sets.select(F.col("node").alias("b"), F.col("members").alias("mb")), "b")
        common = F.size(F.array_intersect("ma", "mb"))
        return both.select("a", "b", common.alias("i"), (F.size("ma") + F.size("mb") - common).alias("u")).filter(F.col("i") * 100 >= F.col("u") * percent).select("a", "b")

    drawn = [F.min(F.struct(F.xxhash64("node", F.lit(s)).alias("h"), F.col("node").alias("b"))).alias(f"d{s}") for s in range(3)]
    own = cand.select("key", F.col("node").alias("a")).join(cand.groupBy("key").agg(*drawn), "key")
    nearest = own.groupBy("a").agg(*(F.min(f"d{s}").alias(f"d{s}") for s in range(3))).select("a", F.explode(F.array(*(f"d{s}.b" for s in range(3)))).alias("b"))
    first = plausible(nearest.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")))
    labels = components(keep.keep(links(first)), keep)

    def merged(more: DataFrame) -> DataFrame:
        """Labels after more links between components."""
        la, lb = (labels.select(F.col("node").alias(x), F.col("component").alias(f"c{x}")) for x in "ab")
        lifted = more.join(la, "a", "left").join(lb, "b", "left").select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"))
        new = keep.keep(components(keep.keep(lifted), keep))
        over = new.select(F.col("node").alias("component"), F.col("component").alias("top"))
        moved = labels.join(over, "component", "left").select("node", F.coalesce("top", "component").alias("component"))
        return keep.keep(moved.union(new).distinct())

    left = None
    for r in range(rounds + 1):
        named = cand.join(labels, "node", "left").withColumn("comp", F.coalesce("component", "node")).drop("component")
        mixed = named.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.max_by(F.struct("node", "comp"), F.xxhash64("node", F.lit(100 + r))).alias("b")).filter("lo <> hi")
        rest = keep.keep(named.join(mixed.select("key", "b"), "key"))
        per = rest.groupBy("key", "comp").agg(F.count("*").alias("c")).groupBy("key").agg(F.sum("c").alias("c"), F.sum(F.col("c") * F.col("c")).alias("q"))
        todo = per.agg(F.sum((F.col("c") * F.col("c") - F.col("q")) / 2), F.sum("c")).first()
        if not todo[0]:
            break
        if r < rounds and todo[0] > 4 * todo[1] and (left is None or todo[0] < 0.7 * left):
            left = todo[0]
            pairs = rest.filter("comp <> b.comp").select(F.least("node", "b.node").alias("a"), F.greatest("node", "b.node").alias("b"))
            labels = merged(links(plausible(pairs)))
            keep.drop(rest)
            continue
        prints = [F.col("prints")[k].alias(f"f{k}") for k in range(bands // 2)]
        tiles = per.select("key", F.ceil(F.col("c") / TILE).cast("int").alias("tiles")).filter("tiles > 1")
        dealt = rest.select("band", "key", "node", "comp").join(tiles, "key", "left").withColumn("tiles", F.coalesce("tiles", F.lit(1)))
        dealt = dealt.withColumn("own", F.expr("cast(pmod(xxhash64(node), tiles) as int)")).withColumn("other", F.explode(F.expr("sequence(0, tiles - 1)")))
        dealt = dealt.select("band", "key", "node", "comp", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))
        side = dealt.join(known.select("node", "n", *ps, *prints), "node")
        earlier = F.expr(" and ".join(f"(a.band <= {k} or (a.f{k // 2} ^ b.f{k // 2}) & {0xFFFFFFFF if k % 2 == 0 else 0x7FFFFFFF00000000}L <> 0{'' if k % 2 == 0 else f' or (a.f{k // 2} < 0) <> (b.f{k // 2} < 0)'})" for k in range(bands - 1)))
        met = F.expr("a.key = b.key and a.lo = b.lo and a.hi = b.hi and (a.own <> b.own or a.lo = a.hi)")  # a pair meets in one tile
        pairs = side.alias("a").join(side.alias("b"), met & (F.col("a.node") < F.col("b.node")) & (F.col("a.comp") != F.col("b.comp")) & alike & earlier).select(*pair).distinct()
        labels = merged(links(pairs))
        break
    if clash:  # a component's name is the least doc_id of its classes
        least = classes.join(labels, "node").groupBy("component").agg(F.min("first").alias("name"))
        labels = labels.join(least, "component").select("node", F.col("name").alias("component"))
    out = slim.join(classes, ["c1", "c2"], "left").join(labels, "node", "left")
    component = F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.coalesce("component", "first"))
    out = out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def op10_fast_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str | None = None) -> DataFrame:
    """Pipeline stage: of each group of near duplicates the document of the smallest id stays, with all its columns."""
    gone = Kept(spark).keep(near_duplicates(docs).filter(~F.col("kept")).select("doc_id").distinct())
    few = gone.count() <= FEW
    return docs.join(F.broadcast(gone) if few else gone, "doc_id", "left_anti").select(*docs.columns)
