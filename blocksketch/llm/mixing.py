"""Mixing sources to target weights by iterative proportional fitting.

Documents fall into cells (source, language, topic); a cell weighs its tokens. Raking multiplies the cells by factors, one
dimension after another, until the weighted tokens of every source, language and topic equal their targets. Targets default to
tempered shares (share to the power `temper`, normalised), which lift small groups. Factors become probabilities by one scale, so
that the expected sampled tokens are `rate` of all; a probability over 1 is 1, and the scale makes up for it. A document stays if
a uniform number hashed from its id and the seed is below its cell's probability.

The topic of a text is the bucket, of `topics`, that most of its words of four or more letters hash into (ties: the lowest; none: 0).
Tokens are words between white space, at least one for each row, so an empty text can be drawn too.

Defined results: null source or language is a group of its own; null text counts one token and topic 0; rows of equal doc_id in
one cell are drawn together; a null doc_id draws as one id. Targets for groups that the corpus lacks are dropped and
the rest rescaled; groups without a target get their own share of what the others leave. An empty table gives no rows.
Up to `most` cells are raked in NumPy on the driver, more by DataFrame rounds.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Kept, table

DIMENSIONS = ("source", "lang", "topic")
NONE = "(none)"


def described(docs: DataFrame, topics: int = 8) -> DataFrame:
    """Adds __source, __lang, __topic and __tokens."""
    words = F.filter(F.split(F.coalesce("text", F.lit("")), r"[ \t-\r]+"), lambda w: w != "")
    out = docs.withColumn("__words", words).withColumn("__in", F.expr(f"transform(filter(__words, w -> length(w) >= 4), w -> pmod(xxhash64(lower(w)), {topics}))"))
    counts = [F.expr(f"size(filter(__in, b -> b = {k}))") for k in range(topics)]
    out = out.withColumn("__n", F.array(*counts)).withColumn("__topic", (F.array_position("__n", F.array_max("__n")) - 1).cast("int"))
    named = {f"__{c}": F.coalesce(F.col(c).cast("string"), F.lit(NONE)) for c in ("source", "lang")}
    return out.withColumns(named | {"__tokens": F.greatest(F.size("__words"), F.lit(1)).cast("long")}).drop("__words", "__in", "__n")


def targets(shares: dict, given: dict | None, temper: float) -> dict:
    """Target shares of the groups in `shares`, which holds their token counts."""
    total = sum(shares.values())
    if given is None:
        raised = {k: (v / total) ** temper for k, v in shares.items()}
        return {k: v / sum(raised.values()) for k, v in raised.items()}
    fixed = {k: float(v) for k, v in given.items() if k in shares}
    free = {k: v for k, v in shares.items() if k not in fixed}
    left = max(0.0, 1 - sum(fixed.values())) if free else 0.0
    out = fixed | {k: left * v / sum(free.values()) for k, v in free.items()}
    return {k: v / sum(out.values()) for k, v in out.items()}


def rake(tokens: np.ndarray, index: list[np.ndarray], goal: list[np.ndarray], rounds: int, close: float) -> np.ndarray:
    """Factors per cell; index and goal give, for each dimension, the cells' groups and the groups' target shares."""
    w = tokens / tokens.sum()
    for _ in range(rounds):
        gap = 0.0
        for at, want in zip(index, goal, strict=True):
            now = np.bincount(at, w, len(want))
            gap = max(gap, np.abs(now - want).max())
            w = w * (want / np.maximum(now, 1e-300))[at]
        if gap < close:
            break
    return w / (tokens / tokens.sum())


def scale(tokens: np.ndarray, factor: np.ndarray, rate: float) -> np.ndarray:
    """Probabilities min(1, k * factor), with k so that they keep `rate` of the tokens."""
    lo, hi = 0.0, 1 / max(factor[factor > 0].min(initial=1), 1e-12)
    for _ in range(200):
        k = (lo + hi) / 2
        lo, hi = (k, hi) if (tokens * np.minimum(1, k * factor)).sum() < rate * tokens.sum() else (lo, k)
    return np.minimum(1, hi * factor)


def _rake_frames(cells: DataFrame, goals: list[DataFrame], rate: float, rounds: int, keep: Kept) -> DataFrame:
    """As rake() and scale(), for more cells than a driver should hold. goals: (group, want) for each dimension."""
    total = cells.agg(F.sum("tokens")).first()[0]
    cur = cells.withColumn("w", F.col("tokens") / total)
    for _ in range(rounds):
        for d, goal in zip(DIMENSIONS, goals, strict=True):
            now = cur.groupBy(f"__{d}").agg(F.sum("w").alias("now")).join(goal, f"__{d}").select(f"__{d}", (F.col("want") / F.col("now")).alias("f"))
            cur = cur.join(now, f"__{d}").withColumn("w", F.col("w") * F.col("f")).drop("f")
        cur = keep.keep(cur)
    cur = keep.keep(cur.withColumn("weight", F.col("w") * total / F.col("tokens")).drop("w"))
    lo, hi = 0.0, 1 / cur.agg(F.min("weight")).first()[0]
    for _ in range(50):
        k = (lo + hi) / 2
        got = cur.agg(F.sum(F.col("tokens") * F.least(F.lit(1.0), F.col("weight") * k))).first()[0]
        lo, hi = (k, hi) if got < rate * total else (lo, k)
    return cur.withColumn("prob", F.least(F.lit(1.0), F.col("weight") * hi))


def probabilities(described_docs: DataFrame, rate: float = 0.5, temper: float = 0.5, given: dict | None = None, rounds: int = 100, close: float = 1e-10, most: int = 1_000_000) -> DataFrame:
    """Cells (__source, __lang, __topic) with tokens, weight (the raking factor) and prob."""
    spark, given = described_docs.sparkSession, given or {}
    names = [f"__{d}" for d in DIMENSIONS]
    keep = Kept(spark)
    cells = keep.keep(described_docs.groupBy(*names).agg(F.sum("__tokens").alias("tokens")))
    schema = "__source string, __lang string, __topic int, tokens long, weight double, prob double"
    if cells.count() > most:
        goals = []
        for d in DIMENSIONS:
            got = cells.groupBy(f"__{d}").agg(F.sum("tokens").alias("want"))
            if d in given:
                want = targets({r[0]: r[1] for r in got.collect()}, given[d], temper)  # as many groups as the caller listed targets for
                goals.append(spark.createDataFrame(list(want.items()), f"__{d} {got.schema[0].dataType.simpleString()}, want double"))
            else:
                raised = got.withColumn("want", F.pow(F.col("want").cast("double"), temper))
                goals.append(raised.crossJoin(F.broadcast(raised.agg(F.sum("want").alias("all")))).select(f"__{d}", (F.col("want") / F.col("all")).alias("want")))
        return _rake_frames(cells, goals, rate, rounds, keep).select(*names, "tokens", "weight", "prob")
    pdf = cells.toPandas().sort_values(names).reset_index(drop=True)
    if pdf.empty:
        return spark.createDataFrame([], schema)
    index, goal = [], []
    for d in DIMENSIONS:
        codes, groups = pdf[f"__{d}"].factorize()
        want = targets(dict(zip(groups, np.bincount(codes, pdf["tokens"]), strict=True)), given.get(d), temper)
        index.append(codes)
        goal.append(np.array([want[g] for g in groups]))
    tokens = pdf["tokens"].to_numpy(float)
    pdf["weight"] = rake(tokens, index, goal, rounds, close)
    pdf["prob"] = scale(tokens, pdf["weight"].to_numpy(), rate)
    return spark.createDataFrame(pa.Table.from_pandas(pdf, preserve_index=False), schema)  # by Arrow: rows would go through Python workers of their own


def drawn(docs: DataFrame, cells: DataFrame, seed: int = 1, most: int = 1_000_000) -> DataFrame:
    """Described documents with __weight, __prob and __sampled."""
    names = [f"__{d}" for d in DIMENSIONS]
    cells = cells.select(*names, F.col("weight").alias("__weight"), F.col("prob").alias("__prob"))
    few = cells.count() <= most
    uniform = F.shiftrightunsigned(F.xxhash64("doc_id", F.lit(seed)), 11).cast("double") / F.lit(float(1 << 53))
    return docs.join(F.broadcast(cells) if few else cells, names).withColumn("__sampled", uniform < F.col("__prob"))


def op1_raked_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = described(table(spark, sf_dir, "documents").select("doc_id", "text", "source", "lang")).select("doc_id", "__source", "__lang", "__topic", "__tokens")
    docs = Kept(spark).keep(docs)
    out = drawn(docs, probabilities(docs))
    return out.select("doc_id", F.col("__source").alias("source"), F.col("__lang").alias("lang"), F.col("__topic").alias("topic"), F.col("__tokens").alias("n_tokens"), F.col("__weight").alias("weight"), F.col("__prob").alias("prob"), F.col("__sampled").alias("sampled"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str | None = None, rate: float = 0.5) -> DataFrame:
    """Pipeline stage: the documents drawn to the tempered mixture, with all their columns."""
    names = docs.columns
    seen = Kept(spark).keep(described(docs))
    return drawn(seen, probabilities(seen, rate=rate)).filter("__sampled").select(*names)
