"""Accuracy measures, exact expectations of the sketched product, and bounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily, bucket_sql, sign_sql
from . import kernel, squares
from .losses import Losses
from .matrix import CoordMatrix


def difference(exact: CoordMatrix, approx: DataFrame) -> DataFrame:
    """(i, j, v, v_hat) of all entries that either has, absent ones as zero. approx (i, j, v_hat)."""
    e = exact.df.select("i", F.col("c").alias("j"), F.col("v").cast("double").alias("v"))
    both = e.join(approx.select("i", "j", "v_hat"), ["i", "j"], "full")
    return both.select("i", "j", F.coalesce("v", F.lit(0.0)).alias("v"), F.coalesce("v_hat", F.lit(0.0)).alias("v_hat"))


def rel_frobenius(exact: CoordMatrix, approx: DataFrame) -> DataFrame:
    """One row: the norm of the error over the norm of the exact product."""
    d = difference(exact, approx)
    return d.agg((F.sqrt(F.sum(F.pow(F.col("v") - F.col("v_hat"), 2))) / F.sqrt(F.sum(F.col("v") * F.col("v")))).alias("rel_frob"))


def gram_rel_frobenius(a: CoordMatrix, projected: DataFrame, width: int) -> DataFrame:
    """rel_frobenius of A A^T and the product of a sketch (i, r, v) of `width` columns with itself, by norms, so that no entry of either leaves its task."""
    n = squares.gram_against(a.df, projected, a.rows, width)
    err = F.greatest(F.col("exact_sq") - 2 * F.col("cross") + F.col("guess_sq"), F.lit(0.0))
    return n.select((F.sqrt(err) / F.sqrt("exact_sq")).alias("rel_frob"))


def eps_achieved(a: CoordMatrix, b: CoordMatrix, exact: CoordMatrix, approx: DataFrame) -> DataFrame:
    """One row: the squared error over the product of the squared norms of A and B."""
    err = difference(exact, approx).agg(F.sum(F.pow(F.col("v") - F.col("v_hat"), 2)).alias("err"))
    na, nb = a.frobenius_sq().withColumnRenamed("sq", "na"), b.frobenius_sq().withColumnRenamed("sq", "nb")
    return err.crossJoin(na).crossJoin(nb).select((F.col("err") / (F.col("na") * F.col("nb"))).alias("eps"))


def cell_variance(a: CoordMatrix, b: CoordMatrix, buckets: int) -> DataFrame:
    """(i, j, var): the exact variance of each estimated entry with `buckets` buckets over all slices:
    (|x|^2 |y|^2 + (x.y)^2 - 2 sum x_c^2 y_c^2) / buckets."""
    right = b.df.select(F.col("i").alias("c"), F.col("c").alias("j"), F.col("v").cast("double").alias("w"))
    left = a.df.select("i", "c", F.col("v").cast("double").alias("v"))
    cross = left.join(right, "c").groupBy("i", "j").agg(F.sum(F.col("v") * F.col("w")).alias("p"), F.sum(F.col("v") * F.col("v") * F.col("w") * F.col("w")).alias("q"))
    nx = left.groupBy("i").agg(F.sum(F.col("v") * F.col("v")).alias("nx"))
    ny = right.groupBy("j").agg(F.sum(F.col("w") * F.col("w")).alias("ny"))
    grid = nx.crossJoin(ny)  # rows of A by columns of B: the size of the result
    out = grid.join(cross, ["i", "j"], "left").na.fill(0.0, ["p", "q"])
    return out.select("i", "j", ((F.col("nx") * F.col("ny") + F.col("p") * F.col("p") - 2 * F.col("q")) / buckets).alias("var"))


def expected_error(a: CoordMatrix, b: CoordMatrix, exact: CoordMatrix, buckets: int) -> DataFrame:
    """One row, without the grid: expected squared Frobenius error, its bound 2/buckets |A|^2|B|^2, and both relative to the exact product."""
    na, nb = a.frobenius_sq().withColumnRenamed("sq", "na"), b.frobenius_sq().withColumnRenamed("sq", "nb")
    nc = exact.frobenius_sq().withColumnRenamed("sq", "nc")
    col = lambda m, key, name: m.df.groupBy(F.col(key).alias("x")).agg(F.sum(F.pow(F.col("v").cast("double"), 2)).alias(name))
    both = col(a, "c", "sa").join(col(b, "i", "sb"), "x").agg(F.sum(F.col("sa") * F.col("sb")).alias("q"))
    one = na.crossJoin(nb).crossJoin(nc).crossJoin(both)
    e = (F.col("na") * F.col("nb") + F.col("nc") - 2 * F.col("q")) / buckets
    bound = 2 * F.col("na") * F.col("nb") / buckets
    return one.select(e.alias("expected_sq"), bound.alias("bound_sq"), F.sqrt(e / F.col("nc")).alias("rms_rel"), F.sqrt(bound / F.col("nc")).alias("bound_rel"))


def _sketches(entries: DataFrame, families: DataFrame, width: int) -> DataFrame:
    """(seed, k, h, i, v): the slices of each row under every family; entries (i, c, v)."""
    e = entries.crossJoin(F.broadcast(families)).select("seed", "k", F.expr(bucket_sql("c", width)).alias("h"), "i", (F.expr(sign_sql("c")) * F.col("v")).alias("v"))
    return e.groupBy("seed", "k", "h", "i").agg(F.sum("v").alias("v"))


def errors_over_seeds(a: CoordMatrix, b: CoordMatrix, exact: CoordMatrix, width: int, seeds: list[int], slices: int, alive: DataFrame | Losses, gram: bool = False) -> DataFrame:
    """(seed, e, err_sq, exact_sq): the squared error of the sketched product by sketch seed and by e, the survivor sets alive(e, bi, bj, k), with the
    squared norm of the exact product. A task multiplies each slice of its square of cells once per seed and every e sums those of its survivors; only sums of
    errors leave it. gram: b is a transposed, cells with bi <= bj stand for both. If alive is Losses, the Gram matrix and its sketches come from the entries of a within squares of rows,
    and exact is not read."""
    if isinstance(alive, Losses):
        if not gram:
            raise ValueError("losses by squares are for Gram matrices")
        per = squares.gram_errors(a.df, a.rows, width, [HashFamily(slices, s) for s in seeds], alive)
        return per.groupBy("seed", "e").agg(F.sum("err_sq").alias("err_sq"), F.sum("exact_sq").alias("exact_sq"))
    spark = a.df.sparkSession
    families = spark.createDataFrame([(s, *r) for s in seeds for r in HashFamily(slices, s).rows], "seed int, k int, u1 long, u0 long, w3 long, w2 long, w1 long, w0 long")
    left = _sketches(a.df, families, width)
    right = (left if gram else _sketches(b.t.df, families, width)).withColumnRenamed("i", "j")
    es = sorted(r.e for r in alive.select("e").distinct().collect())
    cells = -(-a.rows // width), -(-b.cols // width)
    per = kernel.squared_errors(left, right, exact.df.withColumnRenamed("c", "j"), alive, list(seeds), es, slices, width, cells, gram)
    sums = per.groupBy("seed", "e").agg(F.sum("err_sq").alias("err_sq"), F.sum("exact_sq").alias("exact_sq"))
    return sums.select("seed", "e", "err_sq", "exact_sq")


def failure_rate(eps: DataFrame, bound: float, theta: float) -> DataFrame:
    """One row: the share of seeds whose eps_achieved lies above the bound, beside the share that was allowed. eps(seed, eps)."""
    return eps.agg(F.count("*").alias("seeds"), F.avg((F.col("eps") > bound).cast("double")).alias("failed"), F.max("eps").alias("worst_eps")).select(F.lit(bound).alias("eps"), F.lit(theta).alias("theta"), "seeds", "failed", "worst_eps")


def spectral_sq(a: CoordMatrix, rounds: int = 20) -> float:
    """The largest eigenvalue of A A^T by power iteration with joins. The vector goes through the driver up to 100000 columns, which cuts its lineage; longer
    ones stay distributed."""
    x = a.df.select("c").distinct().withColumn("x", F.lit(1.0) + F.pmod(F.col("c"), F.lit(7)) / 10)
    value, held = 0.0, []
    for _ in range(rounds):
        y = a.matvec(x)
        z = a.t.matvec(y.select(F.col("i").alias("c"), F.col("y").alias("x"))).select(F.col("i").alias("c"), F.col("y").alias("x"))
        z = z.persist()
        value = float(z.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0])
        x = z.select("c", (F.col("x") / value).alias("x"))
        if a.cols <= 100_000:
            x = a.df.sparkSession.createDataFrame(x.toPandas())
            z.unpersist()
        else:
            held.append(z)  # the next round reads it
            while len(held) > 2:
                held.pop(0).unpersist()
    for z in held:
        z.unpersist()
    return value
