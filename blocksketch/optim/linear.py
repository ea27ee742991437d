"""Least squares, ridge, kernel ridge and Newton steps of generalised linear models, with exact or sketched Gram matrices."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..operators.matrix import CoordMatrix
from ..operators.multiply import multiply, rbs_gram
from ..operators.sketch import stacked_sketch


def dense(df: DataFrame, n: int, m: int, row: str = "i", col: str = "j", v: str = "v_hat") -> np.ndarray:
    """A small result (n x m) as an array on the driver."""
    got = df.select(F.col(row).alias("i"), F.col(col).alias("j"), F.col(v).cast("double").alias("x")).toPandas()
    out = np.zeros((n, m))
    out[got["i"], got["j"]] = got["x"]
    return out


def gram(x: CoordMatrix, family: HashFamily | None = None, width: int = 64, log=None, policy=None) -> np.ndarray:
    """X^T X, contracting over rows; m x m on the driver. With a family it is sketched on the row side."""
    if family is None:
        return dense(multiply(x.t, x).df, x.cols, x.cols, "i", "c", "v")
    return dense(rbs_gram(x.t, width, family, log, policy), x.cols, x.cols)


def solve(h: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, float]:
    """h^-1 g by Cholesky; an indefinite h is shifted until it is not. Also the shift."""
    shift, base = 0.0, max(1e-12, float(np.abs(np.diag(h)).mean()))
    while True:
        try:
            low = np.linalg.cholesky(h + shift * np.eye(len(h)))
            return np.linalg.solve(low.T, np.linalg.solve(low, g)), shift
        except np.linalg.LinAlgError:
            shift = max(2 * shift, 1e-8 * base, -1.01 * float(np.linalg.eigvalsh(h)[0]))


def moment(x: CoordMatrix, y: DataFrame) -> np.ndarray:
    """X^T y, y(i, y)."""
    got = x.df.join(y, "i").groupBy("c").agg(F.sum(F.col("v") * F.col("y")).alias("g")).collect()
    out = np.zeros(x.cols)
    for c, g in got:
        out[c] = g
    return out


def least_squares(x: CoordMatrix, y: DataFrame, ridge: float = 0.0, family: HashFamily | None = None, width: int = 64) -> np.ndarray:
    """Normal equations; with a family the Gram matrix is sketched, the right side exact."""
    return solve(gram(x, family, width) + ridge * np.eye(x.cols), moment(x, y))[0]


def kernel_ridge(x: CoordMatrix, y: DataFrame, ridge: float, family: HashFamily | None = None, width: int = 64) -> np.ndarray:
    """The dual weights as an array on the driver."""
    out = np.zeros(x.rows)
    got = kernel_weights(x, y, ridge, family, width).toPandas()
    out[got["i"]] = got["weight"]
    return out


def kernel_weights(x: CoordMatrix, y: DataFrame, ridge: float, family: HashFamily | None = None, width: int = 64) -> DataFrame:
    """(i, weight): dual weights (K + ridge I)^-1 y of all rows with the linear kernel K = Z Z^T, where Z is X or its sketch on the feature side (then K is
    the mean over slices). K is never built: the inverse of I + Z^T Z / ridge, features by features on the driver, gives (y - Z (Z^T Z + ridge I)^-1 Z^T y) / ridge,
    and rows stay in the tasks."""
    if family is None:
        z = x
    else:
        at = (F.col("k") * width + F.col("h")).cast("long")
        z = CoordMatrix(stacked_sketch(x, width, family).select("i", at.alias("c"), (F.col("v") / float(np.sqrt(family.slices))).alias("v")), x.rows, family.slices * width)
    w, _ = solve(gram(z) + ridge * np.eye(z.cols), moment(z, y))
    inner = z.matvec(F.broadcast(x.df.sparkSession.createDataFrame([(c, float(v)) for c, v in enumerate(w)], "c long, x double"))).withColumnRenamed("y", "z")
    targets = x.df.sparkSession.range(x.rows).withColumnRenamed("id", "i").join(y, "i", "left")
    return targets.join(inner, "i", "left").select("i", ((F.coalesce("y", F.lit(0.0)) - F.coalesce("z", F.lit(0.0))) / ridge).alias("weight"))


def glm_newton(x: CoordMatrix, y: DataFrame, link: Callable, rounds: int = 8, ridge: float = 1e-3, family_at: Callable[[int], HashFamily] | None = None, width: int = 64) -> tuple[np.ndarray, list[float]]:
    """Newton's method: link(margin, y) gives columns (loss, slope, curvature). The Hessian is the Gram of rows scaled by sqrt(curvature), sketched
    anew in each round if family_at gives families. Also the loss before each round; steps are halved until the loss falls."""
    spark = x.df.sparkSession
    w, losses = np.zeros(x.cols), []
    data = x.df.withColumn("v", F.col("v").cast("double")).persist()
    rows = y.persist()
    mat = CoordMatrix(data, x.rows, x.cols)

    def margins(at: np.ndarray) -> DataFrame:
        wt = spark.createDataFrame([(c, float(v)) for c, v in enumerate(at)], "c long, x double")
        m = mat.matvec(F.broadcast(wt)).select("i", F.col("y").alias("m"))
        return rows.join(m, "i", "left").select("i", "y", F.coalesce("m", F.lit(0.0)).alias("m"))

    def loss(at: np.ndarray) -> float:
        return float(margins(at).agg(F.sum(link(F.col("m"), F.col("y"))[0])).first()[0]) + ridge / 2 * float(at @ at)

    now = loss(w)
    for r in range(rounds):
        losses.append(now)
        _, slope, curve = link(F.col("m"), F.col("y"))
        per = margins(w).select("i", slope.alias("s"), F.sqrt(curve).alias("q")).persist()
        g = moment(mat, per.select("i", F.col("s").alias("y"))) + ridge * w
        scaled = mat.with_(mat.df.join(per.select("i", "q"), "i").select("i", "c", (F.col("v") * F.col("q")).alias("v")))
        h = gram(scaled, family_at(r) if family_at else None, width) + ridge * np.eye(x.cols)
        step, _ = solve(h, g)
        per.unpersist()
        size = 1.0
        while size > 1e-4:
            new = loss(w - size * step)
            if new <= now:
                break
            size /= 2
        else:
            break
        if now - new < 1e-10 * max(1.0, abs(now)):
            w, now = w - size * step, new
            break
        w, now = w - size * step, new
    losses.append(now)
    data.unpersist()
    rows.unpersist()
    return w, losses


def logistic(m, y):
    p = 1 / (1 + F.exp(-m))
    return F.log1p(F.exp(-F.abs(m))) + F.greatest(m, F.lit(0.0)) - y * m, p - y, F.greatest(p * (1 - p), F.lit(1e-6))


def squared_hinge(m, y):
    """Smooth support vector loss; y in {0, 1}."""
    s = 2 * y - 1
    gap = F.greatest(1 - s * m, F.lit(0.0))
    return gap * gap, -2 * s * gap, F.when(gap > 0, F.lit(2.0)).otherwise(F.lit(1e-6))


__all__ = ["dense", "gram", "glm_newton", "kernel_ridge", "kernel_weights", "least_squares", "logistic", "moment", "solve", "squared_hinge", "stacked_sketch"]
