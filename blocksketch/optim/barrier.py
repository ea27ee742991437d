"""Linear programs min c.x, Ax <= b by a log barrier and Newton steps whose Hessian A^T D^2 A is exact or sketched on the constraint side."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily, P
from ..operators.multiply import gram_of_sketch
from .linear import dense, solve


@dataclass
class Trace:
    """Per iteration: tau, objective, step size, and whether the Hessian was indefinite."""

    rows: list[tuple] = field(default_factory=list)

    def frame(self, spark: SparkSession, best: float | None = None) -> DataFrame:
        got = [(k, t, o, s, d, None if best is None else abs(100 * (o - best) / best)) for k, t, o, s, d in self.rows]
        return spark.createDataFrame(got, "iteration int, tau double, objective double, step double, indefinite boolean, gap_pct double")


def rows_frame(problem: DataFrame) -> DataFrame:
    """problem: (i, row ARRAY<DOUBLE>, b)."""
    return problem.select(F.col("i").cast("long").alias("i"), F.col("row").cast("array<double>").alias("row"), F.col("b").cast("double").alias("b"))


#: Values of a program that a task goes through in a pass.
PER_TASK = 500_000


def held(problem: DataFrame, m: int) -> DataFrame:
    """The rows in memory, in no more tasks than their number asks for: an iteration goes through them twice, and many tasks of few rows cost more than the rows."""
    n = problem.persist().count()
    tasks = max(1, -(-n * m // PER_TASK))
    if tasks >= problem.rdd.getNumPartitions():
        return problem
    few = problem.coalesce(tasks).persist()
    few.count()
    problem.unpersist()
    return few


def _summed(sums: DataFrame, by: str, values: int, tasks: int, most: int = 4_000_000) -> dict[int, np.ndarray]:
    """sums(by, v ARRAY<DOUBLE>), `values` from each task, added up by key: by the driver while it gets at most `most` values so, else in tasks."""
    if values * tasks > most:
        each = sums.select(by, F.posexplode("v").alias("c", "x")).groupBy(by, "c").agg(F.sum("x").alias("x"))
        sums = each.groupBy(by).agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "x"))), lambda e: e["x"]).alias("v"))
    out: dict[int, np.ndarray] = {}
    for key, v in sums.select(by, "v").collect():
        out[key] = out[key] + v if key in out else np.array(v, float)
    return out


def barrier_value(problem: DataFrame, x: np.ndarray) -> DataFrame:
    """One row: -sum ln(slack), infinite where a slack is not positive."""
    dot = F.aggregate(F.zip_with("row", F.array(*[F.lit(float(v)) for v in x]), lambda a, b: a * b), F.lit(0.0), lambda s, y: s + y)
    slack = F.col("b") - dot
    return problem.agg((-F.sum(F.when(slack > 0, F.log(slack)).otherwise(F.lit(float("-inf"))))).alias("barrier"))


def _signs(index: np.ndarray, family: HashFamily, width: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    for _, u1, u0, w3, w2, w1, w0 in family.rows:
        q = w3 * index % P
        q = ((q + w2) % P) * index % P
        q = ((q + w1) % P) * index % P
        yield ((u1 * index + u0) % P) % width, 1 - 2 * (((q + w0) % P) % 2)


def gradient(problem: DataFrame, x: np.ndarray) -> np.ndarray:
    """A^T (1/slack)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = np.zeros(len(x))
        for pdf in batches:
            if not pdf.empty:
                a = np.stack(pdf["row"].to_numpy())
                g += a.T @ (1 / (pdf["b"].to_numpy() - a @ x))
        yield pd.DataFrame({"c": np.arange(len(x)), "x": g})

    got = problem.select("row", "b").mapInPandas(run, "c int, x double").groupBy("c").agg(F.sum("x").alias("x")).toPandas()
    out = np.zeros(len(x))
    out[got["c"]] = got["x"]
    return out


def _pass(problem: DataFrame, x: np.ndarray, family: HashFamily | None, width: int, tasks: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Gradient part A^T (1/slack), and A^T D^2 A or the sketches of D A (slices x width x m), in one pass: each task adds up its rows, tasks' sums are added by key."""
    m = len(x)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g = np.zeros(m)
        h = np.zeros((m, m)) if family is None else np.zeros((family.slices * width, m))
        for pdf in batches:
            if pdf.empty:
                continue
            a = np.stack(pdf["row"].to_numpy())
            inv = 1 / (pdf["b"].to_numpy() - a @ x)
            g += a.T @ inv
            da = a * inv[:, None]
            if family is None:
                h += da.T @ da
            else:
                for k, (bucket, sign) in enumerate(_signs(pdf["i"].to_numpy(np.int64), family, width)):
                    np.add.at(h, k * width + bucket, sign[:, None] * da)
        yield pd.DataFrame({"key": np.arange(len(h) + 1), "v": [g, *h]})

    rows = m if family is None else family.slices * width
    got = _summed(problem.mapInPandas(run, "key int, v array<double>"), "key", (rows + 1) * m, tasks or problem.rdd.getNumPartitions())
    out = np.zeros((rows + 1, m))
    for key, v in got.items():
        out[key] = v
    return out[0], out[1:]


def distributed_sketch(problem: DataFrame, x: np.ndarray, family: HashFamily, width: int) -> DataFrame:
    """(i, k, h, v): the stacked sketch of (D A)^T. A task adds up one slice of one batch of rows at a time, width x m values, and sends the rows that it touched."""
    m, slices, seed = len(x), family.slices, family.seed

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        drawn = HashFamily(slices, seed)
        for pdf in batches:
            if pdf.empty:
                continue
            a = np.stack(pdf["row"].to_numpy())
            da = a / (pdf["b"].to_numpy() - a @ x)[:, None]
            for k, (bucket, sign) in enumerate(_signs(pdf["i"].to_numpy(np.int64), drawn, width)):
                touched, place = np.unique(bucket, return_inverse=True)
                y = np.zeros((len(touched), m))
                np.add.at(y, place, sign[:, None] * da)
                yield pd.DataFrame({"k": np.int32(k), "h": touched.astype(np.int32), "row": list(y)})

    rows = problem.select("i", "row", "b").mapInPandas(run, "k int, h int, row array<double>")
    return rows.select("k", "h", F.posexplode("row").alias("i", "v")).groupBy(F.col("i").cast("long").alias("i"), "k", "h").agg(F.sum("v").alias("v"))


def distributed_hessian(problem: DataFrame, x: np.ndarray, family: HashFamily, width: int, keep: np.ndarray) -> np.ndarray:
    """The sketched Hessian by the block products of the sketched Gram, with a task per cell and slice; only its m x m entries reach the driver."""
    m, cells = len(x), len(keep)
    alive = [(i, j, int(k)) for i in range(cells) for j in range(i, cells) for k in np.flatnonzero(keep[i, j])]
    chosen = problem.sparkSession.createDataFrame(alive, "bi int, bj int, k int")
    return dense(gram_of_sketch(distributed_sketch(problem, x, family, width), m, width, family.slices, chosen, ahead=True), m, m)


def survivor_sets(slices: int, cells: int, spare: int, shared: bool, seed: int) -> np.ndarray:
    """cells x cells x slices booleans, symmetric: the slices that count, after `spare` random losses per cell or for all alike."""
    rng = np.random.default_rng(seed)
    keep = np.ones((cells, cells, slices), bool)
    for i in range(cells):
        for j in range(i, cells):
            lost = rng.choice(slices, spare, replace=False) if not shared or (i, j) == (0, 0) else np.flatnonzero(~keep[0, 0])
            keep[i, j, lost] = keep[j, i, lost] = False
    return keep


def sketched_hessian(s: np.ndarray, slices: int, width: int, keep: np.ndarray) -> np.ndarray:
    """The mean over each cell's surviving slices of Y^T Y; s holds the slices' Y below each other."""
    m = s.shape[1]
    y = s.reshape(slices, width, m)
    cell = np.minimum(np.arange(m) // width, len(keep) - 1)
    h = np.zeros((m, m))
    for k in range(slices):
        h += (y[k].T @ y[k]) * keep[:, :, k][np.ix_(cell, cell)]
    return h / keep.sum(2)[np.ix_(cell, cell)]


def barrier_lp(problem: DataFrame, c: np.ndarray, x0: np.ndarray, tau0: float = 32.0, growth: float = 2.0, every: int = 10, iters: int = 100, hessian: str = "exact", slices: int = 16, width: int = 16, spare: int = 0, shared: bool = True, seed: int = 42, most: int = 4_000_000) -> tuple[np.ndarray, Trace]:
    """tau is multiplied by growth after every `every` iterations. A step is halved until it is feasible and lowers the barrier objective
    (a batch of sizes is tried in one pass); each iteration draws a new slice family. A sketch of up to `most` values (32 MB) is multiplied on the driver, which spares a small program
    the shuffles; a larger one never leaves the tasks. Beside it the driver holds m values and an m x m matrix."""
    problem = held(rows_frame(problem), len(x0))
    tasks = problem.rdd.getNumPartitions()
    x, tau, trace = np.array(x0, float), tau0, Trace()
    cells = -(-len(x) // width)
    for k in range(iters):
        family = HashFamily(slices + spare, seed + 1 + k) if hessian == "rbs" else None
        if family is None or family.slices * width * len(x) <= most:
            g, h = _pass(problem, x, family, width, tasks)
        else:
            g, h = gradient(problem, x), None
        if family is not None:
            keep = survivor_sets(family.slices, cells, spare, shared, 1000 * seed + k)
            h = distributed_hessian(problem, x, family, width, keep) if h is None else sketched_hessian(h, family.slices, width, keep)
        grad = tau * c + g
        step, shift = solve(h, grad)
        sizes = 0.5 ** np.arange(24)
        found = _objectives(problem, tau, c, x, step, sizes, tasks)
        now = found[0]
        ok = [i for i in range(len(sizes)) if np.isfinite(found[i + 1]) and found[i + 1] < now]
        size = float(sizes[ok[0]]) if ok else 0.0
        x = x - size * step
        trace.rows.append((k, float(tau), float(c @ x), size, bool(shift > 0)))
        if (k + 1) % every == 0:
            tau *= growth
    problem.unpersist()
    return x, trace


def _small_lp(a: np.ndarray, b: np.ndarray, c: np.ndarray, rounds: int = 200) -> np.ndarray:
    """min c.x, Ax <= b on the driver, by a primal-dual interior point method with a predictor and a corrector step."""
    x, s, y = np.zeros(len(c)), np.maximum(np.abs(b), 1.0), np.ones(len(b))
    scale = 1 + max(np.abs(b).max(), np.abs(c).max())
    reach = lambda v, dv: min(1.0, 0.995 * float(np.min(-v[dv < 0] / dv[dv < 0], initial=np.inf)))
    for _ in range(rounds):
        primal, dual, mu = b - a @ x - s, -c - a.T @ y, s @ y / len(b)
        if max(np.abs(primal).max(), np.abs(dual).max()) < 1e-10 * scale and len(b) * mu < 1e-11 * (1 + abs(c @ x)):
            break
        h = (a * (y / s)[:, None]).T @ a

        def direction(r: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            """Newton step for the complementarity residual r."""
            dx = np.linalg.lstsq(h, dual - a.T @ ((r - y * primal) / s), rcond=None)[0]
            ds = primal - a @ dx
            return dx, ds, (r - y * ds) / s

        _, ds, dy = direction(-s * y)
        ahead = (s + reach(s, ds) * ds) @ (y + reach(y, dy) * dy) / len(b)
        dx, ds, dy = direction((ahead / mu) ** 3 * mu - s * y - ds * dy)
        p, q = reach(s, ds), reach(y, dy)
        x, s, y = x + p * dx, s + p * ds, y + q * dy
    return x


def optimum(problem: DataFrame, c: np.ndarray, radius: float = 1e3, batch: int = 64, tol: float = 1e-8, rounds: int = 200) -> float:
    """The least c.x of a bounded program. The driver solves the rows found so far; each round, one pass finds the rows that its solution breaks most,
    until no row is broken by more than tol. The value of fewer rows is a lower bound, so the last one is the optimum. A box of `radius` starts it."""
    problem, m = rows_frame(problem).persist(), len(c)
    a, b = np.vstack([np.eye(m), -np.eye(m)]), np.full(2 * m, radius)
    try:
        for _ in range(rounds):
            x = _small_lp(a, b, c)
            dot = F.aggregate(F.zip_with("row", F.array(*[F.lit(float(v)) for v in x]), lambda p, q: p * q), F.lit(0.0), lambda p, q: p + q)
            worst = problem.withColumn("over", dot - F.col("b")).filter(F.col("over") > tol).orderBy(F.desc("over"), "i").limit(batch).collect()
            if not worst:
                if np.abs(x).max() > 0.99 * radius:
                    raise ValueError("the program is unbounded, or its solution lies outside the radius")
                return float(c @ x)
            a, b = np.vstack([a, [r.row for r in worst]]), np.append(b, [r.b for r in worst])
        raise ValueError("no optimum within the rounds")
    finally:
        problem.unpersist()


def _objectives(problem: DataFrame, tau: float, c: np.ndarray, x: np.ndarray, step: np.ndarray, sizes: np.ndarray, tasks: int) -> np.ndarray:
    """tau c.x - sum ln(slack) at x and at each step size; infinite outside."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(len(sizes) + 1)
        for pdf in batches:
            if pdf.empty:
                continue
            a = np.stack(pdf["row"].to_numpy())
            slack = (pdf["b"].to_numpy() - a @ x)[:, None] + (a @ step)[:, None] * np.concatenate([[0.0], sizes])
            with np.errstate(invalid="ignore", divide="ignore"):
                total += np.where((slack > 0).all(0), -np.log(slack).sum(0), np.inf)
        yield pd.DataFrame({"s": [0], "v": [total]})

    at = np.concatenate([[0.0], sizes])
    total = _summed(problem.mapInPandas(run, "s int, v array<double>"), "s", len(at), tasks).get(0, np.zeros(len(at)))
    return tau * (c @ x - at * (c @ step)) + total


def embedding_problem(embeddings: DataFrame, dims: int = 64) -> DataFrame:
    """Rows of unit vectors with right side 1, and the box -1 <= x <= 1."""
    n = embeddings.count()
    a = embeddings.select(F.col("vec_id").cast("long").alias("i"), F.col("embedding").cast("array<double>").alias("row"))
    spark = embeddings.sparkSession
    box = spark.createDataFrame([(n + s * dims + d, [float((1 - 2 * s) * (d == e)) for e in range(dims)]) for s in (0, 1) for d in range(dims)], "i long, row array<double>")
    return a.unionByName(box).withColumn("b", F.lit(1.0))


def embedding_cost(embeddings: DataFrame) -> np.ndarray:
    """-sum of the rows weighed evenly from 0.5 to 1, normalised."""
    n = embeddings.count()
    w = F.lit(0.5) + F.lit(0.5) * F.col("vec_id") / max(n - 1, 1)
    got = embeddings.select(w.alias("w"), F.posexplode("embedding").alias("d", "x")).groupBy("d").agg(F.sum(F.col("w") * F.col("x").cast("double")).alias("s")).orderBy("d").collect()
    c = -np.array([r.s for r in got])
    return c / np.linalg.norm(c)
