"""Workloads of sketched optimisation: a linear program on the embeddings, one on suppliers and brands, regressions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from .. import sources
from ..functions.hashing import HashFamily
from ..operators import multiply, straggler
from ..operators.matrix import CoordMatrix, indexed
from ..optim import barrier, linear
from . import sql
from .algebra import doc_term

QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if oracle:
            ORACLES[key] = oracle
        return f

    return add


_LP = "n AS (SELECT count(*) AS n FROM embeddings), lp AS (SELECT vec_id AS i, CAST(embedding AS DOUBLE[]) AS row, CAST(1 AS DOUBLE) AS b FROM embeddings UNION ALL SELECT n + s * 64 + d, list_transform(range(0, 64), lambda e: CASE WHEN e = d THEN CAST(1 - 2 * s AS DOUBLE) ELSE CAST(0 AS DOUBLE) END), CAST(1 AS DOUBLE) FROM n, range(0, 64) AS a(d), range(0, 2) AS b(s))"
POINT = [0.1] * 8 + [0.0] * 56
_POINT = "[" + ", ".join(map(str, POINT)) + "]"
_SLACK = f"{_LP}, s AS (SELECT i, row, b - list_dot_product(row, CAST({_POINT} AS DOUBLE[])) AS slack FROM lp)"


def _problem(spark, d):
    return barrier.embedding_problem(sources.load(spark, d, "embeddings"))


@query(f"WITH {_SLACK} SELECT round(-sum(ln(slack)), 6) AS barrier FROM s")
def lp_barrier_value(spark, d):
    return barrier.barrier_value(_problem(spark, d), np.array(POINT)).select(F.round("barrier", 6).alias("barrier"))


def _scaled(spark, d):
    """(i, c, q, slack): rows with their slack at the interior point."""
    x = F.array(*[F.lit(v) for v in POINT])
    dot = F.aggregate(F.zip_with("row", x, lambda a, b: a * b), F.lit(0.0), lambda s, y: s + y)
    p = _problem(spark, d).withColumn("slack", F.col("b") - dot)
    return p.select("i", "slack", F.posexplode("row").alias("c", "a")).withColumn("c", F.col("c").cast("long"))


_ENTRIES = f"{_SLACK}, e AS (SELECT i, CAST(d - 1 AS BIGINT) AS c, row[d] AS a, slack FROM s, range(1, 65) AS r(d))"


@query(f"WITH {_ENTRIES} SELECT c, round(sum(a / slack), 6) AS g FROM e GROUP BY c")
def lp_step_gradient(spark, d):
    return _scaled(spark, d).groupBy("c").agg(F.round(F.sum(F.col("a") / F.col("slack")), 6).alias("g"))


@query(f"WITH {_ENTRIES} SELECT x.c AS c1, y.c AS c2, round(sum(x.a * y.a / (x.slack * x.slack)), 5) AS h FROM e x JOIN e y USING (i) GROUP BY 1, 2")
def lp_step_hessian(spark, d):
    s = _scaled(spark, d).select("i", "c", (F.col("a") / F.col("slack")).alias("v")).filter("v <> 0")
    n = s.agg(F.max("i")).first()[0] + 1
    a = CoordMatrix(s, n, 64)
    h = multiply.multiply(a.t, a).df.select(F.col("i").alias("c1"), F.col("c").alias("c2"), F.round("v", 5).alias("h"))
    full = spark.range(64).select(F.col("id").alias("c1")).crossJoin(spark.range(64).select(F.col("id").alias("c2")))
    return full.join(h, ["c1", "c2"], "left").na.fill(0.0, ["h"])


@query(f"WITH {sql.family(5)}, {_ENTRIES}, f AS (SELECT c AS i, i AS c, CAST(floor(1000 * a / slack + 0.5) AS BIGINT) AS v FROM e WHERE a <> 0), sa AS ({sql.sketch('f', 16)}) SELECT a.i AS c1, b.i AS c2, CAST(sum(a.v * b.v) AS DOUBLE) / 5 AS h_hat FROM sa a JOIN sa b USING (k, h) GROUP BY 1, 2")
def lp_step_hessian_rbs(spark, d):
    s = _scaled(spark, d).filter("a <> 0").select(F.col("c").alias("i"), F.col("i").alias("c"), F.floor(1000 * F.col("a") / F.col("slack") + 0.5).cast("long").alias("v"))
    a = CoordMatrix(s, 64, s.agg(F.max("c")).first()[0] + 1)
    return multiply.rbs_gram(a, 16, HashFamily(5)).select(F.col("i").alias("c1"), F.col("j").alias("c2"), F.col("v_hat").alias("h_hat"))


_STEP_LOG = sql.log(4, 4, 6)


@query(f"WITH {sql.family(6)}, {_ENTRIES}, f AS (SELECT c AS i, i AS c, CAST(floor(1000 * a / slack + 0.5) AS BIGINT) AS v FROM e WHERE a <> 0), {_STEP_LOG}, {sql.survivors('r <= n - 1')}, sa AS ({sql.sketch('f', 16)}), sb AS (SELECT i AS j, k, h, v FROM sa), {sql.estimate('sa', 'sb', 16)}, upper AS (SELECT * FROM guessed WHERE i // 16 <= j // 16) SELECT i AS c1, j AS c2, v_hat AS h_hat, n_survivors FROM upper UNION ALL SELECT j, i, v_hat, n_survivors FROM upper WHERE i // 16 < j // 16")
def lp_step_hessian_rbs_e1(spark, d):
    """The sketched Hessian of one step with the slowest of six slices ignored in each cell."""
    s = _scaled(spark, d).filter("a <> 0").select(F.col("c").alias("i"), F.col("i").alias("c"), F.floor(1000 * F.col("a") / F.col("slack") + 0.5).cast("long").alias("v"))
    a = CoordMatrix(s, 64, s.agg(F.max("c")).first()[0] + 1)
    got = multiply.rbs_gram(a, 16, HashFamily(6), straggler.task_log(spark, 4, 4, 6), straggler.Policy("drop", 1))
    return got.select(F.col("i").alias("c1"), F.col("j").alias("c2"), F.col("v_hat").alias("h_hat"), "n_survivors")


#: Iterations of the registered programs, slices that count in a sketched Hessian, and after how many iterations tau doubles.
ITERATIONS, SLICES, EVERY = 100, 20, 10


def _trace(spark, d, **how):
    e = sources.load(spark, d, "embeddings")
    c = barrier.embedding_cost(e)
    problem = barrier.embedding_problem(e)
    _, trace = barrier.barrier_lp(problem, c, np.zeros(64), iters=ITERATIONS, every=EVERY, **how)
    return trace.frame(spark, best=barrier.optimum(problem, c))


def _lp(name: str, **how):
    query(None, name)(lambda spark, d: _trace(spark, d, **how))


_lp("lp_trace_exact")
_lp("lp_trace_rbs_e0", hessian="rbs", slices=SLICES)
_lp("lp_trace_rbs_e1", hessian="rbs", slices=SLICES, spare=1)
_lp("lp_trace_rbs_e1_per_cell", hessian="rbs", slices=SLICES, spare=1, shared=False)


@query()
def lp_iteration_time(spark, d):
    """Modelled time of an iteration per day of events, by the number of tasks ignored per cell, with 9 s of invocation. The log of an iteration has the
    day's events as tasks, in 5 cells by their block of users."""
    from ..operators import costs

    tasks = sources.event_log(spark, d).select(F.col("bj").alias("run"), (F.col("bi") % 5).alias("bi"), F.lit(0).alias("bj"), "k", "t_ms", "status")
    logs = straggler.ranked(tasks, ("run", *straggler.CELL))
    left = logs.withColumn("e", F.explode(F.array(*map(F.lit, (0, 1, 2, 4))))).filter("rank <= tasks - e")
    phases = left.groupBy("e", "run").agg(F.max("t_ms").alias("phase_ms"))
    invoke = costs.iteration_time(0)
    return phases.groupBy("e").agg((F.sum("phase_ms") / 1000 + invoke * F.count("*")).alias("total_s"), (F.sum("phase_ms") / 1000).alias("compute_s"))


@query()
def lp_lineitem(spark, d):
    """Weights per brand, capacity per supplier, and a box: the business twin, solved exactly."""
    line = sources.load(spark, d, "lineitem").join(sources.load(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    brands = [r[0] for r in line.select("p_brand").distinct().orderBy("p_brand").collect()]
    wide = line.groupBy("l_suppkey").pivot("p_brand", brands).agg(F.sum("l_quantity"))
    row = F.array(*[F.coalesce(F.col(f"`{b}`"), F.lit(0.0)) for b in brands])
    a = wide.select(F.col("l_suppkey").alias("i"), F.transform(row, lambda x: x / F.aggregate(row, F.lit(0.0), lambda s, y: s + y)).alias("row")).withColumn("b", F.lit(0.5)).persist()
    n, m = a.count(), len(brands)
    box = spark.createDataFrame([(n + s * m + k, [float((1 - 2 * s) * (k == e)) for e in range(m)], 1.0) for s in (0, 1) for k in range(m)], "i long, row array<double>, b double")
    x, trace = barrier.barrier_lp(a.unionByName(box), -np.ones(m), np.zeros(m), iters=ITERATIONS, every=EVERY)
    a.unpersist()
    return spark.createDataFrame([(b, float(v)) for b, v in zip(brands, x, strict=True)], "brand string, weight double")


FEATURES = ("l_quantity", "l_discount", "l_tax", "p_size", "p_retailprice")


def _lines(spark, d):
    """Features by line, numbered by place in the order of the lines' keys, and the target in thousands."""
    line = sources.load(spark, d, "lineitem").join(sources.load(spark, d, "part").select("p_partkey", "p_size", "p_retailprice"), F.col("l_partkey") == F.col("p_partkey"))
    x = line.select("l_orderkey", "l_linenumber", F.array(F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("p_size") / 50.0, F.col("p_retailprice") / 2000).alias("f"), (F.col("l_extendedprice") / 1000).alias("y"))
    x = indexed(x, "i", "l_orderkey", "l_linenumber").persist()
    e = x.select("i", F.posexplode("f").alias("c", "v")).select("i", F.col("c").cast("long").alias("c"), "v")
    return CoordMatrix(e, x.count(), 6), x.select("i", "y"), x


def _named(spark, w, names):
    return spark.createDataFrame([(n, float(v)) for n, v in zip(names, w, strict=True)], "feature string, weight double")


_LINES = "x AS (SELECT [CAST(1 AS DOUBLE), l_quantity / 50, l_discount * 10, l_tax * 10, p_size / CAST(50 AS DOUBLE), p_retailprice / 2000] AS f, l_extendedprice / 1000 AS y FROM lineitem JOIN part ON l_partkey = p_partkey)"


@query(f"WITH {_LINES}, g AS (SELECT a, b, sum(f[a + 1] * CASE WHEN b = 6 THEN y ELSE f[b + 1] END) AS v FROM x, range(0, 6) AS r(a), range(0, 7) AS s(b) GROUP BY 1, 2) SELECT a AS c1, b AS c2, round(v / 1000, 5) AS v FROM g")
def ls_normal_equations(spark, d):
    """The Gram matrix of the features and, as column 6, their products with the target, in thousands."""
    x, y, _ = _lines(spark, d)
    g = multiply.multiply(x.t, x).df.select(F.col("i").alias("c1"), F.col("c").alias("c2"), "v")
    t = x.df.join(y, "i").groupBy(F.col("c").alias("c1")).agg(F.sum(F.col("v") * F.col("y")).alias("v")).select("c1", F.lit(6).cast("long").alias("c2"), "v")
    return g.union(t).select("c1", "c2", F.round(F.col("v") / 1000, 5).alias("v"))


@query()
def ls_exact(spark, d):
    x, y, held = _lines(spark, d)
    w = linear.least_squares(x, y, 1e-6)
    held.unpersist()
    return _named(spark, w, ("one", *FEATURES))


@query()
def ls_sketched(spark, d):
    x, y, held = _lines(spark, d)
    w = linear.least_squares(x, y, 1e-6, HashFamily(8), 256)
    held.unpersist()
    return _named(spark, w, ("one", *FEATURES))


def _indicator(spark, d):
    return sources.load(spark, d, "embeddings").select(F.col("vec_id").alias("i"), (F.col("label") == 0).cast("double").alias("y"))


@query()
def ridge_sketched(spark, d):
    x = sources.embedding_dim(spark, d, None)
    w = linear.least_squares(x, _indicator(spark, d), 1.0, HashFamily(20), 64)
    return _named(spark, w, map(str, range(x.cols)))


@query()
def kernel_ridge(spark, d):
    x = sources.embedding_dim(spark, d, None)
    return linear.kernel_weights(x, _indicator(spark, d), 1.0).select(F.col("i").cast("string").alias("feature"), "weight")


def _labelled(spark, d, top: int = 30):
    """Term counts (capped by a logarithm) and a constant, for labelled documents; the target is quality."""
    x = doc_term(spark, d, top)
    y = sources.load(spark, d, "labels").select(F.col("doc_id").alias("i"), F.col("quality").cast("double").alias("y"))
    e = x.df.select("i", "c", F.log1p(F.col("v").cast("double")).alias("v")).unionByName(y.select("i", F.lit(top).cast("long").alias("c"), F.lit(1.0).alias("v")))
    return CoordMatrix(e.join(y.select("i"), "i", "left_semi"), x.rows, top + 1), y


def _glm(spark, d, link, sketched: bool):
    x, y = _labelled(spark, d)
    w, losses = linear.glm_newton(x, y, link, 4, 1e-2, (lambda r: HashFamily(8, 300 + r)) if sketched else None, 64)
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate(losses)], "round int, loss double")


query(None, "logistic_newton")(lambda spark, d: _glm(spark, d, linear.logistic, False))
query(None, "logistic_newton_sketched")(lambda spark, d: _glm(spark, d, linear.logistic, True))
query(None, "svm_newton")(lambda spark, d: _glm(spark, d, linear.squared_hinge, False))
