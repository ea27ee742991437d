import itertools

import numpy as np
import pytest
from helpers import DATA, coords
from pyspark.sql import functions as F

from blocksketch.functions.hashing import HashFamily
from blocksketch import sources
from blocksketch.operators import straggler
from blocksketch.operators.matrix import CoordMatrix
from blocksketch.optim import barrier, linear
from blocksketch.workloads import optimisation


def _frame(spark, a, b):
    return spark.createDataFrame([(i, [float(x) for x in r], float(y)) for i, (r, y) in enumerate(zip(a, b, strict=True))], "i long, row array<double>, b double")


A = np.array([[1, 2], [3, 1], [-1, 0], [0, -1], [1, 1]], float)
RIGHT = np.array([4, 6, 1, 1, 2.8])
COST = np.array([-1.0, -1.2])


def vertices():
    for i, j in itertools.combinations(range(5), 2):
        m = A[[i, j]]
        if abs(np.linalg.det(m)) > 1e-9:
            x = np.linalg.solve(m, RIGHT[[i, j]])
            if (A @ x <= RIGHT + 1e-9).all():
                yield COST @ x


@pytest.mark.parametrize("how", [{}, {"hessian": "rbs", "slices": 8, "width": 4}, {"hessian": "rbs", "slices": 8, "width": 4, "spare": 1}, {"hessian": "rbs", "slices": 8, "width": 1, "spare": 1, "shared": False}])
def test_lp_reaches_the_best_vertex(spark, how):
    x, trace = barrier.barrier_lp(_frame(spark, A, RIGHT), COST, np.zeros(2), iters=40, every=3, **how)
    best = min(vertices())
    assert (A @ x < RIGHT).all()
    assert abs(COST @ x - best) < 0.05 * abs(best)
    assert len(trace.rows) == 40


def test_barrier_value(spark):
    f = _frame(spark, A, RIGHT)
    assert np.isclose(barrier.barrier_value(f, np.zeros(2)).first()[0], -np.log(RIGHT).sum())
    assert barrier.barrier_value(f, np.array([9.0, 9.0])).first()[0] == float("inf")


def test_solve_shifts_indefinite():
    h = np.array([[1.0, 0], [0, -2.0]])
    x, shift = linear.solve(h, np.ones(2))
    assert shift > 2 and np.allclose((h + shift * np.eye(2)) @ x, 1)


def test_least_squares_and_kernel(spark):
    rng = np.random.default_rng(0)
    x = rng.integers(-5, 6, (40, 3))
    y = x @ np.array([2.0, -1, 0.5]) + 0.01 * rng.normal(size=40)
    m, t = coords(spark, x), spark.createDataFrame([(i, float(v)) for i, v in enumerate(y)], "i long, y double")
    assert np.allclose(linear.least_squares(m, t), np.linalg.lstsq(x, y, rcond=None)[0])
    w = linear.least_squares(m, t, 1e-6, HashFamily(12), 256)
    assert np.abs(w - [2, -1, 0.5]).max() < 0.3
    k = linear.kernel_ridge(m, t, 1.0)
    assert np.allclose(k, np.linalg.solve(x @ x.T + np.eye(40), y))


@pytest.mark.parametrize("link", [linear.logistic, linear.squared_hinge])
def test_newton_lowers_the_loss(spark, link):
    rng = np.random.default_rng(1)
    x = rng.integers(-3, 4, (60, 2))
    y = (x @ [1, -1] + rng.normal(size=60) > 0).astype(float)
    m, t = coords(spark, x), spark.createDataFrame([(i, float(v)) for i, v in enumerate(y)], "i long, y double")
    w, losses = linear.glm_newton(m, t, link, 4, 1e-2)
    assert losses[-1] < losses[0] and all(b <= a + 1e-9 for a, b in zip(losses, losses[1:], strict=False))
    assert w[0] > 0 > w[1]


def test_gram_sketched_on_constraints(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(200, 3))
    df = spark.createDataFrame([(i, c, float(x[i, c])) for i in range(200) for c in range(3)], "i long, c long, v double")
    g = linear.gram(CoordMatrix(df, 200, 3), HashFamily(20, 3), 64)
    assert np.linalg.norm(g - x.T @ x) / np.linalg.norm(x.T @ x) < 0.2
    assert df.agg(F.count("*")).first()[0] == 600


DATA = "/root/testdata/sf0.001"
LP_TRACES = {"lp_trace_exact": {}, "lp_trace_rbs_e0": {"hessian": "rbs", "slices": 20}, "lp_trace_rbs_e1": {"hessian": "rbs", "slices": 20, "spare": 1}, "lp_trace_rbs_e1_per_cell": {"hessian": "rbs", "slices": 20, "spare": 1, "shared": False}}


def test_registered_programs_run_whole(spark, monkeypatch):
    asked = []

    def record(problem, c, x0, **how):
        asked.append(how)
        return x0, barrier.Trace([(0, 32.0, -1.0, 1.0, False)])

    monkeypatch.setattr(barrier, "barrier_lp", record)
    monkeypatch.setattr(barrier, "optimum", lambda problem, c: -2.0, raising=False)
    for name in (*LP_TRACES, "lp_lineitem"):
        optimisation.QUERIES[name](spark, DATA)
    assert asked == [{"iters": 100, "every": 10, **how} for how in (*LP_TRACES.values(), {})]


def test_optimum_is_the_best_vertex(spark):
    assert barrier.optimum(_frame(spark, A, RIGHT), COST, batch=1) == pytest.approx(min(vertices()), abs=1e-7)
    with pytest.raises(ValueError):
        barrier.optimum(_frame(spark, A[2:4], RIGHT[2:4]), COST)


def test_traces_have_a_falling_gap(spark, monkeypatch):
    monkeypatch.setattr(optimisation, "ITERATIONS", 12)
    monkeypatch.setattr(optimisation, "EVERY", 2)
    for name in ("lp_trace_exact", "lp_trace_rbs_e1"):
        gap = [r.gap_pct for r in optimisation.QUERIES[name](spark, DATA).orderBy("iteration").collect()]
        assert None not in gap and gap[0] > gap[5] > gap[-1] > 0


def test_iteration_time_has_a_log_for_each_iteration(spark):
    runs = straggler.task_logs(spark, 2, 2, 20, [50, 51])
    for seed in (50, 51):
        one = straggler.task_log(spark, 2, 2, 20, seed)
        assert sorted(runs.filter(f"run = {seed}").drop("run").collect()) == sorted(one.collect())
    got = {r.e: r for r in optimisation.QUERIES["lp_iteration_time"](spark, DATA).collect()}
    assert set(got) == {0, 1, 2, 4}
    days = sources.event_log(spark, DATA).groupBy("bj").agg(F.max("t_ms").alias("t")).agg(F.sum("t").alias("t"), F.count("*").alias("n")).first()
    assert got[0].compute_s == pytest.approx(days.t / 1000) and got[0].total_s == pytest.approx(days.t / 1000 + 9 * days.n)
    assert got[0].compute_s > got[1].compute_s > got[2].compute_s > got[4].compute_s


def test_distributed_hessian_equals_the_drivers(spark):
    rng = np.random.default_rng(4)
    a = rng.normal(size=(60, 7))
    problem = barrier.rows_frame(spark.createDataFrame([(i, r.tolist(), 5.0 + i / 10) for i, r in enumerate(a)], "i long, row array<double>, b double")).repartition(3)
    x, family, width = rng.normal(size=7) / 20, HashFamily(5, 9), 3
    keep = barrier.survivor_sets(5, 3, 1, False, 2)
    g, h = barrier._pass(problem, x, family, width)
    assert np.allclose(barrier.distributed_hessian(problem, x, family, width, keep), barrier.sketched_hessian(h, 5, width, keep))
    assert np.allclose(barrier.gradient(problem, x), g)
    how = {"iters": 3, "hessian": "rbs", "slices": 4, "width": 3, "spare": 1}
    one, two = (barrier.barrier_lp(problem, np.ones(7) / 7, np.zeros(7), most=m, **how)[0] for m in (10**6, 0))
    assert np.allclose(one, two)


def test_lines_are_numbered_once(spark):
    x, _, held = optimisation._lines(spark, DATA)
    assert held.select("i").distinct().count() == held.count() == x.rows
    f, y = np.array([r.f for r in held.orderBy("i").collect()]), np.array([r.y for r in held.orderBy("i").collect()])
    got = [r.weight for r in optimisation.ls_exact(spark, DATA).collect()]
    assert np.allclose(got, np.linalg.lstsq(f, y, rcond=None)[0], atol=1e-4)
