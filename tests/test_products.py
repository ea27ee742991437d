import itertools

import numpy as np
import pytest
from helpers import array, coords, tiny

from blocksketch.functions.hashing import HashFamily
from blocksketch.operators import accuracy, baselines, coded, multiply, sketch, straggler
from blocksketch.operators.matrix import CoordMatrix, generated, numbered
from blocksketch.operators.straggler import Policy
from blocksketch.workloads import products
from blocksketch.workloads.products import WORKED_BUCKET, WORKED_SIGN


def dense_family(family, n, b):
    """n x K*b, from the same formulas in plain integers."""
    p, out = 2**31 - 1, np.zeros((n, family.slices * b))
    for k, u1, u0, w3, w2, w1, w0 in family.rows:
        for c in range(n):
            q = (((w3 * c + w2) % p * c + w1) % p * c + w0) % p
            out[c, k * b + (u1 * c + u0) % p % b] = 1 - 2 * (q % 2)
    return out


def test_exact_products_agree(spark):
    a, b = tiny()
    x, y = coords(spark, a), coords(spark, b)
    for m in (multiply.multiply(x, y), multiply.band_multiply(x, y, 3), multiply.block_multiply(x, y, 4), multiply.block_multiply(x, y, (2, 5, 1)), multiply.dense_block_multiply(x, y, 4)):
        assert np.array_equal(array(m), a @ b)


def test_block_partials_per_cell(spark):
    x = generated(spark, 4, 6, lambda i, c: i + c)
    parts = multiply.block_partials(x, x.t, 2)
    assert {tuple(r) for r in parts.select("bi", "bj", "k").distinct().collect()} == set(itertools.product(range(2), range(2), range(3)))


def test_sketch_is_the_dense_product(spark):
    a, b = tiny(1)
    family = HashFamily(3, 5)
    s = dense_family(family, 6, 2)
    x, y = coords(spark, a), coords(spark, b)
    for got in (sketch.stacked_sketch(x, 2, family), sketch.located_sketch(x, 2, family)):
        flat = got.selectExpr("i", "k * 2 + h as c", "v")
        assert np.array_equal(array(flat, shape=(4, 6)), a @ s)
    right = sketch.sketch_right(y, 2, family).selectExpr("k * 2 + h as i", "j as c", "v")
    assert np.array_equal(array(right, shape=(6, 3)), s.T @ b)
    one = sketch.count_sketch(x, 2, 5, 1).selectExpr("i", "h as c", "v")
    assert np.array_equal(array(one, shape=(4, 2)), (a @ s)[:, 2:4])


def test_worked_example(spark):
    x = coords(spark, np.arange(1, 10).reshape(1, 9))
    mapping = spark.createDataFrame([(c, h, s) for c, (h, s) in enumerate(zip(WORKED_BUCKET, WORKED_SIGN, strict=True))], "c long, h int, s long")
    got = {r.h: r.v for r in sketch.mapped_sketch(x, mapping).collect()}
    assert got == {1: -8, 2: 5, 3: -14}
    assert sum(v * v for v in got.values()) == 285


@pytest.mark.parametrize("policy,wanted", [(Policy("first", 2), 2), (Policy("drop", 1), 2), (Policy("all"), 3), (Policy("shared", 2), 2), (Policy("deadline", 1, 1), 1)])
def test_rbs_equals_numpy_under_losses(spark, policy, wanted):
    a, b = tiny(2)
    family, w = HashFamily(3, 8), 2
    s = dense_family(family, 6, w)
    log = straggler.task_log(spark, 2, 2, 3, seed=4)
    alive = {}
    for r in straggler.survivors(log, policy).collect():
        alive.setdefault((r.bi, r.bj), []).append(r.k)
    assert all(len(v) == wanted for v in alive.values()) and len(alive) == 4
    got = multiply.rbs_multiply(coords(spark, a), coords(spark, b), w, family, log, policy)
    want = np.zeros((4, 3))
    for i, j in itertools.product(range(4), range(3)):
        ks = alive[i // w, j // w]
        want[i, j] = sum((a[i] @ s[:, k * w : k * w + w]) @ (s[:, k * w : k * w + w].T @ b[:, j]) for k in ks) / len(ks)
    assert np.allclose(array(got, "i", "j", "v_hat", (4, 3)), want)


def test_gram_is_symmetric_and_equals_product(spark):
    a, _ = tiny(3)
    x, family = coords(spark, a), HashFamily(3, 1)
    log = straggler.task_log(spark, 2, 2, 3)
    g = array(multiply.rbs_gram(x, 2, family, log, Policy("drop", 1)), "i", "j", "v_hat", (4, 4))
    assert np.allclose(g, g.T)
    full = array(multiply.rbs_gram(x, 2, family), "i", "j", "v_hat", (4, 4))
    s = dense_family(family, 6, 2)
    assert np.allclose(full, a @ s @ s.T @ a.T / 3)


def test_lost_sketch_blocks_and_no_survivors(spark):
    log = straggler.task_log(spark, 2, 2, 2)
    left = straggler.sketch_losses(log, spark.createDataFrame([("a", 0, 1), ("b", 1, 0)], "side string, block int, k int"))
    assert {(r.bi, r.bj, r.k) for r in left.collect()} == {(0, 0, 0), (1, 0, 0), (1, 0, 1), (1, 1, 1)}


def test_mean_and_variance_over_seeds(spark):
    rng = np.random.default_rng(0)
    x, y, b = rng.integers(-3, 4, 12), rng.integers(-3, 4, 12), 3
    exact = accuracy.cell_variance(coords(spark, x[None, :]), coords(spark, y[:, None]), b).first()["var"]
    got = np.array([(x @ s) @ (s.T @ y) for s in (dense_family(HashFamily(1, seed), 12, b) for seed in range(4000))])
    assert abs(got.mean() - x @ y) < 4 * np.sqrt(exact / len(got))
    assert abs(got.var() / exact - 1) < 0.15
    assert exact <= 2 / b * (x @ x) * (y @ y)


def test_expected_error_matches_seeds_and_bound(spark):
    rng = np.random.default_rng(1)
    a, bm, b, n = rng.integers(-3, 4, (5, 20)), rng.integers(-3, 4, (20, 4)), 4, 3
    x, y = coords(spark, a), coords(spark, bm)
    e = accuracy.expected_error(x, y, multiply.multiply(x, y), b * n).first()
    errs = []
    for seed in range(1500):
        s = dense_family(HashFamily(n, seed), 20, b)
        errs.append(np.sum((a @ bm - a @ s @ s.T @ bm / n) ** 2))
    errs = np.array(errs)
    assert abs(errs.mean() - e.expected_sq) < 5 * errs.std() / np.sqrt(len(errs))
    assert e.expected_sq <= e.bound_sq
    eps, theta = 2 / (b * n) / 0.25, 0.25
    assert (errs > eps * np.sum(a**2) * np.sum(bm**2)).mean() <= theta


def test_straggler_quotas(spark):
    t = [r.t_ms for r in straggler.task_log(spark, 10, 10, 30).collect()]
    assert len(t) == 3000 and t.count(375000) == 2
    assert sum(x > 80000 for x in t) == 150
    assert 39000 < np.median(t) < 42000


def test_peeling_all_small_losses():
    cells = list(itertools.product(range(4), range(4)))
    for n in range(4):
        assert all(coded.decodes(x, 3, 3) for x in itertools.combinations(cells, n))
    assert not coded.decodes([(0, 0), (0, 1), (1, 0), (1, 1)], 3, 3)
    with pytest.raises(coded.Undecodable):
        coded.peel([(0, 0), (0, 2), (2, 0), (2, 2)], 3, 3)


def test_parity_product_is_exact(spark):
    a, b = tiny(4)
    for lost in ([(0, 0)], [(0, 0), (1, 1), (0, 1)], [(2, 0), (0, 2)]):
        assert np.array_equal(array(coded.parity_multiply(coords(spark, a), coords(spark, b), 2, lost)), a @ b)


def test_completion_time():
    times = {(r, c): 10 for r in range(3) for c in range(3)}
    times[1, 1] = 99
    assert coded.completion_time(times, 2, 2) == 10
    times.update({(0, 0): 50, (0, 1): 60, (1, 0): 70})
    assert coded.completion_time(times, 2, 2) == 50


def test_srht_and_sampling(spark):
    a, _ = tiny(5)
    x = coords(spark, a)
    got = array(baselines.srht_sketch(x, 3), "i", "r", "v", (4, 3))
    sign = [1 - 2 * (int(q) % 2) for q in range(0)]
    p, (_, _, _, w3, w2, w1, w0) = 2**31 - 1, HashFamily(1).rows[0]
    sign = [1 - 2 * ((((w3 * c + w2) % p * c + w1) % p * c + w0) % p % 2) for c in range(6)]
    h = np.array([[sign[c] * (-1) ** bin(c & r).count("1") for _, r in baselines.srht_rows(3, 6)] for c in range(6)])
    assert np.array_equal(got, a @ h)
    drawn = baselines.draws(baselines.norm_scores(x, x.t), 50).collect()
    assert len(drawn) == 50 and {r.d for r in drawn} == set(range(50))
    assert all(a[:, r.c].any() for r in drawn)


def test_leverage_scores(spark):
    rng = np.random.default_rng(3)
    a = rng.integers(-3, 4, (3, 7))
    got = {r.c: r.score for r in baselines.leverage_scores(coords(spark, a)).collect()}
    want = np.einsum("ic,ij,jc->c", a, np.linalg.inv(a @ a.T), a)
    assert np.allclose([got.get(c, 0) for c in range(7)], want, atol=1e-5)


def test_spectral_and_blocks(spark):
    a, _ = tiny(6)
    x = coords(spark, a)
    assert np.isclose(accuracy.spectral_sq(x, 60), np.linalg.svd(a)[1][0] ** 2, rtol=1e-3)
    assert np.array_equal(array(CoordMatrix.from_blocks(x.to_blocks(3, 4), 4, 6, 3, 4)), a)


def test_matrix_input_edges(spark):
    df = spark.createDataFrame([(0, 0, 1), (0, 0, 2), (1, None, 5), (None, 1, 5), (2, 2, None)], "i long, c long, v long")
    m = CoordMatrix.of(df, "i", "c", "v").validate()
    assert [tuple(r) for r in m.df.collect()] == [(0, 0, 3)] and (m.rows, m.cols) == (1, 1)
    empty = CoordMatrix.of(df.limit(0), "i", "c", "v")
    assert (empty.rows, empty.cols) == (0, 0) and multiply.multiply(empty, empty.t).df.count() == 0
    with pytest.raises(ValueError):
        CoordMatrix(df, 3, 3).validate()
    names = spark.createDataFrame([("b",), ("a",), ("a",), (None,), ("c",)], "k string")
    assert {r.k: r.c for r in numbered(names, "k").collect()} == {"a": 0, "b": 1, "c": 2}


def test_plans_have_no_cartesian_product(spark):
    a, b = tiny()
    x, y = coords(spark, a), coords(spark, b)
    got = multiply.rbs_multiply(x, y, 2, HashFamily(3))
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan
    one = sketch.stacked_sketch(x, 2, HashFamily(3))._jdf.queryExecution().executedPlan().toString()
    assert one.count("Exchange hashpartitioning") == 1 and "partial_sum" in one


def test_seeds_are_averaged_over_all_suppliers(spark, monkeypatch):
    rng = np.random.default_rng(7)
    a, b, w = rng.integers(-3, 4, (25, 40)), rng.integers(-3, 4, (40, 5)), products.B
    monkeypatch.setattr(products, "_pair", lambda spark, d: (coords(spark, a), coords(spark, b)))
    s = dense_family(HashFamily(32, 7), 40, w)
    got = {r.seeds: r.rel_frob for r in products.unbiased_over_seeds(spark, None).collect()}
    want = {n: np.linalg.norm(a @ b - a @ s[:, : n * w] @ s[:, : n * w].T @ b / n) / np.linalg.norm(a @ b) for n in (1, 4, 32)}
    assert got == pytest.approx(want)


@pytest.mark.parametrize("gram", [False, True])
def test_errors_over_seeds_equal_single_runs(spark, gram):
    a, b = tiny(8)
    x = coords(spark, a)
    y = x.t if gram else coords(spark, b)
    exact, log = multiply.multiply(x, y), straggler.task_log(spark, 2, 2, 4, seed=4)
    alive = None
    for e in (0, 2):
        one = straggler.survivors(log, Policy("drop", e)).selectExpr(f"{e} as e", "bi", "bj", "k")
        alive = one if alive is None else alive.union(one)
    got = {(r.seed, r.e): np.sqrt(r.err_sq / r.exact_sq) for r in accuracy.errors_over_seeds(x, y, exact, 2, [3, 5], 4, alive, gram).collect()}
    want = {}
    for seed, e in itertools.product((3, 5), (0, 2)):
        one = multiply.rbs_gram(x, 2, HashFamily(4, seed), log, Policy("drop", e)) if gram else multiply.rbs_multiply(x, y, 2, HashFamily(4, seed), log, Policy("drop", e))
        want[seed, e] = accuracy.rel_frobenius(exact, one).first()[0]
    assert got == pytest.approx(want)


def test_error_experiments_have_ten_sketches_and_all_sizes(spark, monkeypatch):
    asked = []

    def record(a, b, exact, width, seeds, slices, alive, gram=False):
        asked.append((a.rows, len(set(seeds)), sorted(r.e for r in alive.select("e").distinct().collect())))
        return spark.createDataFrame([(s, e, 1.0, 4.0) for s in seeds for e in asked[-1][2]], "seed int, e int, err_sq double, exact_sq double")

    monkeypatch.setattr(accuracy, "errors_over_seeds", record, raising=False)
    got = [products.QUERIES[q](spark, "/root/testdata/sf0.001").count() for q in ("error_xy_by_e", "eps_by_e", "vs_parity_error")]
    assert got == [11, 11, 9]
    assert [x[1:] for x in asked] == [(10, list(range(11)))] * 2 + [(10, [1])] * 9
    assert [x[0] for x in asked[2:]] == [16 * k for k in range(6, 15)]


def test_parity_on_sketches_decodes_lost_cells(spark):
    a, b = tiny(9)
    x, y, family = coords(spark, a), coords(spark, b), HashFamily(3)
    want = array(multiply.rbs_multiply(x, y, 2, family), "i", "j", "v_hat", (4, 3))
    for lost in ([], [(0, 0), (1, 1), (0, 1)]):
        assert np.allclose(array(multiply.rbs_parity_multiply(x, y, 2, family, lost), "i", "j", "v_hat", (4, 3)), want)
    with pytest.raises(coded.Undecodable):
        multiply.rbs_parity_multiply(x, y, 2, family, [(0, 0), (0, 1), (1, 0), (1, 1)])


def test_methods_of_the_survey_are_registered(spark):
    d = "/root/testdata/sf0.001"
    failed = products.QUERIES["failure_rate"](spark, d).first()
    assert failed.seeds == 20 and failed.failed <= failed.theta
    assert {r.scheme for r in products.QUERIES["band_vs_block_tasks"](spark, d).collect()} == {"band", "block"}
    assert products.QUERIES["leverage_sample_lossy"](spark, d).count() > 0
    assert {r.c: r.messages for r in products.QUERIES["replication_costs"](spark, d).collect()}[4] == 10
