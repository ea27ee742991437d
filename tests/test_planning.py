import math

import numpy as np
import pytest
from helpers import array, coords, tiny

from blocksketch.functions.hashing import HashFamily
from blocksketch.operators import costs
from blocksketch.plans import expr, planner


def test_dimension_and_spares():
    assert planner.plan_dimension(0.1, 0.1, 16) == (208, 13)
    assert planner.plan_dimension(0.1) == (20, 20)
    assert planner.plan_dimension(0.5, 0.5, 4, rank=3) == (24, 6)
    assert planner.plan_spares(40) == 2
    e = planner.plan_spares(40, 0.05, 0.01)
    tail = lambda e: 1 - sum(math.comb(40 + e, x) * 0.05**x * 0.95 ** (40 + e - x) for x in range(e + 1))
    assert tail(e) <= 0.01 < tail(e - 1)


def test_block_sides():
    a, b = planner.plan_block(2 * 10_000, 10_000)
    assert (a, b) == (1, 100)
    a, b = planner.plan_block(48_000_000, 24_000, "both")
    assert round(a) == 980 and b == 4000
    assert (math.ceil(24_000 / math.floor(a)) + 1) ** 2 == 676


def test_task_counts():
    c = planner.task_counts(20480, 122880, 20480, 2048, 61440)
    assert (c["sketch"], c["compute"], c["reduce"]) == (600, 3000, 100)
    assert planner.task_counts(8, 12, 8, 4, 16)["exact_compute"] == 12


def test_choice():
    s = planner.Stats(100, 10_000, 100, 10**6, 10**6, 10**8)
    assert planner.plan_multiply(s, costs.CostModel(memory_entries=20_000)) == "block"
    assert planner.plan_multiply(planner.Stats(1000, 100, 1000, 1, 1, 1)) == "band"
    assert planner.sketch_pays(planner.Stats(160, 9600, 160, 160 * 9600, 160 * 9600, 160 * 160 * 9600), 30, 1, 16)
    assert not planner.sketch_pays(planner.Stats(100, 2000, 83, 5000, 5000, 20_000), 4, 1, 16)


def test_rectangular_sides_are_nearly_square():
    p, q, r = planner.plan_rectangular(2000, 2000, 2000, 30_000)
    assert p * q + q * r + p * r <= 30_000
    assert max(p, q, r) / min(p, q, r) < 2


def test_costs(spark):
    t = spark.createDataFrame([(100, 100, 100, 10, 20)], "m long, n long, l long, a long, b long")
    r = costs.block_costs(costs.band_costs(t)).first()
    assert r.band_entries == 2 * 100**3 / 10 + 100**2 and r.band_tasks == 100
    assert r.block_compute_entries == 3 * 100**3 / 20 and r.block_compute_tasks == 125 and r.block_reduce_tasks == 25
    log = spark.createDataFrame([(101,), (100,), (1,)], "t_ms long")
    assert costs.dollars(log, costs.CostModel()).first().units == 4


def test_rewrites(spark):
    a, b = tiny()
    x, y = expr.Leaf("x", coords(spark, a)), expr.Leaf("y", coords(spark, b))
    assert isinstance(expr.optimise(x @ x.t), expr.Gram)
    assert isinstance(expr.optimise((x.t.t @ y).t), expr.Multiply)
    assert np.array_equal(array(expr.lower(expr.optimise((x @ y).t))), (a @ b).T)
    f = expr.optimise(expr.RowFilter(x @ y, "i < 2"))
    assert isinstance(f, expr.Multiply) and isinstance(f.left, expr.RowFilter)
    want = a @ b
    want[2:] = 0
    assert np.array_equal(array(expr.lower(f)), want)
    chain = expr.optimise(x.t @ x @ y)
    assert np.array_equal(array(expr.lower(chain)), a.T @ a @ b)
    assert "Multiply" in expr.explain(chain)
    with pytest.raises(TypeError):
        expr.lower_sketched(x, 2, HashFamily(2))


def test_chain_order(spark):
    from blocksketch.operators.matrix import CoordMatrix

    df = coords(spark, tiny()[0]).df
    leaf = lambda n, r, c: expr.Leaf(n, CoordMatrix(df, r, c))
    e = expr.optimise((leaf("a", 100, 2) @ leaf("b", 2, 100)) @ leaf("c", 100, 3))
    assert e.left.name == "a"
