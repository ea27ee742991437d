"""What broke on tables of 6 and 60 times sf0.1, on small data."""

import duckdb
import numpy as np
import pytest
from helpers import DATA, array, coords
from pyspark.sql import functions as F
from test_entry import rows

from blocksketch import workloads
from blocksketch.functions.hashing import HashFamily
from blocksketch.operators import accuracy, baselines, losses, multiply, squares, straggler
from blocksketch.operators.matrix import CoordMatrix, bounded
from blocksketch.operators.straggler import Policy
from blocksketch.optim import barrier, linear
from blocksketch.plans import expr
from blocksketch.streaming import stream


def test_logs_of_more_tasks_than_an_int_times_20001(spark):
    log = straggler.task_log(spark, 200, 180, 3)
    assert {r.t_ms for r in log.orderBy("t_ms").limit(1).collect()} == {30000} and log.filter("t_ms = 375000").count() == 2 * 108000 // 3000
    assert straggler.task_logs(spark, 200, 180, 3, [1]).filter("t_ms = 375000").count() == 72


def test_gram_of_many_cells_per_task(spark):
    rng = np.random.default_rng(5)
    a, w, n = rng.integers(-3, 4, (59, 20)) * (rng.random((59, 20)) < 0.3), 2, 3
    family, log = HashFamily(n, 6), straggler.task_log(spark, 30, 30, n)
    u = np.zeros((20, n * w))
    for k, u1, u0, w3, w2, w1, w0 in family.rows:
        for c in range(20):
            q = (((w3 * c + w2) * c + w1) * c + w0) % (2**31 - 1)
            u[c, k * w + (u1 * c + u0) % (2**31 - 1) % w] = 1 - 2 * (q % 2)
    alive = np.zeros((30, 30, n), bool)
    for r in straggler.survivors(log, Policy("drop", 1)).collect():
        alive[r.bi, r.bj, r.k] = True
    want = np.zeros((59, 59))
    for i in range(59):
        for j in range(59):
            x, y = min(i, j), max(i, j)
            want[i, j] = sum((a[x] @ u[:, k * w : k * w + w]) @ (a[y] @ u[:, k * w : k * w + w]) for k in np.flatnonzero(alive[x // w, y // w])) / 2
    got = multiply.rbs_gram(coords(spark, a), w, family, log, Policy("drop", 1))
    assert np.allclose(array(got, "i", "j", "v_hat", (59, 59)), want)


def test_kernel_weights_of_more_rows_than_a_kernel_holds(spark):
    x = CoordMatrix(spark.range(9000).selectExpr("id AS i", "id % 3 AS c", "1.0D * (1 + id % 7) AS v"), 9000, 3)
    y = spark.range(9000).selectExpr("id AS i", "1.0D * (id % 5) AS y")
    got = {r.i: r.weight for r in linear.kernel_weights(x, y, 2.0).collect()}
    n = np.arange(9000)
    z = np.zeros((9000, 3))
    z[n, n % 3] = 1 + n % 7
    w = np.array([got[i] for i in n])
    assert np.allclose(z @ (z.T @ w) + 2 * w, n % 5)


def test_large_sides_are_not_broadcast(spark):
    plan = lambda most: spark.range(10).join(bounded(spark.range(8), most, "merge"), "id")._jdf.queryExecution().optimizedPlan().toString()
    assert "strategy=broadcast" in plan(8) and "strategy=merge" in plan(7) and "broadcast" not in plan(7)


def test_appended_rows_are_files_not_the_drivers(spark, tmp_path):
    spark.range(5).write.parquet(str(tmp_path / "in"))
    spark.range(0).write.parquet(str(tmp_path / "none"))
    read = lambda name: spark.readStream.schema("id long").parquet(str(tmp_path / name))
    got = stream.finished(read("in"), "append")
    assert got.inputFiles() and sorted(r.id for r in got.collect()) == list(range(5))
    assert stream.finished(read("none"), "append").count() == 0


def test_leverage_by_linked_rows(spark):
    rng = np.random.default_rng(3)
    a = np.zeros((12, 30), int)
    for p in range(3):
        a[4 * p : 4 * p + 4, 10 * p : 10 * p + 10] = rng.integers(-3, 4, (4, 10))
    a[3], a[7, 10] = 0, 0
    x = coords(spark, a)
    got = {r.c: r.score for r in baselines.leverage_scores(x, most=4).collect()}
    g = np.linalg.inv(a @ a.T + 1e-9 * (a**2).sum() / 12 * np.eye(12))
    want = {c: a[:, c] @ g @ a[:, c] for c in range(30) if a[:, c].any()}
    assert got.keys() == want.keys() and np.allclose([got[c] for c in want], list(want.values()))
    assert {r.i: r.part for r in baselines.row_parts(x).collect()} == {i: 4 * (i // 4) for i in range(12) if a[i].any()}


MADE_UP = "asymptotic_slopes band_costs block_costs cost_ratio dollars_sweep effective_dimension error_xy_by_e first_n_arrivals illustration_tasks job_dollars lp_iteration_time mat_identity".split()


@pytest.mark.parametrize("name", MADE_UP)
def test_tables_are_read_and_matter(spark, name, tmp_path):
    """A half of the orders and events gives another result than all of them, by the SQL too."""
    for t in ("orders", "events"):
        whole = spark.read.parquet(f"{DATA}/{t}.parquet")
        whole.filter(F.col(whole.columns[0]) % 2 == 0).write.parquet(str(tmp_path / f"{t}.parquet"))
    found = []
    for d in (DATA, str(tmp_path)):
        got = workloads.queries()[name](spark, d)
        found.append(rows(got.columns, [r.asDict() for r in got.collect()]))
        if name in workloads.oracle_sql():
            con = duckdb.connect()
            for t in ("orders", "events"):
                con.execute(f"create view {t} as select * from read_parquet('{d}/{t}.parquet{'' if d == DATA else '/*.parquet'}')")
            want = con.execute(workloads.oracle_sql()[name])
            names = [c[0] for c in want.description]
            assert found[-1] == rows(names, [dict(zip(names, r, strict=True)) for r in want.fetchall()])
    assert found[0] and (found[0] != found[1] or name in ("asymptotic_slopes", "illustration_tasks"))  # a slope of 1/2; sizes by the last index


def test_exact_products_copy_only_what_has_a_partner(spark):
    rng = np.random.default_rng(7)
    a, b = rng.integers(-3, 4, (70, 90)) * (rng.random((70, 90)) < 0.1), rng.integers(-3, 4, (90, 30)) * (rng.random((90, 30)) < 0.3)
    for got in (multiply.band_multiply(coords(spark, a), coords(spark, b), 2), multiply.dense_block_multiply(coords(spark, a), coords(spark, b), 4)):
        assert np.array_equal(array(got), a @ b)
        assert got.df.count() == np.count_nonzero((a != 0).astype(int) @ (b != 0))
        assert "Generate" not in got.df._jdf.queryExecution().optimizedPlan().toString()


def test_programs_of_few_rows_take_few_tasks(spark, monkeypatch):
    rng = np.random.default_rng(4)
    a = rng.random((90, 3))
    rows = [(i, r.tolist(), 1.0) for i, r in enumerate(np.vstack([a, np.eye(3), -np.eye(3)]))]
    frame = barrier.rows_frame(spark.createDataFrame(rows, "i long, row array<double>, b double").repartition(8))
    few = barrier.held(frame, 3)
    assert few.rdd.getNumPartitions() == 1 and few.count() == 96
    monkeypatch.setattr(barrier, "PER_TASK", 50)
    assert barrier.held(frame, 3).rdd.getNumPartitions() == 6
    sums = spark.range(40).selectExpr("cast(id % 4 as int) AS k", "array(double(id), id * 2.5D, 1D) AS v").repartition(5)
    for most in (0, 10**6):
        got = barrier._summed(sums, "k", 12, 5, most)
        assert {k: v.tolist() for k, v in got.items()} == {k: [180.0 + 10 * k, 450 + 25.0 * k, 10] for k in range(4)}


def test_error_of_a_projected_gram_by_norms(spark):
    rng = np.random.default_rng(11)
    a = rng.integers(-3, 4, (150, 40)) * (rng.random((150, 40)) < 0.1)
    a[:64, 20:] = a[64:, :20] = 0  # rows of two bands that share no column
    x = coords(spark, a)
    s = baselines.gaussian_sketch(x, 5)
    got = accuracy.gram_rel_frobenius(x, s, 5)
    z, g = array(s, "i", "r", "v", (150, 5)), a @ a.T
    want = np.linalg.norm(g - z @ z.T) / np.linalg.norm(g)
    assert np.isclose(got.first().rel_frob, want) and np.isclose(accuracy.rel_frobenius(multiply.multiply(x, x.t), baselines.projected_product(s, s)).first().rel_frob, want)
    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInPandas" in plan(workloads.queries()["gaussian_gram_error"](spark, DATA)) and "Aggregate [i#" not in plan(got).split("MapInPandas")[0]


def test_sums_of_partials_where_blocks_are_multiplied(spark):
    rng = np.random.default_rng(12)
    a, b = rng.integers(-3, 4, (200, 50)) * (rng.random((200, 50)) < 0.2), rng.integers(-3, 4, (50, 30)) * (rng.random((50, 30)) < 0.2)
    a[:, 7] = b[21] = 0
    x, y = coords(spark, a), coords(spark, b)
    for block in (2, (3, 8, 5)):
        got = multiply.partial_sums(x.df.withColumn("v", F.explode(F.array(F.col("v") - 9, F.lit(9)))), y.df, block)  # two rows a cell
        want = multiply.block_partials(x, y, block).groupBy("bi", "bj", "k").agg(F.count("*").alias("n_entries"), F.sum("v").alias("total"))
        rows_of = lambda df: sorted(map(tuple, df.select("bi", "bj", "k", "n_entries", "total").collect()))
        assert rows_of(got) == rows_of(want) and got.schema.simpleString() == want.schema.simpleString()
        assert "Aggregate [bi#" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_gram_of_few_columns_shuffles_bands_not_products(spark):
    rng = np.random.default_rng(13)
    for low in (0, -3):
        a = rng.integers(low, 4, (90, 11)) * (rng.random((90, 11)) < 0.2)
        a[8:24] = 0  # a whole band without entries
        x = coords(spark, a)
        for real in (False, True):
            y = x.with_(x.df.withColumn("v", F.col("v").cast("double") / 2)) if real else x
            got = multiply.gram(y)
            assert np.allclose(array(got), a @ a.T / (4 if real else 1)) and got.df.schema["v"].dataType.typeName() == ("double" if real else "long")
            assert got.df.count() == np.count_nonzero((a != 0).astype(int) @ (a != 0).T)
    assert array(multiply.gram(x, short=5)).tolist() == (a @ a.T).tolist()
    plan = workloads.queries()["gram_events"](spark, DATA)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and plan.count("Aggregate") == 1


@pytest.mark.parametrize("narrow", [0, 10**6])
def test_products_by_a_small_right_side_are_not_shuffled(spark, monkeypatch, narrow):
    monkeypatch.setattr(expr, "NARROW", narrow)
    rng = np.random.default_rng(8)
    a = rng.integers(0, 4, (40, 6))
    x = expr.Leaf("x", coords(spark, a))
    got = expr.lower(expr.optimise(x @ x.t @ x))
    assert np.array_equal(array(got), a @ a.T @ a)
    assert ("MapInPandas" in got.df._jdf.queryExecution().optimizedPlan().toString()) == (narrow > 0)


def test_squared_norms_of_a_gram_whose_rows_share_columns_need_no_join(spark, monkeypatch):
    monkeypatch.setattr(squares, "STRIP", 16)
    monkeypatch.setattr(squares, "SIDE", 2)
    rng = np.random.default_rng(21)
    a = rng.integers(-3, 4, (150, 40)) * (rng.random((150, 40)) < 0.3)
    a[16:64] = 0  # whole strips without entries
    for scale in (1, 0.5):
        x = coords(spark, a)
        x = x.with_(x.df.withColumn("v", F.col("v") * scale)) if scale != 1 else x
        s = baselines.gaussian_sketch(x, 5)
        got = accuracy.gram_rel_frobenius(x, s, 5)
        z, g = array(s, "i", "r", "v", (150, 5)), scale**2 * a @ a.T
        assert np.isclose(got.first().rel_frob, np.linalg.norm(g - z @ z.T) / np.linalg.norm(g))
        assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()


SETS = [(0, 4, Policy("drop", 0)), (1, 5, Policy("drop", 1)), (2, 9, Policy("drop", 3)), (3, 5, Policy("first", 2)), (4, 5, Policy("deadline", 40_000, 1)), (5, 5, Policy("shared", 4))]


@pytest.mark.parametrize("bits", [None, 6])
def test_losses_of_logs_that_are_not_ranked_in_one_task(spark, monkeypatch, bits):
    for name, size in (("RANKED", 500), ("STRIPE", 7000), ("CHUNK", 1000)):
        monkeypatch.setattr(losses, name, size)
    x = losses.Losses(spark, 63, 51, SETS, 1, bits)
    want, got = {(r.e, r.bi, r.bj, r.k) for r in x.frame().collect()}, set()
    read, ranked = x.reader(16, 16), x.ranked(16, 16, False)
    assert "Window" not in ranked._jdf.queryExecution().optimizedPlan().toString()
    moved = ranked.collect()
    for gi in range(4):
        for gj in range(4):
            mine = read.moved((r.n, r["size"], r.data) for r in moved if (r.gi, r.gj) == (gi, gj))
            for lo in (0, 8):
                got |= {(SETS[e][0], gi * 16 + lo + a, gj * 16 + b, k) for e, a, b, k in zip(*np.nonzero(read.keep(gi, gj, lo, lo + 8, mine)), strict=True)}
    assert got == want


@pytest.mark.parametrize("policy", [Policy("drop", 2), Policy("shared", 3)])
def test_sketched_gram_by_squares(spark, monkeypatch, policy):
    monkeypatch.setattr(squares, "STRIP", 4)
    monkeypatch.setattr(squares, "SIDE", 2)
    rng = np.random.default_rng(22)
    a = rng.integers(-3, 4, (59, 20)) * (rng.random((59, 20)) < 0.15)
    a[8:16] = 0
    family, rows_of = HashFamily(5, 6), lambda df: {(r.i, r.j): (r.v_hat, r.n_survivors) for r in df.collect()}
    for scale in (1, 0.5):
        x = coords(spark, a)
        x = x.with_(x.df.withColumn("v", F.col("v") * scale)) if scale != 1 else x
        got = multiply.rbs_gram(x, 2, family, losses.Losses(spark, 30, 30, [(2, 5, policy)]))
        want = multiply.rbs_gram(x, 2, family, straggler.task_log(spark, 30, 30, 5), policy)
        assert rows_of(got) == rows_of(want) and got.schema.simpleString() == want.schema.simpleString()
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        assert "Join" not in plan and "Window" not in plan and "Aggregate" not in plan


@pytest.mark.parametrize("es", [(1,), (0, 1, 3)])
def test_errors_over_seeds_by_squares(spark, monkeypatch, es):
    monkeypatch.setattr(squares, "STRIP", 4)
    monkeypatch.setattr(squares, "SIDE", 2)
    rng = np.random.default_rng(23)
    a = rng.integers(-3, 4, (59, 20)) * (rng.random((59, 20)) < 0.15)
    a[8:16] = 0
    x, sets = coords(spark, a), [(e, 4 + e, Policy("drop", e)) for e in es]
    rows_of = lambda df: {(r.seed, r.e): (r.err_sq, r.exact_sq) for r in df.collect()}
    alive = losses.Losses(spark, 30, 30, sets)
    got = accuracy.errors_over_seeds(x, x.t, None, 2, [3, 5], 7, alive, gram=True)
    want = rows_of(accuracy.errors_over_seeds(x, x.t, multiply.multiply(x, x.t), 2, [3, 5], 7, alive.frame(), gram=True))
    assert rows_of(got).keys() == want.keys() and all(np.allclose(v, want[k]) for k, v in rows_of(got).items())
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Window" not in plan
