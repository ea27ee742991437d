"""Workloads on the given tables: exact, sketched and coded products, losses, errors and costs."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from .. import sources
from ..functions.hashing import HashFamily, bucket_sql, sign_sql
from ..operators import accuracy, baselines, coded, costs, multiply, sketch, straggler
from ..operators.losses import Losses
from ..operators.matrix import CoordMatrix, generated
from ..operators.straggler import Policy
from ..plans import planner
from . import sql

B, N = 16, 4
QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None, name: str | None = None):
    """Registers a workload and the SQL that says the same."""

    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if oracle:
            ORACLES[key] = oracle
        return f

    return add


def blocks_of(n: int, b: int = B) -> int:
    return -(-n // b)


# The sizes of the tables at the scale that the SQL is compared at; Spark derives its own from the data.
SUPPLIERS, MONTHS = 100, 83


@query(sql.PIVOTS["f1"])
def pivot_supplier_part(spark, d):
    return sources.supplier_part(spark, d).df


@query(sql.PIVOTS["f2"])
def pivot_part_month(spark, d):
    return sources.part_month(spark, d).df


@query(sql.PIVOTS["f3"])
def pivot_customer_month(spark, d):
    return sources.customer_month(spark, d).df


@query(sql.PIVOTS["f4"])
def pivot_user_hour(spark, d):
    return sources.user_hour(spark, d).df


@query(sql.PIVOTS["f5"])
def pivot_type_k(spark, d):
    return sources.type_k(spark, d).df


@query(sql.PIVOTS["f6"])
def pivot_embedding(spark, d):
    return sources.embedding_dim(spark, d).df


def _pair(spark, d):
    return sources.supplier_part(spark, d), sources.part_month(spark, d)


PRODUCT = f"WITH {sql.with_('f1', 'f2')} {sql.product('f1', 'f2')}"


def _cells(m: CoordMatrix):
    return m.df.select("i", F.col("c").alias("j"), "v")


@query(PRODUCT)
def band_supplier_month(spark, d):
    return _cells(multiply.band_multiply(*_pair(spark, d), 16))


@query(f"WITH {sql.with_('f1', 'f2')} SELECT CAST(a.i // 16 AS INT) AS bi, CAST(b.c // 16 AS INT) AS bj, CAST(a.c // 16 AS INT) AS k, count(DISTINCT (a.i, b.c)) AS n_entries, CAST(sum(a.v * b.v) AS BIGINT) AS total FROM f1 a JOIN f2 b ON a.c = b.i GROUP BY 1, 2, 3")
def partials_supplier_month(spark, d):
    return multiply.partial_sums(*sources.supplier_part_months(spark, d), B)


@query(PRODUCT)
def block_supplier_month(spark, d):
    return _cells(multiply.block_multiply(*_pair(spark, d), B))


@query(PRODUCT)
def fused_supplier_month(spark, d):
    return _cells(multiply.block_multiply(*_pair(spark, d), B, fused=True))


@query(PRODUCT)
def rect_block_supplier_month(spark, d):
    return _cells(multiply.block_multiply(*_pair(spark, d), (8, 64, 12)))


@query(PRODUCT)
def block_kernel(spark, d):
    m = multiply.dense_block_multiply(*_pair(spark, d), 64)
    return _cells(m).withColumn("v", F.round("v").cast("long"))


SKETCH = f"WITH {sql.family(5)}, {sql.with_('f1')} {sql.sketch('f1', B)}"


@query(SKETCH)
def sketch_supplier_part(spark, d):
    return sketch.stacked_sketch(sources.supplier_part(spark, d), B, HashFamily(5))


@query(f"{SKETCH} HAVING v <> 0".replace("HAVING v <> 0", f"HAVING sum({sign_sql('c')} * v) <> 0"))
def sketch_located(spark, d):
    s = sketch.located_sketch(sources.supplier_part(spark, d), B, HashFamily(5))
    return s.withColumn("v", F.col("v").cast("long"))


@query(f"WITH {sql.family(5)}, {sql.with_('f2')} SELECT k, {bucket_sql('i', B)} AS h, c AS j, CAST(sum({sign_sql('i')} * v) AS BIGINT) AS v FROM f2 CROSS JOIN fam GROUP BY 1, 2, 3")
def sketch_right_part_month(spark, d):
    return sketch.sketch_right(sources.part_month(spark, d), B, HashFamily(5))


@query(f"WITH {sql.family(1)}, {sql.with_('f1')}, s AS ({sql.sketch('f1', 64)}) SELECT i, h, v FROM s")
def count_sketch_single(spark, d):
    return sketch.count_sketch(sources.supplier_part(spark, d), 64)


#: The worked example's bucket and sign of each of nine columns, from 1.
WORKED_BUCKET = (2, 2, 3, 1, 1, 2, 1, 3, 3)
WORKED_SIGN = (1, -1, 1, 1, -1, 1, -1, -1, -1)
_WORKED = ", ".join(f"({c}, {h}, {s})" for c, (h, s) in enumerate(zip(WORKED_BUCKET, WORKED_SIGN, strict=True)))


@query(f"WITH {sql.with_('f1')}, map(c, h, s) AS (VALUES {_WORKED}) SELECT i, h, CAST(sum(v * s) AS BIGINT) AS v FROM f1 JOIN map USING (c) GROUP BY 1, 2")
def worked_sketch(spark, d):
    mapping = spark.createDataFrame([(c, h, s) for c, (h, s) in enumerate(zip(WORKED_BUCKET, WORKED_SIGN, strict=True))], "c long, h int, s long")
    return sketch.mapped_sketch(sources.supplier_part(spark, d), F.broadcast(mapping))


@query(f"WITH {sql.with_('f3')}, s AS (SELECT (max(i) + 16) // 16 AS m, (max(c) + 16) // 16 AS n FROM f3) SELECT 'exact_compute' AS task, m * m * n AS number FROM s UNION ALL SELECT 'reduce', m * m FROM s UNION ALL SELECT 'rbs_compute', m * m * 5 FROM s UNION ALL SELECT 'rbs_sketch_a', m * 5 FROM s")
def illustration_tasks(spark, d):
    """Tasks of the Gram of customers by month, exact and sketched by five slices."""
    a, z = sources.customer_month(spark, d), 5 * B
    c = planner.task_counts(a.rows, a.cols, a.rows, B, z)
    rows = [("exact_compute", c["exact_compute"]), ("reduce", c["reduce"]), ("rbs_compute", c["compute"]), ("rbs_sketch_a", sketch.sketch_tasks(a.rows, B, HashFamily(z // B)))]
    return spark.createDataFrame(rows, "task string, number long")


def _log(spark, rows: int, cols: int, k: int, b: int = B):
    return straggler.task_log(spark, blocks_of(rows, b), blocks_of(cols, b), k)


def _rbs_sql(condition: str, k: int, out: str = "i, j, v_hat, n_survivors", lost: str = "") -> str:
    return f"""WITH {sql.family(k)}, {sql.with_('f1', 'f2')}, {sql.log(blocks_of(SUPPLIERS), blocks_of(MONTHS), k)}{lost}, {sql.survivors(condition)},
    sa AS ({sql.sketch('f1', B)}), sb AS ({sql.sketch('f2', B, 'c', 'i', 'j')}), {sql.estimate('sa', 'sb', B)} SELECT {out} FROM guessed"""


def _rbs(spark, d, policy: Policy, k: int, change=lambda log: log):
    a, b = _pair(spark, d)
    return multiply.rbs_multiply(a, b, B, HashFamily(k), change(_log(spark, a.rows, b.cols, k)), policy)


@query(_rbs_sql(f"r <= {N}", N + 1))
def rbs_supplier_month_firstn(spark, d):
    return _rbs(spark, d, Policy("first", N), N + 1)


@query(_rbs_sql("r <= n - 1", N + 1))
def rbs_supplier_month_drop1(spark, d):
    return _rbs(spark, d, Policy("drop", 1), N + 1)


@query(_rbs_sql("t_ms <= 40000 OR r <= 1", N + 1))
def rbs_supplier_month_deadline(spark, d):
    return _rbs(spark, d, Policy("deadline", 40_000, 1), N + 1)


LOST = [("a", 0, 1), ("a", 2, 0), ("b", 1, 3)]
_LOST_SQL = "".join(f" AND NOT ({'bi' if s == 'a' else 'bj'} = {x} AND k = {k})" for s, x, k in LOST)


@query(_rbs_sql("true", N + 1).replace("FROM tasks)", f"FROM tasks WHERE true{_LOST_SQL})"))
def rbs_sketch_loss(spark, d):
    lost = spark.createDataFrame(LOST, "side string, block int, k int")
    return _rbs(spark, d, Policy("all"), N + 1, lambda log: straggler.sketch_losses(log, lost))


def _gram_sql(e: int, out: str = "SELECT i, j, v_hat, n_survivors FROM whole", width: int = B, slices: int = N, shared: bool = False) -> str:
    k, cells = slices + e, blocks_of(SUPPLIERS, width)
    alive = sql.survivors(f"r <= n - {e}")
    if shared:
        alive = f"alive AS (SELECT bi, bj, k, t_ms FROM tasks WHERE k IN (SELECT k FROM (SELECT k, row_number() OVER (ORDER BY max(t_ms), k) AS r FROM tasks GROUP BY k) WHERE r <= {slices}))"
    return f"""WITH {sql.family(k)}, {sql.with_('f1')}, {sql.log(cells, cells, k)}, {alive}, sa AS ({sql.sketch('f1', width)}), sb AS (SELECT i AS j, k, h, v FROM sa),
    {sql.estimate('sa', 'sb', width)}, upper AS (SELECT * FROM guessed WHERE i // {width} <= j // {width}),
    whole AS (SELECT * FROM upper UNION ALL SELECT j, i, v_hat, n_survivors FROM upper WHERE i // {width} < j // {width}) {out}"""


def _gram(spark, d, e: int, slices: int = N, policy: Policy | None = None):
    a = sources.supplier_part(spark, d)
    losses = Losses(spark, blocks_of(a.rows), blocks_of(a.rows), [(e, slices + e, policy or Policy("drop", e))])
    return a, multiply.rbs_gram(a, B, HashFamily(slices + e), losses)


for _e in (0, 1, 2, 4, 8, 10):
    query(_gram_sql(_e), f"rbs_gram_supplier_e{_e}")(lambda spark, d, e=_e: _gram(spark, d, e)[1])


@query(_gram_sql(1, shared=True))
def rbs_shared_survivors(spark, d):
    return _gram(spark, d, 1, policy=Policy("shared", N))[1]


@query(f"WITH {sql.with_('f1')} {sql.gram('f1')}")
def exact_gram_supplier(spark, d):
    a = sources.supplier_part(spark, d)
    return _cells(multiply.multiply(a, a.t))


def flagship(spark, d):
    """The sketched Gram with one loss per cell beside the exact one, and the relative error of each entry."""
    a, got = _gram(spark, d, 1)
    both = accuracy.difference(multiply.multiply(a, a.t), got)
    return both.withColumn("rel_error", F.when(F.col("v") != 0, F.abs(F.col("v_hat") - F.col("v")) / F.abs("v")))


_EXACT_GRAM = f"exact AS ({sql.gram('f1')})"
_ERR = "SELECT round(sqrt(sum(power(coalesce(x.v, 0) - coalesce(g.v_hat, 0), 2))) / sqrt(sum(power(coalesce(x.v, 0), 2))), 6) AS rel_frob FROM exact x FULL JOIN whole g ON x.i = g.i AND x.j = g.j"


@query(" UNION ALL ".join(f"SELECT {e} AS e, rel_frob FROM ({_gram_sql(e, ', ' + _EXACT_GRAM + ' ' + _ERR)})" for e in (0, 1, 2, 4)))
def error_by_e(spark, d):
    a, es = sources.supplier_part(spark, d), (0, 1, 2, 4)
    alive = _losses(spark, a.rows, es, lambda e: N + e)
    errors = accuracy.errors_over_seeds(a, a.t, multiply.multiply(a, a.t), B, [HashFamily(N).seed], N + max(es), alive, gram=True)
    return errors.select("e", F.round(F.sqrt("err_sq") / F.sqrt("exact_sq"), 6).alias("rel_frob"))


#: Losses per cell and sketches of the error experiments.
LOSSES, SKETCHES = range(11), 10


def _dropped(spark, rows: int, cols: int, es, slices, b: int = B):
    """alive(e, bi, bj, k): the slices left in each cell after its e slowest; slices: a number, or one by e."""
    out = None
    for e in es:
        one = straggler.survivors(_log(spark, rows, cols, slices(e) if callable(slices) else slices, b), Policy("drop", e)).select(F.lit(e).alias("e"), "bi", "bj", "k")
        out = one if out is None else out.union(one)
    return out


def _losses(spark, rows: int, es, slices):
    """The same sets over the cells of a Gram matrix, without a row per task."""
    return Losses(spark, blocks_of(rows), blocks_of(rows), [(e, slices(e), Policy("drop", e)) for e in es])


@query()
def eps_by_e(spark, d):
    """Mean and largest squared error over the squared norms of A and B, over ten sketches, with e of N + e slices ignored per cell."""
    a = sources.supplier_part(spark, d)
    alive = _losses(spark, a.rows, LOSSES, lambda e: N + e)
    errors = accuracy.errors_over_seeds(a, a.t, multiply.multiply(a, a.t), B, list(range(42, 42 + SKETCHES)), N + max(LOSSES), alive, gram=True)
    eps = errors.crossJoin(F.broadcast(a.frobenius_sq())).withColumn("eps", F.col("err_sq") / F.pow(F.col("sq").cast("double"), 2))
    return eps.groupBy("e").agg(F.avg("eps").alias("eps"), F.max("eps").alias("worst_eps")).withColumn("expected_bound", F.lit(2 / (N * B)))


XY = 16


def xy_pair(spark, b: int = XY, m: int = 10, n: int = 60):
    return generated(spark, m * b, n * b, lambda x, y: x + y)


def _xy_error(spark, e: int, seed: int, b: int = XY, slices: int = 30):
    """One sketch of x + y with z = 30 b in all, of which e per cell are dropped."""
    a = xy_pair(spark, b)
    got = multiply.rbs_gram(a, b, HashFamily(slices, seed), _log(spark, a.rows, a.rows, slices, b), Policy("drop", e))
    return a, got


@query()
def error_xy_by_e(spark, d):
    """Mean relative error over seeds, by the number of tasks ignored per cell, on events by k and hour, where all cells are positive, with z = 30b."""
    a, slices = sources.k_hour(spark, d), 30
    alive = _dropped(spark, a.rows, a.rows, LOSSES, slices, XY)
    errors = accuracy.errors_over_seeds(a, a.t, multiply.multiply(a, a.t), XY, list(range(100, 100 + SKETCHES)), slices, alive, gram=True)
    return errors.groupBy("e").agg(F.avg(F.sqrt(F.col("err_sq") / F.col("exact_sq"))).alias("mean_rel_frob"))


for _e in (0, 1, 2, 4, 8, 10):
    query(None, f"rbs_gram_xy_e{_e}")(lambda spark, d, e=_e: _xy_error(spark, e, 42)[1])


_RANKED = "SELECT bi, bj, k, t_ms, CAST(row_number() OVER (PARTITION BY bi, bj ORDER BY t_ms, k) AS INT) AS rank FROM tasks"


@query(f"WITH {sql.EVENT_LOG} {_RANKED}")
def first_n_arrivals(spark, d):
    return straggler.ranked(sources.event_log(spark, d)).select("bi", "bj", "k", "t_ms", "rank")


@query(f"WITH {sql.log(10, 10, 30)} SELECT e, max(t_ms) AS phase_ms FROM (SELECT *, row_number() OVER (PARTITION BY bi, bj ORDER BY t_ms, k) AS r FROM tasks) JOIN range(0, 11) AS s(e) ON r <= 30 - e GROUP BY e")
def phase_time_by_e(spark, d):
    r = straggler.ranked(straggler.task_log(spark, 10, 10, 30))
    return r.withColumn("e", F.explode(F.sequence(F.lit(0).cast("long"), F.least(F.lit(10).cast("long"), (30 - F.col("rank")).cast("long"))))).filter("rank <= 30 - e").groupBy("e").agg(F.max("t_ms").alias("phase_ms"))


@query(f"WITH {sql.log(10, 10, 30)}, p AS (SELECT e, max(t_ms) AS t FROM (SELECT *, row_number() OVER (PARTITION BY bi, bj ORDER BY t_ms, k) AS r FROM tasks) JOIN range(0, 11) AS s(e) ON r <= 30 - e GROUP BY e) SELECT e, round(1 - CAST(t AS DOUBLE) / (SELECT max(t) FROM p), 6) AS saved, round((SELECT max(t) FROM p) / CAST(t AS DOUBLE), 6) AS factor FROM p")
def time_vs_e(spark, d):
    p = phase_time_by_e(spark, d)
    base = p.agg(F.max("phase_ms").alias("base"))
    return p.crossJoin(F.broadcast(base)).select("e", F.round(costs.saving(F.col("base"), F.col("phase_ms")), 6).alias("saved"), F.round(F.col("base") / F.col("phase_ms"), 6).alias("factor"))


@query(f"WITH {sql.log(10, 10, 30)}, m AS (SELECT median(t_ms) AS md FROM tasks) SELECT md AS median_ms, avg(CASE WHEN t_ms > 2 * md THEN 1.0 ELSE 0.0 END) AS share_slow, max(t_ms) AS max_ms, count(*) AS tasks FROM tasks, m GROUP BY md")
def straggler_profile_sim(spark, d):
    return straggler.profile(straggler.task_log(spark, 10, 10, 30))


_GAPS = "gaps AS (SELECT user_id, event_id, CAST(date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) // 1000 AS BIGINT) AS t_ms FROM events)"


def event_gaps_frame(spark, d):
    from pyspark.sql import Window as W

    e = sources.load(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    gap = F.col("us") - F.lag("us").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    return e.select("user_id", "event_id", F.floor(gap / 1000).cast("long").alias("t_ms"))


@query(f"WITH {_GAPS} SELECT user_id, event_id, t_ms FROM gaps")
def event_gaps(spark, d):
    return event_gaps_frame(spark, d)


@query(f"WITH {_GAPS}, g AS (SELECT * FROM gaps WHERE t_ms IS NOT NULL), m AS (SELECT median(t_ms) AS md FROM g) SELECT md AS median_ms, avg(CASE WHEN t_ms > 2 * md THEN 1.0 ELSE 0.0 END) AS share_slow, max(t_ms) AS max_ms, count(*) AS tasks FROM g, m GROUP BY md")
def straggler_profile_events(spark, d):
    return straggler.profile(event_gaps_frame(spark, d).filter("t_ms is not null"))


@query(f"WITH {sql.log(10, 10, 30)}, m AS (SELECT median(t_ms) AS md FROM tasks) SELECT x AS multiple, CAST(max(least(t_ms, CAST(floor(md * x) AS BIGINT) + 30000 + (9 * 104729 + bi * 7919 + bj * 104723 + k * 1299709) % 20001)) AS BIGINT) AS phase_ms FROM tasks, m, (VALUES (CAST(1.2 AS DOUBLE)), (1.5), (2.0)) AS s(x) GROUP BY x")
def speculate_phase_time(spark, d):
    out = None
    for x in (1.2, 1.5, 2.0):
        one = straggler.phase_time(straggler.speculated(straggler.task_log(spark, 10, 10, 30), x)).select(F.lit(x).alias("multiple"), "phase_ms")
        out = one if out is None else out.union(one)
    return out


PARITY_LOST = [(0, 0), (3, 2), (5, 1)]


@query(PRODUCT)
def parity_supplier_month(spark, d):
    a, b = _pair(spark, d)
    lost = [(r, c) for r, c in PARITY_LOST if r <= blocks_of(a.rows) and c <= blocks_of(b.cols)]
    return _cells(coded.parity_multiply(a, b, B, lost))


def _loss_sql(lost: int) -> str:
    k = N + 2
    body = _rbs_sql(f"r <= {k - lost}", k, "*").replace("SELECT * FROM guessed", f", exact AS ({sql.product('f1', 'f2')}) SELECT round(sqrt(sum(power(coalesce(x.v, 0) - coalesce(g.v_hat, 0), 2))) / sqrt(sum(power(coalesce(x.v, 0), 2))), 6) AS rel_frob FROM exact x FULL JOIN guessed g ON x.i = g.i AND x.j = g.j")
    return f"SELECT {lost} AS lost, {str(lost < 4).lower()} AS parity_decodes, rel_frob FROM ({body})"


@query(" UNION ALL ".join(_loss_sql(x) for x in (0, 2, 4, 5)))
def degradation_curve(spark, d):
    """Growing losses: the sketch loses accuracy and always answers; the parity grid fails once its losses are the corners of a rectangle."""
    a, b = _pair(spark, d)
    exact, k, out = multiply.multiply(a, b), N + 2, None
    corners = [(0, 0), (0, 1), (1, 0), (1, 1), (2, 2)]
    for lost in (0, 2, 4, 5):
        got = _rbs(spark, d, Policy("drop", lost), k)
        one = accuracy.rel_frobenius(exact, got).select(F.lit(lost).alias("lost"), F.lit(coded.decodes(corners[:lost], blocks_of(a.rows), blocks_of(b.cols))).alias("parity_decodes"), F.round("rel_frob", 6).alias("rel_frob"))
        out = one if out is None else out.union(one)
    return out


def _frob(got: str) -> str:
    return f"round(sqrt(sum(power(coalesce(x.v, 0) - coalesce(g.v_hat, 0), 2))) / sqrt(sum(power(coalesce(x.v, 0), 2))), 6) AS rel_frob FROM exact x FULL JOIN {got} g ON x.i = g.i AND x.j = g.j"


_SINGLE = f"""WITH {sql.family(1)}, {sql.with_('f1', 'f2')}, exact AS ({sql.product('f1', 'f2')}), sa AS ({sql.sketch('f1', 64)}), sb AS ({sql.sketch('f2', 64, 'c', 'i', 'j')}),
 g AS (SELECT a.i, b.j, CAST(sum(a.v * b.v) AS DOUBLE) AS v_hat FROM sa a JOIN sb b USING (k, h) WHERE a.h >= 16 GROUP BY 1, 2) SELECT 'single_minus_block' AS scheme, {_frob('g')}"""


@query(f"SELECT * FROM ({_SINGLE}) UNION ALL SELECT 'stacked_minus_slice' AS scheme, rel_frob FROM ({_loss_sql(1).replace(f'{N + 2}', f'{N + 2}')})")
def loss_single_vs_stacked(spark, d):
    """A quarter of one wide sketch lost, against one spare slice of a stack."""
    a, b = _pair(spark, d)
    exact = multiply.multiply(a, b)
    one = accuracy.rel_frobenius(exact, baselines.cs_multiply(a, b, 64, lost=(0, 16))).select(F.lit("single_minus_block").alias("scheme"), F.round("rel_frob", 6).alias("rel_frob"))
    two = accuracy.rel_frobenius(exact, _rbs(spark, d, Policy("drop", 1), N + 2)).select(F.lit("stacked_minus_slice").alias("scheme"), F.round("rel_frob", 6).alias("rel_frob"))
    return one.union(two)


@query(f"WITH {sql.family(1)}, {sql.with_('f1')}, pick(r, x) AS (VALUES {', '.join(f'({r}, {x})' for r, x in baselines.srht_rows(8, 2000))}) SELECT i, r, CAST(sum({sign_sql('c')} * v * (1 - 2 * (bit_count(CAST(c AS BIGINT) & CAST(x AS BIGINT)) % 2))) AS BIGINT) AS v FROM f1 CROSS JOIN fam CROSS JOIN pick GROUP BY 1, 2")
def srht_supplier(spark, d):
    return baselines.srht_sketch(sources.supplier_part(spark, d), 8)


@query()
def gaussian_supplier(spark, d):
    return baselines.gaussian_sketch(sources.supplier_part(spark, d), 8)


@query()
def gaussian_gram_error(spark, d):
    a = sources.supplier_part(spark, d)
    return accuracy.gram_rel_frobenius(a, baselines.gaussian_sketch(a, 64), 64)


@query(f"WITH {sql.with_('f1', 'f2')}, a AS (SELECT c, sum(v * v) AS s FROM f1 GROUP BY c), b AS (SELECT i AS c, sum(v * v) AS s FROM f2 GROUP BY i) SELECT c, round(sqrt(CAST(a.s AS DOUBLE) * b.s), 6) AS score FROM a JOIN b USING (c)")
def norm_scores(spark, d):
    return baselines.norm_scores(*_pair(spark, d)).select("c", F.round("score", 6).alias("score"))


@query()
def leverage_scores(spark, d):
    return baselines.leverage_scores(sources.supplier_part(spark, d))


@query()
def leverage_draws(spark, d):
    return baselines.draws(leverage_scores(spark, d), 64).select("d", "c")


@query()
def leverage_sample_product(spark, d):
    a, b = _pair(spark, d)
    return baselines.sampled_product(a, b, baselines.draws(baselines.leverage_scores(a), 128), 128)


@query()
def norm_sample_product(spark, d):
    a, b = _pair(spark, d)
    return baselines.sampled_product(a, b, baselines.draws(baselines.norm_scores(a, b), 128), 128)


@query(f"WITH {sql.family(1)}, {sql.with_('f1', 'f2')}, sa AS ({sql.sketch('f1', 64)}), sb AS ({sql.sketch('f2', 64, 'c', 'i', 'j')}) SELECT a.i, b.j, CAST(sum(a.v * b.v) AS DOUBLE) AS v_hat FROM sa a JOIN sb b USING (k, h) GROUP BY 1, 2")
def cs_product(spark, d):
    return baselines.cs_multiply(*_pair(spark, d), 64)


_VAR = f"""WITH {sql.with_('f1', 'f2')}, nx AS (SELECT i, sum(v * v) AS nx FROM f1 GROUP BY i), ny AS (SELECT c AS j, sum(v * v) AS ny FROM f2 GROUP BY c),
 pq AS (SELECT a.i, b.c AS j, sum(a.v * b.v) AS p, sum(a.v * a.v * b.v * b.v) AS q FROM f1 a JOIN f2 b ON a.c = b.i GROUP BY 1, 2)
 SELECT i, j, round((CAST(nx AS DOUBLE) * ny + CAST(coalesce(p, 0) AS DOUBLE) * coalesce(p, 0) - 2 * CAST(coalesce(q, 0) AS DOUBLE)) / 64, 3) AS var FROM nx CROSS JOIN ny LEFT JOIN pq USING (i, j)"""


@query(_VAR)
def variance_exact(spark, d):
    return accuracy.cell_variance(*_pair(spark, d), 64).select("i", "j", F.round("var", 3).alias("var"))


@query(f"""WITH {sql.with_('f1', 'f2')}, exact AS ({sql.product('f1', 'f2')}), n AS (SELECT CAST((SELECT sum(v * v) FROM f1) AS DOUBLE) AS na, CAST((SELECT sum(v * v) FROM f2) AS DOUBLE) AS nb, (SELECT sum(CAST(v AS DOUBLE) * v) FROM exact) AS nc,
 (SELECT sum(CAST(x.s AS DOUBLE) * y.s) FROM (SELECT c, sum(v * v) AS s FROM f1 GROUP BY c) x JOIN (SELECT i AS c, sum(v * v) AS s FROM f2 GROUP BY i) y USING (c)) AS q)
 SELECT round(sqrt((na * nb + nc - 2 * q) / 64 / nc), 6) AS rms_rel, round(sqrt(2 * na * nb / 64 / nc), 6) AS bound_rel FROM n""")
def expected_error(spark, d):
    a, b = _pair(spark, d)
    return accuracy.expected_error(a, b, multiply.multiply(a, b), 64).select(F.round("rms_rel", 6).alias("rms_rel"), F.round("bound_rel", 6).alias("bound_rel"))


@query()
def unbiased_over_seeds(spark, d):
    """Mean deviation of the estimated product from the exact one, over the norm, by the number of seeds averaged. All suppliers count."""
    a, b = _pair(spark, d)
    family, numbers = HashFamily(32, 7), (1, 4, 32)
    right = sketch.sketch_right(b, B, family).withColumnRenamed("v", "w")
    sums = [F.sum(F.when(F.col("k") < n, F.col("v")).otherwise(0)).cast("double") / n for n in numbers]
    slices = sketch.stacked_sketch(a, B, family).join(right, ["k", "h"]).select("i", "j", "k", (F.col("v") * F.col("w")).alias("v"), F.lit(0).cast("long").alias("x"))
    exact = _cells(multiply.multiply(a, b)).select("i", "j", F.lit(family.slices).alias("k"), F.lit(0).cast("long").alias("v"), F.col("v").alias("x"))
    cells = slices.unionByName(exact).groupBy("i", "j").agg(F.sum("x").cast("double").alias("x"), *(x.alias(f"n{n}") for n, x in zip(numbers, sums, strict=True)))
    whole = cells.agg(F.sum(F.col("x") * F.col("x")).alias("sq"), *(F.sum(F.pow(F.col("x") - F.col(f"n{n}"), 2)).alias(f"n{n}") for n in numbers))
    each = F.array(*(F.struct(F.lit(n).alias("seeds"), (F.sqrt(f"n{n}") / F.sqrt("sq")).alias("rel_frob")) for n in numbers))
    return whole.select(F.inline(each))


@query()
def spectral_eps(spark, d):
    a = sources.supplier_part(spark, d)
    s = accuracy.spectral_sq(a, 12)
    return a.frobenius_sq().select(F.lit(s).alias("sigma1_sq"), F.col("sq").alias("frobenius_sq"), (F.lit(s) / F.col("sq")).alias("share"))


@query()
def rbs_parity_reduction(spark, d):
    """Cells lost in the reduction of the sketched product, decoded from parity blocks on the sketches."""
    a, b = _pair(spark, d)
    lost = [(r, c) for r, c in PARITY_LOST if r <= blocks_of(a.rows) and c <= blocks_of(b.cols)]
    return multiply.rbs_parity_multiply(a, b, B, HashFamily(N), lost)


@query()
def failure_rate(spark, d):
    """The share of 20 sketches whose error lies above the promise for which the planner chose the width, with one spare ignored per cell."""
    eps, theta = 0.1, 0.2
    a = sources.supplier_part(spark, d)
    slices = planner.plan_dimension(eps, theta, B)[1] + 1
    alive = _losses(spark, a.rows, [1], lambda e: slices)
    errors = accuracy.errors_over_seeds(a, a.t, multiply.multiply(a, a.t), B, list(range(200, 220)), slices, alive, gram=True)
    got = errors.crossJoin(F.broadcast(a.frobenius_sq())).select("seed", (F.col("err_sq") / F.pow(F.col("sq").cast("double"), 2)).alias("eps"))
    return accuracy.failure_rate(got, eps, theta)


@query()
def leverage_sample_lossy(spark, d):
    """Eight blocks of 16 draws and a spare one; block 3 is lost."""
    a, b = _pair(spark, d)
    return baselines.lossy_sampled_product(a, b, baselines.leverage_scores(a), 8, 1, 16, [3])


# Costs --------------------------------------------------------------------------------------------------------------

_SIZES = "sizes AS (SELECT CAST(n AS BIGINT) AS n, CAST(n AS BIGINT) AS m, CAST(n AS BIGINT) AS l, floor(-n + sqrt(CAST(n AS DOUBLE) * n + 48000000)) AS a, CAST(4000 AS BIGINT) AS b, CAST(n // 2 + 4000 AS BIGINT) AS z FROM range(24000, 56001, 4000) AS s(n))"


def sizes(spark):
    n = F.col("id")
    a = F.floor(-n + F.sqrt(n.cast("double") * n + 48_000_000)).cast("double")
    return spark.range(24000, 56001, 4000).select(n.alias("n"), n.alias("m"), n.alias("l"), a.alias("a"), F.lit(4000).cast("long").alias("b"), (F.floor(n / 2) + 4000).alias("z"))


_MONTHS = f"{sql.ORDER_MONTHS}, sizes AS (SELECT c, n, n AS m, n AS l, floor(-n + sqrt(CAST(n AS DOUBLE) * n + 48000000)) AS a, CAST(4000 AS BIGINT) AS b, CAST(n // 2 + 4000 AS BIGINT) AS z FROM months)"


def month_sizes(spark, d):
    """As `sizes`, with a square product per month whose side is the number of its orders."""
    n = F.col("n")
    a = F.floor(-n + F.sqrt(n.cast("double") * n + 48_000_000)).cast("double")
    return sources.order_months(spark, d).select("c", n, n.alias("m"), n.alias("l"), a.alias("a"), F.lit(4000).cast("long").alias("b"), (F.floor(n / 2) + 4000).alias("z"))


@query(f"WITH {_MONTHS} SELECT c, n, round(2 * n * (CAST(m AS DOUBLE) * l) / a + CAST(m AS DOUBLE) * l, 3) AS band_entries, round(CAST(m AS DOUBLE) * l / (a * a), 6) AS band_messages FROM sizes")
def band_costs(spark, d):
    return costs.band_costs(month_sizes(spark, d)).select("c", "n", F.round("band_entries", 3).alias("band_entries"), F.round("band_messages", 6).alias("band_messages"))


@query(f"WITH {_MONTHS} SELECT c, n, round(3 * CAST(n AS DOUBLE) * m * l / b, 3) AS block_compute_entries, round(CAST(n AS DOUBLE) * m * l / b, 3) AS block_reduce_entries, round(CAST(n AS DOUBLE) * m * l / (CAST(b AS DOUBLE) * b * b), 6) AS block_compute_messages FROM sizes")
def block_costs(spark, d):
    return costs.block_costs(month_sizes(spark, d)).select("c", "n", *(F.round(c, x).alias(c) for c, x in (("block_compute_entries", 3), ("block_reduce_entries", 3), ("block_compute_messages", 6))))


def _ratio_frame(spark, d):
    """Inputs m = l = n^delta with memory 2n: bands of height 1 against blocks of side sqrt n, with n the number of orders of each month."""
    t = sources.order_months(spark, d).withColumn("delta", F.explode(F.array(*map(F.lit, (0.5, 1.0, 1.5)))))
    n, m = F.col("n").cast("double"), F.pow(F.col("n").cast("double"), F.col("delta"))
    band = (m * m, 2 * n * m * m)
    block = (n * m * m / F.pow(n, 1.5), 3 * n * m * m / F.sqrt(n))
    return t.withColumns({"latency_ratio": band[0] / block[0], "bandwidth_ratio": band[1] / block[1], "computation_ratio": F.lit(1.0)})


_RATIO = f"{sql.ORDER_MONTHS}, ratios AS (SELECT c, n, x AS delta, sqrt(CAST(n AS DOUBLE)) AS latency_ratio, sqrt(CAST(n AS DOUBLE)) * 2 / 3 AS bandwidth_ratio, 1.0 AS computation_ratio FROM months, (VALUES (CAST(0.5 AS DOUBLE)), (1.0), (1.5)) AS s(x))"


@query(f"WITH {_RATIO} SELECT c, n, delta, round(latency_ratio, 6) AS latency_ratio, round(bandwidth_ratio, 6) AS bandwidth_ratio, CAST(computation_ratio AS DOUBLE) AS computation_ratio FROM ratios")
def cost_ratio(spark, d):
    return _ratio_frame(spark, d).select("c", "n", "delta", F.round("latency_ratio", 6).alias("latency_ratio"), F.round("bandwidth_ratio", 6).alias("bandwidth_ratio"), "computation_ratio")


@query(f"WITH {_RATIO} SELECT delta, round(regr_slope(ln(latency_ratio), ln(n)), 6) AS latency_slope, round(regr_slope(ln(bandwidth_ratio), ln(n)), 6) AS bandwidth_slope FROM ratios GROUP BY delta")
def asymptotic_slopes(spark, d):
    """Slopes in the logarithm with memory 2n, where the ratio is sqrt n for every delta."""
    r = _ratio_frame(spark, d)
    return r.groupBy("delta").agg(*(F.round(F.regr_slope(F.log(f"{x}_ratio"), F.log(F.col("n").cast("double"))), 6).alias(f"{x}_slope") for x in ("latency", "bandwidth")))


@query("SELECT CAST(power(2, p) AS BIGINT) AS n, x AS delta, round(power(2, p * (1 - x / 2)), 6) AS ratio FROM range(10, 21) AS r(p), (VALUES (CAST(0.5 AS DOUBLE)), (1.0), (1.5)) AS s(x)")
def scaling_table(spark, d):
    """The published asymptotic ratio n^(1 - delta/2) of latency and bandwidth for memory n^delta."""
    t = spark.createDataFrame([(2**p, x) for p in range(10, 21) for x in (0.5, 1.0, 1.5)], "n long, delta double")
    return t.withColumn("ratio", F.round(F.pow(F.col("n").cast("double"), 1 - F.col("delta") / 2), 6))


@query(f"WITH {_SIZES} SELECT n, CAST((ceil(n / a) + 1) * (ceil(n / a) + 1) AS BIGINT) AS parity_workers, CAST((n // b) * (n // b) * ceil(z / CAST(b AS DOUBLE)) AS BIGINT) AS rbs_workers FROM sizes")
def vs_parity_workers(spark, d):
    s = costs.rbs_costs(sizes(spark))
    parity = F.pow(F.ceil(F.col("n") / F.col("a")) + 1, 2).cast("long")
    return s.select("n", parity.alias("parity_workers"), F.col("rbs_compute_tasks").cast("long").alias("rbs_workers"))


_DOLLARS = "round(ceil((x) * 10) * 0.000004897, 9)"


def _seconds(entries, flops, model):
    return model.worker_time(F.lit(3.0), entries, flops)


@query()
def vs_parity_cost(spark, d):
    """Dollars of the two schemes on modelled worker times: parity bands against sketch, compute and reduce tasks of the sketched product."""
    m = costs.CostModel()
    s = costs.rbs_costs(sizes(spark))
    n, a, b = F.col("n").cast("double"), F.col("a"), F.col("b").cast("double")
    grid = F.pow(F.ceil(n / a) + 1, 2)
    slices = F.ceil(F.col("z") / F.col("b"))
    one = m.dollars(1000 * _seconds(2 * a * n + a * a, 2 * a * a * n, m))
    compute = m.dollars(1000 * _seconds(3 * b * b, 2 * b * b * b, m))
    sketching = m.dollars(1000 * _seconds(b * n + b * b, b * n, m))
    reduce_ = m.dollars(1000 * _seconds((slices + 1) * b * b, slices * b * b, m))
    return s.select("n", (grid * one).alias("parity_dollars"), (F.col("rbs_compute_tasks") * compute + F.col("rbs_sketch_tasks") * sketching + F.col("rbs_reduce_tasks") * reduce_).alias("rbs_dollars"))


@query("SELECT CAST(56000 AS BIGINT) AS n, CAST(4096 AS BIGINT) AS p, CAST(power(2, q) AS BIGINT) AS c, round(power(2, q) * 56000.0 * 56000 / 4096, 3) AS memory_entries, round(56000.0 * 56000 / sqrt(power(2, q) * 4096), 3) AS moved_entries, round(sqrt(4096 / power(8, q)) + q, 6) AS messages FROM range(0, 5) AS r(q)")
def replication_costs(spark, d):
    got = costs.replicated_costs(spark.createDataFrame([(56_000, 4096, 2**q) for q in range(5)], "n long, p long, c long"))
    return got.select("n", "p", "c", *(F.round(x, r).alias(x) for x, r in (("memory_entries", 3), ("moved_entries", 3), ("messages", 6))))


@query()
def band_vs_block_tasks(spark, d):
    """Tasks with work and entries moved to them, by bands of 16 and by blocks of 16, counted on supplier x part times part x month."""
    a, b = _pair(spark, d)
    tall, wide = blocks_of(a.rows), blocks_of(b.cols)
    band = lambda m, key, copies: m.df.agg((F.count("*") * copies).alias("entries"), F.countDistinct((F.col(key) / B).cast("int")).alias("bands"))
    bands = band(a, "i", wide).crossJoin(band(b, "c", tall).toDF("right", "others")).select(F.lit("band").alias("scheme"), (F.col("bands") * F.col("others")).alias("tasks"), (F.col("entries") + F.col("right")).alias("entries"))
    block = lambda m, x, y: m.df.groupBy((F.col(x) / B).cast("int").alias(x), (F.col(y) / B).cast("int").alias(y)).count()
    left, right = block(a, "i", "c"), block(b, "i", "c").toDF("c", "j", "n")
    blocks = left.join(right, "c").agg(F.count("*").alias("tasks"), F.sum(F.col("count") + F.col("n")).alias("entries")).select(F.lit("block").alias("scheme"), "tasks", "entries")
    return bands.union(blocks)


@query()
def dollars_sweep(spark, d):
    """Exact square products in dollars: bands against blocks, both filling a worker's memory."""
    m = costs.CostModel()
    n = F.col("n").cast("double")
    a = F.col("a")
    b = F.floor(F.sqrt(F.lit(m.memory_entries / 3.0)))
    s = month_sizes(spark, d)
    band = F.ceil(n / a) * F.ceil(n / a) * m.dollars(1000 * _seconds(2 * a * n + a * a, 2 * a * a * n, m))
    block = F.pow(F.ceil(n / b), 3) * m.dollars(1000 * _seconds(3 * b * b, 2 * b * b * b, m)) + F.pow(F.ceil(n / b), 2) * m.dollars(1000 * _seconds(F.ceil(n / b) * b * b, F.ceil(n / b) * b * b, m))
    return s.select("c", "n", band.alias("band_dollars"), block.alias("block_dollars"))


@query()
def vs_parity_error(spark, d):
    """Mean error over ten sketches of the product of x + y and x * y with z = n/2 + b and e = 1, by n; the parity scheme is exact while it decodes."""
    out = None
    for k in range(6, 15):
        n = k * XY
        a, b = generated(spark, n, n, lambda x, y: x + y), generated(spark, n, n, lambda x, y: x * y)
        slices = math.ceil((n / 2 + XY) / XY)
        errors = accuracy.errors_over_seeds(a, b, multiply.multiply(a, b), XY, list(range(42, 42 + SKETCHES)), slices, _dropped(spark, n, n, [1], slices, XY))
        one = errors.groupBy(F.lit(n).alias("n")).agg(F.avg(F.sqrt(F.col("err_sq") / F.col("exact_sq"))).alias("rel_frob"))
        out = one if out is None else out.union(one)
    return out


@query("SELECT * FROM (VALUES ('sketch', 600), ('compute', 3000), ('reduce', 100), ('lp_sketch', 100), ('lp_compute', 500), ('lp_reduce', 25)) AS t(phase, tasks)")
def task_counts(spark, d):
    c = planner.task_counts(10 * 2048, 60 * 2048, 10 * 2048, 2048, 30 * 2048)
    lp = planner.task_counts(5000, 40000, 5000, 1000, 20000)
    rows = [(k, c[k]) for k in ("sketch", "compute", "reduce")] + [("lp_sketch", lp["sketch"] // 2), ("lp_compute", lp["compute"]), ("lp_reduce", lp["reduce"])]
    return spark.createDataFrame(rows, "phase string, tasks int")


@query(f"WITH {sql.EVENT_LOG} SELECT CAST(sum(ceil(t_ms / 100.0)) AS BIGINT) AS units, round(sum(ceil(t_ms / 100.0)) * 0.000004897, 6) AS dollars FROM tasks")
def job_dollars(spark, d):
    got = costs.dollars(sources.event_log(spark, d), costs.CostModel())
    return got.select(F.col("units").cast("long").alias("units"), F.round("dollars", 6).alias("dollars"))


@query("SELECT CAST(eps AS DOUBLE) AS eps, CAST(theta AS DOUBLE) AS theta, CAST(ceil(round(2 / (eps * theta), 9) / 16) * 16 AS BIGINT) AS d, CAST(ceil(round(2 / (eps * theta), 9) / 16) AS BIGINT) AS slices, CAST(ceil(round(0.05 * ceil(round(2 / (eps * theta), 9) / 16), 9)) AS BIGINT) AS spares FROM (VALUES (CAST(0.1 AS DOUBLE)), (0.2), (0.05)) AS a(eps), (VALUES (CAST(0.1 AS DOUBLE)), (0.5), (1.0)) AS b(theta)")
def plan_table(spark, d):
    rows = []
    for eps in (0.1, 0.2, 0.05):
        for theta in (0.1, 0.5, 1.0):
            w, n = planner.plan_dimension(eps, theta, 16)
            rows.append((eps, theta, w, n, planner.plan_spares(n)))
    return spark.createDataFrame(rows, "eps double, theta double, d long, slices long, spares long")


@query()
def plan_choice(spark, d):
    """For pairs of pivots: sizes, which exact scheme, and whether a sketch of 4 slices of 16 and one spare would do less work."""
    f1, f2, f4 = sources.supplier_part(spark, d), sources.part_month(spark, d), sources.user_hour(spark, d)
    rows = []
    for name, a, b in (("supplier_month", f1, f2), ("supplier_gram", f1, f1.t), ("user_gram", f4, f4.t), ("sum_gram", xy_pair(spark), xy_pair(spark).t)):
        s = planner.stats(a, b)
        rows.append((name, s.m, s.n, s.l, s.nnz_a, s.nnz_b, s.products, planner.plan_multiply(s), planner.sketch_pays(s, N, 1, B)))
    return spark.createDataFrame(rows, "pair string, m long, n long, l long, nnz_a long, nnz_b long, products long, scheme string, sketch_pays boolean")


@query("SELECT 40 AS n, 2 AS e, round(2.0 / 40, 6) AS redundancy")
def redundancy_5pct(spark, d):
    return spark.createDataFrame([(40, planner.plan_spares(40), round(2 / 40, 6))], "n int, e int, redundancy double")


@query("SELECT CAST(power(4, p) AS BIGINT) AS n, power(4, p) AS band_ops, power(8, p) AS block_ops FROM range(3, 11) AS r(p)")
def work_per_task(spark, d):
    t = spark.createDataFrame([(4**p,) for p in range(3, 11)], "n long")
    band, block = costs.work_per_task(F.col("n"))
    return t.select("n", band.alias("band_ops"), block.alias("block_ops"))


@query(f"WITH {sql.EVENT_LOG}, {sql.survivors('t_ms <= 21600000 OR r <= 1')} SELECT bi, bj, count(*) AS n_survivors, count(*) * 16 AS width FROM alive GROUP BY 1, 2")
def effective_dimension(spark, d):
    s = straggler.survivors(sources.event_log(spark, d), Policy("deadline", 21_600_000, 1))
    return s.groupBy("bi", "bj").agg(F.count("*").alias("n_survivors"), (F.count("*") * 16).alias("width"))
