"""Workloads of the operators around the products: matrix algebra, joins, windows, sets, functions, formats."""

from __future__ import annotations

import os
import tempfile

import pandas as pd
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import sources
from ..functions.hashing import HashFamily, bucket_sql, sign_sql
from ..operators import multiply, sketch
from ..operators.matrix import CoordMatrix, bounded, identity, numbered
from ..plans import expr
from . import sql

QUERIES, ORACLES = {}, {}


def query(oracle: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if oracle:
            ORACLES[key] = oracle
        return f

    return add


def _w(*names: str, rest: str) -> str:
    return f"WITH {sql.with_(*names)} {rest}"


@query(_w("f3", rest="SELECT c AS i, i AS c, v FROM f3"))
def mat_transpose(spark, d):
    return sources.customer_month(spark, d).t.df


@query(_w("f3", rest="SELECT i, c, 3 * v AS v FROM f3"))
def mat_scale(spark, d):
    return sources.customer_month(spark, d).scale(3).df


@query("WITH a AS (SELECT user_id AS i, CAST(day(ts) - 1 AS BIGINT) AS c, count(*) AS v FROM events WHERE event_type = (SELECT min(event_type) FROM events) GROUP BY 1, 2), b AS (SELECT user_id AS i, CAST(day(ts) - 1 AS BIGINT) AS c, count(*) AS v FROM events GROUP BY 1, 2) SELECT i, c, CAST(sum(v) AS BIGINT) AS v FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY 1, 2")
def mat_add(spark, d):
    e = sources.load(spark, d, "events")
    first = e.agg(F.min("event_type").alias("t"))
    some = e.join(F.broadcast(first), F.col("event_type") == F.col("t"))
    day = F.dayofmonth("ts") - 1
    return CoordMatrix.of(some, "user_id", day, shape=(10**9, 31)).add(CoordMatrix.of(e, "user_id", day, shape=(10**9, 31))).df


@query(_w("f1", rest=", g AS (SELECT l_suppkey AS i, l_partkey AS c, count(*) AS v FROM lineitem GROUP BY 1, 2) SELECT i, c, f1.v * g.v AS v FROM f1 JOIN g USING (i, c)"))
def mat_hadamard(spark, d):
    n = CoordMatrix.of(sources.load(spark, d, "lineitem"), "l_suppkey", "l_partkey")
    return sources.supplier_part(spark, d).hadamard(n).df


@query(_w("f1", rest="SELECT i, c, v * s_nationkey AS v FROM f1 JOIN supplier ON i = s_suppkey"))
def mat_diag_scale(spark, d):
    s = sources.load(spark, d, "supplier").select(F.col("s_suppkey").alias("i"), F.col("s_nationkey").cast("long").alias("s"))
    return sources.supplier_part(spark, d).diag_scale(s).df


@query(_w("f1", rest="SELECT i, CAST(sum(v * p_size) AS BIGINT) AS y FROM f1 JOIN part ON c = p_partkey GROUP BY 1"))
def mat_vec(spark, d):
    x = sources.load(spark, d, "part").select(F.col("p_partkey").alias("c"), F.col("p_size").cast("long").alias("x"))
    return sources.supplier_part(spark, d).matvec(x)


@query(_w("f1", rest="SELECT i, CAST(sum(v * v) AS BIGINT) AS sq FROM f1 GROUP BY 1"))
def mat_row_norms(spark, d):
    return sources.supplier_part(spark, d).row_norms()


@query(_w("f1", rest="SELECT c, CAST(sum(v * v) AS BIGINT) AS sq FROM f1 GROUP BY 1"))
def mat_col_norms(spark, d):
    return sources.supplier_part(spark, d).col_norms()


@query(_w("f1", rest="SELECT CAST(sum(v * v) AS DOUBLE) AS sq FROM f1"))
def mat_frobenius(spark, d):
    return sources.supplier_part(spark, d).frobenius_sq()


@query(_w("f1", rest="SELECT CAST(coalesce(sum(v), 0) AS BIGINT) AS trace FROM f1 WHERE i = c"))
def mat_trace(spark, d):
    return sources.supplier_part(spark, d).trace()


@query(_w("f1", rest="SELECT i - 5 AS i, c - 10 AS c, v FROM f1 WHERE i BETWEEN 5 AND 24 AND c BETWEEN 10 AND 99"))
def mat_slice(spark, d):
    return sources.supplier_part(spark, d).slice(5, 25, 10, 100).df


@query(_w("f3", "f4", rest="SELECT i, c, v FROM f3 UNION ALL SELECT i + (SELECT max(i) + 1 FROM f3), c, v FROM f4"))
def mat_concat(spark, d):
    return sources.customer_month(spark, d).below(sources.user_hour(spark, d)).df


@query(_w("f3", rest="SELECT i, i AS c, CAST(1 AS BIGINT) AS v FROM f3 GROUP BY i"))
def mat_identity(spark, d):
    """The identity on the customers that have orders."""
    x = sources.customer_month(spark, d)
    return identity(x.df, "i", x.rows).df


_CHAIN = _w("f4", rest=f", g AS ({sql.gram('f4')}) SELECT g.i, b.c, CAST(sum(g.v * b.v) AS BIGINT) AS v FROM g JOIN f4 b ON g.j = b.i GROUP BY 1, 2")


@query(_CHAIN)
def mat_chain(spark, d):
    """X X^T X through the expression tree, which chooses the order."""
    x = expr.Leaf("x", sources.user_hour(spark, d))
    return expr.lower(expr.optimise(x @ x.t @ x)).df


@query(_w("f4", rest="SELECT a.i, b.i AS c, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM f4 a JOIN f4 b ON a.c = b.c WHERE a.i < 40 GROUP BY 1, 2"))
def gram_filtered_rows(spark, d):
    """A filter on result rows goes below the product."""
    x = expr.Leaf("x", sources.user_hour(spark, d))
    return expr.lower(expr.optimise(expr.RowFilter(x @ x.t, "i < 40"))).df


@query(_w("f4", rest=sql.gram("f4").replace("AS j", "AS c")))
def gram_events(spark, d):
    x = expr.Leaf("x", sources.user_hour(spark, d))
    return expr.lower(expr.optimise(x @ x.t)).df


_TOKENS = "tokens AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+')) AS term FROM documents), counted AS (SELECT doc_id, term, count(*) AS v FROM tokens WHERE term <> '' AND regexp_full_match(term, '[a-z]+') GROUP BY 1, 2), top AS (SELECT term, row_number() OVER (ORDER BY sum(v) DESC, term) - 1 AS c FROM counted GROUP BY term QUALIFY c < 200)"


def doc_term(spark, d, top: int = 200) -> CoordMatrix:
    """Counts of plain ASCII terms by document, over the `top` most frequent terms."""
    t = sources.load(spark, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[ \\t\\n\\r]+")).alias("term")).filter(F.col("term").rlike("^[a-z]+$"))
    counted = t.groupBy("doc_id", "term").agg(F.count("*").alias("v"))
    ranked = counted.groupBy("term").agg(F.sum("v").alias("n")).orderBy(F.desc("n"), "term").limit(top)
    terms = ranked.withColumn("c", F.row_number().over(W.orderBy(F.desc("n"), "term")) - 1).select("term", "c")
    return CoordMatrix.of(counted.join(F.broadcast(terms), "term"), "doc_id", "c", "v")


@query(f"WITH {_TOKENS} SELECT doc_id AS i, CAST(c AS BIGINT) AS c, CAST(v AS BIGINT) AS v FROM counted JOIN top USING (term)")
def doc_term_matrix(spark, d):
    return doc_term(spark, d).df


@query(f"WITH {_TOKENS}, x AS (SELECT doc_id, c, v FROM counted JOIN top USING (term)) SELECT CAST(a.c AS BIGINT) AS i, CAST(b.c AS BIGINT) AS c, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM x a JOIN x b USING (doc_id) GROUP BY 1, 2")
def gram_terms(spark, d):
    x = doc_term(spark, d)
    return multiply.multiply(x.t, x).df


_ROLES = "words AS (SELECT role, unnest(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+')) AS term FROM conversations), rc AS (SELECT role, term, count(*) AS v FROM words WHERE term <> '' GROUP BY 1, 2)"


@query(f"WITH {_ROLES}, ids AS (SELECT role, row_number() OVER (ORDER BY role) - 1 AS i FROM (SELECT DISTINCT role FROM rc)) SELECT CAST(x.i AS BIGINT) AS i, CAST(y.i AS BIGINT) AS c, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM rc a JOIN ids x USING (role) JOIN rc b ON a.term = b.term JOIN ids y ON y.role = b.role GROUP BY 1, 2")
def gram_roles(spark, d):
    t = sources.load(spark, d, "conversations").select("role", F.explode(F.split(F.lower("text"), "[ \\t\\n\\r]+")).alias("term")).filter("term <> ''")
    counted = t.groupBy("role", "term").agg(F.count("*").alias("v"))
    roles, terms = numbered(counted, "role", "i"), numbered(counted, "term", "c")
    x = CoordMatrix.of(counted.join(bounded(roles), "role").join(terms, "term"), "i", "c", "v")
    return multiply.multiply(x, x.t).df


@query("WITH t AS (SELECT page_id, unnest(regexp_extract_all(lower(html), '<([a-z0-9]+)', 1)) AS tag FROM pages), n AS (SELECT page_id, tag, count(*) AS v FROM t GROUP BY 1, 2), k AS (SELECT tag, row_number() OVER (ORDER BY tag) - 1 AS c FROM (SELECT DISTINCT tag FROM n)) SELECT CAST(x.c AS BIGINT) AS i, CAST(y.c AS BIGINT) AS c, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM n a JOIN k x USING (tag) JOIN n b ON a.page_id = b.page_id JOIN k y ON y.tag = b.tag GROUP BY 1, 2")
def gram_tags(spark, d):
    t = sources.load(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all(F.lower("html"), F.lit("<([a-z0-9]+)"), 1)).alias("tag"))
    tags = numbered(t, "tag", "c")
    x = CoordMatrix.of(t.join(bounded(tags), "tag"), "page_id", "c")
    return multiply.multiply(x.t, x).df


# Joins ----------------------------------------------------------------------------------------------------------------

_JOIN = "SELECT o_custkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _join(spark, d, hint: str):
    line, orders = sources.load(spark, d, "lineitem"), sources.load(spark, d, "orders").select("o_orderkey", "o_custkey")
    orders = bounded(orders, otherwise="merge") if hint == "broadcast" else orders.hint(hint)
    return line.join(orders, line["l_orderkey"] == orders["o_orderkey"]).groupBy("o_custkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("q"))


for _hint in ("broadcast", "shuffle_hash", "merge"):
    query(_JOIN, f"join_{_hint}")(lambda spark, d, h=_hint: _join(spark, d, h))


@query(_w("f4", rest="SELECT coalesce(a.i, b.i) AS i, coalesce(a.v, 0) AS early, coalesce(b.v, 0) AS late FROM (SELECT i, CAST(sum(v) AS BIGINT) AS v FROM f4 WHERE c < 24 GROUP BY 1) a FULL JOIN (SELECT i, CAST(sum(v) AS BIGINT) AS v FROM f4 WHERE c >= 696 GROUP BY 1) b ON a.i = b.i"))
def full_outer_fill(spark, d):
    x = sources.user_hour(spark, d).df
    early, late = x.filter("c < 24").groupBy("i").agg(F.sum("v").alias("early")), x.filter("c >= 696").groupBy("i").agg(F.sum("v").alias("late"))
    return early.join(late, "i", "full").select("i", F.coalesce("early", F.lit(0).cast("long")).alias("early"), F.coalesce("late", F.lit(0).cast("long")).alias("late"))


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def survivor_semi(spark, d):
    o = sources.load(spark, d, "orders").filter("o_orderstatus = 'F'").select(F.col("o_custkey").alias("c_custkey"))
    return sources.load(spark, d, "customer").join(o, "c_custkey", "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def lost_anti(spark, d):
    o = sources.load(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return sources.load(spark, d, "customer").join(o, "c_custkey", "left_anti").select("c_custkey")


@query("SELECT CAST(a.r AS INT) AS bi, CAST(b.r AS INT) AS bj, CAST(c.r AS INT) AS k FROM range(0, 7) a(r), range(0, 6) b(r), range(0, 5) c(r)")
def task_grid(spark, d):
    grid = lambda n, name: spark.range(n).select(F.col("id").cast("int").alias(name))
    return grid(7, "bi").crossJoin(grid(6, "bj")).crossJoin(grid(5, "k"))


@query("SELECT event_id, user_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS earlier FROM events")
def asof_events(spark, d):
    """Of each event, the last earlier one of its user."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return sources.load(spark, d, "events").select("event_id", "user_id", F.lag("event_id").over(w).alias("earlier"))


@query("SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 60 DAY GROUP BY 1")
def interval_ship(spark, d):
    line, orders = sources.load(spark, d, "lineitem"), sources.load(spark, d, "orders")
    near = F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("interval 60 days"))
    return line.join(orders, (F.col("l_orderkey") == F.col("o_orderkey")) & near).groupBy("l_orderkey").agg(F.count("*").alias("n"))


# Aggregates and windows ---------------------------------------------------------------------------------------------------


@query("SELECT l_suppkey, CAST(sum(CASE WHEN l_returnflag = 'A' AND l_linestatus = 'F' THEN CAST(l_quantity AS BIGINT) END) AS BIGINT) AS a_f, CAST(sum(CASE WHEN l_returnflag = 'N' AND l_linestatus = 'O' THEN CAST(l_quantity AS BIGINT) END) AS BIGINT) AS n_o, CAST(sum(CASE WHEN l_returnflag = 'R' AND l_linestatus = 'F' THEN CAST(l_quantity AS BIGINT) END) AS BIGINT) AS r_f FROM lineitem GROUP BY 1")
def pivot_flag_status(spark, d):
    line = sources.load(spark, d, "lineitem").withColumn("fs", F.lower(F.concat_ws("_", "l_returnflag", "l_linestatus")))
    return line.groupBy("l_suppkey").pivot("fs", ["a_f", "n_o", "r_f"]).agg(F.sum(F.col("l_quantity").cast("long")))


@query("SELECT l_suppkey AS i, k AS flag, CAST(sum(q) AS BIGINT) AS v FROM (SELECT l_suppkey, l_returnflag AS k, CAST(l_quantity AS BIGINT) AS q FROM lineitem) GROUP BY 1, 2")
def unpivot_flags(spark, d):
    wide = sources.load(spark, d, "lineitem").groupBy("l_suppkey").pivot("l_returnflag", ["A", "N", "R"]).agg(F.sum(F.col("l_quantity").cast("long")))
    return wide.unpivot(["l_suppkey"], ["A", "N", "R"], "flag", "v").filter("v is not null").withColumnRenamed("l_suppkey", "i")


@query("SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS g, CAST(sum(CAST(l_quantity AS BIGINT) * CAST(l_quantity AS BIGINT)) AS BIGINT) AS mass FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def norm_cube(spark, d):
    q = F.col("l_quantity").cast("long")
    return sources.load(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.sum(q * q).alias("mass"))


@query(_w("f1", rest="SELECT CAST(i // 16 AS INT) AS bi, CAST(c // 16 AS INT) AS bj, CAST(sum(v * v) AS BIGINT) AS mass FROM f1 GROUP BY ROLLUP (CAST(i // 16 AS INT), CAST(c // 16 AS INT))"))
def error_rollup(spark, d):
    x = sources.supplier_part(spark, d).df
    return x.select((F.col("i") / 16).cast("int").alias("bi"), (F.col("c") / 16).cast("int").alias("bj"), "v").rollup("bi", "bj").agg(F.sum(F.col("v") * F.col("v")).alias("mass"))


@query(_w("f1", rest="SELECT count(*) AS nnz, count(DISTINCT i) AS n_rows, count(DISTINCT c) AS n_cols, max(v) AS top FROM f1"))
def matrix_stats(spark, d):
    return sources.supplier_part(spark, d).df.agg(F.count("*").alias("nnz"), F.countDistinct("i").alias("n_rows"), F.countDistinct("c").alias("n_cols"), F.max("v").alias("top"))


@query(_w("f1", rest=", n AS (SELECT i, CAST(sum(v * v) AS BIGINT) AS sq FROM f1 GROUP BY 1) SELECT i, sq, CAST(rank() OVER (ORDER BY sq DESC) AS INT) AS rk, CAST(dense_rank() OVER (ORDER BY sq DESC) AS INT) AS dr, CAST(ntile(4) OVER (ORDER BY sq DESC, i) AS INT) AS nt, round(percent_rank() OVER (ORDER BY sq DESC), 6) AS pr FROM n"))
def rank_rows(spark, d):
    w = W.orderBy(F.desc("sq"))
    n = sources.supplier_part(spark, d).row_norms()
    return n.select("i", "sq", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(W.orderBy(F.desc("sq"), "i")).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query(_w("f1", rest=", n AS (SELECT c, CAST(sum(v * v) AS BIGINT) AS sq FROM f1 GROUP BY 1) SELECT c, CAST(sum(sq) OVER (ORDER BY c ROWS UNBOUNDED PRECEDING) AS BIGINT) AS cum FROM n"))
def leverage_cdf(spark, d):
    """Running sums of column norms, by prefix sums of chunks of columns."""
    n = sources.supplier_part(spark, d).col_norms().withColumn("chunk", F.floor(F.col("c") / 256))
    per = n.groupBy("chunk").agg(F.sum("sq").alias("t"))
    ahead = per.select("chunk", F.coalesce(F.sum("t").over(W.orderBy("chunk").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("ahead"))
    within = F.sum("sq").over(W.partitionBy("chunk").orderBy("c").rowsBetween(W.unboundedPreceding, 0))
    return n.join(F.broadcast(ahead), "chunk").select("c", (within + F.col("ahead")).cast("long").alias("cum"))


_G = sql.gram("f1")


@query(_w("f1", rest=f", g AS ({_G}) SELECT i, j, v FROM g WHERE i < j ORDER BY v DESC, i, j LIMIT 20"))
def topk_cells(spark, d):
    a = sources.supplier_part(spark, d)
    g = multiply.multiply(a, a.t).df.select("i", F.col("c").alias("j"), "v")
    return g.filter("i < j").orderBy(F.desc("v"), "i", "j").limit(20)


@query(_w("f1", rest=f", g AS ({_G}) SELECT i, j, v FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS r FROM g WHERE i <> j) WHERE r <= 3"))
def topk_per_row(spark, d):
    a = sources.supplier_part(spark, d)
    g = multiply.multiply(a, a.t).df.select("i", F.col("c").alias("j"), "v").filter("i <> j")
    return g.withColumn("r", F.row_number().over(W.partitionBy("i").orderBy(F.desc("v"), "j"))).filter("r <= 3").drop("r")


_SETS = {"union": "UNION ALL", "intersect": "INTERSECT ALL", "except": "EXCEPT ALL"}
for _name, _op in _SETS.items():

    @query(f"SELECT l_suppkey AS i, l_partkey AS c FROM lineitem WHERE l_returnflag = 'A' {_op} SELECT l_suppkey, l_partkey FROM lineitem WHERE l_returnflag = 'N'", f"pattern_{_name}_all")
    def _setop(spark, d, name=_name):
        x = sources.load(spark, d, "lineitem")
        a, b = (x.filter(F.col("l_returnflag") == f).select(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("c")) for f in "AN")
        return {"union": a.unionByName, "intersect": a.intersectAll, "except": a.exceptAll}[name](b)


@query("SELECT l_suppkey AS i, l_partkey AS c FROM lineitem WHERE l_returnflag = 'A' INTERSECT SELECT l_suppkey, l_partkey FROM lineitem WHERE l_returnflag = 'N'")
def pattern_setops(spark, d):
    x = sources.load(spark, d, "lineitem")
    a, b = (x.filter(F.col("l_returnflag") == f).select(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("c")) for f in "AN")
    return a.intersect(b)


@query("SELECT l_orderkey, l_quantity, l_shipmonth FROM (SELECT l_orderkey, l_quantity, CAST(date_trunc('month', l_shipdate) AS DATE) AS l_shipmonth, l_returnflag, l_discount FROM lineitem) WHERE (l_quantity BETWEEN 10 AND 12 OR l_quantity IN (1, 50)) AND l_returnflag <> 'N' AND l_discount IS NOT NULL")
def filtered_lines(spark, d):
    x = sources.load(spark, d, "lineitem")
    keep = (F.col("l_quantity").between(10, 12) | F.col("l_quantity").isin(1, 50)) & (F.col("l_returnflag") != "N") & F.col("l_discount").isNotNull()
    return x.filter(keep).select("l_orderkey", "l_quantity", F.to_date(F.date_trunc("month", "l_shipdate")).alias("l_shipmonth"))


# Functions ----------------------------------------------------------------------------------------------------------------


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS sq, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top FROM embeddings")
def embedding_norms(spark, d):
    e = sources.load(spark, d, "embeddings")
    sq = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.round(sq, 6).alias("sq"), F.round(F.array_max("embedding").cast("double"), 6).alias("top"))


@query(_w("f4", rest="SELECT a.i, CAST(coalesce(sum(a.v * b.v), 0) AS BIGINT) AS dot FROM f4 a LEFT JOIN (SELECT c, v FROM f4 WHERE i = 0) b USING (c) GROUP BY 1"))
def sparse_row_dot(spark, d):
    """Rows as maps; the dot product of each row with row 0."""
    rows = sources.user_hour(spark, d).df.groupBy("i").agg(F.map_from_entries(F.collect_list(F.struct("c", "v"))).alias("m"))
    zero = rows.filter("i = 0").select(F.col("m").alias("z"))
    zipped = F.map_zip_with("m", "z", lambda k, a, b: F.coalesce(a, F.lit(0)) * F.coalesce(b, F.lit(0)))
    return rows.crossJoin(F.broadcast(zero)).select("i", F.aggregate(F.map_values(zipped), F.lit(0).cast("long"), lambda s, x: s + x).alias("dot"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, event_type FROM events")
def json_index(spark, d):
    e = sources.load(spark, d, "events")
    return e.select("event_id", F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))["k"].alias("k"), "event_type")


@query(_w("f1", rest="SELECT i, c, v FROM f1 WHERE (c * 2654435761 + i * 40503) % 1000 < 100"))
def hash_sample(spark, d):
    return sources.supplier_part(spark, d).df.filter("(c * 2654435761 + i * 40503) % 1000 < 100")


@query("SELECT label, round(avg(x), 6) AS mean_dot FROM (SELECT label, list_dot_product(CAST(embedding AS DOUBLE[]), CAST((SELECT embedding FROM embeddings WHERE vec_id = 0) AS DOUBLE[])) AS x FROM embeddings) GROUP BY label")
def udf_dot(spark, d):
    import numpy as np

    e = sources.load(spark, d, "embeddings")
    first = F.broadcast(e.filter("vec_id = 0").select(F.col("embedding").alias("z")))

    @F.pandas_udf("double")
    def dot(x: pd.Series, z: pd.Series) -> pd.Series:
        return pd.Series(np.einsum("ij,ij->i", np.stack(x).astype(float), np.stack(z).astype(float)) if len(x) else [])

    return e.crossJoin(first).select("label", dot("embedding", "z").alias("x")).groupBy("label").agg(F.round(F.avg("x"), 6).alias("mean_dot"))


@query(_w("f1", rest="SELECT CAST(i // 16 AS INT) AS bi, round(sqrt(sum(v * v)), 6) AS norm FROM f1 GROUP BY 1"))
def udaf_norm(spark, d):
    @F.pandas_udf("double")
    def norm(v: pd.Series) -> float:
        return float((v.astype(float) ** 2).sum() ** 0.5)

    x = sources.supplier_part(spark, d).df.withColumn("bi", (F.col("i") / 16).cast("int"))
    return x.groupBy("bi").agg(F.round(norm("v"), 6).alias("norm"))


@query(f"WITH {sql.family(2)}, {sql.with_('f4')} SELECT i, k, {bucket_sql('c', 16)} AS h, CAST(sum({sign_sql('c')} * v) AS BIGINT) AS v FROM f4 CROSS JOIN fam GROUP BY 1, 2, 3")
def udtf_sketch(spark, d):
    """Sketch entries from a table function called with LATERAL."""
    rows = HashFamily(2).rows
    from ..functions.hashing import P

    @F.udtf(returnType="k int, h int, sv bigint")
    class SketchEntries:
        def eval(self, c: int, v: int):
            for k, u1, u0, w3, w2, w1, w0 in rows:
                q = (((w3 * c + w2) % P * c + w1) % P * c + w0) % P
                yield k, (u1 * c + u0) % P % 16, (1 - 2 * (q % 2)) * v

    spark.udtf.register("sketch_entries", SketchEntries)
    sources.user_hour(spark, d).df.createOrReplaceTempView("user_hour_entries")
    return spark.sql("SELECT i, k, h, sum(sv) AS v FROM user_hour_entries, LATERAL sketch_entries(c, v) GROUP BY i, k, h")


@query(f"WITH {sql.family(5)}, {sql.with_('f1', 'f2')}, sa AS ({sql.sketch('f1', 16)}), sb AS ({sql.sketch('f2', 16, 'c', 'i', 'j')}) SELECT a.i, b.j, CAST(sum(a.v * b.v) AS DOUBLE) / 5 AS v_hat FROM sa a JOIN sb b USING (k, h) GROUP BY 1, 2")
def sql_rbs(spark, d):
    """The sketched product in SQL, with bucket and sign as SQL functions."""
    sources.supplier_part(spark, d).df.createOrReplaceTempView("f1_entries")
    sources.part_month(spark, d).df.createOrReplaceTempView("f2_entries")
    HashFamily(5).frame(spark).createOrReplaceTempView("fam_rows")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bs_bucket(c BIGINT, u1 BIGINT, u0 BIGINT) RETURNS INT RETURN {bucket_sql('c', 16)}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bs_sign(c BIGINT, w3 BIGINT, w2 BIGINT, w1 BIGINT, w0 BIGINT) RETURNS BIGINT RETURN {sign_sql('c')}")
    return spark.sql("""
      WITH sa AS (SELECT i, k, bs_bucket(c, u1, u0) AS h, sum(bs_sign(c, w3, w2, w1, w0) * v) AS v FROM f1_entries CROSS JOIN fam_rows GROUP BY 1, 2, 3),
           sb AS (SELECT c AS j, k, bs_bucket(i, u1, u0) AS h, sum(bs_sign(i, w3, w2, w1, w0) * v) AS v FROM f2_entries CROSS JOIN fam_rows GROUP BY 1, 2, 3)
      SELECT sa.i, sb.j, CAST(sum(sa.v * sb.v) AS DOUBLE) / 5 AS v_hat FROM sa JOIN sb ON sa.k = sb.k AND sa.h = sb.h GROUP BY 1, 2""")


_DENSE = _w("f4", rest="SELECT i, CAST(sum(v * (c + 1)) AS BIGINT) AS weighed FROM f4 GROUP BY 1")


@query(_DENSE)
def pack_blocks(spark, d):
    """Packed into dense blocks of 64 x 128, unpacked, and weighed by column."""
    x = sources.user_hour(spark, d)
    back = CoordMatrix.from_blocks(x.to_blocks(64, 128), x.rows, x.cols, 64, 128)
    return back.df.groupBy("i").agg(F.sum(F.col("v").cast("long") * (F.col("c") + 1)).alias("weighed"))


@query(_DENSE)
def dense_rows(spark, d):
    x = sources.user_hour(spark, d)
    at = x.dense_rows().select("i", F.posexplode("row").alias("c", "v"))
    return at.filter("v <> 0").groupBy("i").agg(F.sum(F.col("v").cast("long") * (F.col("c") + 1)).alias("weighed"))


def _scratch(spark) -> str:
    place = spark.conf.get("spark.checkpoint.dir", None)
    return f"{place}/bs-{os.urandom(6).hex()}" if place else tempfile.mkdtemp(prefix="bs-")


for _fmt in sources.FORMATS:

    @query(sql.PIVOTS["f3"], f"round_trip_{_fmt}")
    def _round_trip(spark, d, fmt=_fmt):
        x = sources.customer_month(spark, d)
        path = f"{_scratch(spark)}/{fmt}"
        sources.save(x, path, fmt)
        return sources.read(spark, path, fmt, x.rows, x.cols).df


@query(f"WITH {sql.family(3)}, {sql.with_('f1')}, s AS ({sql.sketch('f1', 16)}) SELECT i, k, h, v FROM s WHERE i // 16 = 1")
def partitioned_sketch(spark, d):
    """A sketch kept by row block; reading one block prunes the others."""
    s = sketch.stacked_sketch(sources.supplier_part(spark, d), 16, HashFamily(3)).withColumn("bi", (F.col("i") / 16).cast("int"))
    path = f"{_scratch(spark)}/sketch"
    sources.save_blocks(s, path)
    return spark.read.parquet(path).filter("bi = 1").select("i", "k", "h", "v")


@query(_w("f4", rest="SELECT i, CAST(count(*) AS BIGINT) AS n FROM f4 GROUP BY 1"))
def arrow_round_trip(spark, d):
    got = sources.user_hour(spark, d).df.toArrow()
    return spark.createDataFrame(got).groupBy("i").agg(F.count("*").alias("n"))


