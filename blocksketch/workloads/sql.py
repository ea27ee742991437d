"""SQL text that the oracles share: the pivots, sketches and estimators, over the registered tables."""

from __future__ import annotations

from ..functions.hashing import HashFamily, bucket_sql, sign_sql
from ..operators.straggler import log_duck

PIVOTS = {
    "f1": "SELECT l_suppkey AS i, l_partkey AS c, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2",
    "f2": "SELECT l_partkey AS i, CAST((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1 AS BIGINT) AS c, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2",
    "f3": "SELECT o_custkey AS i, CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS BIGINT) AS c, count(*) AS v FROM orders GROUP BY 1, 2",
    "f4": "SELECT user_id AS i, CAST((day(ts) - 1) * 24 + hour(ts) AS BIGINT) AS c, count(*) AS v FROM events GROUP BY 1, 2",
    "f5": "SELECT CAST(r AS BIGINT) AS i, CAST(json_extract_string(props, '$.k') AS BIGINT) AS c, count(*) AS v FROM events JOIN (SELECT event_type, dense_rank() OVER (ORDER BY event_type) - 1 AS r FROM (SELECT DISTINCT event_type FROM events)) USING (event_type) GROUP BY 1, 2",
    "f6": "SELECT vec_id AS i, CAST(d - 1 AS BIGINT) AS c, CAST(floor(CAST(embedding[d] AS DOUBLE) * 1000 + 0.5) AS BIGINT) AS v FROM embeddings, range(1, 65) AS r(d)",
}


#: Events as tasks, the SQL of sources.event_log, and the numbers of orders by month.
EVENT_LOG = "gaps AS (SELECT CAST(user_id // 16 AS INT) AS bi, CAST(day(ts) - 1 AS INT) AS bj, event_id AS k, CAST(date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) // 1000 AS BIGINT) AS t_ms FROM events), tasks AS (SELECT * FROM gaps WHERE t_ms IS NOT NULL)"
ORDER_MONTHS = "months AS (SELECT CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS BIGINT) AS c, count(*) AS n FROM orders GROUP BY 1)"


def with_(*names: str) -> str:
    """WITH clauses of the pivots."""
    return ", ".join(f"{n} AS ({PIVOTS[n]})" for n in names)


def product(a: str, b: str, extra: str = "") -> str:
    """Cells (i, j, v) of a times b."""
    return f"SELECT a.i, b.c AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {a} a JOIN {b} b ON a.c = b.i {extra} GROUP BY 1, 2"


def gram(a: str) -> str:
    return f"SELECT a.i, b.i AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {a} a JOIN {a} b ON a.c = b.c GROUP BY 1, 2"


def sketch(a: str, width: int, kept: str = "i", contracted: str = "c", alias: str = "i") -> str:
    """(kept, k, h, v)."""
    return f"SELECT {kept} AS {alias}, k, {bucket_sql(contracted, width)} AS h, CAST(sum({sign_sql(contracted)} * v) AS BIGINT) AS v FROM {a} CROSS JOIN fam GROUP BY 1, 2, 3"


def family(slices: int, seed: int = 42) -> str:
    return HashFamily(slices, seed).values_sql()


def log(bi: int, bj: int, k: int, seed: int = 1) -> str:
    return f"tasks AS ({log_duck(bi, bj, k, seed)})"


def survivors(condition: str) -> str:
    """Tasks by rank within their cell; condition on r (rank), n (tasks of the cell), t_ms."""
    return f"alive AS (SELECT bi, bj, k, t_ms FROM (SELECT *, row_number() OVER (PARTITION BY bi, bj ORDER BY t_ms, k) AS r, count(*) OVER (PARTITION BY bi, bj) AS n FROM tasks) WHERE {condition})"


def estimate(left: str, right: str, width: int) -> str:
    """(i, j, v_hat, n_survivors) from left(i, k, h, v), right(j, k, h, v) and alive."""
    return f"""parts AS (SELECT CAST(a.i // {width} AS INT) AS bi, CAST(b.j // {width} AS INT) AS bj, a.k, a.i, b.j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM {left} a JOIN {right} b USING (k, h) GROUP BY 1, 2, 3, 4, 5),
    number AS (SELECT bi, bj, count(*) AS n_survivors FROM alive GROUP BY 1, 2),
    guessed AS (SELECT i, j, CAST(sum(v) AS DOUBLE) / n_survivors AS v_hat, n_survivors FROM parts SEMI JOIN alive USING (bi, bj, k) JOIN number USING (bi, bj) GROUP BY i, j, n_survivors)"""
