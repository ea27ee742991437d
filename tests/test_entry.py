import duckdb
import pytest
from helpers import DATA

import __spark_entry__ as entry
from blocksketch import workloads

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns == ["i", "j", "v", "v_hat", "rel_error"] and df.count() > 0


def test_every_oracle_has_a_query():
    assert set(workloads.oracle_sql()) <= set(workloads.queries())
    assert len(workloads.queries()) > 100


def rows(cols, data):
    def norm(v):
        return None if v is None or v != v else round(float(v), 6) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    return sorted((tuple(norm(r[c]) for c in sorted(cols)) for r in data), key=str)


#: One of each kind here; the driver compares all of them.
@pytest.mark.parametrize("name", ["block_supplier_month", "sketch_supplier_part", "norm_cube", "topk_per_row", "lp_step_gradient", "stream_tumbling", "sql_rbs", "mat_chain"])
def test_oracles(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{DATA}/{t}.parquet'")
    got = workloads.queries()[name](spark, DATA)
    want = con.execute(workloads.oracle_sql()[name])
    names = [c[0] for c in want.description]
    assert sorted(names) == sorted(got.columns)
    assert rows(got.columns, [r.asDict() for r in got.collect()]) == rows(names, [dict(zip(names, r, strict=True)) for r in want.fetchall()])
