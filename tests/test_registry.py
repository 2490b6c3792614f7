import os

import duckdb
import pytest
from freshview import registry

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in os.listdir(D):
        con.execute(f"create view {t.split('.')[0]} as select * from '{D}/{t}'")
    return con


@pytest.mark.parametrize("name", ["k1_sequence_key", "h1_key_hash_lines", "p10_full_outer_join", "r2_change_table_refresh", "r5_join_delta_sample", "e_median_all_answers", "i5_correction_interval", "i11_bootstrap_correction", "o14_correction_with_outliers", "w2_v13_sample"])
def test_query_equals_sql(spark, duck, name):
    df = registry.queries()[name](spark, D)
    cols = sorted(df.columns)
    cursor = duck.execute(registry.oracle_sql()[name])
    names = [c[0] for c in cursor.description]
    assert sorted(names) == cols

    def rows(values, order):
        plain = lambda v: round(v, 3) if isinstance(v, float) else v
        return sorted((tuple(plain(r[order.index(c)]) for c in cols) for r in values), key=repr)

    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(cursor.fetchall(), names)


def test_every_sql_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries()) and len(registry.queries()) > 100
