"""A few queries against their SQL; the driver compares all of them."""

import duckdb
import pytest

from vecengine import registry

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.mark.parametrize("name", ["exact_knn_l2", "pvq_encode_4", "recall_pv8", "prune_alpha12", "asof_last_event", "stream_mean", "memory_ratio_table"])
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DIR}/{t}.parquet')")
    df = registry.QUERIES[name](spark, DIR)
    cols = sorted(df.columns)
    got = sorted(tuple(r[c] for c in cols) for r in df.collect())
    want = sorted(con.execute(f"SELECT {', '.join(chr(34) + c + chr(34) for c in cols)} FROM ({registry.ORACLE_SQL[name]})").fetchall())
    assert got == want
