"""The driver's contract, and every SQL-checked query on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from curvature_spark.sources.catalog import TABLES

FAST = [
    "fused_oracle", "logit_hessian", "engine_oracle", "quad_least_squares", "compress_topk", "compress_tight", "hsn_rounds_windowk", "hsn_pp_rounds",
    "feature_star_onehot", "feature_text_hash", "join_asof", "join_interval", "join_range", "agg_salted", "win_range_between", "stream_tumbling",
]


@pytest.fixture(scope="module")
def con(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{small}/{t}.parquet')")
    return con


def test_entry_gives_a_round_log(spark):
    rows = entry.entry(spark).collect()
    assert rows and rows[-1]["grad_norm"] < 1e-9


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", FAST)
def test_query_equals_sql(spark, con, small, name):
    df = entry.queries()[name](spark, small)
    got = sorted(map(str, ({c: r[c] for c in sorted(df.columns)} for r in df.collect())))
    rel = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in rel.description]
    want = sorted(map(str, ({c: v for c, v in sorted(zip(names, row, strict=True))} for row in rel.fetchall())))
    assert sorted(df.columns) == sorted(names) and got == want
