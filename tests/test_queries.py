"""Every registered query with SQL against DuckDB on the smallest tables."""

import os

import duckdb
import pytest

from conftest import SMALL
from sessionlens import catalogue

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    return con


def shown(row):
    return repr([round(v, 5) if isinstance(v, float) else v if isinstance(v, int | str | bool | type(None) | list) else str(v) for v in row])


#: The others run where all are asked for, with ALL_QUERIES=1.
FEW = ("clean_full", "cleaning_report", "sess_gap_24h", "sess_duration_30m", "sess_soft", "retention", "feat_dwell", "kmeans_3iter", "fcm_3iter", "fcm_validity", "join_asof", "win_frames", "stream_session_duration", "chain_report", "chain_vectors", "fcm_sweep_fixed", "fcm_3iter_hard", "fcm_3iter_none", "sess_compare", "sess_duration_24h", "stream_scores", "stream_late", "users_auto", "prune_long_tail", "null_fns", "math_fns")


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()) if os.environ.get("ALL_QUERIES") else FEW)
def test_query_is_its_sql(spark, duck, name):
    df = catalogue.queries()[name](spark, SMALL)
    columns = sorted(df.columns)
    rel = duck.execute(catalogue.oracle_sql()[name])
    names = [d[0] for d in rel.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert sorted(map(shown, df.select(*columns).collect())) == sorted(shown([r[i] for i in at]) for r in rel.fetchall())
