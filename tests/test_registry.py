"""A sample of registered queries against DuckDB."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", ["chunk_256", "knn_l2", "knn_l2_blocked", "pq_adc_topk", "ivf_search_np4", "bm25_topk", "hub_prune_exact", "csr_pack", "shard_merge_capped", "token_f1", "interleaved_full_alpha", "search_buffered", "events_session"])
def test_oracle(spark, sf, duck, name):
    got = entry.queries()[name](spark, sf).toPandas()
    want = duck.sql(entry.oracle_sql()[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    rows = lambda f: sorted(map(tuple, f[cols].astype(str).to_numpy()))
    assert rows(got) == rows(want)


def test_flagship(spark):
    assert entry.entry(spark).count() > 0


def test_names_match():
    assert set(entry.oracle_sql()) <= set(entry.queries())
