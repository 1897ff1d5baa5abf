"""The driver contract, and queries against DuckDB on the smallest tables."""

import math

import duckdb
import pytest

import __spark_entry__ as entry_module
from relcodec.sources.tables import TABLES

SF = "/root/testdata/sf0.001"
FAST = ["contingency_counts", "contingency_grouping_sets", "cumulative_masses", "lineitem_codes", "code_length_bound", "delta_bits_lineitem", "objective_pairs", "categorical_breakdown", "roundtrip_orders", "roundtrip_customer", "roundtrip_events",
        "lossy_roundtrip_orders", "markov_chain_bits", "pairwise_copy_bits", "fn_bits", "stream_dedup", "archive_source_scan", "random_access_orders", "prefix_decode_lineitem", "arith_example_codes"]


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if hasattr(v, "isoformat"):
        return str(v)[:26]
    return round(float(v), 4) if type(v).__name__ in ("Decimal", "float") else v


def test_entry_runs(spark):
    assert entry_module.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


@pytest.mark.parametrize("name", FAST)
def test_query_matches_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = entry_module.queries()[name](spark, SF)
    got = sorted((tuple(plain(r[c]) for c in sorted(df.columns)) for r in df.collect()), key=str)
    rel = con.sql(entry_module.oracle_sql()[name])
    columns = rel.columns
    want = sorted((tuple(plain(dict(zip(columns, r, strict=True))[c]) for c in sorted(columns)) for r in rel.fetchall()), key=str)
    assert sorted(df.columns) == sorted(columns) and got == want
