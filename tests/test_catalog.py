"""Registered queries of the tensor engine against their SQL in DuckDB."""

import math

import duckdb
import pyarrow.parquet as pq
import pytest
from pyspark.errors import AnalysisException

from multiway.catalog import ORACLE, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Whole experiments take minutes; the driver runs them, tests of methods cover their parts.
SLOW = ("_recover", "fit_table", "cluster_", "two_stage", "replica_noise", "grids_", "random_numbers", "sampling_")

#: Needs 6,000 events, of which the smallest tables have 1,000: held against SQL on the next larger ones.
LARGER = ("claims_baselines_w4_200",)


def views(folder):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return c


@pytest.fixture(scope="module")
def sql(sf):
    return views(sf)


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 5) + 0.0)
    return v.isoformat()[:19] if hasattr(v, "isoformat") else str(v)


@pytest.mark.parametrize("name", [n for n in ORACLE if n not in LARGER and not any(s in n for s in SLOW)])
def test_query_equals_sql(spark, sf, sql, name):
    df = QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted("|".join(plain(r[c]) for c in columns) for r in df.collect())
    cursor = sql.execute(ORACLE[name])
    names = [c[0] for c in cursor.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert got == sorted("|".join(plain(r[k]) for k in at) for r in cursor.fetchall())


@pytest.mark.parametrize("name", LARGER)
def test_larger_query_equals_sql(spark, name):
    test_query_equals_sql(spark, "/root/testdata/sf0.01", views("/root/testdata/sf0.01"), name)


@pytest.mark.parametrize("name", ["sst_recover", "tst_recover", "dst_lazy_recover", "ccp_hals_recover", "amr_recover"])
def test_recovery_equals_sql(spark, sf, sql, name):
    test_query_equals_sql(spark, sf, sql, name)


#: Queries that once made their data up.
FROM_TABLES = ("claims_huge_w7_generated", "cost_model", "cross_gram", "gaussian_moments", "gram", "gram_hadamard", "gram_rows", "huge_w7_generated", "ind2sub_grid", "khatri_rao", "kronecker")


@pytest.mark.parametrize("name", FROM_TABLES)
def test_query_needs_its_tables(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path)).collect()


@pytest.mark.parametrize("first, then", [("claims_huge_w7_generated", "huge_w7_generated"), ("huge_w7_generated", "claims_huge_w7_generated")])
def test_query_reads_its_tables_after_another(spark, sf, tmp_path, first, then):
    """Nothing is left of what the query beside it found: it fails where the orders have gone, and sees those that have come."""
    orders = pq.read_table(f"{sf}/orders.parquet")
    pq.write_table(orders, tmp_path / "orders.parquet")
    QUERIES[first](spark, str(tmp_path)).collect()
    pq.write_table(orders.slice(0, 1000), tmp_path / "orders.parquet")
    assert {r["config"] for r in QUERIES["huge_w7_generated"](spark, str(tmp_path)).collect()} == {"25^4 R=10"}
    (tmp_path / "orders.parquet").unlink()
    with pytest.raises(AnalysisException):
        QUERIES[then](spark, str(tmp_path)).collect()
