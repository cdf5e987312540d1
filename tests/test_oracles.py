"""Every query with SQL against DuckDB on the smallest tables."""

import datetime
from collections import Counter

import duckdb
import pytest

from discourselab import workloads

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def norm(v):
    if v is None or isinstance(v, float) and v != v:
        return "null"
    if isinstance(v, float):
        return repr(round(v, 6) + 0.0)
    return v.isoformat(" ") if isinstance(v, datetime.datetime) else str(v)


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(workloads.oracle_sql()))
def test_query_equals_sql(spark, small, duck, name):
    df = workloads.queries()[name](spark, small)
    columns = sorted(df.columns)
    found = Counter(tuple(norm(r[c]) for c in columns) for r in df.collect())
    rel = duck.sql(workloads.oracle_sql()[name])
    assert sorted(rel.columns) == columns
    at = [rel.columns.index(c) for c in columns]
    assert found == Counter(tuple(norm(r[i]) for i in at) for r in rel.fetchall())


def test_every_query_but_the_named_ones_has_sql():
    without = set(workloads.queries()) - set(workloads.oracle_sql())
    assert without == {"w37_louvain_month", "w37b_louvain_weighted", "w37c_louvain_joins", "w37d_label_propagation", "w52_density_clusters"}


def test_entry_has_rows(spark, small):
    assert workloads.entry(spark, small).count() == 10
