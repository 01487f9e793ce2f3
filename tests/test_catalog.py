"""Queries against their DuckDB counterparts on the smallest tables."""

import duckdb
import pytest
from lexfold.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def db(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def rows(data, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(str(r[i]) for i in order) for r in data)


@pytest.mark.parametrize("name", sorted(catalog.ORACLE))
def test_equals_sql(spark, sf, db, name):
    got = catalog.QUERIES[name](spark, sf)
    want = db.sql(catalog.ORACLE[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got.collect(), got.columns) == rows(want.fetchall(), want.columns)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLE)))
def test_runs(spark, sf, name):
    rows = catalog.QUERIES[name](spark, sf).collect()
    assert rows or name == "legend_confusable_pairs"


def test_local_legends_are_smaller_for_small_shards(spark, sf):
    """One legend for all is paid by every shard, so it loses as shards get smaller."""
    got = {(r.mode, r["count"], r.corpus): r.cr_input for r in catalog.QUERIES["local_vs_global_legend"](spark, sf).collect()}
    corpora = {c for _, _, c in got}
    assert len(corpora) == 14
    worse = [c for c in corpora if got["global", 125, c] < got["local", 125, c] - 1e-9]
    assert len(worse) >= 5 and all(got["global", 125, c] <= got["global", 2000, c] + 1e-9 for c in corpora)


def test_flagship(spark, sf):
    d = catalog.flagship(spark, sf).collect()
    assert len(d) == 14 * 3 and all(r.cr_input <= r.cr + 1e-9 and r.cr_input >= 0 for r in d)
