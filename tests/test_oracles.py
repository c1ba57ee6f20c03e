"""Every registered query runs; those with SQL give what DuckDB gives on the same tables."""

import decimal

import duckdb
import pytest

from reelspark import registry

registry.load()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"m_time_to_playback", "m_ttp", "m_speedup", "m_full_time", "m_fps_by_res"}  # clocks over queries that are tested by themselves


@pytest.fixture(scope="module")
def db(sf_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def plain(v):
    return float(v) if isinstance(v, decimal.Decimal) else v


def order(row):
    return tuple((v is None, str(v)) for v in row)


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_equals_sql(spark, sf_dir, db, name):
    df = registry.QUERIES[name](spark, sf_dir)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=order)
    rel = db.sql(registry.ORACLES[name])
    assert sorted(rel.columns) == cols
    at = [rel.columns.index(c) for c in cols]
    assert got == sorted((tuple(plain(r[i]) for i in at) for r in rel.fetchall()), key=order)


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES) - SLOW))
def test_runs(spark, sf_dir, name):
    df = registry.QUERIES[name](spark, sf_dir)
    assert df.count() > 0


def test_all_settings_render_the_same(spark, sf_dir):
    assert len({r["digest"] for r in registry.QUERIES["m_exact_settings"](spark, sf_dir).collect()}) == 1
