"""Registered queries against their SQL twins."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = list(entry.registry.oracle_sql())


@pytest.fixture(scope="module")
def db():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def canon(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    cell = lambda v: "" if v is None or (isinstance(v, float) and math.isnan(v)) else repr(v + 0.0) if isinstance(v, float) else str(v)
    return sorted(columns), sorted(tuple(cell(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, db, name):
    df = entry.registry.queries()[name](spark, SF)
    rel = db.sql(entry.registry.oracle_sql()[name])
    assert canon(df.columns, [tuple(r) for r in df.collect()]) == canon(rel.columns, rel.fetchall())


MEASURED = ["rel_sql_functions", *(f"planner_{x}" for x in ("best_b", "sample_size")), *(f"theory_{x}" for x in "chance_mass floor_slope fold_storage gain_equal gain_limit gain_onebit headlines inflation match_prob".split())]


@pytest.mark.parametrize("name", MEASURED)
def test_closed_forms_read_events(spark, name):
    """Before, these queries made their parameters up and read no table."""
    files = entry.queries()[name](spark, SF).inputFiles()
    assert files and all(f.endswith("/events.parquet") for f in files)


def test_entry(spark):
    df = entry.entry(spark)
    assert {"r_hat", "r_exact"} <= set(df.columns) and df.count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
