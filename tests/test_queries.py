"""Every query of the catalogue against its SQL twin on the smallest tables."""

import math

import duckdb
import pytest

from codist.plans import queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    held = duckdb.connect()
    for t in TABLES:
        held.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return held


def plain(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    cell = lambda x: round(x, 9) + 0.0 if isinstance(x, float) and math.isfinite(x) else x
    return [columns[i] for i in order], sorted(str(tuple(cell(r[i]) for i in order)) for r in rows)


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_query(spark, sf, con, name):
    df = queries.QUERIES[name](spark, sf)
    got = plain([tuple(r) for r in df.collect()], df.columns)
    if name not in queries.ORACLES:
        assert got[1]
        return
    held = con.execute(queries.ORACLES[name])
    columns = [d[0] for d in held.description]
    assert got == plain(held.fetchall(), columns)


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_values_of_events_are_tokens(spark, sf, con):
    """Every value that is not null is in one bucket."""
    held = queries.QUERIES["q_events_value_tokens"](spark, sf).where("f LIKE 'value=%'").agg({"tf": "sum"}).first()[0]
    assert held == con.execute("SELECT count(value) FROM events").fetchone()[0]


def test_no_word_is_cut(spark, sf, con):
    """The flagship query, the solvers and the queries named whole see words after the fifth."""
    import __spark_entry__ as entry

    count = "SELECT count(*) FROM (SELECT unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9]+')) FROM documents)"
    (words,), (features,) = con.execute(count).fetchone(), con.execute(f"SELECT count(DISTINCT f) FROM ({queries.LANG}) WHERE sample_id % 5 <> 0").fetchone()
    assert queries.QUERIES["q_lines_roundtrip_whole"](spark, sf).agg({"total": "sum"}).first()[0] == words
    assert queries.QUERIES["q_lbfgs"](spark, sf).first()["features"] == features
    assert queries.QUERIES["q_params_iter3"](spark, sf).count() == features
    assert sorted(map(tuple, entry.entry(spark).collect())) == sorted(map(tuple, queries.QUERIES["q_curve_lang31"](spark, sf).collect()))
