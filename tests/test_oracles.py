"""Every registered query of the library: with SQL it has to match, without it has to run."""

import os

import duckdb
import pytest

from metricblock.queries.all import ORACLE_SQL, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Covered by the trend tests, which run them smaller.
SLOW = {n for n in QUERIES if n.startswith("exp_")} | {"dedup_iterative", "dedup_approx", "match_approx"}


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{os.path.join(sf, t)}.parquet'")
    return c


def rounded(v):
    return round(v, 5) if isinstance(v, float) else v


@pytest.mark.parametrize("name", sorted(set(QUERIES) - SLOW))
def test_query(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    rows = df.collect()
    if name not in ORACLE_SQL:
        assert df.columns
        return
    cursor = duck.execute(ORACLE_SQL[name])
    columns = [d[0] for d in cursor.description]
    assert sorted(columns) == sorted(df.columns)
    expected = sorted((tuple(rounded(r[columns.index(c)]) for c in sorted(columns)) for r in cursor.fetchall()), key=repr)
    got = sorted((tuple(rounded(r[c]) for c in sorted(columns)) for r in rows), key=repr)
    assert got == expected
