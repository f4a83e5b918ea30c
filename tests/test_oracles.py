"""Every registered core query against its DuckDB SQL on the smallest tables; a query without SQL must give rows."""

import os

import duckdb
import pytest

from snippetclones.plans import contract

DIR = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    return c


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(r[i] for i in order) for r in data), key=repr)


@pytest.mark.parametrize("name", sorted(contract.QUERIES))
def test_query(spark, duck, name):
    df = contract.QUERIES[name](spark, DIR)
    got = rows(df.columns, [tuple(r) for r in df.collect()])
    if name in contract.ORACLE:
        cur = duck.execute(contract.ORACLE[name])
        want = rows([c[0] for c in cur.description], cur.fetchall())
        assert len(got) == len(want)
        for a, b in zip(got, want, strict=True):
            assert all(x == y or (isinstance(x, float) and isinstance(y, float) and abs(x - y) < 2e-6) for x, y in zip(a, b, strict=True)), (a, b)
    else:
        assert got or name in {"nm_components"}
