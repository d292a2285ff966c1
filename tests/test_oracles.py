"""Every registered query against its SQL in DuckDB, on the smallest tables."""

from __future__ import annotations

import math
from pathlib import Path

import pytest

from eigenlake.queries import ORACLES, QUERIES

SF = Path("/root/testdata/sf0.001")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: The distributed solver takes half a minute; its parts are tested alone and it runs in test_products.
SLOW = {"eigs_distributed", "eigs_gram_implicit", "eigs_grid"}
#: The shift of this oracle's power iteration suits the spectrum of a larger table.
LARGER = {"laplacian_low"}


@pytest.fixture(scope="module")
def duck():
    duckdb = pytest.importorskip("duckdb")
    if not SF.exists():
        pytest.skip("no test tables here")
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return c


def canonical(rows: list, columns: list[str]) -> list:
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    text = lambda v: "nan" if isinstance(v, float) and math.isnan(v) else repr(v)
    return sorted(tuple(text(r[k]) for k in order) for r in rows)


@pytest.mark.parametrize("name", [n for n in QUERIES if n in ORACLES and n not in SLOW | LARGER])
def test_query_equals_sql(spark, duck, name):
    df = QUERIES[name](spark, str(SF))
    want = duck.sql(ORACLES[name])
    columns = [d[0] for d in want.description]
    assert sorted(df.columns) == sorted(columns)
    assert canonical([tuple(r) for r in df.collect()], df.columns) == canonical(want.fetchall(), columns)


def test_queries_without_sql_run(spark):
    for name in set(QUERIES) - set(ORACLES):
        assert QUERIES[name](spark, str(SF)).count() > 0
