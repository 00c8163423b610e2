"""Every query with an oracle gives the oracle's rows."""

from functools import lru_cache
from pathlib import Path

import duckdb
import pytest

from relanom import registry

SF = "/root/testdata/sf0.01"


@lru_cache(1)
def connection():
    con = duckdb.connect()
    for p in Path(SF).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    return con


def rows(names, values):
    order = sorted(range(len(names)), key=lambda i: names[i])
    clean = lambda v: None if v != v else v
    return sorted(str([clean(r[i]) for i in order]) for r in values)


@pytest.mark.parametrize("name", sorted(registry.oracles()))
def test_oracle(spark, name):
    got = registry.queries()[name](spark, SF)
    cursor = connection().execute(registry.oracles()[name])
    names = [d[0] for d in cursor.description]
    assert sorted(got.columns) == sorted(names)
    want = rows(names, cursor.fetchall())
    found = rows(got.columns, [tuple(r) for r in got.collect()])
    assert len(found) == len(want) and len(want) > 0
    assert found == want
