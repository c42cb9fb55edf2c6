"""Every registered query of the engine against its SQL, on the smallest tables."""

import math

import pytest

from fieldpress import registry

QUERIES, SQL = dict(registry.QUERIES), dict(registry.SQL)


def cell(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if isinstance(v, float):
        return round(v, 9)
    return v


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query_matches_sql(spark, duck, sf, name):
    df = QUERIES[name](spark, sf)
    got = df.collect()
    if name not in SQL:
        assert got
        return
    o = duck.execute(SQL[name])
    names = [d[0] for d in o.description]
    assert sorted(names) == sorted(df.columns)
    order = sorted(df.columns)
    key = lambda r: tuple((x is not None, str(x)) for x in r)
    a = sorted((tuple(cell(r[c]) for c in order) for r in got), key=key)
    b = sorted((tuple(cell(r[names.index(c)]) for c in order) for r in o.fetchall()), key=key)
    assert a == b
