"""All queries of the catalogue against their SQL, at the smallest size."""

import math

import duckdb
import pytest

from splitsort import catalogue
from splitsort.sources import TABLES


@pytest.fixture(scope="module")
def db(sf_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def canon(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    return repr(round(v, 6) + 0.0) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", list(catalogue.QUERIES))
def test_query(spark, sf_dir, db, name):
    out = catalogue.QUERIES[name](spark, sf_dir)
    cols = sorted(out.columns)
    got = sorted(tuple(map(canon, r)) for r in out.select(*cols).collect())
    if name not in catalogue.ORACLES:
        assert got
        return
    ref = db.execute(catalogue.ORACLES[name])
    names = [d[0] for d in ref.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    assert got == sorted(tuple(canon(r[i]) for i in at) for r in ref.fetchall())


def test_join_interval_takes_all_events(spark, sf_dir, db):
    """Pairs of events past the first 300 are there."""
    out = catalogue.QUERIES["join_interval"](spark, sf_dir)
    late = out.where("left_id >= 300 AND right_id >= 300").count()
    spans = "SELECT event_id, user_id, epoch_us(ts) // 1000000 AS a FROM events WHERE event_id >= 300"
    assert late == db.sql(f"SELECT count(*) FROM ({spans}) x JOIN ({spans}) y ON abs(x.a - y.a) < 600 AND x.user_id < y.user_id").fetchall()[0][0] > 0
