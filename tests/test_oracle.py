"""Every engine query with a DuckDB counterpart gives the same rows."""

import os

import duckdb
import pytest

from wavemotif import catalog
from wavemotif.sources import views as V

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"create view {f.removesuffix('.parquet')} as select * from '{SF}/{f}'")
    return c


def norm(v):
    return tuple(map(norm, v)) if isinstance(v, (list, tuple)) else repr(v) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_same_rows(spark, con, name):
    df = catalog.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(map(norm, r)) for r in df.select(*cols).collect())
    r = con.execute(catalog.oracle_sql()[name])
    names = [c[0] for c in r.description]
    want = sorted(tuple(norm(row[names.index(c)]) for c in cols) for row in r.fetchall())
    assert sorted(names) == cols
    assert got == want


@pytest.mark.parametrize("method", ["all", "cftree", "hash", "parallel", "cf_shards"])
def test_planted_shapes_are_found(spark, method):
    """A fixture of the runs up to 30: both shapes are found; two pulses look like themselves 12 steps on, so only the step is precise."""
    big = "/root/testdata/sf0.01"
    rows, truth = (v(spark, big).where("series_id <= 30") for v in (V.planted_view, V.planted_truth))
    runs = rows.select("series_id").distinct().count()
    got = {r["shape"]: r for r in catalog.planted_quality(rows, truth, 25, method=method).collect()}
    assert set(got) == {"held_step", "two_pulses"}
    assert all(r.instances == 5 * runs and r.recall >= 0.8 for r in got.values()) and got["held_step"].precision >= 0.8
