"""Every query that SQL can express, against DuckDB; the others must run and keep their schema."""

import pytest

from tests.oracle import same
from tidegate import registry

SF = "/root/testdata/sf0.001"
QUERIES, ORACLES = registry.queries(), registry.oracle_sql()
#: queries without an oracle that may be empty
MAY_BE_EMPTY = {"r9_rate_source"}


def folder(name: str) -> str:
    """Whole runs take fewer, longer iterations on the next larger tables."""
    return "/root/testdata/sf0.01" if name.endswith("_run") or name[0] in "xm" and name not in ("x9_marks_by_cut",) else SF


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_matches_sql(spark, name):
    same(QUERIES[name](spark, folder(name)), folder(name), ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, name):
    rows = QUERIES[name](spark, folder(name)).toPandas()
    assert len(rows.columns) and (len(rows) or name in MAY_BE_EMPTY)
    if "stopped" in rows.columns:  # whole runs end by patience, or say why not
        assert set(rows.stopped) <= {"patience", "diverged", "crashed"}
        done = rows[rows.stopped == "patience"]
        assert (done.iterations > 0).all() and (done.minutes > 0).all() and (done.independence >= 0.9).all() and (done.calls > done.iterations).all()
