"""Every workload with an oracle gives DuckDB's rows."""

import pytest

from chapterforge import workloads

ORACLES = workloads.oracle_sql()


def cells(frame, columns):
    show = lambda v: f"{v:.6f}" if isinstance(v, float) else str(int(v)) if isinstance(v, bool) else str(v)
    return sorted(tuple(map(show, r)) for r in frame[columns].itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_oracle(spark, duck, data, name):
    ours, theirs = workloads.queries()[name](spark, data).toPandas(), duck.execute(ORACLES[name]).fetchdf()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert cells(ours, sorted(ours.columns)) == cells(theirs, sorted(ours.columns))


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 3
