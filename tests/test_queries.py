"""Every query against its SQL on the smallest tables, and its columns."""

import pytest

from noisytree import catalogue
from tests.conftest import TINY


def plain(v):
    return repr(v + 0.0) if isinstance(v, float) else str(v)


def check(spark, duck, run, text):
    df = run(spark, TINY)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    r = duck.execute(text)
    names = [d[0] for d in r.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    assert got == sorted(tuple(plain(row[i]) for i in at) for row in r.fetchall())


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_equals_sql(spark, duck, name):
    check(spark, duck, catalogue.queries()[name], catalogue.oracle_sql()[name])


@pytest.mark.parametrize("name", sorted(set(catalogue.queries()) - set(catalogue.oracle_sql())))
def test_runs(spark, name):
    assert catalogue.queries()[name](spark, TINY).count() > 0


@pytest.mark.parametrize("name", ["amplification_table", "budget_geometric", "budget_uniform", "budget_workload_nodes", "leaf_boxes", "worst_case_curve"])
def test_reads_a_given_table(spark, name):
    assert any(t in f for f in catalogue.queries()[name](spark, TINY).inputFiles() for t in ("lineitem", "orders"))


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 60
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
