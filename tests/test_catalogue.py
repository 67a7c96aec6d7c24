import pytest

from tangentia.plans import catalogue
from tests.oracle import both

SQL = sorted(catalogue.oracle_sql())
SLOW = {"double_center", "directed_min_label"}


@pytest.mark.parametrize("name", [n for n in SQL if n not in SLOW])
def test_query_equals_its_sql(spark, sf_dir, name):
    ours, theirs = both(spark, sf_dir, catalogue.queries()[name], catalogue.oracle_sql()[name])
    assert ours == theirs


def test_entry_imports_without_a_session():
    import __spark_entry__

    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
