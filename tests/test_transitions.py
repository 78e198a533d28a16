import pytest

from pathsieve import catalog
from tests.conftest import DATA
from tests.test_workloads import duck, test_query_equals_its_sql  # noqa: F401


@pytest.mark.parametrize("name", ["transitions_q1", "transitions_qb", "op_udtf_transitions"])
def test_transitions_are_counted_over_given_edges(spark, duck, name):  # noqa: F811
    assert catalog.QUERIES[name](spark, DATA).inputFiles()
    test_query_equals_its_sql(spark, duck, name)
