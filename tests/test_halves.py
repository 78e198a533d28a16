import pytest

from pathsieve import catalog
from pathsieve.operators import baselines, levels, recursive, udf_modes
from pathsieve.sources import encodings
from pathsieve.workloads import WORKLOADS
from tests.conftest import DATA
from tests.test_workloads import duck, test_query_equals_its_sql  # noqa: F401


def q4(spark, **changes):
    return WORKLOADS["q4_knows"].query(spark, DATA, max_len=3, **changes)


def test_halves_make_the_edges(spark):
    graph = encodings.stored(spark, DATA, "knows")
    plain = encodings.ENCODINGS["knows"](spark, DATA).edges
    assert graph.parts.exact and sorted(graph.edges.collect()) == sorted(plain.collect())
    assert graph.parts.begin.selectExpr("sum(n)").first()[0] == plain.count()
    assert graph.where("t > 0").parts is None


NAMES = [n for n in catalog.QUERIES if n.startswith(("base_", "cand_", "q4_", "rewrites_")) and "_q4" in f"_{n}" or n in ("q4_knows", "q4_knows_long")]


@pytest.mark.parametrize("name", NAMES)
def test_q4_equals_its_sql(spark, duck, name):  # noqa: F811
    test_query_equals_its_sql(spark, duck, name)
