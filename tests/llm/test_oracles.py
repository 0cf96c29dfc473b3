import pytest

from tests.harness import compare
from textimpute.llm.oracles import ORACLES
from textimpute.llm.queries import QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, sf, name):
    assert compare(spark, sf, QUERIES[name], ORACLES[name]) == ""
