from __future__ import annotations

import pytest

from vecforest.llm import registry


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_its_sql(spark, sf, duck, same, name):
    same(registry.queries()[name](spark, sf), duck.execute(registry.oracle_sql()[name]).df())


def test_each_operator_is_registered():
    names = registry.queries()
    assert all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11)) and "pipeline" in names
