"""Operators that SQL can express agree with it over whole tables."""

from __future__ import annotations

import oracle
import pytest
from conftest import SF01

from cubegrid.llm import registry


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_oracle(spark, name):
    assert oracle.difference(registry.QUERIES[name](spark, SF01), oracle.connect(SF01), registry.ORACLE_SQL[name]) is None
