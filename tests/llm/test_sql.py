"""Operators that SQL can express, on whole given tables."""

import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(__file__)))
from helpers import assert_same  # noqa: E402

from bspgraph.llm import queries  # noqa: E402


@pytest.mark.parametrize("name", queries.ORACLES)
def test_answers_of_sql(spark, sf, duck, name):
    assert_same(queries.QUERIES[name](spark, sf).toPandas(), duck.sql(queries.ORACLES[name]).df())
