"""Every query with a SQL form against DuckDB on the smallest tables."""

import pytest
from conftest import SMALL, same

from distds import queries as core

ORACLES = core.oracle_sql()
#: The same plan as another query here, and slow for its many rounds.
ALIKE = {"cg_generic", "cg_walk"}


@pytest.mark.parametrize("name", sorted(set(ORACLES) - ALIKE))
def test_oracle(spark, duck, name):
    same(core.queries()[name](spark, SMALL), duck.sql(ORACLES[name]))


@pytest.mark.parametrize("name", sorted(set(core.queries()) - set(ORACLES)))
def test_runs(spark, name):
    assert core.queries()[name](spark, SMALL).limit(5).collect()
