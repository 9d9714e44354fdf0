"""Every query of the method and of the operators around it that has SQL, against DuckDB at the smallest scale."""

import pytest

from lakeadapt.plans import registered
from tests.conftest import SF
from tests.oracle import same

ENTRIES = registered()


@pytest.mark.parametrize("name", sorted(ENTRIES.oracles))
def test_same_rows(spark, name):
    same(ENTRIES.queries[name](spark, SF), ENTRIES.oracles[name], SF)
