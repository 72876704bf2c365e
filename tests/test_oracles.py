"""Every registered workload against the SQL that restates it from the base tables."""

import pytest
from conftest import SF, canonical

from statewitness import registry

ORACLES = registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(registry.queries()))
def test_workload(spark, duck, name):
    got = registry.queries()[name](spark, SF).toPandas()
    if name not in ORACLES:
        assert len(got) >= 0 and len(got.columns)
        return
    want = duck.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert canonical(got) == canonical(want)


def test_approximate_counts_are_close(spark, duck):
    exact = duck.execute("SELECT count(DISTINCT user_id) FROM events").fetchall()[0][0]
    for name in ("op_approx_distinct", "op_hll_union"):
        found = registry.queries()[name](spark, SF).first()[0]
        assert abs(found - exact) <= 0.1 * exact
