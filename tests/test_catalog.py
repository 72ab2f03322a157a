"""Every catalogue key runs; those with SQL agree with DuckDB."""

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent))
import parity  # noqa: E402
from lpstream.plans import catalog  # noqa: E402

QUERIES, ORACLES = catalog.queries(), catalog.oracle_sql()


def test_keys():
    assert ORACLES.keys() <= QUERIES.keys() and len(QUERIES) > 150


@pytest.mark.parametrize("key", sorted(ORACLES))
def test_parity(key, spark, sf):
    assert parity.compare(spark, sf, QUERIES[key], ORACLES[key]) is None
    spark.catalog.clearCache()


@pytest.mark.parametrize("key", sorted(k for k in QUERIES.keys() - ORACLES.keys() if not k.startswith("ratio_")))
def test_rows_only(key, spark, sf):
    df = QUERIES[key](spark, sf)
    if "holds" in df.columns:
        found = [r.holds for r in df.collect()]
        assert found and all(found)
    else:
        assert df.count() > 0
    spark.catalog.clearCache()
