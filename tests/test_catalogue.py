"""Every query beside its oracle on the smallest tables; the others run and give rows."""

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent))
import oracle

from recordlink import catalog


@pytest.fixture(scope="module")
def con(sf_dir):
    return oracle.connect(sf_dir)


@pytest.mark.parametrize("name", list(catalog.QUERIES))
def test_query(spark, con, sf_dir, name):
    fn = catalog.QUERIES[name]
    if name in catalog.ORACLES:
        assert oracle.compare(spark, con, name, fn, catalog.ORACLES[name], sf_dir) == ""
    else:
        assert fn(spark, sf_dir).count() > 0


def test_entry_points():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries()) and "link_full" in e.queries()
