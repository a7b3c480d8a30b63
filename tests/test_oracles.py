"""Every registered query of the engine against its SQL on the smallest tables; those without SQL have to run."""

import pytest

import __spark_entry__ as entry
from twinfold.queries import methods, more_methods, streams, surround

from conftest import same_rows

MODULES = (methods, more_methods, surround, streams)
WITH = [(m, k) for m in MODULES for k in m.QUERIES if k in m.ORACLES]
WITHOUT = [(m, k) for m in MODULES for k in m.QUERIES if k not in m.ORACLES]


@pytest.mark.parametrize("module,name", WITH, ids=[k for _, k in WITH])
def test_same_as_sql(spark, data, module, name):
    same_rows(module.QUERIES[name](spark, data), module.ORACLES[name], data)


@pytest.mark.parametrize("module,name", WITHOUT, ids=lambda x: x if isinstance(x, str) else "")
def test_runs(spark, data, module, name):
    assert module.QUERIES[name](spark, data).count() >= 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
