"""Every query with a DuckDB twin against it, at the smallest scale; the others run and give rows."""

import pytest

import __spark_entry__ as entry
from conftest import SF

OWN = {k: v for m in entry.OWN for k, v in m.queries().items()}
SQL = {k: v for m in entry.OWN for k, v in m.oracle_sql().items()}
SLOW = {"ratio_by_source", "ratio_by_quality", "bit_costs_by_code"}


@pytest.mark.parametrize("name", sorted(SQL))
def test_twin(name, same):
    same(OWN[name], SQL[name])


@pytest.mark.parametrize("name", sorted(set(OWN) - set(SQL) - SLOW))
def test_runs(name, spark):
    assert OWN[name](spark, SF).count() > 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_plans(spark):
    from repeatfold.workloads import methods

    docs = methods.load_table(spark, SF, "documents").where("n_chars < 100")
    from repeatfold.operators.fold import fold, sizes

    plan = sizes(fold(docs, ["doc_id"]))._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(n_chars), LessThan(n_chars,100)]" in plan and "source" not in plan.split("ReadSchema")[1].split(">")[0] and "Exchange" not in plan
