"""The tables of the accountant stand on the given tables."""

import duckdb
import pytest

from synthguard import workloads
from synthguard.plans import budget
from synthguard.sources.tables import TABLES

SF = "/root/testdata/sf0.001"


def _oracle(sql):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return sorted(c.execute(sql).fetchall())


def _alike(spark, name):
    df = workloads.QUERIES[name](spark, SF)
    # the plan reads a given table; it was made of constants before
    assert df.inputFiles()
    got, want = sorted(map(tuple, df.collect())), _oracle(workloads.SQL[name])
    assert len(got) == len(want) and all(a == pytest.approx(b) if isinstance(b, float) else a == b for x, y in zip(got, want, strict=True) for a, b in zip(x, y, strict=True))
    return df, got


def test_release_budget_is_that_of_the_seeds(spark):
    df, got = _alike(spark, "release_budget_table")
    seeds = workloads.split_of(spark, SF, "S")
    assert len(got) == 49 and {r[3] for r in got} == {seeds.count()}
    assert {r[4] for r in got} == {sum(r["count"] for r in seeds.groupBy(*workloads.ORDER[:4]).count().collect() if r["count"] >= 50)}
    assert (got[28][1], got[28][2]) == pytest.approx((budget.release_epsilon(50, 4.0, 1.0, 29).eps, budget.release_epsilon(50, 4.0, 1.0, 29).delta))


def test_sensitivity_is_that_of_the_splits(spark):
    df, got = _alike(spark, "sensitivity_table")
    n = workloads.split_of(spark, SF, "T").count()
    assert ("orderline_micro", "T", n, pytest.approx(budget.entropy_sensitivity(n))) in got and {r[0] for r in got} == {"orderline_micro", "document_micro", "event_micro", "conversation_micro"}
