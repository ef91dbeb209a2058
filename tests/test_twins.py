"""Each query that SQL can express against its SQL twin; the others run and return rows."""

import pytest
from twin import duck, spark_rows

from contrast import workloads

#: What a run of statistics or a timed one returns differs by machine; the rows are there.
LEAST = {"ablations": 12, "discretisations": 5, "classify_rules": 2, "covering_contrast": 2, "mine_stats_doc": 1}


@pytest.mark.parametrize("name", sorted(workloads.ORACLE_SQL))
def test_twin(spark, tiny, name):
    assert spark_rows(workloads.QUERIES[name](spark, tiny)) == duck(tiny, workloads.ORACLE_SQL[name])


@pytest.mark.parametrize("name", sorted(workloads.QUERIES.keys() - workloads.ORACLE_SQL.keys()))
def test_runs(spark, tiny, name):
    rows = workloads.QUERIES[name](spark, tiny).collect()
    assert len(rows) >= LEAST.get(name, 1)
    for r in rows:
        held = r.asDict()
        if "score" in held:
            assert 0 < held["score"] <= 1
        if name != "mine_toxic_anytime" and "complete" in held:
            assert held["complete"]
