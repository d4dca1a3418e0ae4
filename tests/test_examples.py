"""The worked examples are answered over given tables: their answers follow the tables."""

import pytest

from rulemat.workloads import experiments

NAMES = ["rex_hyperedges", "rex_strata", "rex_impact_r8", "rex_impact_r4", "rex_drop_567", "rdel_plan"]


@pytest.mark.parametrize("name", NAMES)
def test_answers_follow_the_tables(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    got = experiments.QUERIES[name](spark, sf)
    db = duckdb.connect()
    for t in ("customer", "supplier", "orders"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = db.execute(experiments.ORACLES[name])
    assert got.columns == [c[0] for c in want.description] and got.columns[-1] == "facts"
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall())
