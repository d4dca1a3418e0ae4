"""Closure and ancestors of chains, and of graphs that are none."""

import pytest

from rulemat.engine.store import Storage
from rulemat.graphops import ancestors, closure


def chain(spark, *pairs):
    return spark.createDataFrame(list(pairs), "a long, b long")


@pytest.mark.parametrize("pairs", [[(k, k + 1) for k in range(30)], [(k, k + 1) for k in range(30)] + [(0, 50), (12, 4)], [(1, 1), (1, 2)], [(0, 1), (1, 2), (2, 0)], []])
def test_closure_and_ancestors(spark, pairs, tmp_path):
    storage = Storage(spark)
    cuts = []

    def cut(df, name):
        cuts.append(name)
        return storage.write(df).frame

    want, step = set(pairs), set(pairs)
    while step:
        step = {(a, d) for a, b in step for c, d in pairs if b == c} - want
        want |= step
    assert {tuple(x) for x in closure(chain(spark, *pairs), cut).collect()} == want
    cuts.clear()
    nodes = spark.createDataFrame([(20,), (2,)], "node long")
    assert {tuple(x) for x in ancestors(chain(spark, *pairs), nodes, cut).collect()} == {(b, a) for a, b in want if b in (2, 20)}
    if len(pairs) == 30:
        assert len(cuts) < 14  # twenty levels in half as many steps
