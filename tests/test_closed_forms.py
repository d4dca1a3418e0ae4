"""Closures read from labels and ranks: right after every update, and without written pairs."""

import pytest
from pyspark.sql import functions as F

from rulemat.engine import Config, Reasoner
from rulemat.engine.baselines import equal_state, from_scratch
from rulemat.engine.store import Storage
from rulemat.graphops import closure
from rulemat.workloads import rulesets

N = 40
RULES = rulesets.NEAR + "@a n(x, count(y)) <- near(x, y) group x.\n@m med(x, median(t)) <- near(x, y), temp(y, t) group x."


@pytest.fixture
def most(monkeypatch):
    """The most rows that were written at once."""
    seen, write = [0], Storage.write

    def watched(self, df):
        part = write(self, df)
        seen[0] = max(seen[0], part.rows)
        return part

    monkeypatch.setattr(Storage, "write", watched)
    return seen


def chain(spark, *pairs):
    return spark.createDataFrame(list(pairs), "a long, b long")


def links(spark, lo, hi):
    return chain(spark, *((k, k + 1) for k in range(lo, hi)))


def facts(r, pred):
    return {tuple(x) for x in r.relation(pred).collect()}


def engine(spark, config=None):
    temp = spark.range(0, 2 * N, 3).select("id", F.col("id").cast("double"))
    r = Reasoner(spark, RULES, {"hasNeighbour": links(spark, 0, N - 1), "temp": temp}, config or Config())
    r.materialise()
    return r


def plain(r):
    """The same program and facts without closed forms."""
    return from_scratch(r, pattern_closure="off")


def test_aggregates_and_updates_write_no_pairs(spark, most):
    r = engine(spark)
    assert facts(r, "n") == {(k, N) for k in range(N)}
    r.insert_facts("hasNeighbour", links(spark, N - 1, N + 9))
    assert facts(r, "n") == {(k, N + 10) for k in range(N + 10)}
    assert {d[1:] for d in r.log.deltas if d[1] == "near" and d[2] > 100} == {("near", (N + 10) ** 2 - N * N, 0)}
    r.delete_facts("hasNeighbour", chain(spark, (19, 20)))
    assert facts(r, "n") == {(k, 20) for k in range(20)} | {(k, N - 10) for k in range(20, N + 10)}
    assert {d[1:] for d in r.log.deltas if d[1] == "near" and d[3] > 100} == {("near", 0, (N + 10) ** 2 - 20 * 20 - (N - 10) ** 2)}
    assert most[0] <= 4 * (N + 10)  # nodes and edges, no pairs
    assert equal_state(r, plain(r)) == {}


def test_transitive_node_of_chains(spark, most):
    n = 12
    r = Reasoner(spark, rulesets.NEAR + "@a n(x, count(y)) <- near(x, y) group x.", {"hasNeighbour": links(spark, 0, n - 1)})
    r.materialise()
    r.delete_rules(["r2"])
    assert facts(r, "near") == {(a, b) for a in range(n) for b in range(a + 1, n)}
    assert facts(r, "n") == {(a, n - 1 - a) for a in range(n - 1)}
    assert most[0] <= 4 * n
    r.update(add_facts={"hasNeighbour": chain(spark, (100, 101))}, drop_facts={"hasNeighbour": chain(spark, (0, 1))})
    want = {(a, b) for a in range(1, n) for b in range(a + 1, n)} | {(100, 101)}
    assert facts(r, "near") == want and facts(r, "n") == {(a, n - 1 - a) for a in range(1, n - 1)} | {(100, 1)}
    r.insert_rules("@r9 near(x, z) <- near(x, y), more(y, z).")
    r.delete_facts("hasNeighbour", chain(spark, (100, 101)))  # a fact of the base only
    assert facts(r, "near") == want - {(100, 101)}


def test_rules_that_read_pairs_and_other_groups(spark):
    r = engine(spark)
    r.insert_rules("@p far(x, y) <- near(x, y), temp(x, s), temp(y, t), s < t.\n@q w(x, count(y)) <- near(x, y), near(y, x) group x.\n@u v(x, s, max(y)) <- near(y, x), temp(y, s) group x, s.")
    r.insert_facts("hasNeighbour", chain(spark, (60, 61)))
    r.delete_facts("hasNeighbour", chain(spark, (9, 10)))
    assert equal_state(r, plain(r)) == {}
    r.delete_rules(["r3"])
    assert equal_state(r, plain(r)) == {}


def test_reach_along_a_long_chain_takes_few_rounds(spark):
    program = "reach(x) <- start(x). reach(y) <- reach(x), e(x, y). start(0)."
    edges = chain(spark, *((k, k + 1) for k in range(99)), (50, 20), (70, 200))
    r = Reasoner(spark, program, {"e": edges})
    r.materialise()
    assert facts(r, "reach") == {(k,) for k in (*range(100), 200)}
    assert r.log.counts["rounds"] < 30  # 100 before


def written(monkeypatch):
    n, write = [0], Storage.write
    monkeypatch.setattr(Storage, "write", lambda self, df: (n.__setitem__(0, n[0] + 1), write(self, df))[1])
    return n


@pytest.mark.parametrize("slice_rows", [10**6, 0])
def test_a_change_of_many_edges_is_labelled_in_one_pass(spark, monkeypatch, slice_rows):
    """The same facts and differences whether all edges are one slice or only the touched ones are
    followed; in the first case an update writes its change and the labels, and nothing else."""
    monkeypatch.setattr("rulemat.engine.patterns.FEW_EDGES", 2)
    monkeypatch.setattr("rulemat.engine.patterns.SLICE", slice_rows)
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links(spark, 0, 9)})
    r.materialise()
    n = written(monkeypatch)
    late = links(spark, 9, 14).unionByName(chain(spark, (30, 31), (40, 40)))
    r.insert_facts("hasNeighbour", late)
    assert slice_rows == 0 or n[0] == 2
    assert ("near", 15 * 15 - 100 + 4 + 1, 0) in {d[1:] for d in r.log.deltas}
    assert facts(r, "near") == facts(plain(r), "near")
    n[0] = 0
    r.delete_facts("hasNeighbour", late)
    assert slice_rows == 0 or n[0] == 3
    assert ("near", 0, 15 * 15 - 100 + 4 + 1) in {d[1:] for d in r.log.deltas}
    assert facts(r, "near") == facts(plain(r), "near") == {(a, b) for a in range(10) for b in range(10)}
    r.delete_facts("hasNeighbour", links(spark, 0, 9))
    assert facts(r, "near") == set()
    r.insert_facts("hasNeighbour", links(spark, 0, 4))
    assert facts(r, "near") == {(a, b) for a in range(5) for b in range(5)}


def test_a_thousand_changes_are_labelled_in_one_pass(spark, monkeypatch):
    """Fewer edges than ``FEW_EDGES`` changed, but enough that following them takes more jobs."""
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links(spark, 0, 9)})
    r.materialise()
    n = written(monkeypatch)
    late = spark.range(1200).selectExpr("100 + 2 * id AS a", "101 + 2 * id AS b").unionByName(links(spark, 9, 11).toDF("a", "b"))
    r.insert_facts("hasNeighbour", late)
    assert n[0] == 2 and r.log.deltas[-1][1:] == ("near", 4800 + 144 - 100, 0)
    assert facts(r, "near") == {(a, b) for a in range(12) for b in range(12)} | {(100 + 2 * k + x, 100 + 2 * k + y) for k in range(1200) for x in (0, 1) for y in (0, 1)}
    n[0] = 0
    r.delete_facts("hasNeighbour", late)
    assert n[0] == 3 and facts(r, "near") == {(a, b) for a in range(10) for b in range(10)}


def test_all_pairs_of_labels_come_from_arrays(spark, monkeypatch):
    """A reader of all facts gets the same ones, without a join of nodes with nodes."""
    monkeypatch.setattr("rulemat.graphops.PAIRS_A_TASK", 20)
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links(spark, 0, 9).unionByName(chain(spark, (20, 21), (30, 30)))})
    r.materialise()
    r.delete_facts("hasNeighbour", chain(spark, (4, 5)))
    whole = r.relation("near", whole=True)
    assert "explode(nodes" in whole._jdf.queryExecution().toString()
    rows = [tuple(x) for x in whole.collect()]
    assert whole.columns == r.relation("near").columns and len(rows) == len(set(rows)) == 25 + 25 + 4 + 1 and set(rows) == facts(r, "near")
    monkeypatch.setattr("rulemat.graphops.BROADCAST_ROWS", 3)
    r.insert_facts("hasNeighbour", chain(spark, (4, 5)))
    assert {tuple(x) for x in r.relation("near", whole=True).collect()} == facts(r, "near") and r.relation("near", whole=True).count() == 105
    assert r.relation("hasNeighbour", whole=True).count() == 12 - 1


def test_a_symmetric_node_is_written_once(spark, monkeypatch):
    """What is left when the transitive rule goes: links both ways, from one write."""
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links(spark, 0, 9).unionByName(chain(spark, (3, 2), (5, 5)))})
    r.materialise()
    n = written(monkeypatch)
    r.delete_rules(["r3"])
    assert n[0] == 1
    assert facts(r, "near") == {(a, b) for k in range(9) for a, b in ((k, k + 1), (k + 1, k))} | {(5, 5)}
    r.delete_facts("hasNeighbour", chain(spark, (3, 2), (5, 5), (7, 8)))
    assert facts(r, "near") == {(a, b) for k in range(9) if k != 7 for a, b in ((k, k + 1), (k + 1, k))}


def stored(df, at):
    """Bytes a pair of a file of all pairs."""
    df.write.parquet(str(at))
    return sum(f.stat().st_size for f in at.glob("*.parquet")) / df.sparkSession.read.parquet(str(at)).count()


@pytest.mark.parametrize("broadcast", [2_000_000, 3])
def test_all_pairs_are_made_run_by_run(spark, monkeypatch, broadcast):
    """The same pairs, of labels and of chains, with components of less, just and more than a run."""
    monkeypatch.setattr("rulemat.graphops.TILE", 4)
    monkeypatch.setattr("rulemat.graphops.PAIRS_A_TASK", 50)
    monkeypatch.setattr("rulemat.graphops.BROADCAST_ROWS", broadcast)
    sizes = (14, 9, 4, 3, 2)
    groups = [[100 * k + (7 * j) % 97 for j in range(n)] for k, n in enumerate(sizes)]
    edges = chain(spark, *((a, b) for g in groups for a, b in zip(g, g[1:])))
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": edges})
    r.materialise()
    rows = [tuple(x) for x in r.relation("near", whole=True).collect()]
    assert len(rows) == sum(n * n for n in sizes) and set(rows) == {(a, b) for g in groups for a in g for b in g}
    ordered = {(a, b) for g in groups for k, a in enumerate(g) for b in g[k + 1 :]}
    r.delete_rules(["r2"])
    whole = r.relation("near", whole=True)
    assert "explode(nodes" in whole._jdf.queryExecution().toString()
    rows = [tuple(x) for x in whole.collect()]
    assert whole.columns == ["c0", "c1"] and len(rows) == len(ordered) and set(rows) == ordered == facts(r, "near")
    rows = [tuple(x) for x in closure(edges, lambda df, name: r.storage.write(df).frame).collect()]
    assert len(rows) == len(ordered) and set(rows) == ordered


def test_all_pairs_take_little_disk(spark, tmp_path):
    """A file of all pairs repeats nodes where a writer can tell; nodes beside nodes take 2 to 4 bytes a pair."""
    edges = spark.range(3000).selectExpr("id * 7919 % 104729 AS a", "(id + 1) * 7919 % 104729 AS b")
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": edges})
    r.materialise()
    assert stored(r.relation("near", whole=True), tmp_path / "labels") < 0.4
    r.delete_rules(["r2"])
    assert stored(r.relation("near", whole=True), tmp_path / "ranks") < 0.4
    assert stored(closure(edges, lambda df, name: r.storage.write(df).frame), tmp_path / "closure") < 0.4
