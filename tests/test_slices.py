"""Components and chains from slices of edges: right whatever the slices, and few jobs for long chains."""

import random

import pyarrow as pa
import pytest

from rulemat import graphops, slices
from rulemat.engine import Reasoner, patterns
from rulemat.workloads import rulesets


@pytest.fixture
def cut(spark, tmp_path):
    def write(df, name):
        at = str(tmp_path / f"{len(list(tmp_path.iterdir()))}-{name}")
        df.write.parquet(at)
        return spark.read.schema(df.schema).parquet(at)

    return write


@pytest.fixture(params=[graphops.FEW_LINKS, 0])
def bounds(request, monkeypatch):
    monkeypatch.setattr(graphops, "FEW_LINKS", request.param)


def dealt(spark, edges, parts=5):
    """Edges over several tasks, so that components and chains span slices."""
    kind = "string" if isinstance(edges[0][0], str) else "long"
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", str(parts))
    return spark.createDataFrame(edges, f"a {kind}, b {kind}")


@pytest.fixture(autouse=True)
def restored(spark):
    yield
    spark.conf.set("spark.sql.adaptive.enabled", "true")
    spark.conf.set("spark.sql.shuffle.partitions", "2")


def least(edges):
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {x: find(x) for x in list(root)}


@pytest.mark.parametrize("name", [int, "é{}".format])
def test_components_across_slices(spark, cut, bounds, name):
    rng = random.Random(7)
    edges = [(name(rng.randrange(300)), name(rng.randrange(300))) for _ in range(200)] + [(name(999), name(999))]
    got = {r.node: r.component for r in graphops.contracted(dealt(spark, edges), cut).collect()}
    assert got == least(edges)


def test_chains_across_slices(spark, cut, bounds):
    nodes, want, edges = list(range(400)), {}, []
    random.Random(3).shuffle(nodes)
    for lo, n in ((0, 2), (2, 5), (7, 90), (97, 200)):
        chain = nodes[lo : lo + n]
        edges += zip(chain, chain[1:])
        want |= {x: (chain[-1], n - 1 - k) for k, x in enumerate(chain)}
    got = {r.node: (r.component, r.left) for r in graphops.chain_ranks(dealt(spark, edges), cut).collect()}
    assert got == want
    for circle in ([(5000, 5000)], [(k, k % 7 + 1001) for k in range(1001, 1008)]):
        assert graphops.chain_ranks(dealt(spark, edges + circle), cut) is None


def test_slices_hold_a_bounded_number_of_edges(monkeypatch):
    monkeypatch.setattr(slices, "SLICE", 4)
    batch = pa.RecordBatch.from_pydict({"a": range(10), "b": range(1, 11), "left": [1] * 10})
    assert [b.num_rows for b in slices.tails(iter([batch, batch.slice(0, 3)]))] == [4, 4, 4, 1]
    assert [b.column("root")[0].as_py() for b in slices.stars(iter([batch]))] == [0, 4, 8]


def test_a_long_chain_takes_few_jobs(spark):
    links = spark.range(0, 3000).selectExpr("id AS a", "id + 1 AS b")
    spark.sparkContext.setJobGroup("chain", "chain")
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links})
    r.materialise()
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup("chain"))
    spark.sparkContext.setJobGroup("", "")
    assert r.relation("near").count() == 3001**2
    assert jobs < 40  # over 100 before


def test_aggregates_along_chains_make_no_pairs(spark, monkeypatch):
    """Both directions, ties, nodes without and with several readings, loose ends."""
    links = [(k, k + 1) for k in range(30)] + [(100, 101), (103, 102), (102, 104)]
    temps = [(k, float(k * 7 % 5)) for k in range(1, 30, 2)] + [(9, 50.0), (9, -50.0), (101, 1.0), (103, float("inf")), (102, 2.0)]
    rules = "near(x, y) <- e(x, y). near(x, z) <- near(x, y), near(y, z). @a n(x, count(y)) <- near(x, y) group x. @b b(y, count(x)) <- near(x, y) group y. @m m(x, median(t)) <- near(x, y), temp(y, t) group x. @w w(y, median(t)) <- near(x, y), temp(x, t) group y."
    monkeypatch.setattr(patterns, "ranked_pairs", lambda a, b, n, pairs: spark.createDataFrame([], "a long, b long"))  # pairs come from nowhere else
    r = Reasoner(spark, rules, {"e": spark.createDataFrame(links, "a long, b long"), "temp": spark.createDataFrame(temps, "a long, t double")})
    r.materialise()
    after = dict(links)
    pairs = set()
    for x in after:
        y = x
        while y in after:
            y = after[y]
            pairs.add((x, y))

    def groups(side, value):
        out = {}
        for p in pairs:
            for t in value(p[1 - side]):
                out.setdefault(p[side], []).append(t)
        return out

    heat = lambda k: [t for j, t in temps if j == k]
    spoken = lambda found: {k: str(v) for k, v in found.items()}

    def middle(v):
        v = sorted(v)
        return (v[(len(v) - 1) // 2] + v[len(v) // 2]) / 2

    for pred, side, value, fn in (("n", 0, lambda k: [k], len), ("b", 1, lambda k: [k], len), ("m", 0, heat, middle), ("w", 1, heat, middle)):
        assert spoken(dict(map(tuple, r.relation(pred).collect()))) == spoken({k: fn(v) for k, v in groups(side, value).items()}), pred
