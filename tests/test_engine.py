"""Engine against a small set evaluator, and incremental states against recomputation."""

import collections
import itertools
import operator
import random
import statistics

import pytest

from rulemat import graphops
from rulemat.engine import Config, Reasoner
from rulemat.engine.baselines import equal_state, from_scratch, with_recursive
from rulemat.lang import RuleError, UnstratifiableError, parse_program
from rulemat.lang.syntax import Const
from rulemat.plans.depgraph import build_rule_graph, condense
from rulemat.workloads import datasets, experiments, rulesets


def evaluate(text, facts):
    """All facts by brute force: every rule over every combination, node by node."""
    p = parse_program(text)
    db = {k: set(v) for k, v in facts.items()}
    for r in [r for r in p if not r.positives]:
        db.setdefault(r.head.pred, set()).add(tuple(a.value for a in r.head.args))
    p = p.without([r.id for r in p if not r.positives])
    h = condense(build_rule_graph(p))

    def bindings(r):
        for combo in itertools.product(*[db.get(a.pred, ()) for a in r.positives]):
            env, ok = {}, True
            for a, row in zip(r.positives, combo, strict=True):
                for t, v in zip(a.args, row, strict=True):
                    ok &= (t.value == v) if isinstance(t, Const) else t.name == "_" or env.setdefault(t.name, v) == v
            val = lambda t, env=env: t.value if isinstance(t, Const) else env[t.name]
            compare = {"=": operator.eq, "!=": operator.ne, "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge}
            ok = ok and all(compare[c.op](val(c.left), val(c.right)) for c in r.comps)
            if ok and not any(tuple(map(val, a.args)) in db.get(a.pred, ()) for a in r.negatives):
                yield env, val

    for n in h.topo_order():
        while True:
            before = sum(map(len, db.values()))
            for rid in h.nodes[n]:
                r = p.rules[rid]
                if r.agg:
                    seen = {}
                    for env, _ in bindings(r):
                        seen.setdefault(tuple(env[g] for g in r.agg.group), {})[tuple(sorted(env.items()))] = env[r.agg.var]
                    fn = {"count": len, "sum": sum, "max": max, "min": min, "median": statistics.median, "avg": statistics.mean}[r.agg.fn]
                    for g, vs in seen.items():
                        row = dict(zip(r.agg.group, g, strict=True)) | {r.agg.result: fn(list(vs.values()))}
                        db.setdefault(r.head.pred, set()).add(tuple(row[a.name] for a in r.head.args))
                else:
                    for _, val in list(bindings(r)):
                        db.setdefault(r.head.pred, set()).add(tuple(map(val, r.head.args)))
            if sum(map(len, db.values())) == before:
                break
    return {k: v for k, v in db.items() if v}


def state(r):
    return {p: rows for p in r.state.bag().index if (rows := {tuple(x) for x in r.relation(p).collect()})}


def frames(spark, facts):
    return {p: spark.createDataFrame(sorted(rows), ", ".join(f"x{k} long" for k in range(len(next(iter(rows)))))) for p, rows in facts.items()}


FACTS = {"e1": {(1, 2), (2, 3), (3, 4)}, "e2": {(1, 7), (2, 7), (5, 6)}, "p3": {(2, 7), (7, 1)}, "p6": {(1, 7), (2, 7)}, "p7": {(5, 6)}}


def test_running_example(spark):
    r = Reasoner(spark, rulesets.REX, frames(spark, FACTS))
    r.materialise()
    assert state(r) == evaluate(rulesets.REX, FACTS)
    log = r.insert_rules(rulesets.REX_R8)
    assert log.direct == {"hn2"} and state(r) == evaluate(rulesets.REX + rulesets.REX_R8, FACTS)
    r.delete_rules(["r4"])
    left = "\n".join(x for x in (rulesets.REX + rulesets.REX_R8).splitlines() if not x.startswith("@r4"))
    assert state(r) == evaluate(left, FACTS)


def test_whole_nodes_vanish_without_reasoning(spark):
    r = Reasoner(spark, rulesets.REX, frames(spark, FACTS))
    r.materialise()
    before = {n: s for n, s in r.state.stores.items()}
    log = r.delete_rules(["r5", "r6", "r7"])
    assert log.dropped == ["hn3", "hn4"] and not log.visited and not log.counts["rules_run"]
    assert all(r.state.stores[n] is before[n] for n in r.state.stores)


PROGRAM = """
@r1 t(x, y) <- e(x, y).
@r2 t(x, z) <- t(x, y), e(y, z).
@r3 far(x, y) <- n(x), n(y), !t(x, y).
@r4 deg(x, count(y)) <- t(x, y) group x.
@r5 big(x) <- deg(x, d), d > 2.
@r6 s(y, x) <- t(x, y), big(x).
@r7 s(x, y) <- s(y, x), !e(x, y).
@r8 e(x, y) <- extra(x, y).
"""


@pytest.mark.parametrize("method", ["rederive", "backward_forward", "counting"])
def test_random_updates(spark, method):
    """Mixed updates of facts and rules keep the state equal to recomputation."""
    rng = random.Random(len(method))
    facts = {"e": {(rng.randrange(5), rng.randrange(5)) for _ in range(6)}, "n": {(i,) for i in range(5)}, "extra": {(0, 4), (4, 2)}}
    r = Reasoner(spark, PROGRAM, frames(spark, facts), Config(deletion_method=method, allow_cross=True, pattern_closure="off", linear_after=2))
    r.materialise()
    assert state(r) == evaluate(PROGRAM, facts)
    rules = parse_program(PROGRAM).rules
    gone: set[str] = set()
    for step in range(2 if method == "rederive" else 1):
        add = {(rng.randrange(5), rng.randrange(5)) for _ in range(2)} - facts["e"]
        drop = set(rng.sample(sorted(facts["e"]), min(2, len(facts["e"]) - 1)))
        out = {rng.choice(sorted(set(rules) - gone - {"r1"}))} if step != 1 else set()
        back = set(list(gone)[:1])
        r.update(add_rules=[rules[i] for i in back], drop_rules=out, add_facts=frames(spark, {"e": add}) if add else {}, drop_facts=frames(spark, {"e": drop}))
        facts["e"] = (facts["e"] - drop) | add
        gone = (gone | out) - back
        text = "\n".join(f"@{i} {x.text()}." for i, x in rules.items() if i not in gone)
        assert state(r) == evaluate(text, facts), (step, out, back)


@pytest.mark.parametrize("config", [Config(insertion_mode="redo"), Config(successor_policy="always", downstream="redo"), Config(bag="merged", order="dp", layout="c0"), Config(evaluation="naive", unit="stratum", eager_filters=False)], ids=["redo", "always", "merged", "naive"])
def test_variants_agree(spark, config):
    r = Reasoner(spark, rulesets.REX, frames(spark, FACTS), config)
    r.materialise()
    r.insert_rules(rulesets.REX_R8)
    r.delete_rules(["r3"])
    assert equal_state(r, from_scratch(r)) == {}


def test_masked_support(spark):
    """A fact that is explicit and derived stays visible while either support lasts."""
    r = Reasoner(spark, "p(x) <- a(x). q(x) <- p(x).", {"a": spark.createDataFrame([(1,)], "x long"), "p": spark.createDataFrame([(1,), (2,)], "x long")})
    r.materialise()
    r.delete_facts("p", spark.createDataFrame([(1,)], "x long"))
    assert state(r)["q"] == {(1,), (2,)}
    r.delete_facts("a", spark.createDataFrame([(1,)], "x long"))
    assert state(r)["q"] == {(2,)} and state(r)["p"] == {(2,)}


def test_rejected_updates_leave_the_state(spark):
    r = Reasoner(spark, rulesets.REX, frames(spark, FACTS))
    r.materialise()
    before = r.state
    for bad, error in (("p2(x, y) <- e1(x, y), !p5(x, y).", UnstratifiableError), ("p9(x, y) <- e1(x, x).", RuleError), ("p1(x) <- e1(x, x).", RuleError)):
        with pytest.raises(error):
            r.insert_rules(bad)
        assert r.state is before
    with pytest.raises(RuleError):
        r.delete_rules(["r99"])
    log = r.insert_rules("p4(u, v) <- p2(u, v).")
    assert not log.direct and r.state.program.rules == before.program.rules


def test_empty_and_unknown(spark):
    assert state(Reasoner(spark, "")) == {}
    r = Reasoner(spark, "p(x, y) <- nothing(x, y). c(count(x)) <- p(x, y).")
    r.materialise()
    assert state(r) == {}


def test_linear_chain_by_doubling(spark):
    n = 40
    facts = {"p": {(i, i + 1) for i in range(n)}}
    text = "@a odd(x, y) <- p(x, y). @b even(x, z) <- odd(x, y), p(y, z). @c odd(x, z) <- even(x, y), p(y, z)."
    r = Reasoner(spark, text, frames(spark, facts), Config(linear_after=2))
    r.materialise()
    got = state(r)
    assert got["odd"] == {(i, j) for i in range(n + 1) for j in range(i + 1, n + 1) if (j - i) % 2} and len(got["even"]) == sum((j - i) % 2 == 0 for i in range(n + 1) for j in range(i + 1, n + 1))
    assert r.log.counts["rounds"] < 15


def test_goal_explain_save(spark, tmp_path):
    r = Reasoner(spark, rulesets.NEAR, {"hasNeighbour": spark.createDataFrame([(1, 2), (2, 3)], "a long, b long")})
    r.materialise()
    assert {x[0] for x in r.query("near(1, y), y > 1").collect()} == {2, 3}
    proof = r.explain("near", 1, 3)
    assert proof[0][0] == "near(1, 3)" and any(rule == "explicit" for _, rule in proof)
    r.save(str(tmp_path / "s"))
    again = Reasoner.restore(spark, str(tmp_path / "s"))
    assert state(again) == state(r) and again.profile() == r.profile()
    again.delete_rules(["r2"])
    assert state(again)["near"] == {(1, 2), (2, 3), (1, 3)}


def test_recursive_query_baseline(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(6)], "c0 long, c1 long")
    assert with_recursive(e, 10).count() == 21


def test_components_of_a_long_shuffled_path(spark, tmp_path):
    n = 2000
    ids = list(range(n))
    random.Random(3).shuffle(ids)
    edges = spark.createDataFrame(list(zip(ids, ids[1:], strict=False)) + [(n + 1, n), (n + 2, n + 1), (n + 5, n + 5)], "a long, b long")
    at = iter(range(10**6))

    def cut(df, name):
        path = str(tmp_path / f"{name}{next(at)}")
        df.write.parquet(path)
        return spark.read.parquet(path)

    got = {r.node: r.component for r in graphops.components(edges, cut).collect()}
    assert got == {k: 0 for k in range(n)} | {k: n for k in (n, n + 1, n + 2)}


def test_whole_table_queries_cover_all_customers(spark, sf):
    """Queries named rs1_ and the facts of rs2_ reach every customer, not only low ids."""
    customers = {r.c_custkey: r.c_nationkey for r in datasets.read(spark, sf, "customer").collect()}
    size = collections.Counter(customers.values())
    got = {r.c0: r.c1 for r in experiments.QUERIES["rs1_near_count"](spark, sf).collect()}
    assert got == {k: size[n] for k, n in customers.items() if size[n] > 1}
    assert max(got) > 100
    assert datasets.trade(spark, sf)["p2"].count() == len(customers)


def test_scc_of_a_path_and_cycles(spark, tmp_path):
    path = [(k, k + 1) for k in range(1, 60)]
    rings = [(100, 101), (101, 102), (102, 100), (102, 110), (110, 111), (111, 110), (60, 100), (111, 200), (300, 300)]
    at = iter(range(10**6))

    def cut(df, name):
        to = str(tmp_path / f"{name}{next(at)}")
        df.write.parquet(to)
        return spark.read.parquet(to)

    got = sorted(map(tuple, graphops.scc(spark.createDataFrame(path + rings, "a long, b long"), cut).collect()))
    alone = [*range(1, 61), 200, 300]
    assert got == sorted([(k, k) for k in alone] + [(k, 100) for k in (100, 101, 102)] + [(k, 110) for k in (110, 111)])


def near(facts):
    """Closed pairs and their counts by union of sets."""
    groups = []
    for a, b in facts:
        touched = [g for g in groups if a in g or b in g]
        groups = [g for g in groups if g not in touched] + [set().union({a, b}, *touched)]
    return {(a, b) for g in groups for a in g for b in g}


def test_label_store_follows_updates(spark):
    """A symmetric and transitive node is kept as labels through mixed updates of its edges."""
    rng = random.Random(4)
    facts = {(rng.randrange(14), rng.randrange(14)) for _ in range(9)}
    text = rulesets.NEAR + "@c n(x, count(y)) <- near(x, y) group x. @l lone(x) <- all(x), !near(x, x)."
    r = Reasoner(spark, text, frames(spark, {"hasNeighbour": facts, "all": {(i,) for i in range(15)}}))
    r.materialise()
    for step in range(4):
        add = {(rng.randrange(14), rng.randrange(14)) for _ in range(2)} - facts if step != 1 else set()
        drop = set(rng.sample(sorted(facts), 3)) if step else set()
        r.update(add_facts=frames(spark, {"hasNeighbour": add}) if add else {}, drop_facts=frames(spark, {"hasNeighbour": drop}) if drop else {})
        facts = (facts - drop) | add
        want, got = near(facts), state(r)
        assert got["near"] == want
        assert got["n"] == {(x, sum(a == x for a, _ in want)) for x, _ in want}
        assert got.get("lone", set()) == {(i,) for i in range(15) if (i, i) not in want}
    node = r.state.hyper.node_of()["r3"]
    assert all(p.labels is not None for p in r.state.stores[node].get("near").parts)


CONFIGS = {
    "stratum": Config(unit="stratum", allow_cross=True), "both": Config(layout="both", allow_cross=True), "checkpoint": Config(cut="checkpoint", allow_cross=True),
    "pairs": Config(agg_over="pairs", allow_cross=True, insertion_mode="auto"), "delta": Config(successor_policy="delta", bound_aware=False, allow_cross=True, order="dp"), "merged": Config(bag="merged", allow_cross=True, scc="low_link"),
}


@pytest.mark.parametrize("name", CONFIGS)
def test_variants_equal_brute_force(spark, name):
    """Recursion, negation, aggregates and joins after a mixed update, against the evaluator."""
    facts = {"e": {(0, 1), (1, 2), (2, 0), (3, 4)}, "n": {(i,) for i in range(5)}, "extra": {(0, 4), (4, 2)}}
    r = Reasoner(spark, PROGRAM, frames(spark, facts), CONFIGS[name])
    r.materialise()
    r.update(drop_rules=["r6"], add_facts=frames(spark, {"e": {(4, 0)}}), drop_facts=frames(spark, {"e": {(2, 0)}}))
    facts["e"] = {(0, 1), (1, 2), (3, 4), (4, 0)}
    rules = parse_program(PROGRAM).rules
    assert state(r) == evaluate("\n".join(f"@{i} {x.text()}." for i, x in rules.items() if i != "r6"), facts)


def test_stratum_baseline_deletes_what_it_derived(spark):
    r = Reasoner(spark, rulesets.NEAR, frames(spark, {"hasNeighbour": {(i, i + 1) for i in range(6)}}), Config(unit="stratum", pattern_closure="off"))
    r.materialise()
    r.delete_facts("hasNeighbour", spark.createDataFrame([(2, 3)], "a long, b long"))
    assert state(r)["near"] == near({(0, 1), (1, 2), (3, 4), (4, 5), (5, 6)})


def test_explain_of_a_dense_relation(spark):
    """The only proof is one of many bindings; all facts of a proof are proved below it."""
    n = 70
    facts = {"e": {(0, i) for i in range(1, n)} | {(i, 0) for i in range(1, n)} | {(n - 1, n)}}
    r = Reasoner(spark, "t(x, y) <- e(x, y). t(x, z) <- t(x, y), t(y, z).", frames(spark, facts))
    r.materialise()
    proof = r.explain("t", 5, n)
    assert proof[0][0] == f"t(5, {n})" and f"e({n - 1}, {n})" in dict(proof)
    assert r.explain("t", n, 5) == []


def test_batches_survive_a_restart(spark, tmp_path):
    from rulemat.streaming.updates import run_fact_updates

    spark.createDataFrame([("+", "hasNeighbour", 1, 2)], "op string, pred string, a long, b long").write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("op string, pred string, a long, b long").parquet(str(tmp_path / "in"))
    r = Reasoner(spark, rulesets.NEAR, schemas={"hasNeighbour": ["bigint", "bigint"]})
    r.materialise()
    run_fact_updates(r, source, str(tmp_path / "c1"), {"hasNeighbour": ["a", "b"]}, save_to=str(tmp_path / "state")).awaitTermination()
    again = Reasoner.restore(spark, str(tmp_path / "state"))
    version = again.state.version
    # the stream lost its note of the batch, and delivers it again
    run_fact_updates(again, source, str(tmp_path / "c2"), {"hasNeighbour": ["a", "b"]}).awaitTermination()
    assert again.state.version == version and state(again)["near"] == {(1, 1), (1, 2), (2, 1), (2, 2)}
