import random

import pytest

from rulemat.lang import UnstratifiableError, parse_program
from rulemat.plans.depgraph import build_rule_graph, components, condense, require_acyclic, reverse_finish, stratify
from rulemat.plans.impact import execution_plan, on_delete, on_insert
from rulemat.plans.order import Stats, left_deep, rank
from rulemat.workloads import rulesets


def graphs(text):
    g = build_rule_graph(parse_program(text))
    return g, condense(g)


def test_running_example():
    g, h = graphs(rulesets.REX)
    assert {n: set(r) for n, r in h.nodes.items()} == {"hn1": {"r1"}, "hn2": {"r2", "r3", "r4"}, "hn3": {"r5"}, "hn4": {"r6", "r7"}}
    assert h.edges == {("hn1", "hn2", "P"), ("hn2", "hn4", "P"), ("hn3", "hn4", "P"), ("hn2", "hn3", "N")}
    hit = on_insert(g, h, parse_program(rulesets.REX_R8))
    assert hit.direct == {"hn2"} and hit.hyper.nodes["hn2"] == {"r2", "r3", "r4", "r8"}
    cut = on_delete(hit.graph, hit.hyper, ["r4"])
    assert cut.direct == {"hn2", "hn3", "hn4", "hn5", "hn6"}
    gone = on_delete(g, h, ["r5", "r6", "r7"])
    assert gone.gone == {"hn3", "hn4"} and not gone.direct


def test_deletion_without_change_of_structure():
    g, h = graphs(rulesets.RDEL)
    hit = on_delete(g, h, ["r7"])
    assert [(set(hit.hyper.nodes[s.node]), s.role) for s in execution_plan(hit.hyper, hit.direct)] == [({"r2", "r3"}, "direct"), ({"r4", "r5", "r6"}, "downstream")]
    assert on_delete(g, h, ["r7"], "always").direct == {"hn2", "hn3"}


@pytest.mark.parametrize(("text", "nodes", "preds"), [(rulesets.RS1, 5, 6), (rulesets.RS2, 14, 15), (rulesets.RS3, 14, 15)])
def test_profiles(text, nodes, preds):
    p = parse_program(text)
    assert (len(condense(build_rule_graph(p)).nodes), len(p.preds())) == (nodes, preds)


def test_components_agree_with_reachability():
    rng = random.Random(4)
    for _ in range(60):
        n = rng.randint(1, 9)
        after = {f"v{i}": sorted({f"v{rng.randrange(n)}" for _ in range(rng.randint(0, 3))}) for i in range(n)}
        reach = {v: set(reverse_finish([v], after)) for v in after}
        want = {frozenset(w for w in after if w in reach[v] and v in reach[w]) for v in after}
        assert set(components(after)) == set(components(after, "low_link")) == want


@pytest.mark.parametrize("text", ["p(x) <- q(x), !p(x).", "p(x) <- q(x), !r(x). r(x) <- p(x).", "a(x) <- e(x), !b(x). b(x) <- c(x). c(x) <- a(x).", "a(x, count(y)) <- b(x, y) group x. b(x, y) <- a(x, y)."])
def test_unstratifiable(text):
    with pytest.raises(UnstratifiableError):
        require_acyclic(graphs(text)[1])


def test_strata():
    g, _ = graphs(rulesets.RS3)
    s = stratify(g)
    for a, b, k in g.edges:
        assert s[a] <= s[b] if k == "P" else s[a] < s[b]


def test_incremental_edges():
    p = parse_program(rulesets.RS2)
    whole = build_rule_graph(p)
    g = build_rule_graph(p.without(["r4", "r9", "r14"]))
    g.add([p.rules[r] for r in ("r14", "r4", "r9")])
    assert g.edges == whole.edges
    g.remove(["r9"])
    assert g.edges == build_rule_graph(p.without(["r9"])).edges


def test_body_order():
    (r,) = parse_program("h(x, z) <- a(x, y), b(y, z), c(x), d(7, z), e(1, 2).")
    stats = Stats({"a": 1000, "b": 10, "c": 5, "d": 50, "e": 9}, {})
    order = [r.positives[k].pred for k in left_deep(r, stats, "heuristic")]
    assert order[0] == "e" and order[1] == "d"
    assert [r.positives[k].pred for k in left_deep(r, stats, "text")] == ["a", "b", "c", "d", "e"]
    assert sorted(left_deep(r, stats, "dp")) == [0, 1, 2, 3, 4]
    assert [rank(a) for a in r.positives] == [2, 2, 3, 1, 0]
