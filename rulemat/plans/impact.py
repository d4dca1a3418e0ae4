"""Which nodes a rule update concerns directly, and the order in which to revisit nodes."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from ..lang.syntax import Rule
from .depgraph import HyperGraph, RuleGraph, components, reverse_finish, require_acyclic, rule_order

POLICIES = ("structural", "always", "delta")


@dataclass
class Impact:
    graph: RuleGraph
    hyper: HyperGraph
    #: Nodes whose rules or components changed, by new name.
    direct: set[str]
    #: Old nodes whose stores each new node takes over.
    sources: dict[str, list[str]]
    #: Old nodes that vanished.
    gone: set[str] = field(default_factory=set)
    #: New rules of each node.
    fresh: dict[str, set[str]] = field(default_factory=dict)


@dataclass(frozen=True)
class Step:
    node: str
    role: str  # direct or downstream


def _named(parts: Iterable[frozenset[str]], old: dict[str, str], taken: set[str]) -> dict[str, frozenset[str]]:
    """A part keeps the name of its smallest rule's old node if no smaller part took it."""
    free = max([0, *(int(n[2:]) for n in taken if n[2:].isdigit())])
    out: dict[str, frozenset[str]] = {}
    for part in sorted(parts, key=lambda p: min(map(rule_order, p))):
        name = next((old[r] for r in sorted(part, key=rule_order) if r in old and old[r] not in out), None)
        if name is None:
            free += 1
            name = f"hn{free}"
        out[name] = part
    return out


def _edges(graph: RuleGraph, hyper: HyperGraph) -> None:
    of = hyper.node_of()
    hyper.edges = {(of[a], of[b], k) for a, b, k in graph.edges if of[a] != of[b] or k != "P"}


def on_insert(graph: RuleGraph, hyper: HyperGraph, rules: Iterable[Rule], method: str = "two_pass") -> Impact:
    """Every new rule starts as a node of its own; components of that graph merge nodes."""
    rules = list(rules)
    new = {r.id for r in rules}
    g = graph.copy()
    g.add(rules)
    old = hyper.node_of()
    unit = {r: old.get(r, f"+{r}") for r in g.rules}
    after: dict[str, set[str]] = {u: set() for u in unit.values()}
    for a, b, _ in g.edges:
        after[unit[a]].add(unit[b])
    merged = components({k: sorted(v) for k, v in after.items()}, method)
    members: dict[str, set[str]] = {}
    for r, u in unit.items():
        members.setdefault(u, set()).add(r)
    parts = [frozenset(r for u in m for r in members[u]) for m in merged]
    h = HyperGraph(_named(parts, old, set(hyper.nodes)))
    _edges(g, h)
    require_acyclic(h)
    sources = {n: sorted({old[r] for r in rs if r in old}) for n, rs in h.nodes.items()}
    fresh = {n: set(rs & new) for n, rs in h.nodes.items() if rs & new}
    direct = {n for n in h.nodes if n in fresh or len(sources[n]) > 1}
    return Impact(g, h, direct, sources, set(), fresh)


def on_delete(graph: RuleGraph, hyper: HyperGraph, ids: Iterable[str], policy: str = "structural", method: str = "two_pass") -> Impact:
    """Nodes that lose rules are split anew or vanish.  ``policy`` says when their successors
    are revisited in full: after a change of structure, always, or never."""
    if policy not in POLICIES:
        raise ValueError(f"unknown successor policy {policy}")
    gone = set(ids)
    g = graph.copy()
    g.remove(gone)
    old = hyper.node_of()
    dirty = {old[r] for r in gone}
    parts: list[frozenset[str]] = [rs for n, rs in hyper.nodes.items() if n not in dirty]
    changed: list[frozenset[str]] = []
    structural: set[str] = set()
    after = g.successors()
    for n in dirty:
        rest = hyper.nodes[n] - gone
        split = components({r: [b for b in after[r] if b in rest] for r in rest}, method)
        changed += split
        if len(split) != 1:
            structural.add(n)
    h = HyperGraph(_named([*parts, *changed], old, set(hyper.nodes)))
    _edges(g, h)
    of = h.node_of()
    direct = {of[min(p)] for p in changed}
    vanished = {n for n in dirty if not hyper.nodes[n] - gone}
    revisit = dirty if policy == "always" else structural - vanished if policy == "structural" else set()
    for n in revisit:
        for m in hyper.successors()[n]:
            left = hyper.nodes[m] - gone
            direct |= {of[r] for r in left}
    sources = {n: sorted({old[r] for r in rs}) for n, rs in h.nodes.items()}
    return Impact(g, h, direct, sources, vanished)


def execution_plan(hyper: HyperGraph, direct: Iterable[str], also: Iterable[str] = ()) -> list[Step]:
    """Direct nodes and all they reach, in a topological order of just that part."""
    direct = set(direct)
    roots = sorted(direct | set(also))
    return [Step(n, "direct" if n in direct else "downstream") for n in reverse_finish(roots, hyper.successors())]
