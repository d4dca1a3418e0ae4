"""Rule dependency graph, its components, and the condensed graph that orders evaluation.

Rules number thousands at most, so all of this is driver metadata.  Edge kinds: ``P`` positive,
``N`` negated, ``A`` aggregated body (strict like a negated one).
"""

from __future__ import annotations

import heapq
from collections import defaultdict
from collections.abc import Iterable
from dataclasses import dataclass, field

from ..lang.checks import UnstratifiableError
from ..lang.syntax import Program, Rule

Edge = tuple[str, str, str]


class RuleGraph:
    """Rules as vertices; an edge from the rule that makes a predicate to the one that reads it.
    Rules come and go one by one, touching only the edges of their own predicates."""

    def __init__(self, rules: Iterable[Rule] = ()):
        self.rules: dict[str, Rule] = {}
        self.makers: dict[str, set[str]] = defaultdict(set)
        self.readers: dict[str, set[tuple[str, str]]] = defaultdict(set)
        self.edges: set[Edge] = set()
        self.add(rules)

    def copy(self) -> RuleGraph:
        out = RuleGraph()
        out.rules, out.edges = dict(self.rules), set(self.edges)
        out.makers = defaultdict(set, {k: set(v) for k, v in self.makers.items()})
        out.readers = defaultdict(set, {k: set(v) for k, v in self.readers.items()})
        return out

    @staticmethod
    def _reads(rule: Rule) -> set[tuple[str, str]]:
        positive = "A" if rule.agg else "P"
        return {(a.pred, positive) for a in rule.positives} | {(a.pred, "N") for a in rule.negatives}

    def add(self, rules: Iterable[Rule]) -> None:
        rules = list(rules)
        for r in rules:
            self.rules[r.id] = r
            self.makers[r.head.pred].add(r.id)
            for pred, kind in self._reads(r):
                self.readers[pred].add((r.id, kind))
        for r in rules:
            self.edges |= {(r.id, reader, kind) for reader, kind in self.readers[r.head.pred]}
            self.edges |= {(maker, r.id, kind) for pred, kind in self._reads(r) for maker in self.makers[pred]}

    def remove(self, ids: Iterable[str]) -> None:
        gone = set(ids)
        for i in gone:
            r = self.rules.pop(i)
            self.makers[r.head.pred].discard(i)
            for pred, kind in self._reads(r):
                self.readers[pred].discard((i, kind))
        self.edges = {e for e in self.edges if e[0] not in gone and e[1] not in gone}

    def subgraph(self, kind: str) -> set[tuple[str, str]]:
        return {(a, b) for a, b, k in self.edges if k == kind}

    def successors(self) -> dict[str, list[str]]:
        out: dict[str, set[str]] = {r: set() for r in self.rules}
        for a, b, _ in self.edges:
            out[a].add(b)
        return {k: sorted(v) for k, v in out.items()}


def reverse_finish(nodes: Iterable[str], after: dict[str, list[str]]) -> list[str]:
    """Nodes reached from ``nodes``, last finished first, by an explicit stack."""
    seen: set[str] = set()
    done: list[str] = []
    for root in nodes:
        if root in seen:
            continue
        seen.add(root)
        stack = [(root, iter(after.get(root, ())))]
        while stack:
            node, rest = stack[-1]
            nxt = next((n for n in rest if n not in seen), None)
            if nxt is None:
                done.append(node)
                stack.pop()
            else:
                seen.add(nxt)
                stack.append((nxt, iter(after.get(nxt, ()))))
    return done[::-1]


def components(after: dict[str, list[str]], method: str = "two_pass") -> list[frozenset[str]]:
    """Strongly connected components, smallest member first.  ``two_pass`` walks the graph and
    its reverse; ``low_link`` needs one walk and serves as a cross-check."""
    if method == "two_pass":
        back: dict[str, list[str]] = {n: [] for n in after}
        for a, bs in after.items():
            for b in bs:
                back[b].append(a)
        assigned: set[str] = set()
        found = []
        for root in reverse_finish(sorted(after), after):
            if root in assigned:
                continue
            part, todo = {root}, [root]
            assigned.add(root)
            while todo:
                for n in back[todo.pop()]:
                    if n not in assigned:
                        assigned.add(n)
                        part.add(n)
                        todo.append(n)
            found.append(frozenset(part))
    elif method == "low_link":
        index: dict[str, int] = {}
        low: dict[str, int] = {}
        held: list[str] = []
        on: set[str] = set()
        found = []
        for root in sorted(after):
            if root in index:
                continue
            work = [(root, iter(after[root]))]
            index[root] = low[root] = len(index)
            held.append(root)
            on.add(root)
            while work:
                node, rest = work[-1]
                for n in rest:
                    if n not in index:
                        index[n] = low[n] = len(index)
                        held.append(n)
                        on.add(n)
                        work.append((n, iter(after[n])))
                        break
                    if n in on:
                        low[node] = min(low[node], index[n])
                else:
                    work.pop()
                    if work:
                        low[work[-1][0]] = min(low[work[-1][0]], low[node])
                    if low[node] == index[node]:
                        part = set()
                        while True:
                            x = held.pop()
                            on.discard(x)
                            part.add(x)
                            if x == node:
                                break
                        found.append(frozenset(part))
    else:
        raise ValueError(f"unknown method {method}")
    return sorted(found, key=min)


@dataclass
class HyperGraph:
    """Components of a rule graph as nodes; edges between them by kind."""

    nodes: dict[str, frozenset[str]]
    edges: set[Edge] = field(default_factory=set)

    def node_of(self) -> dict[str, str]:
        return {r: n for n, rs in self.nodes.items() for r in rs}

    def successors(self) -> dict[str, list[str]]:
        out: dict[str, set[str]] = {n: set() for n in self.nodes}
        for a, b, _ in self.edges:
            if a != b:
                out[a].add(b)
        return {k: sorted(v) for k, v in out.items()}

    def predecessors(self, node: str) -> set[str]:
        return {a for a, b, _ in self.edges if b == node and a != b}

    def topo_order(self) -> list[str]:
        """Topological order over all edges; among ready nodes the one with the smallest rule."""
        after = self.successors()
        waiting = {n: len(self.predecessors(n)) for n in self.nodes}
        key = lambda n: (min(map(rule_order, self.nodes[n])), n)
        ready = [(key(n), n) for n, k in waiting.items() if not k]
        heapq.heapify(ready)
        out = []
        while ready:
            _, n = heapq.heappop(ready)
            out.append(n)
            for m in after[n]:
                waiting[m] -= 1
                if not waiting[m]:
                    heapq.heappush(ready, (key(m), m))
        return out


def rule_order(rule_id: str) -> tuple[str, int, str]:
    """Natural order of rule names: r2 before r10."""
    digits = "".join(c for c in rule_id if c.isdigit())
    return (rule_id.rstrip("0123456789"), int(digits) if digits else -1, rule_id)


def condense(graph: RuleGraph, names: dict[frozenset[str], str] | None = None, method: str = "two_pass") -> HyperGraph:
    """The graph of components.  Positive edges join different components; a strict edge inside
    one component stays as a self loop, which ``require_acyclic`` rejects."""
    parts = sorted(components(graph.successors(), method), key=lambda p: min(map(rule_order, p)))
    nodes = {(names or {}).get(p) or f"hn{k}": p for k, p in enumerate(parts, 1)}
    hyper = HyperGraph(nodes)
    of = hyper.node_of()
    hyper.edges = {(of[a], of[b], k) for a, b, k in graph.edges if of[a] != of[b] or k != "P"}
    return hyper


def require_acyclic(hyper: HyperGraph) -> None:
    loops = sorted(n for a, n, _ in hyper.edges if a == n)
    if loops:
        raise UnstratifiableError(f"negation or aggregation inside the cycle of rules {sorted(hyper.nodes[loops[0]])}")


def stratify(graph: RuleGraph) -> dict[str, int]:
    """Smallest stratum of each rule: not below a positive, above a strict dependency."""
    hyper = condense(graph)
    require_acyclic(hyper)
    level: dict[str, int] = {}
    for n in hyper.topo_order():
        level[n] = max([0, *(level[a] + (k != "P") for a, b, k in hyper.edges if b == n)])
    return {r: level[n] for n, rs in hyper.nodes.items() for r in rs}


def build_rule_graph(program: Program) -> RuleGraph:
    return RuleGraph(program)
