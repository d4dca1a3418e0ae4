"""Evaluation of one node's rules to a fixpoint, on relations that never leave the cluster."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang.syntax import Atom, Rule, Var
from ..plans.compile import Compiler, Resolver, union
from ..plans.order import Stats
from .metrics import UpdateLog
from .store import FactStore, Relation, Storage

Ext = Callable[[str], DataFrame | None]


@dataclass
class Context:
    storage: Storage
    compiler: Compiler
    stats: Stats
    log: UpdateLog
    max_rounds: int | None = None
    evaluation: str = "semi_naive"
    compact_parts: int = 6
    #: Rounds after which a linear node is finished by path doubling; None never.
    linear_after: int | None = 10


def minus(df: DataFrame, other: DataFrame | None) -> DataFrame:
    return df if other is None else df.join(other, df.columns, "left_anti")


def meet(df: DataFrame, other: DataFrame | None) -> DataFrame | None:
    return None if other is None else df.join(other, df.columns, "left_semi")


class Node:
    """The relations of one node during its evaluation: external ones, its own store, deltas."""

    def __init__(self, ctx: Context, rules: list[Rule], ext: Ext, own: FactStore):
        self.ctx, self.rules, self.ext, self.own = ctx, rules, ext, own
        self.heads = {r.head.pred for r in rules}
        self.recursive = any(a.pred in self.heads for r in rules for a in r.positives)
        self._ext: dict[str, DataFrame | None] = {}

    def external(self, pred: str) -> DataFrame | None:
        if pred not in self._ext:
            self._ext[pred] = self.ext(pred)
        return self._ext[pred]

    def visible(self, pred: str, own: Relation | None = None) -> DataFrame:
        a = self.external(pred)
        b = (own if own is not None else self.own.get(pred)).frame() if pred in self.heads or own is not None else None
        if a is None and b is None:
            return self.ctx.compiler.empty(pred)
        if a is None or b is None:
            return a if b is None else b
        return a.unionByName(b).distinct()

    def resolver(self, at: int | None = None, changed: DataFrame | None = None, negated: bool = False, before: Callable[[str], DataFrame] | None = None) -> Resolver:
        """Reads the visible relations; position ``at`` reads a change, and later positions
        read the state before it where one is given."""

        def resolve(k: int, atom: Atom, neg: bool) -> DataFrame:
            if at is not None and k == at and neg == negated:
                return changed
            if before is not None and not neg and not negated and at is not None and k > at and atom.pred in self.heads:
                return before(atom.pred)
            return self.visible(atom.pred)

        return resolve

    def add(self, found: dict[str, list[DataFrame]]) -> dict[str, DataFrame]:
        """Put new facts of the candidates into the own store; returns those newly visible."""
        fresh: dict[str, DataFrame] = {}
        for pred, frames in found.items():
            new = minus(union(frames).distinct(), self.own.get(pred).frame())
            part = self.ctx.storage.write(new)
            self.ctx.log.counts["facts"] += part.rows
            if not part.rows:
                continue
            rel = self.own.get(pred)
            self.own = self.own.put(pred, rel.plus(part))
            outside = self.external(pred)
            fresh[pred] = part.frame if outside is None else minus(part.frame, outside)
        return fresh

    def compact(self) -> None:
        for pred, rel in self.own.relations.items():
            if len(rel.parts) > self.ctx.compact_parts:
                self.own = self.own.put(pred, Relation((self.ctx.storage.write(rel.frame().coalesce(max(1, min(rel.rows // 100_000 + 1, 200)))),)))

    def frame(self, rule: Rule, resolve: Resolver, **how: object) -> DataFrame:
        if not how and (labels := by_component(rule, self.ext)) is not None:
            return self.ctx.compiler.component_frame(rule, resolve, self.ctx.stats, *labels)
        if not how and rule.agg and self.ctx.compiler.runs_along(rule) and (ranks := by_component(rule, self.ext, "ranks")) is not None and len(rule.agg.group) == 1:
            return self.ctx.compiler.chain_frame(rule, resolve, self.ctx.stats, *ranks)
        return self.ctx.compiler.rule_frame(rule, resolve, self.ctx.stats, **how)

    def evaluate(self, rules: list[Rule]) -> dict[str, list[DataFrame]]:
        """One full application of rules."""
        found: dict[str, list[DataFrame]] = {}
        for r in rules:
            found.setdefault(r.head.pred, []).append(self.frame(r, self.resolver()))
        return found

    def close(self, fresh: dict[str, DataFrame]) -> None:
        """Semi-naive rounds until nothing new appears; ``fresh`` are the last new facts."""
        rounds = 0
        while fresh and self.recursive:
            rounds += 1
            if self.ctx.max_rounds and rounds > self.ctx.max_rounds:
                raise RuntimeError(f"no fixpoint within {self.ctx.max_rounds} rounds")
            self.ctx.log.counts["rounds"] += 1
            if self.ctx.evaluation != "naive" and self.ctx.linear_after is not None and rounds > self.ctx.linear_after and (far := self.jump(fresh)) is not None:
                self.add(far)
                break
            if self.ctx.evaluation != "naive" and self.ctx.linear_after is not None and rounds == self.ctx.linear_after + 1 and (far := self.leap()) is not None:
                fresh = self.add(far)
                continue
            if self.ctx.evaluation == "naive":
                fresh = self.add(self.evaluate(self.rules))
                continue
            old = {p: Relation(self.own.get(p).parts[:-1]) for p in fresh}
            before = lambda p: self.visible(p, old.get(p, self.own.get(p)))  # noqa: B023, E731
            found: dict[str, list[DataFrame]] = {}
            for r in self.rules:
                for k, a in enumerate(r.positives):
                    if a.pred in fresh:
                        found.setdefault(r.head.pred, []).append(self.frame(r, self.resolver(k, fresh[a.pred], before=before), first=k))
            fresh = self.add(found)
            if max(len(x.parts) for x in self.own.relations.values()) > 2 * self.ctx.compact_parts:
                self.compact()
                self.ctx.log.counts["compactions"] += 1
                self._whole_before()
        self.compact()

    def _whole_before(self) -> None:
        """After compaction the newest facts are no part of their own; re-joining a few pairs
        twice is harmless, so later positions simply read the whole relation."""
        for p, rel in self.own.relations.items():
            self.own = self.own.put(p, Relation((*rel.parts, _NOTHING)))


    def jump(self, fresh: dict[str, DataFrame]) -> dict[str, list[DataFrame]] | None:
        """All consequences of facts in a node whose recursion is linear on one column: steps
        (predicate, value) to (predicate, value) are closed by doubling, so a chain of n steps
        takes log2(n) rounds, and one join carries the facts along the closed steps."""
        if (way := linear(self.rules, self.heads)) is None:
            return None
        keep, rules = way
        kinds = {self.ctx.compiler.types[p][1 - keep] for p in self.heads}
        if len(kinds) != 1 or any(len(self.ctx.compiler.types[p]) != 2 for p in self.heads):
            return None
        steps = []
        for r, k in rules:
            rest = replace(r, positives=tuple(a for i, a in enumerate(r.positives) if i != k))
            b = self.ctx.compiler.bindings(rest, lambda i, a, n: self.visible(a.pred), self.ctx.stats)
            steps.append(b.select(F.lit(r.positives[k].pred).alias("c0"), F.col(f"v_{r.positives[k].args[1 - keep].name}").alias("c1"), F.lit(r.head.pred).alias("c2"), F.col(f"v_{r.head.args[1 - keep].name}").alias("c3")))
        base = self.ctx.storage.write(union(steps).distinct())
        if base.rows > 4 * max(1000, self.own.rows):
            return None
        path = Atom("t", tuple(map(Var, ("g", "y", "h", "z")))), Atom("t", tuple(map(Var, ("h", "z", "k", "w"))))
        rule = Rule("doubling", Atom("t", tuple(map(Var, ("g", "y", "k", "w")))), path)
        types = {"t": ["string", *kinds, "string", *kinds]}
        ctx = replace(self.ctx, compiler=self.ctx.compiler.typed(types), linear_after=None)
        own = run_node(ctx, [rule], lambda p: base.frame)
        whole = base.frame if not own.rows else base.frame.unionByName(own.get("t").frame()).distinct()
        facts = union([df.select(F.lit(p).alias("c0"), F.col(f"c{1 - keep}").alias("c1"), F.col(f"c{keep}").alias("x")) for p, df in fresh.items()])
        far = self.ctx.storage.write(facts.join(whole, ["c0", "c1"]).select("c2", "x", "c3").distinct()).frame
        order = ["x", "c3"] if keep == 0 else ["c3", "x"]
        return {p: [far.where(F.col("c2") == p).select(F.col(order[0]).alias("c0"), F.col(order[1]).alias("c1"))] for p in self.heads}


    def leap(self) -> dict[str, list[DataFrame]] | None:
        """New facts of a node whose recursion is linear over single values: each round goes as
        far as all rounds before it, along steps of doubled length, until nothing new comes up
        or the doubled steps are too many.  Rounds of the usual kind go on from there."""
        ctx = self.ctx
        steps = []
        for r in (r for r in self.rules if any(a.pred in self.heads for a in r.positives)):
            at = [k for k, a in enumerate(r.positives) if a.pred in self.heads]
            ends = [t for k in at for t in r.positives[k].args] + list(r.head.args)
            if len(at) != 1 or r.agg or len(ends) != 2 or not all(isinstance(t, Var) and t.name != "_" for t in ends):
                return None
            rest = replace(r, positives=tuple(a for i, a in enumerate(r.positives) if i != at[0]))
            if not {t.name for t in ends} <= {v for a in rest.positives for v in a.vars()} | {b.var for b in rest.binds} or ends[0].name not in {v for a in rest.positives for v in a.vars()}:
                return None
            b = ctx.compiler.bindings(rest, lambda i, a, n: self.visible(a.pred), ctx.stats)
            steps.append(b.select(F.lit(r.positives[at[0]].pred).alias("g"), F.col(f"v_{ends[0].name}").alias("y"), F.lit(r.head.pred).alias("h"), F.col(f"v_{ends[1].name}").alias("z")))
        if not steps or any(len(ctx.compiler.types[p]) != 1 for p in self.heads) or len({ctx.compiler.types[p][0] for p in self.heads}) != 1:
            return None
        step = ctx.storage.write(union(steps).distinct())
        limit = 4 * max(1000, step.rows)
        known = ctx.storage.write(union([self.visible(p).select(F.lit(p).alias("g"), F.col("c0").alias("y")) for p in sorted(self.heads)])).frame
        news: list[DataFrame] = []
        while step.rows <= limit:
            far = known.join(step.frame, ["g", "y"]).select(F.col("h").alias("g"), F.col("z").alias("y")).distinct()
            new = ctx.storage.write(far.join(known, ["g", "y"], "left_anti"))
            if not new.rows:
                break
            news.append(new.frame)
            known = ctx.storage.write(known.unionByName(new.frame)).frame
            on = step.frame.select(F.col("g").alias("h"), F.col("y").alias("z"), F.col("h").alias("k"), F.col("z").alias("w"))
            step = ctx.storage.write(step.frame.join(on, ["h", "z"]).select("g", "y", F.col("k").alias("h"), F.col("w").alias("z")).distinct())
            ctx.log.counts["rounds"] += 1
        if not news:
            return None
        whole = union(news)
        return {p: [whole.where(F.col("g") == p).select(F.col("y").alias("c0"))] for p in sorted(self.heads)}


def by_component(rule: Rule, ext: Ext, form: str = "labels") -> tuple[int, int, DataFrame] | None:
    """The atom of an aggregate whose relation is at rest as labels and whose group is the same
    for all nodes of a component, the place of the grouped variable in it, and the labels.  Of
    ``ranks`` the group follows from a node's place in its chain."""
    find = getattr(ext, form, None)
    if find is None or not rule.agg:
        return None
    for k, a in enumerate(rule.positives):
        if len(a.args) != 2 or not all(isinstance(t, Var) and t.name != "_" for t in a.args) or a.args[0] == a.args[1]:
            continue
        for side in (0, 1):
            x = a.args[side].name
            others = [v for i, b in enumerate(rule.positives) if i != k for v in b.vars()] + [v for b in rule.negatives for v in b.vars()]
            others += [v for b in rule.binds for v in (*b.expr.vars(), b.var)] + [v for c in rule.comps for v in c.vars()]
            if x in rule.agg.group and x not in others and x not in (rule.agg.var, rule.agg.result) and (labels := find(a.pred)) is not None:
                return k, side, labels
    return None


def linear(rules: list[Rule], heads: set[str]) -> tuple[int, list[tuple[Rule, int]]] | None:
    """The column that every recursive rule passes on unchanged from its only recursive atom,
    and those rules with the position of that atom; None if there is no such column."""
    for keep in (0, 1):
        out = []
        for r in rules:
            at = [k for k, a in enumerate(r.positives) if a.pred in heads]
            if not at:
                continue
            if len(at) > 1 or r.agg or len(r.head.args) != 2:
                break
            a = r.positives[at[0]]
            rest = [t for i, x in enumerate(r.positives) if i != at[0] for t in x.args] + [t for x in r.negatives for t in x.args]
            used = {t.name for t in rest if isinstance(t, Var)} | {v for b in r.binds for v in (*b.expr.vars(), b.var)} | {v for c in r.comps for v in c.vars()}
            names = [getattr(t, "name", "_") for t in (*a.args, *r.head.args)]
            if len(a.args) != 2 or "_" in names or names[keep] != names[2 + keep] or names[keep] in used or names[1 - keep] not in used or names[3 - keep] not in used or names[keep] in (names[1 - keep], names[3 - keep]):
                break
            out.append((r, at[0]))
        else:
            if out:
                return keep, out
    return None


class _Nothing:
    rows, path, frame = 0, None, None


_NOTHING = _Nothing()


def run_node(ctx: Context, rules: list[Rule], ext: Ext, own: FactStore | None = None) -> FactStore:
    """Evaluate a node's rules from its inputs."""
    node = Node(ctx, rules, ext, own or FactStore())
    ctx.log.counts["rules_run"] += len(rules)
    node.close(node.add(node.evaluate(rules)))
    return node.own


def distinct_values(df: DataFrame) -> list[int]:
    """Approximate distinct values of every column, from mergeable sketches, in one job."""
    row = df.agg(*[F.approx_count_distinct(c) for c in df.columns]).first()
    return [int(x) for x in row]


