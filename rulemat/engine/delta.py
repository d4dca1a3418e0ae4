"""Maintenance of one node's store when its inputs changed.

Input changes are the visible additions and removals of each predicate the node reads from
outside.  Removal candidates are found on the old state, then kept or dropped by one of three
methods; additions are found on the new state; both read only joins with a change.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lang.syntax import Rule
from ..plans.compile import Resolver, column, union, value
from .fixpoint import Context, Ext, Node, meet, minus
from .store import EMPTY, FactStore, Part, Relation

METHODS = ("rederive", "backward_forward", "counting")


@dataclass
class Change:
    """Added and removed facts per predicate; absent means none."""

    plus: dict[str, Part] = field(default_factory=dict)
    minus: dict[str, Part] = field(default_factory=dict)

    def __bool__(self) -> bool:
        return any(p.rows for p in (*self.plus.values(), *self.minus.values()))

    def touches(self, preds: set[str]) -> bool:
        return any(p.rows and k in preds for d in (self.plus, self.minus) for k, p in d.items())


def diff(ctx: Context, old: FactStore, new: FactStore, closed: Callable[[Context, Part, Part | None], tuple[Part | None, Part | None]] | None = None) -> Change:
    """Facts that one store has and the other has not, per predicate; shared handles cost nothing,
    and ``closed`` compares a single closed form with another single part."""
    out = Change()
    for pred in {*old.relations, *new.relations}:
        a, b = old.get(pred), new.get(pred)
        if a is b:
            continue
        if closed is not None and (flip := _closed_side(a, b)) is not None:
            one, other = (b, a) if flip else (a, b)
            live = [p for p in other.parts if p.rows]
            gained, lost = closed(ctx, next(p for p in one.parts if p.rows), live[0] if len(live) == 1 else Part(other.frame(), other.rows, None) if live else None)
            for side, part in ((out.minus if flip else out.plus, gained), (out.plus if flip else out.minus, lost)):
                if part is not None and part.rows:
                    side[pred] = part
            continue
        fa, fb = a.frame(), b.frame()
        if fb is not None:
            shared = {id(p) for p in a.parts}
            more = [p for p in b.parts if id(p) not in shared and p.rows]
            if len(more) == 1 and {id(p) for p in a.parts if p.rows} <= {id(p) for p in b.parts}:
                out.plus[pred] = more[0]  # a relation's parts are disjoint
                continue
            grown = Relation(tuple(more)).frame()
            if grown is not None and (part := ctx.storage.write(minus(grown, fa))).rows:
                out.plus[pred] = part
        if fa is not None:
            kept = {id(p) for p in b.parts}
            left = Relation(tuple(p for p in a.parts if id(p) not in kept)).frame()
            if left is not None and (part := ctx.storage.write(minus(left, fb))).rows:
                out.minus[pred] = part
    return out


def _closed_side(a: Relation, b: Relation) -> bool | None:
    """Whether the first (False) or the second (True) of two relations is a single closed form
    that the other, another or of plain parts, can be compared with; None if neither is."""
    pa, pb = ([p for p in r.parts if p.rows] for r in (a, b))
    whole = [len(p) == 1 and p[0].closed for p in (pa, pb)]
    if all(whole):
        return None if pa[0].ranks is not None and pb[0].ranks is not None else False
    if not any(whole) or any(p.closed for p in (pa if whole[1] else pb)):
        return None
    return whole[1]


def in_closed(df: DataFrame, part: Part) -> DataFrame:
    """The pairs of ``df`` that a closed form holds, looked up in its labels or ranks."""
    table = part.labels if part.labels is not None else part.ranks
    side = lambda c: table.select(F.col("node").alias(c), *[F.col(k).alias(f"{c}_{k}") for k in table.columns if k != "node"])
    both = df.join(side("c0"), "c0").join(side("c1"), "c1").where("c0_component = c1_component")
    return (both if part.ranks is None else both.where("c0_left > c1_left")).select("c0", "c1")


class Maintainer:
    def __init__(self, ctx: Context, old_rules: list[Rule], new_rules: list[Rule], ext_old: Ext, ext_new: Ext, own: FactStore, change: Change, method: str = "rederive"):
        self.ctx, self.method, self.change = ctx, method, change
        self.before = Node(ctx, old_rules, ext_old, own)
        self.after = Node(ctx, [*old_rules, *new_rules], ext_new, own)
        self.old_rules, self.new_rules, self.start = old_rules, new_rules, own
        for pred in (p for n in (self.before, self.after) for p in n.heads):
            self.before.heads.add(pred)

    # candidates

    def _heads(self, node: Node, rules: list[Rule], pos: dict[str, DataFrame], neg: dict[str, DataFrame]) -> dict[str, list[DataFrame]]:
        """Heads of instantiations of ``node`` that use a changed fact."""
        out: dict[str, list[DataFrame]] = {}
        for r in rules:
            if r.agg:
                continue
            for k, a in enumerate(r.positives):
                if a.pred in pos:
                    out.setdefault(r.head.pred, []).append(node.frame(r, node.resolver(k, pos[a.pred]), first=k))
            for k, a in enumerate(r.negatives):
                if a.pred in neg:
                    out.setdefault(r.head.pred, []).append(node.frame(r, node.resolver(k, neg[a.pred], negated=True), flip=k))
        return out

    def _written(self, frames: dict[str, list[DataFrame]], keep: dict[str, Relation], without: dict[str, Relation]) -> dict[str, Part]:
        """Candidates that are in ``keep`` and not in ``without``."""
        out = {}
        for pred, fs in frames.items():
            inside = meet(union(fs).distinct(), keep.get(pred, EMPTY).frame())
            if inside is not None and (part := self.ctx.storage.write(minus(inside, without.get(pred, EMPTY).frame()))).rows:
                out[pred] = part
        return out

    def _still_hidden(self, parts: dict[str, Part]) -> dict[str, DataFrame]:
        """Facts that are not visible through another store either."""
        return {p: minus(x.frame, self.after.external(p)) for p, x in parts.items()}

    def _drop(self, gone: dict[str, Relation]) -> None:
        own = self.after.own
        for pred, rel in gone.items():
            if rel.rows:
                left = self.ctx.storage.write(minus(own.get(pred).frame(), rel.frame()))
                own = own.put(pred, Relation((left,)) if left.rows else EMPTY)
        self.after.own = own

    # deletion methods

    def _over_delete(self) -> dict[str, Relation]:
        pos = {p: x.frame for p, x in self.change.minus.items()}
        neg = {p: x.frame for p, x in self.change.plus.items()}
        own = dict(self.start.relations)
        gone: dict[str, Relation] = {}
        rounds, limit = 0, self.ctx.linear_after
        while pos or neg:
            rounds += 1
            if limit is not None and rounds > limit and not neg and (far := self.before.jump(pos)) is not None:
                for pred, part in self._written(far, own, gone).items():
                    gone[pred] = gone.get(pred, EMPTY).plus(part)
                    self.ctx.log.counts["over_deleted"] += part.rows
                break
            found = self._written(self._heads(self.before, self.old_rules, pos, neg), own, gone)
            for pred, part in found.items():
                gone[pred] = gone.get(pred, EMPTY).plus(part)
                self.ctx.log.counts["over_deleted"] += part.rows
            pos, neg = (self._still_hidden(found) if self.before.recursive else {}), {}
        return gone

    def _rederived(self, gone: dict[str, Relation]) -> dict[str, list[DataFrame]]:
        """Dropped facts that one step over what is left still derives."""
        out: dict[str, list[DataFrame]] = {}
        for r in self.old_rules:
            if r.agg or not gone.get(r.head.pred, EMPTY).rows:
                continue
            lost = gone[r.head.pred].frame()
            self.ctx.log.counts["rechecked"] += gone[r.head.pred].rows
            out.setdefault(r.head.pred, []).append(meet(self._guarded(self.after, r, lost, self.after.resolver()), lost))
        return out

    def _guarded(self, node: Node, r: Rule, facts: DataFrame, resolve: Resolver) -> DataFrame:
        """Heads of ``r`` restricted to given facts before the body is joined."""
        seed = facts
        for k, a in enumerate(r.head.args):
            if not hasattr(a, "name"):
                seed = seed.where(F.col(f"c{k}") == value(a))
        at = {}
        positive = {v for a in r.positives for v in a.vars()}
        for k, a in enumerate(r.head.args):
            if hasattr(a, "name") and a.name in positive:
                at.setdefault(a.name, k)
        if not at:
            return node.frame(r, resolve)
        seed = seed.select(*[F.col(f"c{k}").alias(column(v)) for v, k in at.items()]).distinct()
        return node.frame(r, resolve, seed=seed)

    def _backward_forward(self) -> dict[str, Relation]:
        """Delete only what has no proof left: candidates are proved from facts outside the node
        and from proved facts; what a proof might need is fetched one level at a time."""
        ctx = self.ctx
        pos = {p: x.frame for p, x in self.change.minus.items()}
        neg = {p: x.frame for p, x in self.change.plus.items()}
        gone: dict[str, Relation] = {}
        while pos or neg:
            cands = self._written(self._heads(self.before, self.old_rules, pos, neg), dict(self.start.relations), gone)
            if not cands:
                break
            unproved = self._unproved(cands, gone)
            for pred, part in unproved.items():
                gone[pred] = gone.get(pred, EMPTY).plus(part)
                ctx.log.counts["over_deleted"] += part.rows
            pos, neg = (self._still_hidden(unproved) if self.before.recursive else {}), {}
        return gone

    def _unproved(self, cands: dict[str, Part], gone: dict[str, Relation]) -> dict[str, Part]:
        ctx, heads = self.ctx, self.after.heads
        check = {p: Relation((x,)) for p, x in cands.items()}
        proved: dict[str, Relation] = {}

        def limited(pred: str, inner: DataFrame | None) -> DataFrame:
            a = self.after.external(pred)
            if a is None or inner is None:
                return a if inner is None and a is not None else inner if inner is not None else ctx.compiler.empty(pred)
            return a.unionByName(inner).distinct()

        while True:
            while True:  # forward: facts to check that a step over proved and outside facts derives
                reader = lambda k, a, n: limited(a.pred, proved.get(a.pred, EMPTY).frame()) if a.pred in heads and not n else self.after.visible(a.pred)
                moved = False
                for pred, rel in check.items():
                    todo = minus(rel.frame(), proved.get(pred, EMPTY).frame())
                    got = [meet(self._guarded(self.after, r, todo, reader), todo) for r in self.old_rules if r.head.pred == pred and not r.agg]
                    part = ctx.storage.write(union(got).distinct()) if got else None
                    if part is not None and part.rows:
                        proved[pred] = proved.get(pred, EMPTY).plus(part)
                        moved = True
                if not moved or not self.before.recursive:
                    break
            left = {p: part for p, x in cands.items() if (part := ctx.storage.write(minus(x.frame, proved.get(p, EMPTY).frame()))).rows}
            if not left or not self.before.recursive:
                return left
            # backward: own facts that instantiations of unproved facts use
            used: dict[str, list[DataFrame]] = {}
            remaining = lambda p: minus(self.start.get(p).frame(), gone.get(p, EMPTY).frame()) if self.start.get(p).rows else ctx.compiler.empty(p)
            reader = lambda k, a, n: limited(a.pred, remaining(a.pred)) if a.pred in heads and not n else self.after.visible(a.pred)
            for r in self.old_rules:
                if r.agg or r.head.pred not in check:
                    continue
                todo = minus(check[r.head.pred].frame(), proved.get(r.head.pred, EMPTY).frame())
                seed = self._seed(r, todo)
                b = ctx.compiler.bindings(r, reader, ctx.stats, **({"seed": seed} if seed is not None else {}))
                for a in r.positives:
                    if a.pred in heads:
                        used.setdefault(a.pred, []).append(b.select(*[(value(t) if not hasattr(t, "name") else F.col(column(t.name))).alias(f"c{k}") for k, t in enumerate(a.args)]) if all(getattr(t, "name", "") != "_" for t in a.args) else remaining(a.pred))
            grown = False
            for pred, fs in used.items():
                part = ctx.storage.write(minus(meet(union(fs).distinct(), remaining(pred)), check.get(pred, EMPTY).frame()))
                if part.rows:
                    ctx.log.counts["rechecked"] += part.rows
                    check[pred] = check.get(pred, EMPTY).plus(part)
                    grown = True
            if not grown:
                return left

    def _seed(self, r: Rule, facts: DataFrame) -> DataFrame | None:
        positive = {v for a in r.positives for v in a.vars()}
        at = {}
        for k, a in enumerate(r.head.args):
            if hasattr(a, "name") and a.name in positive:
                at.setdefault(a.name, k)
        return facts.select(*[F.col(f"c{k}").alias(column(v)) for v, k in at.items()]).distinct() if at else None

    def _counting(self) -> dict[str, Relation]:
        """Numbers of derivations before and after, for the facts that lost one; facts at zero go.
        Only for nodes without recursion: a fact's derivations use outside facts alone."""
        if self.before.recursive:
            raise ValueError("counting needs a node without recursion")
        pos = {p: x.frame for p, x in self.change.minus.items()}
        neg = {p: x.frame for p, x in self.change.plus.items()}
        touched = self._written(self._heads(self.before, self.old_rules, pos, neg), dict(self.start.relations), {})
        gone: dict[str, Relation] = {}
        for pred, part in touched.items():
            frames = []
            for node, sign in ((self.before, 0), (self.after, 1)):
                for r in self.old_rules:
                    if r.head.pred == pred:
                        frames.append(meet(self._guarded(node, r, part.frame, node.resolver()), part.frame).withColumn("after", F.lit(sign)))
            keys = [f"c{k}" for k in range(len(self.ctx.compiler.types[pred]))]
            counts = union(frames).groupBy(*keys).agg(F.sum(1 - F.col("after")).alias("had"), F.sum("after").alias("has"))
            left = self.ctx.storage.write(counts.where((F.col("had") > 0) & (F.col("has") == 0)).select(*keys))
            self.ctx.log.counts["rechecked"] += part.rows
            if left.rows:
                gone[pred] = Relation((left,))
        return gone

    # the step

    def run(self) -> FactStore:
        ctx = self.ctx
        if any(r.agg for r in self.old_rules):
            return self._groups()
        changed = {p for d in (self.change.plus, self.change.minus) for p, x in d.items() if x.rows}
        back: dict[str, list[DataFrame]] = {}
        if changed and self.old_rules and self.start.rows:
            method = "rederive" if self.method == "counting" and self.before.recursive else self.method
            gone = {"rederive": self._over_delete, "backward_forward": self._backward_forward, "counting": self._counting}[method]()
            self._drop(gone)
            if method == "rederive" and gone:
                back = self._rederived(gone)
        found: dict[str, list[DataFrame]] = back
        pos = {p: x.frame for p, x in self.change.plus.items()}
        neg = {p: x.frame for p, x in self.change.minus.items()}
        for more in (self._heads(self.after, self.old_rules, pos, neg), self.after.evaluate(self.new_rules) if self.new_rules else {}):
            for pred, fs in more.items():
                found.setdefault(pred, []).extend(fs)
        ctx.log.counts["rules_run"] += len(self.new_rules)
        self.after.close(self.after.add(found))
        return self.after.own

    def _groups(self) -> FactStore:
        """An aggregate's groups that a change touches are computed again."""
        (rule,) = self.old_rules
        c, keys = self.ctx.compiler, [column(v) for v in rule.agg.group]
        hits: list[DataFrame] = []
        for node, pos, neg in ((self.before, self.change.minus, self.change.plus), (self.after, self.change.plus, self.change.minus)):
            for k, a in enumerate(rule.positives):
                if a.pred in pos:
                    hits.append(c.bindings(rule, node.resolver(k, pos[a.pred].frame), self.ctx.stats, first=k).select(*keys))
            for k, a in enumerate(rule.negatives):
                if a.pred in neg:
                    hits.append(c.bindings(rule, node.resolver(k, neg[a.pred].frame, negated=True), self.ctx.stats, flip=k).select(*keys))
        if not hits:
            return self.start
        pred, own = rule.head.pred, self.start.get(rule.head.pred)
        at = [next((i for i, t in enumerate(rule.head.args) if getattr(t, "name", None) == v), None) for v in rule.agg.group]
        if not keys or None in at:
            new = self.ctx.storage.write(c.rule_frame(rule, self.after.resolver(), self.ctx.stats))
            return self.start.put(pred, Relation((new,)) if new.rows else EMPTY)
        touched = self.ctx.storage.write(union(hits).distinct())
        self.ctx.log.counts["groups"] += touched.rows
        b = c.bindings(rule, self.after.resolver(), self.ctx.stats).join(touched.frame, keys, "left_semi")
        frames = [c.head(rule, c.aggregated(rule, b))]
        if own.rows:
            as_head = touched.frame.select(*[F.col(k).alias(f"c{i}") for k, i in zip(keys, at, strict=True)])
            frames.append(own.frame().join(as_head, as_head.columns, "left_anti"))
        new = self.ctx.storage.write(union(frames))
        return self.start.put(pred, Relation((new,)) if new.rows else EMPTY)


