"""One rule as one DataFrame: filters, joins, anti joins, arithmetic, aggregation.

The plan is declared and left to Catalyst: constants are filters that reach the scan, shared
variables are equi-join keys, negated atoms are left anti joins.
"""

from __future__ import annotations

import copy
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.registry import call
from ..lang.syntax import Atom, Compare, Const, Expr, Rule, Var
from ..slices import counts_before, medians_before
from .order import Stats, left_deep, negative_order

#: Gives the relation that an atom reads: (position in its part, atom, negated).
Resolver = Callable[[int, Atom, bool], DataFrame]


def column(var: str) -> str:
    return f"v_{var}"


def value(term: object) -> Column:
    return F.lit(term.value) if isinstance(term, Const) else F.col(column(term.name))


def expression(e: Expr | Var | Const) -> Column:
    if not isinstance(e, Expr):
        return value(e)
    args = [expression(a) for a in e.args]
    if e.op == "term":
        return args[0]
    if e.op == "neg":
        return -args[0]
    if e.op == "/":
        return args[0].cast("double") / args[1].cast("double")
    if e.op in "+-*%":
        return {"+": args[0].__add__, "-": args[0].__sub__, "*": args[0].__mul__, "%": args[0].__mod__}[e.op](args[1])
    return call(e.op, args)


def comparison(c: Compare) -> Column:
    a, b = value(c.left), value(c.right)
    return {"=": a == b, "!=": a != b, "<": a < b, "<=": a <= b, ">": a > b, ">=": a >= b}[c.op]


def atom_frame(atom: Atom, relation: DataFrame) -> DataFrame:
    """The relation's rows that match an atom, with one column per variable."""
    at: dict[str, int] = {}
    tests = []
    for k, a in enumerate(atom.args):
        if isinstance(a, Const):
            tests.append(F.col(f"c{k}") == F.lit(a.value))
        elif a.name != "_":
            if a.name in at:
                tests.append(F.col(f"c{k}") == F.col(f"c{at[a.name]}"))
            else:
                at[a.name] = k
    for t in tests:
        relation = relation.where(t)
    return relation.select(*[F.col(f"c{k}").alias(column(v)) for v, k in at.items()]) if at else relation.select(F.lit(1).alias("v__any")).limit(1)


# Aggregate operators and their functions.
_AGGREGATES = {"max": F.max, "min": F.min, "avg": F.avg, "sum": F.sum, "median": F.median, "count": F.count}


class Compiler:
    """Turns rules into frames under the given options."""

    def __init__(self, spark: SparkSession, types: dict[str, list[str]], order: str = "cost", eager: bool = True, bound_aware: bool = True, allow_cross: bool = False, agg_over: str = "bindings", median: str = "exact"):
        self.spark, self.types, self.order, self.eager, self.bound_aware = spark, types, order, eager, bound_aware
        self.allow_cross, self.agg_over, self.median = allow_cross, agg_over, median

    def typed(self, more: dict[str, list[str]]) -> Compiler:
        out = copy.copy(self)
        out.types = self.types | more
        return out

    def empty(self, pred: str) -> DataFrame:
        return self.spark.createDataFrame([], ", ".join(f"c{k} {t}" for k, t in enumerate(self.types[pred])))

    def bindings(self, rule: Rule, resolve: Resolver, stats: Stats, first: int | None = None, seed: DataFrame | None = None, flip: int | None = None) -> DataFrame:
        """Bindings of the body's variables.  ``seed`` restricts them to given values of some
        variables; ``flip`` joins that negated atom instead of excluding it."""
        binds, comps = list(rule.binds), list(rule.comps)
        now, bound = seed, set()
        if seed is not None:
            bound = {c[2:] for c in seed.columns}
        pending = negative_order(rule, stats, self.order)
        if flip is not None:
            changed = rule.negatives[flip]
            f = atom_frame(changed, resolve(flip, changed, True)).distinct()
            now, bound = self._join(now, f, bound, changed, rule), bound | set(changed.vars())
            pending.remove(flip)

        def settle(now: DataFrame, last: bool) -> DataFrame:
            nonlocal binds, comps, pending
            moved = True
            while moved and (self.eager or last):
                moved = False
                for b in list(binds):
                    if set(b.expr.vars()) <= bound:
                        e = expression(b.expr)
                        now = now.where(F.col(column(b.var)) == e) if b.var in bound else now.withColumn(column(b.var), e)
                        bound.add(b.var)
                        binds.remove(b)
                        moved = True
                for c in list(comps):
                    if set(c.vars()) <= bound:
                        now = now.where(comparison(c))
                        comps.remove(c)
                        moved = True
            if last:
                for k in list(pending):
                    a = rule.negatives[k]
                    other = atom_frame(a, resolve(k, a, True))
                    keys = [column(v) for v in a.vars()]
                    now = now.join(other, keys, "left_anti") if keys else now.join(other, F.lit(True), "left_anti")
            return now

        for k in left_deep(rule, stats, self.order, self.bound_aware, first):
            a = rule.positives[k]
            now = self._join(now, atom_frame(a, resolve(k, a, False)), bound, a, rule)
            bound |= set(a.vars())
            now = settle(now, False)
        if now is None:
            now = self.spark.range(1).select(F.lit(1).alias("v__any"))
        return settle(now, True)

    def _join(self, now: DataFrame | None, f: DataFrame, bound: set[str], atom: Atom, rule: Rule) -> DataFrame:
        if now is None:
            return f
        keys = [column(v) for v in atom.vars() if v in bound]
        if keys:
            return now.join(f, keys)
        if not atom.vars():
            return now.join(f, F.lit(True), "left_semi")
        if not self.allow_cross:
            raise ValueError(f"{rule.id}: {atom} shares no variable with the atoms before it; set allow_cross to permit a cross product")
        return now.crossJoin(f)

    def head(self, rule: Rule, bindings: DataFrame) -> DataFrame:
        """Head rows of bindings, typed as the predicate; duplicates remain."""
        return bindings.select(*[value(a).cast(t).alias(f"c{k}") for k, (a, t) in enumerate(zip(rule.head.args, self.types[rule.head.pred], strict=True))])

    def _aggregable(self, rule: Rule, bindings: DataFrame) -> DataFrame:
        """The rows that a rule's aggregate runs over."""
        g = rule.agg
        names = list(dict.fromkeys([*g.group, g.var])) if self.agg_over == "pairs" else sorted({v for a in rule.positives for v in a.vars()} | {b.var for b in rule.binds})
        rows = bindings.select(*[column(v) for v in names])
        if self.agg_over == "pairs" or any(not isinstance(t, Const) and t.name == "_" for a in rule.positives for t in a.args):
            rows = rows.distinct()  # bindings of all variables of sets are a set
        return rows

    def aggregated(self, rule: Rule, bindings: DataFrame) -> DataFrame:
        g, rows = rule.agg, self._aggregable(rule, bindings)
        fn = (lambda c: F.percentile_approx(c, 0.5)) if g.fn == "median" and self.median == "approx" else _AGGREGATES[g.fn]
        made = fn(F.col(column(g.var))).alias(column(g.result))
        out = rows.groupBy(*[column(v) for v in g.group]).agg(made)
        return out.where(F.col(column(g.result)).isNotNull()) if not g.group and g.fn != "count" else out if g.group else out.where(F.col(column(g.result)) > 0) if g.fn == "count" else out

    def rule_frame(self, rule: Rule, resolve: Resolver, stats: Stats, **how: object) -> DataFrame:
        """Head rows of a rule (not distinct)."""
        b = self.bindings(rule, resolve, stats, **how)
        return self.head(rule, self.aggregated(rule, b) if rule.agg else b)

    def component_frame(self, rule: Rule, resolve: Resolver, stats: Stats, at: int, side: int, labels: DataFrame) -> DataFrame:
        """Head rows of an aggregate over a symmetric and transitive relation, from its labels:
        every group is made once per component and then given to the component's nodes."""
        x = column(rule.positives[at].args[side].name)
        ends = ("component", "node") if side == 0 else ("node", "component")
        relation = labels.select(*[F.col(e).alias(f"c{k}") for k, e in enumerate(ends)])
        made = self.aggregated(rule, self.bindings(rule, lambda k, a, n: relation if k == at and not n else resolve(k, a, n), stats))
        return self.head(rule, made.withColumnRenamed(x, "_component").join(labels.select(F.col("node").alias(x), F.col("component").alias("_component")), "_component"))

    def runs_along(self, rule: Rule) -> bool:
        """Whether an aggregate grouped by one node alone can be made in one pass along a chain."""
        return self.agg_over != "pairs" and (rule.agg.fn == "count" or (rule.agg.fn == "median" and self.median == "exact"))

    def chain_frame(self, rule: Rule, resolve: Resolver, stats: Stats, at: int, side: int, ranks: DataFrame) -> DataFrame:
        """Head rows of an aggregate over a transitive relation of chains, from its ranks: the
        groups of a chain contain each other, so one pass along it makes them all.  A task holds
        the rows of a chain."""
        x, y = (column(rule.positives[at].args[k].name) for k in (side, 1 - side))
        ends = ("component", "node") if side == 0 else ("node", "component")
        relation = ranks.select(*[F.col(e).alias(f"c{k}") for k, e in enumerate(ends)])
        rows = self._aggregable(rule, self.bindings(rule, lambda k, a, n: relation if k == at and not n else resolve(k, a, n), stats))
        key = F.col("left") if side == 0 else -F.col("left")
        count, result = rule.agg.fn == "count", column(rule.agg.result)
        value = F.col(column(rule.agg.var))
        value = F.when(value.isNotNull(), F.lit(1.0)) if count else value.cast("double")
        nodes = ranks.select("component", key.alias("key"), F.lit(True).alias("asks"), "node", F.lit(None).cast("double").alias("value"))
        given = rows.join(ranks.select(F.col("node").alias(y), key.alias("key")), y).select(F.col(x).alias("component"), "key", F.lit(False).alias("asks"), F.col(y).alias("node"), value.alias("value"))
        made = nodes.unionByName(given).groupBy("component").applyInArrow(counts_before if count else medians_before, f"node {dict(ranks.dtypes)['node']}, result {'long' if count else 'double'}")
        return self.head(rule, made.select(F.col("node").alias(x), F.col("result").alias(result)))


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
