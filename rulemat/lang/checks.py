"""Checks of rules and programs; a failed check leaves all state as it was."""

from __future__ import annotations

from collections import Counter

from .syntax import Program, Rule, Var


class RuleError(ValueError):
    """A rule that is not safe or not consistent with the program."""


class UnstratifiableError(RuleError):
    """Negation or aggregation inside a cycle of rules."""


def require_safe(rule: Rule) -> None:
    """Every variable occurs in a positive atom, or is bound by arithmetic over such."""
    if not rule.positives:
        if rule.negatives or rule.comps or rule.binds or any(isinstance(a, Var) for a in rule.head.args):
            raise RuleError(f"{rule.id}: no positive atom binds its variables")
        return
    bound = {v for a in rule.positives for v in a.vars()}
    left = list(rule.binds)
    while ready := [b for b in left if set(b.expr.vars()) <= bound]:
        bound |= {b.var for b in ready}
        left = [b for b in left if b not in ready]
    if left:
        raise RuleError(f"{rule.id}: {left[0].var} is computed from unbound variables")
    for a in rule.negatives:
        if free := set(a.vars()) - bound:
            raise RuleError(f"{rule.id}: {sorted(free)} occur only in negated {a.pred}")
    for c in rule.comps:
        if free := set(c.vars()) - bound:
            raise RuleError(f"{rule.id}: {sorted(free)} are compared but not bound")
    if rule.agg:
        if rule.agg.var not in bound or set(rule.agg.group) - bound:
            raise RuleError(f"{rule.id}: the aggregated and grouping variables must occur in the body")
        bound = set(rule.agg.group) | {rule.agg.result}
    if free := {a.name for a in rule.head.args if isinstance(a, Var)} - bound:
        raise RuleError(f"{rule.id}: head variables {sorted(free)} are not bound")


def check_program(program: Program, arities: dict[str, int] | None = None) -> None:
    seen = dict(arities or {})
    for r in program:
        require_safe(r)
        for a in (r.head, *r.positives, *r.negatives):
            if seen.setdefault(a.pred, len(a.args)) != len(a.args):
                raise RuleError(f"{r.id}: {a.pred} has {seen[a.pred]} columns, not {len(a.args)}")
    heads = Counter(r.head.pred for r in program)
    for r in program:
        if r.agg and heads[r.head.pred] > 1:
            raise RuleError(f"{r.id}: {r.head.pred} is aggregated and may have no second rule")
