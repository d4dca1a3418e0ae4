"""Order of the atoms of a body: positive part, then negated part, then aggregation.

``heuristic`` ranks atoms by shape: both columns known, one known, none known, type atoms;
``cost`` breaks ties, and sorts joins, by estimated rows; ``dp`` searches all left-deep orders
of bodies with up to ``MAX_DP`` atoms; ``text`` keeps the written order.  Connected atoms come
first in every mode but ``text``, so that no cross product arises where one can be avoided.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

from ..lang.syntax import Atom, Const, Rule, Var

MODES = ("cost", "heuristic", "text", "dp")
MAX_DP = 10


@dataclass
class Stats:
    """Rows of each predicate and distinct values of each of its columns."""

    rows: dict[str, int]
    distinct: dict[tuple[str, int], int]

    def size(self, pred: str) -> int:
        return max(1, self.rows.get(pred, 1000))

    def ndv(self, pred: str, col: int) -> int:
        return max(1, self.distinct.get((pred, col), max(1, int(self.size(pred) ** 0.75))))


def split(rule: Rule) -> tuple[list[Atom], list[Atom], object]:
    return list(rule.positives), list(rule.negatives), rule.agg


def rank(atom: Atom, bound: set[str] = frozenset(), bound_aware: bool = True) -> int:
    """0 all columns known, 1 some known, 2 none known, 3 a type atom with a free variable."""
    known = [isinstance(a, Const) or (bound_aware and isinstance(a, Var) and a.name in bound) for a in atom.args]
    if all(known):
        return 0
    if len(atom.args) == 1:
        return 3
    return 1 if any(known) else 2


def rank_negative(atom: Atom) -> int:
    return rank(atom, frozenset(), False)


def cost(atom: Atom, stats: Stats, bound: set[str] = frozenset()) -> float:
    """Expected rows of an atom given bound variables."""
    out = float(stats.size(atom.pred))
    for k, a in enumerate(atom.args):
        if isinstance(a, Const) or (isinstance(a, Var) and a.name in bound):
            out /= stats.ndv(atom.pred, k)
    return out


def _dp(atoms: list[Atom], stats: Stats) -> list[int]:
    """Cheapest left-deep order: cost is the sum of intermediate sizes."""
    n = len(atoms)
    best: dict[frozenset[int], tuple[float, float, tuple[int, ...]]] = {frozenset([k]): (0.0, cost(a, stats), (k,)) for k, a in enumerate(atoms)}
    for size in range(2, n + 1):
        for group in map(frozenset, combinations(range(n), size)):
            options = []
            for last in group:
                before = best[group - {last}]
                bound = {v for k in before[2] for v in atoms[k].vars()}
                apart = not bound & set(atoms[last].vars()) and bool(atoms[last].vars())
                rows = before[1] * cost(atoms[last], stats, bound)
                options.append((before[0] + rows * (1e6 if apart else 1), rows, (*before[2], last)))
            best[group] = min(options)
    return list(best[frozenset(range(n))][2])


def left_deep(rule: Rule, stats: Stats, mode: str = "cost", bound_aware: bool = True, first: int | None = None) -> list[int]:
    """Positions of the positive atoms in join order; ``first`` (a changed atom) leads."""
    atoms = list(rule.positives)
    if mode not in MODES:
        raise ValueError(f"unknown order {mode}")
    if mode == "text":
        rest = [k for k in range(len(atoms)) if k != first]
        return rest if first is None else [first, *rest]
    if mode == "dp" and len(atoms) <= MAX_DP and first is None:
        return _dp(atoms, stats)
    todo, out, bound = set(range(len(atoms))), [], set()
    while todo:
        if first is not None and not out:
            pick = first
        else:
            near = [k for k in todo if not bound or bound & set(atoms[k].vars()) or not atoms[k].vars()] or sorted(todo)
            key = lambda k: (rank(atoms[k], bound, bound_aware), cost(atoms[k], stats, bound) if mode != "heuristic" else 0, k)  # noqa: B023, E731
            pick = min(near, key=key)
        out.append(pick)
        todo.discard(pick)
        bound |= set(atoms[pick].vars())
    return out


def negative_order(rule: Rule, stats: Stats, mode: str = "cost") -> list[int]:
    if mode == "text":
        return list(range(len(rule.negatives)))
    return sorted(range(len(rule.negatives)), key=lambda k: (rank_negative(rule.negatives[k]), cost(rule.negatives[k], stats) if mode != "heuristic" else 0, k))
