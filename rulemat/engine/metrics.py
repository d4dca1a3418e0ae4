"""Counters of one update, and measures over states."""

from __future__ import annotations

import math
import time
from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass, field


@dataclass
class UpdateLog:
    """What an update did: seconds, visited nodes, rounds and facts per node."""

    kind: str
    seconds: float = 0.0
    plan: list[tuple[str, str]] = field(default_factory=list)
    direct: set[str] = field(default_factory=set)
    visited: list[str] = field(default_factory=list)
    skipped: list[str] = field(default_factory=list)
    dropped: list[str] = field(default_factory=list)
    counts: Counter = field(default_factory=Counter)
    deltas: list[tuple[str, str, int, int]] = field(default_factory=list)


def timed(run: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    out = run()
    return out, time.perf_counter() - began


def slope(points: list[tuple[float, float]]) -> float:
    """Least-squares exponent of y ~ x**k."""
    xs, ys = [math.log(x) for x, _ in points], [math.log(max(y, 1e-9)) for _, y in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)
