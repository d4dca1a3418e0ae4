"""What the incremental methods are compared with."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from .reasoner import Reasoner


def from_scratch(r: Reasoner, **options: object) -> Reasoner:
    """Recompute the current program on the current facts."""
    facts = {p: rel.frame() for p, rel in r.state.explicit.relations.items() if rel.rows}
    out = Reasoner(r.spark, r.state.program, facts, replace(r.config, **options), {p: t for p, t in r.declared.items()})
    out.materialise()
    return out


def naive(r: Reasoner) -> Reasoner:
    """All rules on all facts in every round."""
    return from_scratch(r, evaluation="naive")


def by_stratum(r: Reasoner) -> Reasoner:
    """Strata instead of components as units."""
    return from_scratch(r, unit="stratum")


def equal_state(a: Reasoner, b: Reasoner) -> dict[str, int]:
    """Facts in which two states differ, per predicate; empty means equal."""
    out = {}
    for p in {*a.state.bag().index, *b.state.bag().index}:
        x, y = a.relation(p), b.relation(p)
        n = x.join(y, x.columns, "left_anti").count() + y.join(x, y.columns, "left_anti").count()
        if n:
            out[p] = n
    return out


def with_recursive(df: DataFrame, depth: int) -> DataFrame:
    """Spark's own recursive query over an acyclic edge table, bounded in depth: it keeps
    duplicates, so it diverges on cycles and serves as a baseline for chains only."""
    df.createOrReplaceTempView("recursive_edges")
    return df.sparkSession.sql(
        f"WITH RECURSIVE t(c0, c1, d) AS (SELECT c0, c1, 1 FROM recursive_edges UNION ALL SELECT t.c0, e.c1, d + 1 FROM t JOIN recursive_edges e ON t.c1 = e.c0 WHERE d < {int(depth)}) SELECT DISTINCT c0, c1 FROM t"
    )
