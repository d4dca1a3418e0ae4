"""Updates that arrive as streams.

Every micro-batch is one transaction of the engine, and the version it leads to carries its
name.  With ``save_to`` that version is saved before the stream notes the batch as done, so a
batch that is delivered again after a restart from the saved state changes nothing.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..engine import Reasoner
from ..lang.syntax import SyntaxFault
from ..lang.checks import RuleError


def run_fact_updates(reasoner: Reasoner, changes: DataFrame, checkpoint: str, preds: dict[str, list[str]], trigger: dict[str, object] | None = None, save_to: str | None = None) -> StreamingQuery:
    """``changes`` has op (+ or -), pred and the columns that ``preds`` names per predicate."""

    def apply(batch: DataFrame, batch_id: int) -> None:
        name = f"facts:{batch_id}"
        if name in reasoner.state.batches:
            return
        batch = batch.persist()
        try:
            side = lambda op: {p: d for p, cols in preds.items() if not (d := batch.where((F.col("op") == op) & (F.col("pred") == p)).select(*cols)).isEmpty()}
            reasoner.update(add_facts=side("+"), drop_facts=side("-"), batch=name)
            if save_to:
                reasoner.save(save_to)
        finally:
            batch.unpersist()

    return changes.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def run_rule_updates(reasoner: Reasoner, changes: DataFrame, checkpoint: str, rejected: Callable[[str, str], None] | None = None, trigger: dict[str, object] | None = None, save_to: str | None = None) -> StreamingQuery:
    """``changes`` has seq, op (+ or -) and text (a rule, or a rule's id).  Rules that the engine
    rejects go to ``rejected`` with the reason; the state stays as it was."""

    def apply(batch: DataFrame, batch_id: int) -> None:
        for k, (op, text) in enumerate(batch.orderBy("seq").select("op", "text").collect()):  # rules are few and small
            try:
                reasoner.update(**({"add_rules": text} if op == "+" else {"drop_rules": [text]}), batch=f"rules:{batch_id}:{k}")
            except (RuleError, SyntaxFault) as e:
                if rejected:
                    rejected(text, str(e))
        if save_to:
            reasoner.save(save_to)

    return changes.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def rule_lease(reasoner: Reasoner, events: DataFrame, checkpoint: str, raised: str, cleared: str, rules: str, ids: list[str], found: Callable[[Reasoner], None] | None = None) -> StreamingQuery:
    """Load rules when a batch holds an event that satisfies ``raised``; drop them again when
    one satisfies ``cleared``.  ``found`` looks at the state while the rules are loaded."""

    def apply(batch: DataFrame, batch_id: int) -> None:
        if f"lease:{batch_id}:cleared" in reasoner.state.batches:
            return
        loaded = set(ids) <= set(reasoner.state.program.rules)
        if not loaded and not batch.where(raised).isEmpty():
            reasoner.update(add_rules=rules, batch=f"lease:{batch_id}:raised")
            loaded = True
            if found:
                found(reasoner)
        if loaded and not batch.where(cleared).isEmpty():
            reasoner.update(drop_rules=ids, batch=f"lease:{batch_id}:cleared")

    return events.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_facts(reasoner: Reasoner, pred: str, live: DataFrame) -> None:
    """Make a predicate's facts equal to the live window: late facts enter, expired ones leave,
    both in one transaction."""
    now = reasoner.state.explicit.get(pred).frame()
    cols = live.toDF(*[f"c{k}" for k in range(len(live.columns))])
    if now is None:
        reasoner.insert_facts(pred, cols)
        return
    cols = cols.select(*[F.col(c).cast(t) for c, t in now.dtypes])
    reasoner.update(add_facts={pred: cols.join(now, now.columns, "left_anti")}, drop_facts={pred: now.join(cols, now.columns, "left_anti")})
