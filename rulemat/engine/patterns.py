"""Nodes with a known closed form: a symmetric and transitive relation is the set of all pairs
inside connected components, so n labels stand for n**2 pairs; a transitive one over chains is the
set of pairs in the order of a chain, so n ranks stand for them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graphops import chain_ranks, closure, contracted, paired, ranked_pairs, tiled_pairs
from ..lang.syntax import Rule, Var
from ..slices import SLICE
from .delta import Change, in_closed
from .store import FactStore, Part, Relation


#: New edges that are joined to components on the driver; more go through Spark.
FEW_EDGES = 10_000
#: Changed edges that are followed one by one where all edges are one slice; more cost more jobs
#: than labelling that slice again.
FEW_CHANGES = 1_000


@dataclass(frozen=True)
class Closure:
    pred: str
    base: tuple[Rule, ...]


def symmetric_transitive(rules: list[Rule]) -> Closure | None:
    """Recognise a node of exactly p(y,x) <- p(x,y) and p(x,z) <- p(x,y), p(y,z)."""
    preds = {r.head.pred for r in rules}
    if len(preds) != 1 or len(rules) != 2 or any(r.negatives or r.binds or r.comps or r.agg for r in rules):
        return None
    (p,) = preds
    if any(a.pred != p or len(a.args) != 2 for r in rules for a in r.positives) or any(not isinstance(t, Var) or t.name == "_" for r in rules for a in (r.head, *r.positives) for t in a.args):
        return None
    names = lambda a: tuple(t.name for t in a.args)
    one = [r for r in rules if len(r.positives) == 1 and names(r.head) == names(r.positives[0])[::-1] and len(set(names(r.head))) == 2]
    two = []
    for r in rules:
        if len(r.positives) == 2:
            for a, b in (r.positives, r.positives[::-1]):
                (x, y), (y2, z) = names(a), names(b)
                if y == y2 and names(r.head) == (x, z) and len({x, y, z}) == 3:
                    two.append(r)
    return Closure(p, ()) if len(one) == 1 and len(two) >= 1 else None


def transitive(rules: list[Rule]) -> Closure | None:
    """Recognise a node of exactly p(x,z) <- p(x,y), p(y,z)."""
    if len(rules) != 1 or rules[0].negatives or rules[0].binds or rules[0].comps or rules[0].agg or len(rules[0].positives) != 2:
        return None
    r = rules[0]
    if any(a.pred != r.head.pred or len(a.args) != 2 or any(not isinstance(t, Var) or t.name == "_" for t in a.args) for a in (r.head, *r.positives)):
        return None
    for a, b in (r.positives, r.positives[::-1]):
        (x, y), (y2, z) = (tuple(t.name for t in p.args) for p in (a, b))
        if y == y2 and tuple(t.name for t in r.head.args) == (x, z) and len({x, y, z}) == 3:
            return Closure(r.head.pred, ())
    return None


def copied(rules: list[Rule]) -> str | None:
    """Recognise a node of one rule that only renames another predicate, p(x, y) <- q(x, y): that one."""
    if len(rules) != 1 or rules[0].negatives or rules[0].binds or rules[0].comps or rules[0].agg or len(rules[0].positives) != 1:
        return None
    head, body = rules[0].head, rules[0].positives[0]
    names = [t.name if isinstance(t, Var) else "_" for t in body.args]
    same = names == [t.name if isinstance(t, Var) else "_" for t in head.args]
    return body.pred if same and "_" not in names and len(set(names)) == len(names) and head.pred != body.pred else None


def symmetric(rules: list[Rule]) -> str | None:
    """Recognise a node of exactly p(y,x) <- p(x,y)."""
    if len(rules) != 1 or rules[0].negatives or rules[0].binds or rules[0].comps or rules[0].agg or len(rules[0].positives) != 1:
        return None
    head, body = rules[0].head, rules[0].positives[0]
    if head.pred != body.pred or len(head.args) != 2 or any(not isinstance(t, Var) or t.name == "_" for t in (*head.args, *body.args)):
        return None
    (a, b), (x, y) = (tuple(t.name for t in atom.args) for atom in (head, body))
    return head.pred if a == y and b == x and a != b else None


def expand_symmetric(ctx: object, pred: str, ext: object) -> FactStore:
    """The node's store: its base relation, turned round and as it is, in one job."""
    base = ext(pred)
    if base is None:
        return FactStore()
    part = ctx.storage.write(base.unionByName(base.select(F.col("c1").alias("c0"), F.col("c0").alias("c1"))).distinct())
    return FactStore({pred: Relation((part,))}) if part.rows else FactStore()


def expand_transitive(ctx: object, pattern: Closure, ext: object) -> FactStore:
    """The node's store: ranks where the base relation is a set of chains, else the pairs."""
    base = ext(pattern.pred)
    if base is None:
        return FactStore()
    cut = lambda df, name: ctx.storage.write(df).frame
    edges = base.select(F.col("c0").alias("a"), F.col("c1").alias("b"))
    if (ranks := chain_ranks(edges, cut)) is None:
        part = ctx.storage.write(closure(edges, cut, chains=False).select(F.col("a").alias("c0"), F.col("b").alias("c1")))
    else:
        at = ctx.storage.write(ranks)
        sizes = at.frame.groupBy("component").agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2)).first()[0]
        pairs = ranked_pairs(at.frame, at.frame, at.rows, int(sizes or 0))
        part = Part(pairs.toDF("c0", "c1"), int(sizes or 0), at.path, ranks=at.frame, every=tiled_pairs(at.frame, at.rows, int(sizes or 0), after=True))
    return FactStore({pattern.pred: Relation((part,))}) if part.rows else FactStore()


def labels(base: DataFrame, cut: object, rows: int | None = None) -> DataFrame:
    """(node, component) of the undirected graph of a binary relation, of at most ``rows`` if known."""
    return contracted(base.select(F.col("c0").alias("a"), F.col("c1").alias("b")), cut, rows)


def label_part(at: Part, pairs: int | None = None) -> Part:
    """A part that stands for the ``pairs`` (counted here if not given) of a label table at rest:
    n rows for n**2 facts."""
    sizes = pairs
    if sizes is None:
        sizes = at.frame.groupBy("component").agg(F.count("*").alias("n")).agg(F.sum(F.col("n") * F.col("n"))).first()[0]
    left, right = at.frame.select(F.col("node").alias("c0"), "component"), at.frame.select(F.col("node").alias("c1"), "component")
    pairs = paired(left, right, "c0", at.rows, int(sizes or 0)).select("c0", "c1")
    return Part(pairs, int(sizes or 0), at.path, labels=at.frame, every=tiled_pairs(at.frame, at.rows, int(sizes or 0)))


def _labelled(ctx: object, base: DataFrame, rows: int | None = None) -> DataFrame:
    """Labels of a relation's nodes.  Nodes whose only edge is a loop are a component of their own."""
    return labels(base, lambda df, name: ctx.storage.write(df).frame, rows)


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("c0").alias("node")).unionByName(edges.select(F.col("c1").alias("node"))).distinct()


def expand_labels(ctx: object, rules: list[Rule], pattern: Closure, ext: object) -> FactStore:
    """The node's store as labels; a label table never holds more rows than there are nodes."""
    base = ext(pattern.pred)
    if base is None:
        return FactStore()
    part = label_part(ctx.storage.write(_labelled(ctx, base, ext.rows(pattern.pred))))
    return FactStore({pattern.pred: Relation((part,))}) if part.rows else FactStore()


def maintain_labels(ctx: object, pattern: Closure, before: FactStore, change: Change, ext: object) -> tuple[FactStore, dict[str, Part], dict[str, Part]]:
    """The node's store after a change of its base relation, and the pairs it gained and lost.

    Components that lose an edge are labelled again from the edges left in them; new edges
    merge labels.  After a change of many edges, all edges are joined again if they are one
    slice, which takes one job.  The pairs that came together or apart are counted, and made
    only if a rule reads them."""
    cut = lambda df: ctx.storage.write(df).frame
    pred, base = pattern.pred, ext(pattern.pred)
    old = next((p.labels for p in before.get(pred).parts if p.labels is not None), None)
    if old is None and before.get(pred).rows:  # pairs read from a saved state: each node's least partner is its label
        old = cut(before.get(pred).frame().groupBy(F.col("c0").alias("node")).agg(F.min("c1").alias("component")))
    now = old
    gone, come = change.minus.get(pred), change.plus.get(pred)
    many = sum(x.rows for x in (gone, come) if x is not None) > min(FEW_CHANGES, FEW_EDGES)
    if whole := many and base is not None and ext.rows(pred) <= SLICE:
        now = _labelled(ctx, base, ext.rows(pred))
    if not whole and now is not None and gone is not None and gone.rows:
        hit = cut(now.join(_ends(gone.frame), "node", "left_semi").select("component").distinct())
        inside = cut(now.join(hit, "component", "left_semi").select("node"))
        rest = now.join(hit, "component", "left_anti")
        if base is not None:
            near = base.join(inside.select(F.col("node").alias("c0")), "c0", "left_semi").join(inside.select(F.col("node").alias("c1")), "c1", "left_semi")
            left = ctx.storage.write(near.select("c0", "c1"))
            again = _joined_here(ctx, left.frame) if left.rows <= FEW_EDGES else _labelled(ctx, left.frame)
            rest = rest.unionByName(again.select(*rest.columns))
        now = cut(rest.select("node", "component"))
    if not whole and come is not None and come.rows:
        edges, ends = come.frame, _ends(come.frame)
        known = ends.join(now, "node", "left") if now is not None else ends.withColumn("component", F.lit(None).cast(dict(ends.dtypes)["node"]))
        known = cut(known.select("node", F.coalesce("component", "node").alias("component"), F.col("component").isNull().alias("new")))
        side = lambda c: known.select(F.col("node").alias(c), F.col("component").alias(f"{c}_label"))
        between = edges.join(side("c0"), "c0").join(side("c1"), "c1").select(F.col("c0_label").alias("c0"), F.col("c1_label").alias("c1"))
        merged = _joined_here(ctx, between) if come.rows <= FEW_EDGES else labels(between, lambda df, name: cut(df))
        both = known.where("new").select("node", "component")
        both = both if now is None else now.select("node", "component").unionByName(both)
        root = merged.select(F.col("node").alias("component"), F.col("component").alias("root"))
        now = both.join(root, "component", "left").select("node", F.coalesce("root", "component").alias("component"))
    at = ctx.storage.write(now) if now is not None else None
    both, pairs = _matched(old, at.frame if at is not None and at.rows else None)
    store = FactStore({pred: Relation((label_part(at, pairs["now"]),))}) if at is not None and at.rows else FactStore()
    gained, lost = _moved(both, pairs, come is not None, gone is not None)
    return store, {pred: gained} if gained is not None and gained.rows else {}, {pred: lost} if lost is not None and lost.rows else {}


def _joined_here(ctx: object, edges: DataFrame) -> DataFrame:
    """(node, component) of at most ``FEW_EDGES`` edges, on the driver."""
    root: dict[object, object] = {}

    def find(x: object) -> object:
        while root.setdefault(x, x) != x:
            root[x] = x = root[root[x]]
        return x

    for a, b in edges.collect():
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    # a node whose only edge is a loop is its own root
    kind = edges.schema[0].dataType.simpleString()
    return ctx.storage.spark.createDataFrame([(x, find(x)) for x in list(root)], f"node {kind}, component {kind}")


def _matched(old: DataFrame | None, new: DataFrame | None) -> tuple[DataFrame | None, dict[str, int]]:
    """(node, was, now) of two label tables, and the numbers of their nodes, of the pairs of each
    and of those in common, all from the sizes of the groups in one job."""
    if old is None and new is None:
        return None, {}
    empty = (old if old is not None else new).limit(0)
    a, b = (df if df is not None else empty for df in (old, new))
    both = a.select("node", F.col("component").alias("was")).join(b.select("node", F.col("component").alias("now")), "node", "full")
    sets = [[F.col("was"), F.col("now")], [F.col("was")], [F.col("now")]]
    groups = both.groupingSets(sets, "was", "now").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))
    square = lambda g, live: F.sum(F.when((F.col("g") == g) & F.expr(live), F.col("n") * F.col("n")))
    sums = groups.agg(F.sum(F.when(F.col("g") == 0, F.col("n"))), square(0, "was IS NOT NULL AND now IS NOT NULL"), square(1, "was IS NOT NULL"), square(2, "now IS NOT NULL")).first()
    return both, {k: int(n or 0) for k, n in zip(("nodes", "common", "was", "now"), sums, strict=True)}


def _moved(both: DataFrame | None, pairs: dict[str, int], came: bool, went: bool) -> tuple[Part | None, Part | None]:
    """Pairs that have one label now and had not (if edges came), and the other way round (if
    edges went)."""
    if both is None:
        return None, None
    moved = both.where(~F.col("was").eqNullSafe(F.col("now")))
    out = []
    for mine, other, may in (("now", "was", came), ("was", "now", went)):
        if not may:
            out.append(None)
            continue
        held, rows = both.where(F.col(mine).isNotNull()), pairs[mine] - pairs["common"]
        # a node that came to others (or left them) has another label than before
        held = held.join(moved.select(mine).distinct(), mine, "left_semi")
        side = lambda c: held.select(F.col("node").alias(c), F.col(mine).alias("component"), F.col(other).alias(f"{c}_other"))  # noqa: B023, E731
        found = paired(side("c0"), side("c1"), "c0", pairs["nodes"], rows).where(~F.coalesce(F.col("c0_other") == F.col("c1_other"), F.lit(False)))
        out.append(Part(found.select("c0", "c1"), rows, None, lazy=True))
    return out[0], out[1]


def closed_diff(ctx: object, old: Part, new: Part | None) -> tuple[Part | None, Part | None]:
    """Pairs that a closed form gained and lost against another state of the node, counted."""
    if new is None:
        return None, Part(old.frame, old.rows, None, lazy=True)
    common = in_closed(new.frame, old).count() if not new.closed else _common(old, new)
    lazy = lambda mine, other, n: Part(mine.frame.join(other.frame, ["c0", "c1"], "left_anti"), n, None, lazy=True) if n else None
    return lazy(new, old, new.rows - common), lazy(old, new, old.rows - common)


def _common(a: Part, b: Part) -> int:
    """Pairs that labels and ranks, or two tables of labels, have in common."""
    x, y = (p.labels if p.labels is not None else p.ranks for p in (a, b))
    both = x.select("node", F.col("component").alias("was")).join(y.select("node", F.col("component").alias("now")), "node")
    n = F.col("n") * F.col("n") if a.ranks is None and b.ranks is None else F.col("n") * (F.col("n") - 1) / 2
    return int(both.groupBy("was", "now").agg(F.count("*").alias("n")).agg(F.sum(n)).first()[0] or 0)
