"""The engine: a program, explicit facts, and one derived store per node of the rule graph."""

from __future__ import annotations

import copy
import itertools
import json
import time
from collections.abc import Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.checks import RuleError, check_program
from ..lang.syntax import Const, Expr, Program, Rule, Var, parse_atoms, parse_rules
from ..plans import impact
from ..plans.compile import Compiler, column, union
from ..plans.depgraph import HyperGraph, RuleGraph, condense, require_acyclic, stratify
from ..plans.order import Stats
from .delta import Change, Maintainer, diff
from .fixpoint import Context, Node, by_component, distinct_values, minus, run_node
from .metrics import UpdateLog
from .patterns import closed_diff, copied, expand_labels, expand_symmetric, expand_transitive, maintain_labels, symmetric, symmetric_transitive, transitive
from .store import EMPTY, FactStore, Relation, Storage, StoreBag

EXPLICIT = "explicit"


@dataclass(frozen=True)
class Config:
    """Variants; all of them lead to the same facts."""

    insertion_mode: str = "seeded"  # seeded, redo, auto
    successor_policy: str = "structural"  # structural, always, delta
    downstream: str = "delta"  # delta, redo
    deletion_method: str = "rederive"  # rederive, backward_forward, counting
    unit: str = "component"  # component, stratum
    evaluation: str = "semi_naive"  # semi_naive, naive
    bag: str = "pointers"  # pointers, merged
    layout: str = "none"  # none, c0, c1, both
    order: str = "cost"  # cost, heuristic, text, dp
    eager_filters: bool = True
    bound_aware: bool = True
    agg_over: str = "bindings"  # bindings, pairs
    median: str = "exact"  # exact, approx
    pattern_closure: str = "auto"  # auto, off
    scc: str = "two_pass"  # two_pass, low_link
    cut: str = "parquet"  # parquet, checkpoint
    max_rounds: int | None = None
    linear_after: int | None = 10
    parallel_nodes: int = 1
    allow_cross: bool = False
    sketches: bool = False  # distinct values of explicit columns for the cost order


@dataclass(frozen=True)
class State:
    """One version: everything a reader or an update needs, immutable."""

    program: Program
    graph: RuleGraph
    hyper: HyperGraph
    explicit: FactStore
    stores: dict[str, FactStore] = field(default_factory=dict)
    version: int = 0
    #: Names of the stream batches that this version contains.
    batches: frozenset[str] = frozenset()

    def bag(self) -> StoreBag:
        return StoreBag({EXPLICIT: self.explicit, **self.stores})


def infer_types(program: Program, known: dict[str, list[str]]) -> dict[str, list[str]]:
    """Column types of all predicates, from explicit ones through the rules to a fixpoint."""
    from ..functions.registry import returns

    wide = {"int": "bigint", "smallint": "bigint", "tinyint": "bigint", "float": "double"}
    rank = ["boolean", "bigint", "double"]
    types: dict[str, list[str | None]] = {p: [wide.get(t, t) for t in ts] for p, ts in known.items()}

    def const(v: object) -> str:
        return "boolean" if isinstance(v, bool) else "bigint" if isinstance(v, int) else "double" if isinstance(v, float) else "string"

    def join(a: str | None, b: str | None, where: str) -> str | None:
        if a is None or b is None or a == b:
            return a or b
        if a in rank[1:] and b in rank[1:]:
            return max(a, b, key=rank.index)
        raise RuleError(f"type mismatch at {where}: {a} and {b}")

    def of(e: object, env: dict[str, str | None]) -> str | None:
        if isinstance(e, Const):
            return const(e.value)
        if isinstance(e, Var):
            return env.get(e.name)
        args = [of(a, env) for a in e.args]
        if e.op in ("term", "neg"):
            return args[0]
        if e.op == "/":
            return "double"
        if e.op in "+-*%":
            return None if None in args else join(*args, str(e))
        return returns(e.op, args)

    for _ in range(len(program) * 4 + 8):
        before = {p: list(t) for p, t in types.items()}
        for r in program:
            env: dict[str, str | None] = {}
            for a in r.positives:
                have = types.setdefault(a.pred, [None] * len(a.args))
                for t, k in zip(a.args, have, strict=True):
                    if isinstance(t, Var) and t.name != "_":
                        env[t.name] = join(env.get(t.name), k, f"{r.id}: {t.name}") if {env.get(t.name), k} <= {None, "bigint", "double"} else env.get(t.name) or k
                        if env[t.name] and k and env[t.name] != k and not {env[t.name], k} <= {"bigint", "double"}:
                            raise RuleError(f"{r.id}: {t.name} is {env[t.name]} and {k}")
            for b in r.binds:
                env[b.var] = env.get(b.var) or of(b.expr, env)
            if r.agg:
                kind = env.get(r.agg.var)
                env[r.agg.result] = "bigint" if r.agg.fn == "count" else "double" if r.agg.fn in ("avg", "median") else kind
            for a in r.negatives:
                types.setdefault(a.pred, [None] * len(a.args))
            own = types.setdefault(r.head.pred, [None] * len(r.head.args))
            for k, t in enumerate(r.head.args):
                kind = const(t.value) if isinstance(t, Const) else env.get(t.name)
                if r.head.pred in known:
                    if kind and own[k] and kind != own[k] and not {kind, own[k]} <= {"bigint", "double"}:
                        raise RuleError(f"{r.id}: column {k} of {r.head.pred} is {own[k]}, not {kind}")
                    continue
                own[k] = join(own[k], kind, f"{r.id}: {r.head.pred}")
        if types == before:
            break
    return {p: [t or "bigint" for t in ts] for p, ts in types.items()}


class Reasoner:
    """Materialises a program over explicit facts and keeps it right under updates.

    An update builds a new version beside the old one and replaces it at the end; when it
    fails, the old version stays.
    """

    def __init__(self, spark: SparkSession, program: Program | str, facts: dict[str, DataFrame] | None = None, config: Config | None = None, schemas: dict[str, list[str]] | None = None):
        self.spark, self.config = spark, config or Config()
        self.storage = Storage(spark, self.config.cut)
        self.null_terms: dict[str, int] = {}
        self.log = UpdateLog("none")
        rules = program if isinstance(program, Program) else Program({r.id: r for r in parse_rules(program)})
        self.declared: dict[str, list[str]] = dict(schemas or {})
        explicit = FactStore()
        for pred, df in (facts or {}).items():
            explicit = explicit.put(pred, Relation((self._load(pred, df),)))
        inline = [r for r in rules if not r.positives]
        rules = rules.without(r.id for r in inline)
        for pred in sorted({r.head.pred for r in inline}):
            explicit = self._with_inline(explicit, pred, [r for r in inline if r.head.pred == pred])
        check_program(rules, {p: len(t) for p, t in self.declared.items()})
        graph = RuleGraph(rules)
        hyper = condense(graph, method=self.config.scc)
        require_acyclic(hyper)
        self.types = infer_types(rules, self.declared)
        self.ndv: dict[tuple[str, int], int] = {}
        if self.config.sketches:
            for pred, rel in explicit.relations.items():
                if rel.rows:
                    self.ndv |= {(pred, k): n for k, n in enumerate(distinct_values(rel.frame()))}
        self.state = State(rules, graph, hyper, explicit)

    def fork(self) -> Reasoner:
        """An independent engine on the same immutable state; no data is copied."""
        out = copy.copy(self)
        out.types, out.declared = dict(self.types), dict(self.declared)
        return out

    # loading

    def _load(self, pred: str, df: DataFrame) -> object:
        return self.storage.write(self._rows(pred, df))

    def _rows(self, pred: str, df: DataFrame) -> DataFrame:
        """A frame as facts: columns c0.., set semantics, rows with a null term left out."""
        if any(t.startswith(("map", "array", "struct")) for _, t in df.dtypes):
            raise RuleError(f"{pred}: nested columns cannot be terms; flatten them first")
        wide = {"int": "bigint", "smallint": "bigint", "tinyint": "bigint", "float": "double"}
        want = self.declared.get(pred) or [wide.get(t, t) for _, t in df.dtypes]
        if len(want) != len(df.columns):
            raise RuleError(f"{pred} has {len(want)} columns, not {len(df.columns)}")
        self.declared[pred] = want
        cols = df.toDF(*[f"c{k}" for k in range(len(df.columns))])
        cols = cols.select(*[F.col(f"c{k}").cast(t).alias(f"c{k}") for k, t in enumerate(want)])
        return cols.dropna().distinct()

    def _with_inline(self, explicit: FactStore, pred: str, rules: list[Rule]) -> FactStore:
        if any(isinstance(a, Var) for r in rules for a in r.head.args):
            raise RuleError(f"{pred}: a fact has no variables")
        rows = self.spark.createDataFrame([tuple(a.value for a in r.head.args) for r in rules])
        old = explicit.get(pred).frame()
        part = self._load(pred, rows if old is None else rows.toDF(*old.columns).unionByName(old))
        return explicit.put(pred, Relation((part,)))

    # contexts and views

    def _context(self, state: State, log: UpdateLog) -> Context:
        c = self.config
        bag = state.bag()
        stats = Stats({p: bag.rows(p) for p in bag.index}, self.ndv)
        compiler = Compiler(self.spark, self.types, c.order, c.eager_filters, c.bound_aware, c.allow_cross, c.agg_over, c.median)
        return Context(self.storage, compiler, stats, log, c.max_rounds, c.evaluation, linear_after=c.linear_after)

    def _ext(self, state: State, own: Iterable[str]) -> object:
        """Visible relations of a state without a node's own stores."""
        bag, hidden = state.bag(), frozenset(own)

        def relation(pred: str) -> DataFrame | None:
            if self.config.layout != "none" and self.config.bag != "merged":
                return bag.ordered(pred, "c1" if self.config.layout == "c1" else "c0", self.storage, hidden)
            df = bag.relation(pred, hidden)
            if df is not None and self.config.bag == "merged":
                df = self.storage.write(df).frame
            return df

        whole = lambda pred: bag.covering(pred, hidden)
        relation.labels = lambda pred: p.labels if (p := whole(pred)) is not None else None
        relation.rows = lambda pred: sum(bag.stores[m].get(pred).rows for m in bag.members(pred) if m not in hidden)
        relation.ranks = lambda pred: p.ranks if (p := whole(pred)) is not None else None
        return relation

    def relation(self, pred: str, by: str | None = None, whole: bool = False) -> DataFrame:
        """All visible facts of a predicate, explicit and derived; with ``by`` from copies in the
        order of that column, which the ``layout`` must keep.  ``whole`` suits a reader of all
        facts: pairs of labels are made faster, but a filter on c1 applies to the pairs made."""
        bag = self.state.bag()
        if whole and (part := bag.covering(pred)) is not None and part.every is not None:
            return part.every
        df = bag.ordered(pred, by, self.storage) if by and self.config.layout in (by, "both") else bag.relation(pred)
        if df is None:
            return self._context(self.state, self.log).compiler.empty(pred)
        return df

    def _looked_up(self, atom: object) -> DataFrame:
        """The relation of an atom, in the order of its first constant argument."""
        at = next((f"c{k}" for k, t in enumerate(atom.args[:2]) if isinstance(t, Const)), None)
        return self.relation(atom.pred, at)

    def register_views(self) -> list[str]:
        names = self.state.bag().index
        for p in names:
            self.relation(p).createOrReplaceTempView(p)
        return sorted(names)

    def query(self, goal: str) -> DataFrame:
        """Bindings of a conjunctive goal over the materialisation, one column per variable."""
        parts = parse_atoms(goal)
        rule = Rule("goal", replace(parts["positives"][0], pred="_goal"), **{k: tuple(v) for k, v in parts.items()})
        ctx = self._context(self.state, self.log)
        got = ctx.compiler.bindings(rule, lambda k, a, n: self._looked_up(a), ctx.stats)
        return got.select(*[F.col(c).alias(c[2:]) for c in got.columns if c != "v__any"]).distinct()

    def explain(self, pred: str, *values: object) -> list[tuple[str, str]]:
        """One proof of a fact: pairs of fact and the rule (or ``explicit``) that gives it, each
        fact before those that it rests on; empty if the fact does not hold.

        Bindings of the rules for a fact are walked one by one, without those whose body uses a
        fact that still waits for its own proof, until one's body facts all have proofs."""
        goal = (pred, tuple(values))
        proved: dict[tuple, tuple[str, list[tuple]]] = {}
        stack: list[list] = [[goal, self._ways(goal, {goal}), None]]  # fact, its ways, the way tried now
        while stack:
            fact, ways, way = stack[-1]
            way = stack[-1][2] = way or next(ways, None)
            if way is None:  # no way is left; whoever needed this fact goes on with another
                stack.pop()
                if stack:
                    stack[-1][2] = None
                continue
            missing = next((n for n in way[1] if n not in proved), None)
            if missing is None:
                proved[fact] = way
                stack.pop()
            else:
                stack.append([missing, self._ways(missing, {missing, *(f for f, _, _ in stack)}), None])
        out, todo, seen = [], [goal] if goal in proved else [], set()
        while todo:
            fact = todo.pop()
            if fact not in seen:
                seen.add(fact)
                out.append((f"{fact[0]}({', '.join(map(str, fact[1]))})", proved[fact][0]))
                todo += proved[fact][1]
        return out

    def _ways(self, fact: tuple[str, tuple], path: set[tuple]) -> Iterator[tuple[str, list[tuple]]]:
        """Rules that give a fact, with the body facts of each binding that uses none of ``path``."""
        pred, values = fact
        here = self.state.explicit.get(pred).frame()
        if here is not None and not here.where(_equals(values)).isEmpty():
            yield EXPLICIT, []
        ctx = self._context(self.state, self.log)
        for r in (r for r in self.state.program if r.head.pred == pred):
            if any(isinstance(a, Const) and a.value != v for a, v in zip(r.head.args, values, strict=True)):
                continue
            b = ctx.compiler.bindings(r, lambda k, a, n: self.relation(a.pred), ctx.stats)
            for a, v in zip(r.head.args, values, strict=True):
                if isinstance(a, Var) and column(a.name) in b.columns:
                    b = b.where(F.col(column(a.name)) == F.lit(v))
            for row in b.toLocalIterator():
                need = [(a.pred, tuple(t.value if isinstance(t, Const) else row[column(t.name)] for t in a.args)) for a in r.positives if all(not isinstance(t, Var) or t.name != "_" for t in a.args)]
                if path.isdisjoint(need):
                    yield r.id, need

    # materialisation

    def materialise(self) -> StoreBag:
        """Evaluate every node in topological order."""
        began = time.perf_counter()
        log = UpdateLog("materialise")
        state = replace(self.state, stores={})
        if self.config.unit == "stratum":
            stores = self._by_stratum(state, log)
        else:
            stores = {}
            for wave in self._waves(state.hyper):
                run = lambda n: (n, self._fresh(replace(state, stores=dict(stores)), n, log))  # noqa: B023, E731
                if self.config.parallel_nodes > 1 and len(wave) > 1:
                    with ThreadPoolExecutor(self.config.parallel_nodes) as pool:
                        stores |= dict(pool.map(run, wave))
                else:
                    for n in wave:
                        stores |= [run(n)]
                log.visited += wave
        self._commit(replace(state, stores=stores), log, began)
        return self.state.bag()

    def _waves(self, hyper: HyperGraph) -> list[list[str]]:
        """Nodes in topological order; in parallel mode independent nodes share a wave."""
        order = hyper.topo_order()
        if self.config.parallel_nodes <= 1:
            return [[n] for n in order]
        depth: dict[str, int] = {}
        for n in order:
            depth[n] = 1 + max([0, *(depth[p] for p in hyper.predecessors(n))])
        return [[n for n in order if depth[n] == d] for d in range(1, max(depth.values(), default=0) + 1)]

    def _fresh(self, state: State, node: str, log: UpdateLog) -> FactStore:
        rules = [state.program.rules[r] for r in sorted(state.hyper.nodes[node])]
        pattern = symmetric_transitive(rules) if self.config.pattern_closure == "auto" else None
        ctx = self._context(state, log)
        ext = self._ext(state, [node])
        if (same := self._copy(state, node, rules)) is not None:
            return same
        if pattern:
            return expand_labels(ctx, rules, pattern, ext)
        c = self.config
        if c.pattern_closure == "auto" and c.evaluation != "naive" and c.max_rounds is None and (pred := symmetric(rules)) is not None:
            return expand_symmetric(ctx, pred, ext)
        if self._transitive(rules) is not None:
            return expand_transitive(ctx, self._transitive(rules), ext)
        return run_node(ctx, rules, ext)

    def _transitive(self, rules: Iterable[Rule]) -> object:
        """The closed form of a transitive node, which reads too much to suit a bound on rounds."""
        c = self.config
        return transitive(list(rules)) if c.pattern_closure == "auto" and c.evaluation != "naive" and c.max_rounds is None else None

    def _copy(self, state: State, node: str, rules: list[Rule]) -> FactStore | None:
        """The store of a node that renames a predicate: the parts that hold it, if they are those
        of one store and at rest as plain rows.  Nothing is read or written."""
        source = copied(rules) if self.config.pattern_closure == "auto" else None
        if source is None or self.types.get(source) != self.types.get(rules[0].head.pred):
            return None
        bag = state.bag()
        members = [m for m in bag.members(source) if m != node]
        parts = [p for m in members for p in bag.stores[m].get(source).parts if p.rows]
        if len(members) != 1 or any(p.closed or p.lazy for p in parts):
            return None
        return FactStore({rules[0].head.pred: Relation(tuple(parts))})

    def _by_stratum(self, state: State, log: UpdateLog) -> dict[str, FactStore]:
        """Baseline: a stratum's rules are one unit, whatever their components.  Afterwards each
        component gets what its own rules derive, so that later updates find their owner's facts."""
        level, of = stratify(state.graph), state.hyper.node_of()
        stores: dict[str, FactStore] = {}
        for s in sorted(set(level.values())):
            rules = [state.program.rules[r] for r in sorted(level) if level[r] == s]
            for r in (r for r in rules if r.agg):  # aggregates read complete lower strata only
                now = replace(state, stores=dict(stores))
                stores[of[r.id]] = run_node(self._context(now, log), [r], self._ext(now, []))
            rules = [r for r in rules if not r.agg]
            now = replace(state, stores=dict(stores))
            ctx, ext = self._context(now, log), self._ext(now, [])
            own = run_node(ctx, rules, ext)
            whole = Node(ctx, rules, ext, own)
            for pred, rel in own.relations.items():
                owners: dict[str, list[Rule]] = {}
                for r in rules:
                    if r.head.pred == pred:
                        owners.setdefault(of[r.id], []).append(r)
                for node, mine in owners.items():
                    if len(owners) > 1:
                        part = ctx.storage.write(union([whole.frame(r, whole.resolver()) for r in mine]).distinct())
                        rel = Relation((part,)) if part.rows else EMPTY
                    stores[node] = stores.get(node, FactStore()).put(pred, rel)
        return {n: stores.get(n, FactStore()) for n in state.hyper.nodes}

    # updates

    def insert_rules(self, rules: str | Iterable[Rule]) -> UpdateLog:
        return self.update(add_rules=rules)

    def delete_rules(self, ids: Iterable[str]) -> UpdateLog:
        return self.update(drop_rules=ids)

    def insert_facts(self, pred: str, df: DataFrame) -> UpdateLog:
        return self.update(add_facts={pred: df})

    def delete_facts(self, pred: str, df: DataFrame) -> UpdateLog:
        return self.update(drop_facts={pred: df})

    def update(self, add_rules: str | Iterable[Rule] = (), drop_rules: Iterable[str] = (), add_facts: dict[str, DataFrame] | None = None, drop_facts: dict[str, DataFrame] | None = None, batch: str | None = None) -> UpdateLog:
        """One transaction: rules out, rules in, facts out and in; then every node that the
        changes reach, once, in topological order.  The new version carries the name of the
        ``batch``; one that a version already carries changes nothing."""
        began = time.perf_counter()
        old = self.state
        if batch is not None and batch in old.batches:
            return UpdateLog("repeated")
        log = UpdateLog("update")
        types, declared = dict(self.types), dict(self.declared)
        try:
            new, dirty, removed = self._structure(old, list(drop_rules), add_rules, log)
            explicit, change = self._facts(old.explicit, add_facts or {}, drop_facts or {}, log)
            new = replace(new, explicit=explicit)
            state = self._revisit(old, new, dirty, removed, change, log)
            state = replace(state, batches=old.batches | ({batch} if batch is not None else set()))
        except BaseException:
            self.types, self.declared = types, declared
            raise
        self._commit(state, log, began)
        return log

    def _structure(self, old: State, drop: list[str], add: str | Iterable[Rule], log: UpdateLog) -> tuple[State, dict[str, tuple[list[str], set[str], bool]], set[str]]:
        """New graphs and, per directly concerned node: old nodes it comes from, its new rules,
        and whether it must be redone."""
        shapes = {r.shape(): r.id for r in old.program}
        drop = [shapes.get(d, d) for d in drop]
        for d in drop:
            if d not in old.program.rules:
                raise RuleError(f"there is no rule {d}")
        rules = list(parse_rules(add)) if isinstance(add, str) else list(add)
        kept = old.program.without(drop)
        present = {r.shape() for r in kept}
        fresh: list[Rule] = []
        for r in rules:
            if r.shape() in present:
                continue  # the same rule again changes nothing
            if r.id in kept.rules:
                if isinstance(add, str):
                    number = next(k for k in itertools.count(len(kept) + 1) if f"r{k}" not in kept.rules and all(f.id != f"r{k}" for f in fresh))
                    r = replace(r, id=f"r{number}")
                else:
                    raise RuleError(f"rule {r.id} exists already")
            present.add(r.shape())
            fresh.append(r)
        program = kept.plus(fresh)
        check_program(program, {p: len(t) for p, t in self.declared.items()})
        self.types = self.types | infer_types(program, self.declared)
        state, dirty = old, {}
        removed: set[str] = set()
        if drop:
            hit = impact.on_delete(old.graph, old.hyper, drop, self.config.successor_policy, self.config.scc)
            removed |= hit.gone
            log.dropped = sorted(hit.gone)
            dirty = {n: (hit.sources[n], set(), True) for n in hit.direct}
            names = {n: hit.sources[n] for n in hit.hyper.nodes}
            state = replace(old, program=kept, graph=hit.graph, hyper=hit.hyper)
        else:
            names = {n: [n] for n in old.hyper.nodes}
        if fresh:
            hit = impact.on_insert(state.graph, state.hyper, fresh, self.config.scc)
            after: dict[str, tuple[list[str], set[str], bool]] = {}
            for n, came in hit.sources.items():
                redo = any(c in dirty for c in came)
                if n in hit.direct or redo:
                    mode = self.config.insertion_mode
                    rules_of = [program.rules[r] for r in hit.hyper.nodes[n]]
                    auto = mode == "auto" and (symmetric_transitive(rules_of) is not None or len(came) > 1)
                    after[n] = (sorted({o for c in came for o in names[c]}), hit.fresh.get(n, set()), redo or mode == "redo" or auto)
            dirty = after
            state = replace(old, program=program, graph=hit.graph, hyper=hit.hyper)
        log.direct = set(dirty)
        return replace(state, program=program), dirty, removed

    def _facts(self, explicit: FactStore, add: dict[str, DataFrame], drop: dict[str, DataFrame], log: UpdateLog) -> tuple[FactStore, Change]:
        change = Change()
        ctx_new = explicit
        for pred, df in drop.items():
            rel = ctx_new.get(pred)
            if not rel.rows:
                continue
            goes = self._rows(pred, df)
            part = self.storage.write(rel.frame().join(goes, goes.columns, "left_semi"))
            if part.rows:
                left = self.storage.write(minus(rel.frame(), part.frame))
                ctx_new = ctx_new.put(pred, Relation((left,)) if left.rows else EMPTY)
                change.minus[pred] = part
        for pred, df in add.items():
            rows = self._rows(pred, df)
            self.types.setdefault(pred, self.declared[pred])
            part = self.storage.write(minus(rows, ctx_new.get(pred).frame()))
            if part.rows:
                ctx_new = ctx_new.put(pred, ctx_new.get(pred).plus(part))
                change.plus[pred] = part
        log.counts["explicit_plus"] = sum(p.rows for p in change.plus.values())
        log.counts["explicit_minus"] = sum(p.rows for p in change.minus.values())
        return ctx_new, change

    def _revisit(self, old: State, new: State, dirty: dict[str, tuple[list[str], set[str], bool]], removed: set[str], change: Change, log: UpdateLog) -> State:
        of_old = old.hyper.node_of()
        came = {n: sorted({of_old[r] for r in rs if r in of_old}) for n, rs in new.hyper.nodes.items()}
        stores = {n: old.stores.get(n, FactStore()) for n in new.hyper.nodes if n not in dirty}
        # changes by predicate, as candidates: what any store gained or lost
        plus: dict[str, list[object]] = {p: [x] for p, x in change.plus.items()}
        lost: dict[str, list[object]] = {p: [x] for p, x in change.minus.items()}
        for n in removed:
            for pred, rel in old.stores.get(n, FactStore()).relations.items():
                lost.setdefault(pred, []).extend(rel.parts)
        also = {n for n, rs in new.hyper.nodes.items() if any(p in {*plus, *lost} for r in rs for p in new.program.rules[r].body_preds())}
        steps = impact.execution_plan(new.hyper, dirty, also)
        log.plan = [(s.node, s.role) for s in steps]
        moved: set[str] = set()
        for step in steps:
            n = step.node
            now = replace(new, stores=dict(stores))
            ctx = self._context(now, log)
            ids = new.hyper.nodes[n]
            rules = {r: new.program.rules[r] for r in sorted(ids)}
            sources, fresh, redo = dirty.get(n, (came[n], set(), False))
            # the store of a transitive node also holds facts of its base, so no other rules go on from it
            redo = redo or (n in dirty and any(self._transitive(old.program.rules[r] for r in old.hyper.nodes[s]) is not None for s in sources if s in old.hyper.nodes))
            before = _merged(ctx, [old.stores.get(s, FactStore()) for s in sources], {r.head.pred for r in rules.values()}) if n not in moved else FactStore()
            ext_old, ext_new = self._ext(old, sources), self._ext(now, [n])
            reads = {p for r in rules.values() for p in r.body_preds()}
            alone = {p for p in reads if len([m for m in old.bag().members(p) if m not in sources]) <= 1 and len([m for m in now.bag().members(p) if m != n]) <= 1}
            heavy = {p for p in reads for x in (*plus.get(p, ()), *lost.get(p, ())) if x.rows and (x.lazy or x.closed)}
            # an aggregate over a closed form is computed again: from labels that takes no pairs
            again = n not in dirty and all(r.agg for r in rules.values()) and bool(heavy or (reads & {*plus, *lost} and any(by_component(r, ext_new) for r in rules.values())))
            # a closed form of chains is made anew, too; only a whole one may stand for its base
            again = again or (self._transitive(rules.values()) is not None and bool(reads & {*plus, *lost}))
            change_in = Change() if again else self._visible(ctx, {p for p in reads if p in plus or p in lost}, plus, lost, (old.bag(), sources), (now.bag(), [n]), alone, n in dirty)
            if n not in dirty and not again and not change_in.touches(reads):
                log.skipped.append(n)
                continue
            log.visited.append(n)
            pattern = symmetric_transitive(list(rules.values())) if self.config.pattern_closure == "auto" and not (redo or n in dirty) and self.config.downstream != "redo" and sources == [n] else None
            if pattern:
                stores[n], gained, gone = maintain_labels(ctx, pattern, old.stores.get(n, FactStore()), change_in, ext_new)
                for pred, part in gained.items():
                    plus.setdefault(pred, []).append(part)
                for pred, part in gone.items():
                    lost.setdefault(pred, []).append(part)
                log.deltas += [(n, p, gained[p].rows if p in gained else 0, gone[p].rows if p in gone else 0) for p in sorted({*gained, *gone})]
                continue
            same = self._copy(now, n, list(rules.values())) if not redo and n not in dirty and self.config.downstream != "redo" and sources == [n] else None
            if same is not None:  # what its source gained and lost, and nothing else
                ((source,), (head,)) = reads, same.relations
                stores[n] = same
                for many, side in ((plus, change_in.plus), (lost, change_in.minus)):
                    if source in side:
                        many.setdefault(head, []).append(side[source])
                log.deltas.append((n, head, *(side[source].rows if source in side else 0 for side in (change_in.plus, change_in.minus))))
                continue
            if again or redo or (n not in dirty and self.config.downstream == "redo"):
                store = self._fresh(now, n, log)
            else:
                olds = [r for i, r in rules.items() if i not in fresh]
                news = [r for i, r in rules.items() if i in fresh]
                if news and news[0].agg:
                    store = run_node(ctx, news, ext_new)
                else:
                    store = Maintainer(ctx, olds, news, ext_old, ext_new, before, change_in, self.config.deletion_method).run()
            stores[n] = store
            origin = _together([old.stores.get(s, FactStore()) for s in sources], {r.head.pred for r in rules.values()})
            delta = diff(ctx, origin, store, closed_diff)
            if len(sources) == 1 and len([m for m, c in came.items() if sources[0] in c]) > 1:
                # a split node: what its old store held and no part holds is lost
                gone_preds = {p for p in old.stores.get(sources[0], FactStore()).relations if p not in store.relations and all(p not in {new.program.rules[r].head.pred for r in new.hyper.nodes[m]} for m, c in came.items() if sources[0] in c)}
                for p in gone_preds:
                    lost.setdefault(p, []).extend(old.stores[sources[0]].get(p).parts)
            for pred, part in delta.plus.items():
                plus.setdefault(pred, []).append(part)
            for pred, part in delta.minus.items():
                lost.setdefault(pred, []).append(part)
            dropped_heads = {p for s in sources for p in old.stores.get(s, FactStore()).relations} - {new.program.rules[r].head.pred for m, c in came.items() if set(c) & set(sources) for r in new.hyper.nodes[m]}
            for pred in dropped_heads:
                for s in sources:
                    lost.setdefault(pred, []).extend(old.stores.get(s, FactStore()).get(pred).parts)
            log.deltas += [(n, p, delta.plus[p].rows if p in delta.plus else 0, delta.minus[p].rows if p in delta.minus else 0) for p in sorted({*delta.plus, *delta.minus})]
        return replace(new, stores={n: stores.get(n, FactStore()) for n in new.hyper.nodes})

    def _visible(self, ctx: Context, preds: set[str], plus: dict[str, list], lost: dict[str, list], before: tuple[StoreBag, list[str]], after: tuple[StoreBag, list[str]], alone: set[str], rebuilt: bool) -> Change:
        """Candidates that really change what a node sees: the union of the stores but its own.
        Where one store is ``alone`` with a predicate, nothing else can show or hide its facts;
        only a ``rebuilt`` node can meet candidates of stores that are its own."""
        out = Change()
        for pred in sorted(preds):
            for many, side, here, against in ((plus, out.plus, after, before), (lost, out.minus, before, after)):
                parts = [x for x in many.get(pred, ()) if x.rows]
                if not parts:
                    continue
                if pred in alone and not rebuilt and len(parts) == 1 and not parts[0].closed and not parts[0].lazy and not (plus.get(pred) and lost.get(pred)):
                    side[pred] = parts[0]
                    continue
                cand = union([x.frame for x in parts])
                cand = cand.distinct() if len(parts) > 1 else cand
                if rebuilt:
                    inside = here[0].relation(pred, frozenset(here[1]))
                    if inside is None:
                        continue
                    cand = cand.join(inside, cand.columns, "left_semi")
                part = self.storage.write(against[0].missing(cand, pred, frozenset(against[1])))
                if part.rows:
                    side[pred] = part
        return out

    def _commit(self, state: State, log: UpdateLog, began: float) -> None:
        log.seconds = time.perf_counter() - began
        self.state, self.log = replace(state, version=self.state.version + 1), log

    # inspection

    def sizes_df(self) -> DataFrame:
        rows = [(n, p, r.rows) for n, s in self.state.bag().stores.items() for p, r in sorted(s.relations.items())]
        return self.spark.createDataFrame(rows, "node_id string, predicate string, rows long")

    def total_facts(self) -> int:
        bag = self.state.bag()
        return sum(self.relation(p).count() if len(bag.members(p)) > 1 else bag.rows(p) for p in bag.index)

    def rules_df(self) -> DataFrame:
        rows = [(r.id, r.head.pred, r.text(), len(r.positives), len(r.negatives), r.agg is not None) for r in self.state.program]
        return self.spark.createDataFrame(rows, "rule_id string, head string, body_text string, n_pos int, n_neg int, is_agg boolean")

    def rule_edges_df(self) -> DataFrame:
        return self.spark.createDataFrame(sorted(self.state.graph.edges), "src string, dst string, kind string")

    def hypernodes_df(self) -> DataFrame:
        return self.spark.createDataFrame([(n, r) for n, rs in self.state.hyper.nodes.items() for r in sorted(rs)], "node_id string, rule_id string")

    def hyperedges_df(self) -> DataFrame:
        return self.spark.createDataFrame(sorted(self.state.hyper.edges), "src string, dst string, kind string")

    def strata_df(self) -> DataFrame:
        return self.spark.createDataFrame(sorted(stratify(self.state.graph).items()), "rule_id string, stratum int")

    def plan_df(self) -> DataFrame:
        return self.spark.createDataFrame([(k, n, role) for k, (n, role) in enumerate(self.log.plan)], "step int, node_id string, role string")

    def deltas_df(self) -> DataFrame:
        return self.spark.createDataFrame([(self.state.version, *d) for d in self.log.deltas], "update_id int, node_id string, predicate string, n_plus long, n_minus long")

    def profile(self) -> dict[str, object]:
        p = self.state.program
        heads = p.heads()
        return {"rules": len(p), "nodes": len(self.state.hyper.nodes), "predicates": len(p.preds()), "explicit_negation": any(a.pred not in heads for r in p for a in r.negatives), "derived_negation": any(a.pred in heads for r in p for a in r.negatives), "aggregation": any(r.agg for r in p)}

    # saving

    def save(self, path: str) -> None:
        """Write the state: relations in Parquet, and a manifest written last."""
        manifest = {"version": self.state.version, "rules": [[r.id, r.text()] for r in self.state.program], "nodes": {n: sorted(rs) for n, rs in self.state.hyper.nodes.items()}, "types": self.types, "declared": self.declared, "batches": sorted(self.state.batches), "relations": []}
        base = f"{path}/v{self.state.version}"
        for n, s in self.state.bag().stores.items():
            for p, r in s.relations.items():
                if r.rows:
                    r.frame().write.mode("overwrite").parquet(f"{base}/node={n}/pred={p}")
                    manifest["relations"].append([n, p, r.rows])
        self.spark.createDataFrame([(json.dumps(manifest),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @classmethod
    def restore(cls, spark: SparkSession, path: str, config: Config | None = None) -> Reasoner:
        from .store import Part

        m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        rules = Program({i: replace(parse_rules(t)[0], id=i) for i, t in m["rules"]})
        out = cls(spark, rules, None, config, m["declared"])
        out.types = m["types"]
        stores: dict[str, FactStore] = {}
        for n, p, rows in m["relations"]:
            at = f"{path}/v{m['version']}/node={n}/pred={p}"
            schema = ", ".join(f"c{k} {t}" for k, t in enumerate(m["types"].get(p) or m["declared"][p]))
            stores[n] = stores.get(n, FactStore()).put(p, Relation((Part(spark.read.schema(schema).parquet(at), rows, at),)))
        graph = RuleGraph(rules)
        names = {frozenset(rs): n for n, rs in m["nodes"].items()}
        hyper = condense(graph, names)
        out.state = State(rules, graph, hyper, stores.pop(EXPLICIT, FactStore()), {n: stores.get(n, FactStore()) for n in hyper.nodes}, m["version"], frozenset(m["batches"]))
        return out

    def vacuum(self) -> int:
        """Delete files that the current version does not read."""
        live = self.state.explicit.paths()
        for s in self.state.stores.values():
            live |= s.paths()
        return self.storage.vacuum(live)


def _equals(values: tuple[object, ...]) -> object:
    out = F.lit(True)
    for k, v in enumerate(values):
        out = out & (F.col(f"c{k}") == F.lit(v))
    return out


def _together(stores: list[FactStore], preds: set[str]) -> FactStore:
    """Stores side by side, without reading them; equal facts may occur twice."""
    out = FactStore()
    for s in stores:
        for p, r in s.relations.items():
            if p in preds:
                out = out.put(p, Relation((*out.get(p).parts, *r.parts)))
    return out


def _merged(ctx: Context, stores: list[FactStore], preds: set[str]) -> FactStore:
    """One store of several; where two hold a predicate, duplicates are dropped."""
    out = _together(stores, preds)
    for p, r in out.relations.items():
        if sum(p in s.relations for s in stores) > 1:
            out = out.put(p, Relation((ctx.storage.write(r.frame().distinct()),)))
    return out


__all__ = ["Config", "Reasoner", "State", "Expr"]
