"""The experiments as queries, with closed-form SQL for what each state must hold."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..engine import Config, Reasoner
from ..engine.baselines import from_scratch
from ..lang import parse_program
from ..lang.syntax import Program
from ..plans.depgraph import stratify
from ..plans.impact import execution_plan, on_delete, on_insert
from . import datasets, rulesets

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: Independent nodes of the larger rule sets run side by side.
WIDE = Config(parallel_nodes=4)
_states: dict[tuple[str, str, str], Reasoner] = {}


def _kept(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], Reasoner]) -> Reasoner:
    """One materialisation per session and data, forked by the queries that start from it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _states:
        r = make()
        r.materialise()
        _states[key] = r
    return _states[key].fork()


def rs1(spark: SparkSession, sf_dir: str) -> Reasoner:
    return _kept(spark, sf_dir, "rs1", lambda: Reasoner(spark, rulesets.RS1, datasets.nations(spark, sf_dir)))


def rs2(spark: SparkSession, sf_dir: str) -> Reasoner:
    return _kept(spark, sf_dir, "rs2", lambda: Reasoner(spark, rulesets.RS2, datasets.trade(spark, sf_dir), WIDE))


def rs3(spark: SparkSession, sf_dir: str) -> Reasoner:
    return _kept(spark, sf_dir, "rs3", lambda: Reasoner(spark, rulesets.RS3, datasets.trade(spark, sf_dir), WIDE))


def _add(name: str, query: Query, sql: str | None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


# ------------------------------------------------------------------ chains, RS1
#
# All customers, as one chain per nation in the order of their keys.

_CHAINS = """
WITH f AS (SELECT c_custkey AS k, c_nationkey AS n, c_acctbal AS v, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS i,
                  count(*) OVER (PARTITION BY c_nationkey) AS size FROM customer),
m AS (SELECT n, median(v) AS m FROM f WHERE size > 1 GROUP BY n)
"""
_NEAR = "SELECT a.k AS c0, b.k AS c1 FROM f a JOIN f b ON a.n = b.n WHERE a.size > 1"
_add("rs1_near", lambda s, d: rs1(s, d).relation("near"), _CHAINS + _NEAR)
_add("rs1_near_count", lambda s, d: rs1(s, d).relation("nearCount"), _CHAINS + "SELECT k AS c0, size AS c1 FROM f WHERE size > 1")
_add("rs1_median", lambda s, d: rs1(s, d).relation("medTemp").select("c0", F.round("c1", 4).alias("c1")), _CHAINS + "SELECT k AS c0, round(m, 4) AS c1 FROM f JOIN m USING (n)")
_add("rs1_suspect", lambda s, d: rs1(s, d).relation("suspect").select("c0", F.round("c1", 4).alias("c1")), _CHAINS + "SELECT k AS c0, round(v - m, 4) AS c1 FROM f JOIN m USING (n) WHERE v - m > 5000")


def _rs1_after(update: Callable[[Reasoner, str], object], pred: str = "near") -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = rs1(spark, sf_dir)
        update(r, sf_dir)
        return r.relation(pred, whole=True)

    return run


def _bridge(r: Reasoner, sf_dir: str) -> None:
    """One link between the chains of nations 0 and 1."""
    c = datasets.read(r.spark, sf_dir, "customer")
    last = c.where("c_nationkey = 0").agg(F.max("c_custkey").alias("a"))
    first = c.where("c_nationkey = 1").agg(F.min("c_custkey").alias("b"))
    r.insert_facts("hasNeighbour", last.crossJoin(first).dropna())  # one row each


def _break(r: Reasoner, sf_dir: str) -> None:
    """The middle link of nation 0 goes."""
    r.delete_facts("hasNeighbour", datasets.ranked_links(r.spark, sf_dir).where((F.col("nation") == 0) & (F.col("rank") == F.floor(F.col("size") / 2))).select("a", "b"))


_BRIDGED = "SELECT a.k AS c0, b.k AS c1 FROM f a JOIN f b ON greatest(a.n, 1) = greatest(b.n, 1) WHERE a.size > 1 OR a.n < 2"
_BROKEN = "g AS (SELECT k, n, n = 0 AND i > size // 2 AS late, count(*) OVER (PARTITION BY n, n = 0 AND i > size // 2) AS size FROM f)"
_add("rs1_insert_fact", _rs1_after(_bridge), _CHAINS + _BRIDGED)
_add("rs1_insert_fact_count", _rs1_after(_bridge, "nearCount"), f"{_CHAINS} SELECT c0, count(*) AS c1 FROM ({_BRIDGED}) GROUP BY c0")
_add("rs1_delete_fact", _rs1_after(_break), f"{_CHAINS}, {_BROKEN} SELECT a.k AS c0, b.k AS c1 FROM g a JOIN g b ON a.n = b.n AND a.late = b.late WHERE a.size > 1")
_add("rs1_delete_fact_count", _rs1_after(_break, "nearCount"), f"{_CHAINS}, {_BROKEN} SELECT k AS c0, size AS c1 FROM g WHERE size > 1")
_add("rs1_delete_symmetric", _rs1_after(lambda r, d: r.delete_rules(["r2"])), _CHAINS + "SELECT a.k AS c0, b.k AS c1 FROM f a JOIN f b ON a.n = b.n AND a.i < b.i")
_add("rs1_delete_transitive", _rs1_after(lambda r, d: r.delete_rules(["r3"])), _CHAINS + "SELECT a.k AS c0, b.k AS c1 FROM f a JOIN f b ON a.n = b.n AND abs(a.i - b.i) = 1")


def _grown(percent: int, shrink: bool) -> Query:
    """Every chain grows by a percentage of its length, and shrinks again."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        links = datasets.ranked_links(spark, sf_dir)
        early = F.col("rank") < F.floor(F.col("size") * 100 / (100 + percent))
        late = links.where(~early).select("a", "b")
        r = _kept(spark, sf_dir, f"grow-{percent}", lambda: Reasoner(spark, rulesets.NEAR, {"hasNeighbour": links.where(early).select("a", "b")}))
        r.insert_facts("hasNeighbour", late)
        if shrink:
            r.delete_facts("hasNeighbour", late)
        return r.relation("near", whole=True)

    return run


for _p in (10, 20, 30, 40, 50):
    _add(f"ds1_grow_{_p}", _grown(_p, False), _CHAINS + _NEAR)
    _add(f"ds1_shrink_{_p}", _grown(_p, True), f"{_CHAINS} SELECT a.k AS c0, b.k AS c1 FROM f a JOIN f b ON a.n = b.n WHERE greatest(a.i, b.i) <= a.size * 100 // {100 + _p} AND a.size * 100 // {100 + _p} > 1")

# A program with recursion, aggregation, negation and a body of several joins.
VARIED = rulesets.NEAR + """
@v4 nearCount(x, count(y)) <- near(x, y) group x.
@v5 warm(x) <- temp(x, t), t > 5000.
"""
VARIED_LAST = "@v6 picked(x, y) <- nearCount(x, c), temp(y, t), near(x, y), warm(x), !warm(y), c > 2, t < 2000."


def _variant(config: Config) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = Reasoner(spark, VARIED, datasets.nations(spark, sf_dir), config)
        r.materialise()
        r.insert_rules(VARIED_LAST)
        _break(r, sf_dir)
        return r.relation("picked")

    return run


_VARIANTS = {
    "naive": Config(evaluation="naive"), "stratum": Config(unit="stratum"), "merged_bag": Config(bag="merged"), "layout_c0": Config(layout="c0"), "layout_c1": Config(layout="c1"), "layout_both": Config(layout="both"),
    "order_text": Config(order="text", allow_cross=True), "order_dp": Config(order="dp"), "order_heuristic": Config(order="heuristic"), "backward_forward": Config(deletion_method="backward_forward"), "counting": Config(deletion_method="counting"),
    "downstream_redo": Config(downstream="redo"), "successor_delta": Config(successor_policy="delta"), "successor_always": Config(successor_policy="always"), "insertion_redo": Config(insertion_mode="redo"), "insertion_auto": Config(insertion_mode="auto"),
    "low_link": Config(scc="low_link"), "no_pattern": Config(pattern_closure="off"), "lazy_filters": Config(eager_filters=False), "bound_unaware": Config(bound_aware=False), "agg_pairs": Config(agg_over="pairs"), "cut_checkpoint": Config(cut="checkpoint"),
}
_PICKED = f"{_CHAINS}, {_BROKEN} SELECT a.k AS c0, b.k AS c1 FROM g a JOIN g b ON a.n = b.n AND a.late = b.late JOIN f x ON x.k = a.k JOIN f y ON y.k = b.k WHERE a.size > 2 AND x.v > 5000 AND y.v < 2000"
for _name, _config in _VARIANTS.items():
    _add(f"variant_{_name}", _variant(_config), _PICKED)

# ------------------------------------------------------------------ trade, RS2

_TRADE = """
WITH c AS (SELECT c_custkey AS k, c_nationkey AS nk, n_regionkey AS rk, row_number() OVER (PARTITION BY n_regionkey ORDER BY c_custkey) AS i,
                  count(*) OVER (PARTITION BY n_regionkey) AS size FROM customer JOIN nation ON c_nationkey = n_nationkey),
p2 AS (SELECT k * 4 AS c0, CAST(nk AS BIGINT) * 4 + 2 AS c1 FROM c),
p3 AS (SELECT CAST(n_nationkey AS BIGINT) * 4 + 2 AS c0, CAST(n_regionkey AS BIGINT) * 4 + 3 AS c1 FROM nation),
q1 AS (SELECT a.k * 4 AS c0, b.k * 4 AS c1 FROM c a JOIN c b ON a.rk = b.rk WHERE a.size > 1),
q2 AS (SELECT k * 4 AS c0, CAST(rk AS BIGINT) * 4 + 3 AS c1 FROM c),
q3 AS (SELECT DISTINCT o_custkey * 4 AS c0, CAST(s_nationkey AS BIGINT) * 4 + 2 AS c1 FROM orders JOIN lineitem ON o_orderkey = l_orderkey
       JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey),
q4 AS (SELECT * FROM q3 INTERSECT SELECT * FROM p2),
q5 AS (SELECT a.k * 4 AS c0, b.k * 4 AS c1 FROM c a JOIN c b ON a.rk = b.rk AND b.i > a.i AND (b.i - a.i) % 2 = 1),
q6 AS (SELECT a.k * 4 AS c0, b.k * 4 AS c1 FROM c a JOIN c b ON a.rk = b.rk AND b.i > a.i AND (b.i - a.i) % 2 = 0),
q7 AS (SELECT * FROM q3 EXCEPT SELECT * FROM p2),
q8 AS (SELECT DISTINCT a.k * 4 AS c0, CAST(b.nk AS BIGINT) * 4 + 2 AS c1 FROM c a JOIN c b ON a.rk = b.rk UNION SELECT * FROM q2),
q9 AS (SELECT c0, c1 FROM q7 WHERE c0 IN (SELECT c0 FROM q6) UNION SELECT * FROM q4),
q10a AS (SELECT * FROM q2), q10b AS (SELECT DISTINCT q9.c0, p3.c1 FROM q9 JOIN p3 ON q9.c1 = p3.c0),
q10 AS (SELECT * FROM q10a UNION SELECT * FROM q10b)
"""


def _trade_sql(select: str) -> str:
    return f"{_TRADE} SELECT c0, c1 FROM ({select})"


for _q in range(1, 11):
    _add(f"rs2_q{_q}", lambda s, d, q=_q: rs2(s, d).relation(f"q{q}"), _trade_sql(f"SELECT * FROM q{_q}"))


def _after_delete(make: Callable[[SparkSession, str], Reasoner], ids: list[str], pred: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = make(spark, sf_dir)
        r.delete_rules(ids)
        return r.relation(pred)

    return run


def _after_insert(make: Callable[[SparkSession, str], Reasoner], rules: str, ids: list[str], pred: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = make(spark, sf_dir)
        r.delete_rules(ids)
        r.insert_rules(list(parse_program(rules).only(ids)))
        return r.relation(pred)

    return run


_DELETED = {
    "r10_r15_r17": ("q10", "SELECT DISTINCT q4.c0, p3.c1 FROM q4 JOIN p3 ON q4.c1 = p3.c0"), "r10_r15_r18": ("q10", "SELECT * FROM q2"), "r18": ("q10", "SELECT * FROM q10a"), "r17": ("q10", "SELECT * FROM q10b"),
    "r4": ("q10", "SELECT * FROM q10b"), "r3": ("q1", "SELECT c0, c1 FROM q1 JOIN c a ON a.k * 4 = c0 JOIN c b ON b.k * 4 = c1 WHERE abs(a.i - b.i) = 1"), "r2": ("q1", "SELECT c0, c1 FROM q1 JOIN c a ON a.k * 4 = c0 JOIN c b ON b.k * 4 = c1 WHERE a.i < b.i"),
}
for _name, _ids in rulesets.UPDATES.items():
    _pred, _sql = _DELETED[_name]
    _add(f"rs2_delete_{_name}", _after_delete(rs2, _ids, _pred), _trade_sql(_sql))
    _add(f"rs2_insert_{_name}", _after_insert(rs2, rulesets.RS2, _ids, _pred), _trade_sql(f"SELECT * FROM {_pred}"))
_add("rs3_delete_r6", _after_delete(rs3, ["r6"], "q7"), _trade_sql("SELECT * FROM q3"))
_add("rs3_delete_r10n", _after_delete(rs3, ["r10n"], "q9"), _trade_sql("SELECT * FROM q4"))
_add("rs3_insert_r6", _after_insert(rs3, rulesets.RS3, ["r6"], "q7"), _trade_sql("SELECT * FROM q7"))
_add("rs3_insert_r10n", _after_insert(rs3, rulesets.RS3, ["r10n"], "q9"), _trade_sql("SELECT * FROM q9"))


def rs2_footprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the explicit store and of every node's store."""
    return rs2(spark, sf_dir).sizes_df().where("node_id <> 'explicit'").groupBy("predicate").agg(F.sum("rows").alias("rows")).where("predicate in ('q1', 'q2', 'q3', 'q4', 'q5', 'q6', 'q7')")


_add("rs2_footprint", rs2_footprint, _TRADE + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT 'q{k}' AS predicate, CAST(count(*){'+ (SELECT count(*) FROM c WHERE i < size)' if k == 1 else ''} AS BIGINT) AS rows FROM q{k}" for k in (2, 3, 4, 5, 6, 7)) + " UNION ALL SELECT 'q1', CAST((SELECT count(*) FROM q1) + (SELECT count(*) FROM c WHERE i < size) AS BIGINT))")


def rs2_visible(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Visible facts of every derived predicate: what a merged store would hold."""
    r = rs2(spark, sf_dir)
    counts = [r.relation(f"q{k}").agg(F.count("*").alias("rows")).select(F.lit(f"q{k}").alias("predicate"), "rows") for k in range(1, 11)]
    return reduce(DataFrame.unionByName, counts)


_add("rs2_visible", rs2_visible, _TRADE + " UNION ALL ".join(f"SELECT 'q{k}' AS predicate, count(*) AS rows FROM q{k}" for k in range(1, 11)))


def baseline_equality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Symmetric difference of the incremental state and recomputation, per predicate."""
    r = rs2(spark, sf_dir)
    r.delete_rules(["r6"])
    again = from_scratch(r)
    rows = []
    for p in sorted(r.state.program.heads()):
        a, b = r.relation(p), again.relation(p)
        rows.append((p, a.exceptAll(b).count() + b.exceptAll(a).count()))
    return spark.createDataFrame(rows, "predicate string, differing long")


_add("rs2_equals_scratch", baseline_equality, "SELECT * FROM (VALUES ('q1', 0), ('q10', 0), ('q2', 0), ('q3', 0), ('q5', 0), ('q6', 0), ('q7', 0), ('q8', 0), ('q9', 0)) t(predicate, differing)")

# ------------------------------------------------------------- worked examples


# The explicit relations of the examples are given tables.  Every answer also says how many explicit
# facts the rules of a node (or a rule) read: what a visit to it starts from.


def _example(spark: SparkSession, sf_dir: str, rules: str, names: tuple[str, str, str]) -> Reasoner:
    """An example's program over customers and their nations, nations and their suppliers, customers and their orders."""
    columns = (("customer", "c_custkey", "c_nationkey"), ("supplier", "s_nationkey", "s_suppkey"), ("orders", "o_custkey", "o_orderkey"))
    return Reasoner(spark, rules, {p: datasets.read(spark, sf_dir, t).select(x, y) for p, (t, x, y) in zip(names, columns, strict=True)})


def _rex(spark: SparkSession, sf_dir: str) -> Reasoner:
    return _example(spark, sf_dir, rulesets.REX, ("e1", "p3", "e2"))


def _explicit_read(r: Reasoner, rules: Iterable[str], program: Program | None = None) -> int:
    """Explicit facts of the predicates in the bodies of some rules."""
    program = program or r.state.program
    return sum(r.state.explicit.get(p).rows for p in {p for i in rules for p in program.rules[i].body_preds()})


def _rex_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _rex(spark, sf_dir)
    return spark.createDataFrame([(a, b, k, _explicit_read(r, r.state.hyper.nodes[b])) for a, b, k in sorted(r.state.hyper.edges)], "src string, dst string, kind string, facts long")


def _rex_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _rex(spark, sf_dir)
    return spark.createDataFrame([(i, s, _explicit_read(r, [i])) for i, s in sorted(stratify(r.state.graph).items())], "rule_id string, stratum int, facts long")


def _rex_r8(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, more = _rex(spark, sf_dir), parse_program(rulesets.REX_R8)
    hit, program = on_insert(r.state.graph, r.state.hyper, more), r.state.program.plus(more)
    return spark.createDataFrame([(n, i, _explicit_read(r, [i], program)) for n in sorted(hit.direct) for i in sorted(hit.hyper.nodes[n])], "node_id string, rule_id string, facts long")


def _rex_r4(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, more = _rex(spark, sf_dir), parse_program(rulesets.REX_R8)
    hit, program = on_insert(r.state.graph, r.state.hyper, more), r.state.program.plus(more)
    hit = on_delete(hit.graph, hit.hyper, ["r4"])
    return spark.createDataFrame([(n, _explicit_read(r, hit.hyper.nodes[n], program)) for n in sorted(hit.direct)], "node_id string, facts long")


def _rex_drop(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _rex(spark, sf_dir)
    before, hit = r.state.hyper.nodes, on_delete(r.state.graph, r.state.hyper, ["r5", "r6", "r7"])
    states = [("kept", n) for n in sorted(hit.hyper.nodes)] + [("dropped", n) for n in sorted(hit.gone)]
    return spark.createDataFrame([(s, n, _explicit_read(r, before[n])) for s, n in states], "state string, node_id string, facts long")


def _rdel(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _example(spark, sf_dir, rulesets.RDEL, ("e1", "c", "f"))
    hit = on_delete(r.state.graph, r.state.hyper, ["r7"])
    rows = [(k, sorted(hit.hyper.nodes[s.node]), s.role) for k, s in enumerate(execution_plan(hit.hyper, hit.direct))]
    return spark.createDataFrame([(k, ",".join(m), role, _explicit_read(r, m)) for k, m, role in rows], "step int, rules string, role string, facts long")


def _rex_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _kept(spark, sf_dir, "rex", lambda: Reasoner(spark, rulesets.REX + rulesets.REX_FACTS))
    r.insert_rules(rulesets.REX_R8)
    out = [r.relation(p).select(F.lit(p).alias("pred"), "c0", "c1") for p in ("p2", "p5", "p7")]
    return out[0].unionByName(out[1]).unionByName(out[2])


def _sized(columns: str, rows: str) -> str:
    """Rows of an answer, whose last value names the relation that is read: its distinct facts, or none."""
    tables = (("c", "customer", "c_custkey", "c_nationkey"), ("s", "supplier", "s_nationkey", "s_suppkey"), ("o", "orders", "o_custkey", "o_orderkey"))
    counts = " UNION ALL ".join(f"SELECT '{k}' AS rel, count(*) AS facts FROM (SELECT DISTINCT {x}, {y} FROM {t} WHERE {x} IS NOT NULL AND {y} IS NOT NULL)" for k, t, x, y in tables)
    names = columns.replace("CAST(step AS INT) AS ", "").replace("CAST(stratum AS INT) AS ", "")
    return f"WITH n AS ({counts}) SELECT {columns}, coalesce(n.facts, 0) AS facts FROM (VALUES {rows}) t({names}, rel) LEFT JOIN n USING (rel)"


_add("rex_hyperedges", _rex_edges, _sized("src, dst, kind", "('hn1', 'hn2', 'P', 's'), ('hn2', 'hn3', 'N', 'o'), ('hn2', 'hn4', 'P', ''), ('hn3', 'hn4', 'P', '')"))
_add("rex_strata", _rex_strata, _sized("rule_id, CAST(stratum AS INT) AS stratum", "('r1', 0, 'c'), ('r2', 0, 's'), ('r3', 0, ''), ('r4', 0, ''), ('r5', 1, 'o'), ('r6', 1, ''), ('r7', 1, '')"))
_add("rex_impact_r8", _rex_r8, _sized("node_id, rule_id", "('hn2', 'r2', 's'), ('hn2', 'r3', ''), ('hn2', 'r4', ''), ('hn2', 'r8', 's')"))
_add("rex_impact_r4", _rex_r4, _sized("node_id", "('hn2', 's'), ('hn3', 'o'), ('hn4', ''), ('hn5', ''), ('hn6', 's')"))
_add("rex_drop_567", _rex_drop, _sized("state, node_id", "('kept', 'hn1', 'c'), ('kept', 'hn2', 's'), ('dropped', 'hn3', 'o'), ('dropped', 'hn4', '')"))
_add("rdel_plan", _rdel, _sized("CAST(step AS INT) AS step, rules, role", "(0, 'r2,r3', 'direct', 's'), (1, 'r4,r5,r6', 'downstream', 'o')"))
_add("rex_after_r8", _rex_facts, "SELECT pred, CAST(c0 AS BIGINT) AS c0, CAST(c1 AS BIGINT) AS c1 FROM (VALUES ('p2', 1, 7), ('p2', 2, 7), ('p2', 7, 7), ('p5', 5, 6), ('p7', 1, 7), ('p7', 2, 7), ('p7', 5, 6)) t(pred, c0, c1)")

# -------------------------------------------------------- anomalies on a farm

FARM = rulesets.JUDGE.replace("5000", "5")


def _farm(spark: SparkSession, sf_dir: str) -> Reasoner:
    return _kept(spark, sf_dir, "farm", lambda: Reasoner(spark, rulesets.NEAR, datasets.farms(spark, sf_dir)))


def farm_anomaly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An event fetches the judging rules; the suspects they find."""
    r = _farm(spark, sf_dir)
    r.insert_rules(FARM)
    return r.relation("suspect").select("c0", F.round("c1", 4).alias("c1"))


def farm_anomaly_cycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same, and afterwards the rules go again; what is left, by predicate."""
    r = _farm(spark, sf_dir)
    log = r.insert_rules(FARM)
    assert log.visited
    r.delete_rules(["r4", "r5", "r6"])
    return r.sizes_df().groupBy("predicate").agg(F.max("rows").alias("rows")).where("predicate in ('near', 'suspect', 'medTemp', 'nearCount')")


_FARM = """
WITH f AS (SELECT c_custkey AS k, c_nationkey AS n, count(*) OVER (PARTITION BY c_nationkey) AS size FROM customer),
t AS (SELECT user_id AS k, round(avg(value), 6) AS v FROM events GROUP BY user_id),
m AS (SELECT n, median(v) AS m FROM f JOIN t USING (k) WHERE size > 1 GROUP BY n)
"""
_add("farm_anomaly", farm_anomaly, _FARM + "SELECT f.k AS c0, round(v - m, 4) AS c1 FROM f JOIN t USING (k) JOIN m USING (n) WHERE size > 1 AND v - m > 5")
_add("farm_anomaly_cycle", farm_anomaly_cycle, _FARM + "SELECT 'near' AS predicate, CAST(sum(CASE WHEN a.size > 1 THEN 1 ELSE 0 END) AS BIGINT) AS rows FROM f a JOIN f b ON a.n = b.n")
