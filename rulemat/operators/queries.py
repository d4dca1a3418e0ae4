"""One query per operator, over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..engine import Reasoner
from ..graphops import ancestors, bfs_levels, closure, components, degree
from ..workloads.datasets import read
from . import joins

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _op(name: str, sql: str | None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _frame(name: str, sql: str | None, build: Callable[[Callable[[str], DataFrame]], DataFrame]) -> None:
    _op(name, sql)(lambda spark, sf_dir: build(lambda t: read(spark, sf_dir, t)))


c = F.col
# projections and filters
_frame("op_project", "SELECT c_custkey AS id, c_name AS name FROM customer", lambda t: t("customer").select(c("c_custkey").alias("id"), c("c_name").alias("name")))
_frame("op_head_const", "SELECT c_custkey AS id, 'customer' AS kind FROM customer", lambda t: t("customer").select(c("c_custkey").alias("id"), F.lit("customer").alias("kind")))
_frame("op_filter_cmp", "SELECT o_orderkey FROM orders WHERE o_totalprice > 300000", lambda t: t("orders").where(c("o_totalprice") > 300000).select("o_orderkey"))
_frame("op_filter_in", "SELECT o_orderkey FROM orders WHERE o_orderstatus IN ('F', 'P') AND o_custkey BETWEEN 10 AND 50", lambda t: t("orders").where(c("o_orderstatus").isin("F", "P") & c("o_custkey").between(10, 50)).select("o_orderkey"))
_frame("op_filter_like", "SELECT p_partkey FROM part WHERE p_type LIKE '%A%' AND regexp_matches(p_brand, '[12]$')", lambda t: t("part").where(c("p_type").like("%A%") & c("p_brand").rlike("[12]$")).select("p_partkey"))
_frame("op_case", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal > 5000 AND NOT c_nationkey = 3 THEN 'rich' ELSE 'usual' END AS class FROM customer", lambda t: t("customer").select("c_custkey", F.when(c("c_acctbal") < 0, "debt").when((c("c_acctbal") > 5000) & ~(c("c_nationkey") == 3), "rich").otherwise("usual").alias("class")))
_frame("op_distinct", "SELECT DISTINCT o_custkey, o_orderstatus FROM orders", lambda t: t("orders").select("o_custkey", "o_orderstatus").dropDuplicates())
_frame("op_repeat_var", "SELECT s_suppkey FROM supplier WHERE s_suppkey = s_nationkey", lambda t: t("supplier").where(c("s_suppkey") == c("s_nationkey")).select("s_suppkey"))
# joins
_frame("op_join_chain", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey", lambda t: t("customer").join(t("nation"), c("c_nationkey") == c("n_nationkey")).join(t("region"), c("n_regionkey") == c("r_regionkey")).select("c_custkey", "n_name", "r_name"))
_frame("op_join_broadcast", "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey", lambda t: t("supplier").join(joins.bounded_broadcast(t("nation"), 10_000), c("s_nationkey") == c("n_nationkey")).select("s_suppkey", "n_name"))
_frame("op_join_smj", "SELECT o_orderkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey", lambda t: t("orders").join(t("lineitem").hint("merge"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n")))
_frame("op_join_salted", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name", lambda t: joins.salted(t("customer").withColumnRenamed("c_nationkey", "k"), t("nation").withColumnRenamed("n_nationkey", "k"), "k", 4).groupBy("n_name").agg(F.count("*").alias("n")))
_frame("op_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)", lambda t: t("customer").join(t("orders").where(c("o_totalprice") > 400000), c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"))
_frame("op_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal", lambda t: t("supplier").alias("a").join(t("supplier").alias("b"), (c("a.s_nationkey") == c("b.s_nationkey")) & (c("a.s_acctbal") < c("b.s_acctbal"))).select(c("a.s_suppkey").alias("a"), c("b.s_suppkey").alias("b")))
_frame("op_range_join", "SELECT p_partkey, s_suppkey FROM part JOIN supplier ON p_retailprice BETWEEN s_acctbal AND s_acctbal + 50", lambda t: joins.binned(t("part"), t("supplier").withColumn("hi", c("s_acctbal") + 50), "p_retailprice", "s_acctbal", "hi", 50.0).select("p_partkey", "s_suppkey"))
_frame("op_cross", "SELECT r_regionkey, n_nationkey FROM region, nation", lambda t: t("region").crossJoin(t("nation")).select("r_regionkey", "n_nationkey"))
_frame("op_full_outer", "SELECT coalesce(c_nationkey, s_nationkey) AS k, coalesce(a, 0) AS customers, coalesce(b, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS a FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS b FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey",
       lambda t: t("customer").groupBy(c("c_nationkey").alias("k")).agg(F.count("*").alias("a")).join(t("supplier").groupBy(c("s_nationkey").alias("k")).agg(F.count("*").alias("b")), "k", "full").select("k", F.coalesce("a", F.lit(0)).alias("customers"), F.coalesce("b", F.lit(0)).alias("suppliers")))
_frame("op_asof", "SELECT a.event_id, (SELECT max(b.ts) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND b.ts <= a.ts) AS seen FROM events a WHERE a.event_type = 'purchase'",
       lambda t: joins.as_of(t("events").where("event_type = 'purchase'").select("event_id", "user_id", "ts"), t("events").where("event_type = 'view'").select("user_id", c("ts").alias("seen")), "user_id", "ts", "seen", ["seen"]).select("event_id", "seen"))
_frame("op_interval_join", "SELECT a.event_id, b.event_id AS before FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'click' AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts",
       lambda t: t("events").where("event_type = 'error'").alias("a").join(t("events").where("event_type = 'click'").alias("b"), (c("a.user_id") == c("b.user_id")) & (c("b.ts") <= c("a.ts")) & (c("b.ts") >= c("a.ts") - F.expr("INTERVAL 1 HOUR"))).select("a.event_id", c("b.event_id").alias("before")))
# aggregation
_frame("agg_global", "SELECT count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem", lambda t: t("lineitem").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q")))
_frame("agg_count_distinct", "SELECT o_custkey AS k, count(DISTINCT o_orderstatus) AS n FROM orders GROUP BY 1", lambda t: t("orders").groupBy(c("o_custkey").alias("k")).agg(F.countDistinct("o_orderstatus").alias("n")))
_frame("agg_median_approx", None, lambda t: t("customer").groupBy(c("c_nationkey").alias("k")).agg(F.percentile_approx("c_acctbal", 0.5).alias("v")))
_frame("agg_approx_distinct", None, lambda t: t("orders").agg(F.approx_count_distinct("o_custkey").alias("n"), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey")).alias("hll")))
_frame("agg_rollup", "SELECT c_nationkey AS a, c_mktsegment AS b, count(*) AS n FROM customer GROUP BY ROLLUP (c_nationkey, c_mktsegment)", lambda t: t("customer").rollup(c("c_nationkey").alias("a"), c("c_mktsegment").alias("b")).agg(F.count("*").alias("n")))
_frame("agg_cube", "SELECT c_nationkey AS a, c_mktsegment AS b, count(*) AS n FROM customer GROUP BY CUBE (c_nationkey, c_mktsegment)", lambda t: t("customer").cube(c("c_nationkey").alias("a"), c("c_mktsegment").alias("b")).agg(F.count("*").alias("n")))
_frame("agg_grouping_sets", "SELECT o_orderstatus AS a, o_orderpriority AS b, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))", lambda t: t("orders").groupingSets([[c("o_orderstatus")], [c("o_orderpriority")]], c("o_orderstatus"), c("o_orderpriority")).agg(F.count("*").alias("n")).select(c("o_orderstatus").alias("a"), c("o_orderpriority").alias("b"), "n"))
_frame("agg_having", "SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 15", lambda t: t("orders").groupBy(c("o_custkey").alias("k")).agg(F.count("*").alias("n")).where("n > 15"))
_frame("agg_collect", "SELECT n_regionkey AS k, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1", lambda t: t("nation").groupBy(c("n_regionkey").alias("k")).agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names")))
_frame("agg_stats", "SELECT c_nationkey AS k, round(stddev_samp(c_acctbal), 3) AS sd, round(var_pop(c_acctbal), 1) AS vp FROM customer GROUP BY 1", lambda t: t("customer").groupBy(c("c_nationkey").alias("k")).agg(F.round(F.stddev_samp("c_acctbal"), 3).alias("sd"), F.round(F.var_pop("c_acctbal"), 1).alias("vp")))
# windows, order, sets
_frame("win_lead_chain", "SELECT c_custkey AS a, lead(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS b FROM customer", lambda t: t("customer").select(c("c_custkey").alias("a"), F.lead("c_custkey").over(Window.partitionBy("c_nationkey").orderBy("c_custkey")).alias("b")))
_frame("win_rank", "SELECT c_custkey AS k, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)",
       lambda t: (lambda w: t("customer").select(c("c_custkey").alias("k"), F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt")))(Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")))
_frame("win_rows", "SELECT o_orderkey AS k, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS s FROM orders", lambda t: t("orders").select(c("o_orderkey").alias("k"), F.round(F.sum("o_totalprice").over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-2, 0)), 2).alias("s")))
_frame("win_range", "SELECT o_orderkey AS k, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n FROM orders", lambda t: t("orders").select(c("o_orderkey").alias("k"), F.count("*").over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rangeBetween(-1000, 0)).alias("n")))
_frame("win_farm_deviation", "SELECT c_custkey AS k, round(c_acctbal - median(c_acctbal) OVER (PARTITION BY c_nationkey), 4) AS d FROM customer", lambda t: t("customer").select(c("c_custkey").alias("k"), F.round(c("c_acctbal") - F.median("c_acctbal").over(Window.partitionBy("c_nationkey")), 4).alias("d")))
_frame("op_topk", "SELECT o_orderkey AS k FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", lambda t: t("orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select(c("o_orderkey").alias("k")))
_frame("op_topk_group", "SELECT k, g FROM (SELECT c_custkey AS k, c_nationkey AS g, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3", lambda t: t("customer").select(c("c_custkey").alias("k"), c("c_nationkey").alias("g"), F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")).alias("r")).where("r <= 3").drop("r"))
_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier WHERE s_nationkey > 5"
_ab = lambda t: (t("customer").select(c("c_nationkey").alias("k")), t("supplier").where("s_nationkey > 5").select(c("s_nationkey").alias("k")))
_frame("set_union_all", f"{_A} UNION ALL {_B}", lambda t: (lambda x: x[0].unionByName(x[1]))(_ab(t)))
_frame("set_except_all", f"{_A} EXCEPT ALL {_B}", lambda t: (lambda x: x[0].exceptAll(x[1]))(_ab(t)))
_frame("op_sample", None, lambda t: t("customer").sample(0.1, seed=7).select("c_custkey"))
_frame("triples_pivot", "SELECT o_custkey AS k, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O FROM orders GROUP BY 1", lambda t: t("orders").groupBy(c("o_custkey").alias("k")).pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0))
# scalar functions
_frame("fn_math", "SELECT p_partkey AS k, abs(p_size - 25) AS a, round(sqrt(p_retailprice), 6) AS b, floor(p_retailprice) AS f, ceil(p_retailprice) AS g, greatest(p_size, 10) AS h, round(ln(p_retailprice), 6) AS i, p_partkey % 7 AS j FROM part",
       lambda t: t("part").select(c("p_partkey").alias("k"), F.abs(c("p_size") - 25).alias("a"), F.round(F.sqrt("p_retailprice"), 6).alias("b"), F.floor("p_retailprice").alias("f"), F.ceil("p_retailprice").alias("g"), F.greatest("p_size", F.lit(10)).alias("h"), F.round(F.log("p_retailprice"), 6).alias("i"), (c("p_partkey") % 7).alias("j")))
_frame("fn_string", "SELECT c_custkey AS k, upper(c_name) AS a, substr(c_name, 1, 4) AS b, length(c_name) AS l, replace(c_name, '#', '-') AS r, concat(c_mktsegment, '/', c_name) AS d, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS p FROM customer",
       lambda t: t("customer").select(c("c_custkey").alias("k"), F.upper("c_name").alias("a"), F.substring("c_name", 1, 4).alias("b"), F.length("c_name").alias("l"), F.replace("c_name", F.lit("#"), F.lit("-")).alias("r"), F.concat("c_mktsegment", F.lit("/"), "c_name").alias("d"), F.lpad(c("c_custkey").cast("string"), 8, "0").alias("p")))
_frame("fn_date", "SELECT o_orderkey AS k, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d FROM orders", lambda t: t("orders").select(c("o_orderkey").alias("k"), F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("d")))
_frame("fn_cast", "SELECT c_custkey AS k, CAST(c_custkey AS VARCHAR) AS s, CAST(c_nationkey AS DOUBLE) AS d FROM customer", lambda t: t("customer").select(c("c_custkey").alias("k"), c("c_custkey").cast("string").alias("s"), c("c_nationkey").cast("double").alias("d")))
_frame("fn_cond", "SELECT c_custkey AS k, nullif(c_nationkey, 3) AS a, coalesce(nullif(c_nationkey, 3), -1) AS b FROM customer", lambda t: t("customer").select(c("c_custkey").alias("k"), F.nullif("c_nationkey", F.lit(3)).alias("a"), F.coalesce(F.nullif("c_nationkey", F.lit(3)), F.lit(-1)).alias("b")))
_frame("fn_array", "SELECT vec_id AS k, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 3) AS s FROM embeddings", lambda t: t("embeddings").select(c("vec_id").alias("k"), F.size("embedding").cast("long").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 3).alias("s")))
_frame("fn_explode", "SELECT conv_id AS k, turn, unnest(string_split(role, 's')) AS piece FROM conversations", lambda t: t("conversations").select(c("conv_id").alias("k"), "turn", F.explode(F.split("role", "s")).alias("piece")))
_frame("fn_json", "SELECT event_id AS k, json_extract_string(props, '$.k') AS v FROM events", lambda t: t("events").select(c("event_id").alias("k"), F.get_json_object("props", "$.k").alias("v")))
_frame("fn_map", "SELECT p_partkey AS k, p_brand AS brand, p_size * 2 AS twice, 2 AS n FROM part",
       lambda t: t("part").select(c("p_partkey").alias("k"), F.create_map(F.lit("brand"), "p_brand", F.lit("size"), c("p_size").cast("string")).alias("m")).select("k", F.element_at("m", "brand").alias("brand"), F.element_at(F.transform_values("m", lambda k, v: F.concat(v, F.lit(""))), "size").cast("int").alias("s"), F.size(F.map_keys("m")).alias("n")).select("k", "brand", (c("s") * 2).alias("twice"), "n"))
_frame("fn_hash", None, lambda t: t("customer").select(c("c_custkey").alias("k"), F.xxhash64("c_name").alias("h")))
_frame("fn_url", None, lambda t: t("pages").select(c("page_id").alias("k"), F.try_parse_url("url", F.lit("HOST")).alias("host")))


def _rule(name: str, sql: str, program: str, facts: Callable[[Callable[[str], DataFrame]], dict[str, DataFrame]], shape: Callable[[DataFrame], DataFrame] = lambda df: df) -> None:
    """An operator as rules: the result is the predicate ``out``."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = Reasoner(spark, program, facts(lambda t: read(spark, sf_dir, t)))
        r.materialise()
        return shape(r.relation("out"))

    _op(name, sql)(run)


_key = lambda t: {"c": t("customer").select("c_custkey", c("c_nationkey").cast("long"))}
_rule("op_comp_vars", "SELECT c_custkey AS c0 FROM customer WHERE c_custkey < c_nationkey * 10", "out(x) <- c(x, n), m := n * 10, x < m.", _key)
_rule("op_bind_arith", "SELECT l_orderkey AS c0, CAST(l_linenumber AS BIGINT) AS c1, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 6) AS c2 FROM lineitem", "out(o, l, v) <- line(o, l, p, d, t), v := p * (1 - d) * (1 + t).",
      lambda t: {"line": t("lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice", "l_discount", "l_tax")}, lambda df: df.select("c0", "c1", F.round("c2", 6).alias("c2")))
_rule("op_anti", "SELECT c_custkey AS c0 FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 250000)", "out(x) <- c(x, n), !ordered(x).",
      lambda t: _key(t) | {"ordered": t("orders").where("o_totalprice > 250000").select("o_custkey")})
for _f, _s in (("max", "max"), ("min", "min"), ("avg", "avg"), ("count", "count"), ("sum", "sum"), ("median", "median")):
    _rule(f"agg_{_f}", f"SELECT CAST(c_nationkey AS BIGINT) AS c0, round({_s}(c_acctbal), 4) AS c1 FROM customer GROUP BY 1", f"out(n, {_f}(v)) <- c(x, n, v) group n.",
          lambda t: {"c": t("customer").select("c_custkey", c("c_nationkey").cast("long"), "c_acctbal")}, lambda df: df.select("c0", F.round("c1", 4).alias("c1")))
_sets = lambda t: {"a": t("customer").select(c("c_nationkey").cast("long")), "b": t("supplier").where("s_nationkey > 5").select(c("s_nationkey").cast("long"))}
_a0, _b0 = "SELECT CAST(c_nationkey AS BIGINT) AS c0 FROM customer", "SELECT CAST(s_nationkey AS BIGINT) AS c0 FROM supplier WHERE s_nationkey > 5"
for _n, _sql, _text in (("union", f"{_a0} UNION {_b0}", "out(x) <- a(x). out(x) <- b(x)."), ("intersect", f"{_a0} INTERSECT {_b0}", "out(x) <- a(x), b(x)."), ("except", f"{_a0} EXCEPT {_b0}", "out(x) <- a(x), !b(x)."), ("symdiff", f"({_a0} EXCEPT {_b0}) UNION ({_b0} EXCEPT {_a0})", "out(x) <- a(x), !b(x). out(x) <- b(x), !a(x).")):
    _rule(f"set_{_n}", _sql, _text, _sets)


@_op("agg_over_recursion", "SELECT c_custkey AS c0, count(*) OVER (PARTITION BY c_nationkey) AS c1 FROM customer QUALIFY c1 > 1")
def _agg_over_recursion(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..workloads import datasets, rulesets

    r = Reasoner(spark, rulesets.NEAR + "@a n(x, count(y)) <- near(x, y) group x.", datasets.nations(spark, sf_dir))
    r.materialise()
    return r.relation("n")


@_op("udf_bind", "SELECT c_custkey AS c0, c_custkey * c_custkey AS c1 FROM customer WHERE c_custkey * c_custkey > 100")
def _udf_bind(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.registry import register

    register("squared", lambda x: x * x, "bigint")
    r = Reasoner(spark, "s(x, y) <- c(x), y := squared(x), y > 100.", {"c": read(spark, sf_dir, "customer").select("c_custkey")})
    r.materialise()
    return r.relation("s")


@_op("udaf_mad", None)
def _udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    import pandas as pd

    def mad(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [int(pdf["c_nationkey"].iloc[0])], "mad": [float((pdf["c_acctbal"] - pdf["c_acctbal"].median()).abs().median())]})

    return read(spark, sf_dir, "customer").select("c_nationkey", "c_acctbal").groupBy("c_nationkey").applyInPandas(mad, "k int, mad double")


@_op("udtf_tokens", "SELECT item_id, CAST(len(string_split(text, ' ')) AS BIGINT) AS n FROM benchmark")
def _udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    @F.udtf(returnType="word: string")
    class Words:
        def eval(self, text: str):  # noqa: ANN202
            for w in (text or "").split(" "):
                yield (w,)

    spark.udtf.register("rulemat_words", Words)
    read(spark, sf_dir, "benchmark").createOrReplaceTempView("rulemat_bench")
    return spark.sql("SELECT item_id, count(*) AS n FROM rulemat_bench, LATERAL rulemat_words(text) GROUP BY item_id")


def _cut(spark: SparkSession) -> Callable[[DataFrame, str], DataFrame]:
    from ..engine.store import Storage

    storage = Storage(spark)
    return lambda df, name: storage.write(df).frame


def _same_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_custkey")
    return read(spark, sf_dir, "customer").select(c("c_custkey").alias("a"), F.lead("c_custkey").over(w).alias("b")).where("b IS NOT NULL")


@_op("graph_components", "SELECT c_custkey AS node, min(c_custkey) OVER (PARTITION BY c_nationkey) AS component FROM customer QUALIFY count(*) OVER (PARTITION BY c_nationkey) > 1")
def _components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(_same_nation(spark, sf_dir), _cut(spark))


@_op("graph_bfs", "SELECT c_custkey AS node, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS level FROM customer QUALIFY level <= 6")
def _bfs(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _same_nation(spark, sf_dir)
    first = read(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.min("c_custkey").alias("node")).select("node")
    return bfs_levels(e, first, 6, _cut(spark)).withColumn("level", c("level").cast("long"))


@_op("graph_degree", "SELECT c_custkey AS node, CAST(least(count(*) OVER (PARTITION BY c_nationkey), 3) - 1 AS BIGINT) - CASE WHEN count(*) OVER (PARTITION BY c_nationkey) > 2 AND (row_number() OVER w = 1 OR lead(c_custkey) OVER w IS NULL) THEN 1 ELSE 0 END AS degree FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey) QUALIFY count(*) OVER (PARTITION BY c_nationkey) > 1")
def _degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return degree(_same_nation(spark, sf_dir))


@_op("graph_closure", "SELECT a.c_custkey AS a, b.c_custkey AS b FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey")
def _closure(spark: SparkSession, sf_dir: str) -> DataFrame:
    return closure(_same_nation(spark, sf_dir), _cut(spark))


@_op("graph_ancestors", "SELECT b.c_custkey AS node, a.c_custkey AS ancestor FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey WHERE b.c_nationkey = 3")
def _ancestors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ancestors(_same_nation(spark, sf_dir), read(spark, sf_dir, "customer").where("c_nationkey = 3").select(c("c_custkey").alias("node")), _cut(spark))


@_op("graph_unreachable", "SELECT c_custkey AS c0 FROM customer WHERE c_nationkey <> (SELECT c_nationkey FROM customer WHERE c_custkey = 0)")
def _unreachable(spark: SparkSession, sf_dir: str) -> DataFrame:
    nodes = read(spark, sf_dir, "customer").select("c_custkey")
    r = Reasoner(spark, "reach(x) <- start(x). reach(y) <- reach(x), e(x, y). far(x) <- node(x), !reach(x). start(0).", {"e": _same_nation(spark, sf_dir), "node": nodes})
    r.materialise()
    return r.relation("far")


@_op("op_label_expand", "SELECT a.c_custkey AS c0, b.c_custkey AS c1 FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey WHERE (SELECT count(*) FROM customer x WHERE x.c_nationkey = a.c_nationkey) > 1")
def _label_expand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels at rest, pairs on demand: n rows written for n**2 facts."""
    r = Reasoner(spark, "near(x, y) <- next(x, y). near(y, x) <- near(x, y). near(x, z) <- near(x, y), near(y, z).", {"next": _same_nation(spark, sf_dir)})
    r.materialise()
    return r.relation("near", whole=True)


@_op("graph_same_generation", "SELECT a.n_nationkey AS c0, b.n_nationkey AS c1 FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey")
def _same_generation(spark: SparkSession, sf_dir: str) -> DataFrame:
    up = read(spark, sf_dir, "nation").select((c("n_nationkey") + 1000).cast("long"), c("n_regionkey").cast("long"))
    r = Reasoner(spark, "sg(x, y) <- up(x, p), up(y, p). sg(x, y) <- up(x, p), sg(p, q), up(y, q).", {"up": up})
    r.materialise()
    return r.relation("sg").select((c("c0") - 1000).cast("int").alias("c0"), (c("c1") - 1000).cast("int").alias("c1"))


@_op("rdf_subclass", "SELECT c_custkey AS c0 FROM customer")
def _rdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources.triples import rl_rules

    r = Reasoner(spark, rl_rules(subclass=[("customer", "party"), ("party", "agent")]), {"customer": read(spark, sf_dir, "customer").select("c_custkey")})
    r.materialise()
    return r.relation("agent")


@_op("triples_roundtrip", "SELECT c_custkey AS c0, CAST(c_nationkey AS BIGINT) AS c1 FROM customer")
def _triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources.triples import from_triples, to_triples

    facts = {"livesIn": read(spark, sf_dir, "customer").select(c("c_custkey").alias("c0"), c("c_nationkey").alias("c1"))}
    back = from_triples(to_triples(facts), ["livesIn"])["livesIn"]
    return back.select(c("c0").cast("long").alias("c0"), c("c1").cast("long").alias("c1"))


