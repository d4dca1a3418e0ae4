"""Windows, duplicates, joins and last values over a stream of readings, as queries."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..engine import Reasoner
from ..sharing import shared_root
from ..workloads import datasets, experiments, rulesets
from ..workloads.datasets import read
from .updates import rule_lease, run_fact_updates, run_rule_updates

Query = Callable[[SparkSession, str], DataFrame]


def _scratch(spark: SparkSession) -> str:
    return f"{shared_root(spark)}/stream-{uuid.uuid4().hex[:12]}"


def stream_of(spark: SparkSession, sf_dir: str, name: str, per_batch: int = 1) -> DataFrame:
    """A table as a stream of its files."""
    schema = read(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(f"{sf_dir}/{name}.parque[t]")


def drained(df: DataFrame, mode: str) -> DataFrame:
    """Run a stream over all that is there, and return its result table."""
    spark, at = df.sparkSession, _scratch(df.sparkSession)
    last: list[int] = []

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/batch={batch_id}")
        last.append(batch_id)

    df.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{at}/out/batch={max(last)}") if last else spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(f"{at}/out/*") if last else spark.createDataFrame([], df.schema)


def events(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    return stream_of(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def _windows(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = events(spark, sf_dir)
        w = F.window("ts", "1 hour") if kind == "tumbling" else F.window("ts", "2 hours", "1 hour")
        out = drained(e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")), "complete")
        return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")

    return run


def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = events(spark, sf_dir)
    out = drained(e.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")), "complete")
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(stream_of(spark, sf_dir, "events").select("user_id", "event_type").dropDuplicates(), "append")


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-static join: events of customers of one segment."""
    c = read(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    return drained(stream_of(spark, sf_dir, "events").join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "append")


def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors with the clicks of the same user within the hour before."""
    a = events(spark, sf_dir).where("event_type = 'error'").select("event_id", "user_id", F.col("ts").alias("at"))
    b = events(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("before"), F.col("user_id").alias("who"), "ts")
    return drained(a.join(b, F.expr("user_id = who AND ts BETWEEN at - INTERVAL 1 HOUR AND at")).select("event_id", "before"), "append")


def stream_last_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Last reading of each user, kept as state across batches."""

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: object) -> Iterator[pd.DataFrame]:
        ts, event, value = state.get if state.exists else (-1, -1, 0.0)
        for p in parts:
            p = p.sort_values(["us", "event_id"])
            row = p.iloc[-1]
            if (int(row["us"]), int(row["event_id"])) > (ts, event):
                ts, event, value = int(row["us"]), int(row["event_id"]), float(row["value"])
        state.update((ts, event, value))
        yield pd.DataFrame({"user_id": [key[0]], "event_id": [event], "us": [ts], "value": [value]})

    e = stream_of(spark, sf_dir, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"), "value")
    out = e.groupBy("user_id").applyInPandasWithState(step, "user_id long, event_id long, us long, value double", "ts long, event long, value double", "update", "NoTimeout")
    # one row per user and batch: the latest is the state's last word
    return drained(out, "update").groupBy("user_id").agg(F.max(F.struct("us", "event_id")).alias("m")).select("user_id", "m.event_id")


def stream_incremental_near(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers arrive as a stream and stand near their nation's mark; the closure follows
    batch by batch."""
    r = Reasoner(spark, rulesets.NEAR, schemas={"hasNeighbour": ["bigint", "bigint"]})
    r.materialise()
    pairs = stream_of(spark, sf_dir, "customer").select(F.lit("+").alias("op"), F.lit("hasNeighbour").alias("pred"), F.col("c_custkey").alias("a"), (-1 - F.col("c_nationkey")).cast("bigint").alias("b"))
    run_fact_updates(r, pairs, f"{_scratch(spark)}/state", {"hasNeighbour": ["a", "b"]}).awaitTermination()
    return r.relation("near")


def stream_rule_lease(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events raise an alarm that loads the judging rules, and the suspects found while they are
    loaded; a later event drops the rules again."""
    r = Reasoner(spark, rulesets.NEAR, datasets.farms(spark, sf_dir))
    r.materialise()
    found: list[DataFrame] = []
    judge = rulesets.JUDGE.replace("5000", "5")
    rule_lease(r, stream_of(spark, sf_dir, "events"), f"{_scratch(spark)}/state", "event_type = 'error'", "event_type = 'signup'", judge, ["r4", "r5", "r6"], lambda x: found.append(x.relation("suspect"))).awaitTermination()
    assert not {"r4", "r5", "r6"} & set(r.state.program.rules)
    return found[0].select("c0", F.round("c1", 4).alias("c1"))


def stream_rule_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules arrive as a stream, one of them against the negation constraint; nations' neighbours
    by the rules that were taken in."""
    at = f"{_scratch(spark)}/rules"
    rows = [(1, "+", "@s near(y, x) <- near(x, y)."), (2, "+", "@bad near(x, y) <- hasNeighbour(x, y), !near(y, x)."), (3, "+", "@t near(x, z) <- near(x, y), near(y, z)."), (4, "-", "@none")]
    spark.createDataFrame(rows, "seq long, op string, text string").write.parquet(at)
    r = Reasoner(spark, "near(x, y) <- hasNeighbour(x, y).", datasets.nations(spark, sf_dir))
    r.materialise()
    rejected: list[str] = []
    run_rule_updates(r, spark.readStream.schema("seq long, op string, text string").parquet(at), f"{at}-state", lambda text, why: rejected.append(text)).awaitTermination()
    assert len(rejected) == 2
    return r.relation("near")


QUERIES: dict[str, Query] = {"stream_tumbling": _windows("tumbling"), "stream_sliding": _windows("sliding"), "stream_session": stream_session, "stream_dedup": stream_dedup, "stream_join": stream_join, "stream_stream_join": stream_stream_join, "stream_last_value": stream_last_value, "stream_incremental_near": stream_incremental_near, "stream_rule_lease": stream_rule_lease, "stream_rule_updates": stream_rule_updates}
ORACLES: dict[str, str] = {
    "stream_tumbling": "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT time_bucket(INTERVAL 1 HOUR, ts) - k * INTERVAL 1 HOUR AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY 1, 2",
    "stream_session": """WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events),
        s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM a) SELECT min(ts) AS start, user_id, count(*) AS n FROM s GROUP BY user_id, g""",
    "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "stream_join": "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "stream_stream_join": "SELECT a.event_id, b.event_id AS before FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'click' AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts",
    "stream_last_value": "SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id FROM events GROUP BY 1",
    "stream_incremental_near": "WITH x AS (SELECT c_custkey AS k, c_nationkey AS n FROM customer UNION ALL SELECT DISTINCT -1 - c_nationkey, c_nationkey FROM customer) SELECT a.k AS c0, b.k AS c1 FROM x a JOIN x b ON a.n = b.n",
    "stream_rule_updates": "SELECT a.c_custkey AS c0, b.c_custkey AS c1 FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey WHERE (SELECT count(*) FROM customer x WHERE x.c_nationkey = a.c_nationkey) > 1",
    "stream_rule_lease": experiments.ORACLES["farm_anomaly"],
}
