"""Explicit facts of the experiments, read from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Kinds of nodes that share columns: key * 4 + tag.
TAGS = {"customer": 0, "supplier": 1, "nation": 2, "region": 3}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tagged(col: Column, kind: str) -> Column:
    return col.cast("bigint") * 4 + TAGS[kind]


def chain(spark: SparkSession, sf_dir: str, n: int) -> dict[str, DataFrame]:
    """Customers as a chain of n nodes with a reading each."""
    c = read(spark, sf_dir, "customer").where(F.col("c_custkey") < n)
    links = c.where(F.col("c_custkey") + 1 < n).select("c_custkey", (F.col("c_custkey") + 1).alias("next"))
    return {"hasNeighbour": links, "temp": c.select("c_custkey", "c_acctbal")}


def ranked_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, nation, rank, size): links from each customer to the next one of its nation, with
    the rank of ``a`` in it (from 1) and the number of its customers."""
    own = Window.partitionBy("c_nationkey")
    order = own.orderBy("c_custkey")
    ranked = read(spark, sf_dir, "customer").select(
        F.col("c_custkey").alias("a"), F.lead("c_custkey").over(order).alias("b"), F.col("c_nationkey").alias("nation"), F.row_number().over(order).alias("rank"), F.count("*").over(own).alias("size")
    )
    return ranked.where(F.col("b").isNotNull())


def nations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """A chain per nation over all customers with a reading each."""
    return {"hasNeighbour": ranked_links(spark, sf_dir).select("a", "b"), "temp": read(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")}


def _below(df: DataFrame, key: str, n: int | None) -> DataFrame:
    return df if n is None else df.where(F.col(key) < n)


def farms(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """A chain per nation; readings are the mean event values of the users of the same key."""
    readings = read(spark, sf_dir, "events").groupBy("user_id").agg(F.round(F.avg("value"), 6).alias("reading"))
    return {"hasNeighbour": ranked_links(spark, sf_dir).select("a", "b"), "temp": readings}


def trade(spark: SparkSession, sf_dir: str, n: int | None = None) -> dict[str, DataFrame]:
    """Five relations between customers, suppliers, nations and regions; all customers, or those of keys below n."""
    c = _below(read(spark, sf_dir, "customer"), "c_custkey", n).select("c_custkey", "c_nationkey")
    nation = read(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    order = Window.partitionBy("n_regionkey").orderBy("c_custkey")
    placed = c.join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.lead("c_custkey").over(order).alias("next"))
    orders = _below(read(spark, sf_dir, "orders"), "o_custkey", n).select("o_orderkey", "o_custkey")
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    bought = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    return {
        "p1": placed.where(F.col("next").isNotNull()).select(tagged(F.col("c_custkey"), "customer"), tagged(F.col("next"), "customer")),
        "p2": c.select(tagged(F.col("c_custkey"), "customer"), tagged(F.col("c_nationkey"), "nation")),
        "p3": nation.select(tagged(F.col("n_nationkey"), "nation"), tagged(F.col("n_regionkey"), "region")),
        "p4": bought.select(tagged(F.col("o_custkey"), "customer"), tagged(F.col("l_suppkey"), "supplier")).distinct(),
        "p5": read(spark, sf_dir, "supplier").select(tagged(F.col("s_suppkey"), "supplier"), tagged(F.col("s_nationkey"), "nation")),
    }
