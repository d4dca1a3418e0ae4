"""Facts from tables and files, rules from texts and tables, and sinks."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.syntax import Program, parse_program, parse_rules


@dataclass(frozen=True)
class FactSpec:
    """A predicate read from a table: columns (or expressions) and an optional filter, which
    both reach the scan."""

    pred: str
    table: str
    columns: tuple[str, ...]
    where: str | None = None


def from_tables(spark: SparkSession, folder: str, specs: list[FactSpec], fmt: str = "parquet") -> dict[str, DataFrame]:
    out: dict[str, DataFrame] = {}
    for s in specs:
        df = spark.read.format(fmt).load(f"{folder}/{s.table}.{fmt}")
        df = df.where(s.where) if s.where else df
        df = df.selectExpr(*s.columns)
        out[s.pred] = out[s.pred].union(df) if s.pred in out else df
    return out


def from_file(spark: SparkSession, path: str, fmt: str, schema: str, **options: str) -> DataFrame:
    """CSV, JSON, ORC or Parquet rows under a given schema."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def load_program(spark: SparkSession, path: str) -> Program:
    """Rules from text files that Spark can read."""
    lines = [r[0] for r in spark.read.option("wholetext", True).text(path).collect()]  # a program is small
    return parse_program("\n".join(lines))


def program_from_table(df: DataFrame) -> Program:
    """Rules from a table (rule_id, body_text)."""
    rules = {}
    for r in df.select("rule_id", "body_text").collect():  # one row per rule
        (rule,) = parse_rules(f"@{r[0]} {r[1]}.")
        rules[rule.id] = rule
    return Program(rules)


def write_relations(reasoner: object, path: str) -> None:
    """All visible facts, partitioned by predicate, as text columns beside the arity."""
    for pred in reasoner.state.bag().index:
        reasoner.relation(pred).write.mode("overwrite").parquet(f"{path}/pred={pred}")


def publish(reasoner: object, prefix: str = "") -> list[str]:
    """Tables in the catalogue, one per predicate."""
    names = []
    for pred in reasoner.state.bag().index:
        reasoner.relation(pred).write.mode("overwrite").saveAsTable(f"{prefix}{pred}")
        names.append(f"{prefix}{pred}")
    return names


def bucketed(df: DataFrame, table: str, by: str, buckets: int) -> DataFrame:
    """A relation stored clustered and sorted by a join column, so that joins on it need no
    shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(table)
    return df.sparkSession.table(table)


def null_terms(df: DataFrame) -> DataFrame:
    """How many rows a load would leave out for a null term."""
    any_null = F.lit(False)
    for c in df.columns:
        any_null = any_null | F.col(c).isNull()
    return df.agg(F.sum(any_null.cast("long")).alias("null_terms"))
