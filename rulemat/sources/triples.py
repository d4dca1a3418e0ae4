"""Triples (s, p, o), N-Triples lines, and ontology templates as rules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lang.syntax import Program, parse_program

TYPE = "type"
_LINE = r"^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|\"(?:[^\"\\]|\\.)*\"(?:\^\^<[^>]*>|@[A-Za-z-]+)?)\s*\.\s*$"


def to_triples(facts: dict[str, DataFrame]) -> DataFrame:
    """Unary facts become type triples, binary facts one triple each."""
    out = None
    for p, df in sorted(facts.items()):
        if len(df.columns) > 2:
            continue
        a = df.columns[0]
        t = df.select(F.col(a).cast("string").alias("s"), F.lit(TYPE if len(df.columns) == 1 else p).alias("p"), (F.lit(p) if len(df.columns) == 1 else F.col(df.columns[1]).cast("string")).alias("o"))
        out = t if out is None else out.unionByName(t)
    return out


def from_triples(triples: DataFrame, preds: list[str], types: list[str] = ()) -> dict[str, DataFrame]:
    """The relations of some predicates and classes."""
    out = {p: triples.where(F.col("p") == p).select(F.col("s").alias("c0"), F.col("o").alias("c1")) for p in preds}
    return out | {t: triples.where((F.col("p") == TYPE) & (F.col("o") == t)).select(F.col("s").alias("c0")) for t in types}


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Well-formed lines only; comments and malformed lines are left out."""
    lines = spark.read.text(path)
    return lines.where(F.col("value").rlike(_LINE)).select(*[F.regexp_extract("value", _LINE, k).alias(n) for k, n in ((1, "s"), (2, "p"), (3, "o"))])


def write_ntriples(triples: DataFrame, path: str) -> None:
    iri = lambda c: F.when(F.col(c).rlike(r"^(<|_:|\")"), F.col(c)).otherwise(F.concat(F.lit("<"), F.col(c), F.lit(">")))
    triples.select(F.concat_ws(" ", iri("s"), iri("p"), iri("o"), F.lit(".")).alias("value")).write.mode("overwrite").text(path)


def rl_rules(subclass: list[tuple[str, str]] = (), subproperty: list[tuple[str, str]] = (), domain: list[tuple[str, str]] = (), range_: list[tuple[str, str]] = (), inverse: list[tuple[str, str]] = (), symmetric: list[str] = (), transitive: list[str] = ()) -> Program:
    """Rules for ontology axioms."""
    lines = [f"{b}(x) <- {a}(x)." for a, b in subclass] + [f"{b}(x, y) <- {a}(x, y)." for a, b in subproperty]
    lines += [f"{k}(x) <- {p}(x, _)." for p, k in domain] + [f"{k}(y) <- {p}(_, y)." for p, k in range_]
    lines += [f"{b}(y, x) <- {a}(x, y). {a}(y, x) <- {b}(x, y)." for a, b in inverse]
    lines += [f"{p}(y, x) <- {p}(x, y)." for p in symmetric] + [f"{p}(x, z) <- {p}(x, y), {p}(y, z)." for p in transitive]
    return parse_program("\n".join(lines))
