"""Mixing sources to target weights by temperature.

Shares of white-space separated tokens per source are raised to an exponent and normalised.
The exponent is found by bisection: either for a target entropy of the weights, or for a
repetition limit (the most repeated source is read ``max_epochs`` times while the least
repeated one is read once).  Weights become token budgets, and budgets are realised as
permuted blocks: each source's documents fall into blocks by a digest of doc_id; an epoch
visits the blocks of a source in the order of a digest of source, epoch and block; whole
epochs come first, the rest of a budget is the start of one more permutation, cut inside
its last block at the document that fills the budget.

Only totals per source (one row per source name) come to the driver; orders run over at
most ``16**BLOCK_DIGITS`` blocks of a source and over the documents of single blocks.

Defined cases: a null source is the source named by the empty string; a source without
tokens is read once; rows that repeat a doc_id and order key are decided alike; an empty
table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh_name

#: Blocks of a source: 16**3.
BLOCK_DIGITS = 3
MAX_EPOCHS = 1.5
SEED = "mix"


def tempered(tokens: dict[str, int], alpha: float) -> dict[str, float]:
    """Normalised weights of the shares raised to ``alpha``."""
    total = sum(tokens.values())
    raised = {s: math.exp(alpha * math.log(n / total)) for s, n in tokens.items() if n}
    norm = math.fsum(raised.values())
    return {s: x / norm for s, x in raised.items()}


def entropy(weights: dict[str, float]) -> float:
    return -math.fsum(w * math.log(w) for w in weights.values() if w > 0)


def epochs(tokens: dict[str, int], weights: dict[str, float]) -> dict[str, float]:
    """Passes over each source when the least repeated one is read once."""
    rate = {s: w / tokens[s] for s, w in weights.items()}
    least = min(rate.values(), default=1.0)
    return {s: r / least for s, r in rate.items()}


def find_alpha(tokens: dict[str, int], max_epochs: float | None = None, target_entropy: float | None = None, steps: int = 200) -> float:
    """Bisect the exponent in [0, 1]: flat weights at 0, natural shares at 1.  Repetition and
    entropy both fall as it grows; the smallest exponent within the limits is taken."""
    if len([n for n in tokens.values() if n]) < 2:
        return 1.0

    def fits(alpha: float) -> bool:
        w = tempered(tokens, alpha)
        if target_entropy is not None:
            return entropy(w) <= target_entropy
        return max(epochs(tokens, w).values()) <= max_epochs

    low, high = 0.0, 1.0
    if fits(low):
        return low
    for _ in range(steps):
        mid = (low + high) / 2
        if mid in (low, high):
            break
        low, high = (low, mid) if fits(mid) else (mid, high)
    return high


def block_of(doc_id: Column) -> Column:
    return F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), 1, BLOCK_DIGITS)


def token_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _digest(*parts: Column | str) -> Column:
    return F.md5(F.concat_ws("|", *(F.lit(p) if isinstance(p, str) else p for p in parts)).cast("binary"))


_USED = ("doc_id", "text", "source")
_REST = "mix_rest"


def _slim(docs: DataFrame) -> DataFrame:
    """The columns that mixing reads, and all others in one, so that no name can clash."""
    rest = [c for c in docs.columns if c not in _USED]
    return docs.select(*_USED, F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(rest)], F.lit(0).alias("none")).alias(_REST))


def _back(docs: DataFrame) -> list[Column]:
    rest = [c for c in docs.columns if c not in _USED]
    return [F.col(c) if c in _USED else F.col(f"{_REST}.c{rest.index(c)}").alias(c) for c in docs.columns]


def mix(docs: DataFrame, max_epochs: float = MAX_EPOCHS, target_entropy: float | None = None) -> DataFrame:
    """All columns of ``docs`` and mix_tokens, mix_weight, mix_copies (how often the mixture
    reads the document), mix_block; these get underscores after them where ``docs`` has them."""
    made = [F.col(c).alias(fresh_name(docs, c)) for c in ("mix_tokens", "mix_weight", "mix_copies", "mix_block")]
    return _mix(_slim(docs), max_epochs, target_entropy).select(*_back(docs), *made)


def _mix(docs: DataFrame, max_epochs: float = MAX_EPOCHS, target_entropy: float | None = None) -> DataFrame:
    spark = docs.sparkSession
    base = docs.withColumns({"mix_source": F.coalesce(F.col("source"), F.lit("")), "mix_block": block_of(F.col("doc_id")), "mix_tokens": token_count(F.col("text"))})
    blocks = base.groupBy("mix_source", "mix_block").agg(F.sum("mix_tokens").alias("block_tokens"))
    tokens = {r[0]: r[1] for r in blocks.groupBy("mix_source").agg(F.sum("block_tokens")).collect()}
    alpha = find_alpha(tokens, max_epochs, target_entropy)
    weights = tempered(tokens, alpha) if sum(tokens.values()) else {}
    passes = epochs(tokens, weights)
    rows = [(s, float(weights.get(s, 0.0)), *(divmod(round(n * passes.get(s, 1.0)), n) if n else (1, 0))) for s, n in tokens.items()]
    sources = spark.createDataFrame(rows, "mix_source string, mix_weight double, whole long, rest long")
    ahead = Window.partitionBy("mix_source").orderBy("block_key").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    plan = (
        blocks.join(F.broadcast(sources), "mix_source")
        .withColumn("block_key", _digest(SEED, F.col("mix_source"), F.col("whole").cast("string"), F.col("mix_block")))
        .withColumn("left", F.col("rest") - (F.sum("block_tokens").over(ahead) - F.col("block_tokens")))
        .select("mix_source", "mix_block", "mix_weight", "whole", F.when(F.col("left") <= 0, 0).when(F.col("left") >= F.col("block_tokens"), F.col("block_tokens") + 1).otherwise(F.col("left")).alias("left"), "block_tokens")
    )
    known = base.join(plan, ["mix_source", "mix_block"])
    cut = (F.col("left") > 0) & (F.col("left") <= F.col("block_tokens"))
    inside = Window.partitionBy("mix_source", "mix_block").orderBy("doc_key").rangeBetween(Window.unboundedPreceding, -1)
    key = F.conv(F.substring(_digest(SEED, F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, 12), 16, 10).cast("long")
    edge = known.where(cut).withColumn("doc_key", key).withColumn("before", F.coalesce(F.sum("mix_tokens").over(inside), F.lit(0))).withColumn("extra", (F.col("before") < F.col("left")).cast("long")).drop("doc_key", "before")
    whole = known.where(~cut).withColumn("extra", (F.col("left") > 0).cast("long"))
    return whole.unionByName(edge).withColumn("mix_copies", F.col("whole") + F.col("extra")).drop("mix_source", "whole", "left", "block_tokens", "extra")


def mixture(docs: DataFrame, **limits: float) -> DataFrame:
    """The mixture itself: each document as often as the budgets read it, with its epoch and
    the sort key that realises the permuted block order, beside the columns of ``docs``."""
    mixed = _mix(_slim(docs), **limits).withColumn("mix_epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("mix_copies") - 1)))
    order = _digest(SEED, F.coalesce(F.col("source"), F.lit("")), F.col("mix_epoch").cast("string"), F.col("mix_block"))
    return mixed.select(*_back(docs), F.col("mix_epoch").alias(fresh_name(docs, "mix_epoch")), order.alias(fresh_name(docs, "mix_order")))


def mixing_report(docs: DataFrame) -> DataFrame:
    return mix(docs.select("doc_id", "text", "source")).select("doc_id", "source", F.col("mix_tokens").alias("n_tokens"), F.round("mix_weight", 6).alias("weight"), F.col("mix_copies").alias("n_copies"))


ORACLE_SQL = r"""
WITH b AS (SELECT doc_id, source, coalesce(source, '') AS s, substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 3) AS block,
                  len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS n FROM documents),
t AS (SELECT s, sum(n) AS tokens FROM b GROUP BY s),
r AS (SELECT *, tokens / sum(tokens) OVER () AS p FROM t),
x AS (SELECT greatest(0, CASE WHEN count(*) FILTER (WHERE p > 0) < 2 OR max(p) = min(p) FILTER (WHERE p > 0) THEN 0
                        ELSE 1 - ln(1.5) / ln(max(p) / min(p) FILTER (WHERE p > 0)) END) AS alpha FROM r),
e AS (SELECT s, tokens, CASE WHEN p > 0 THEN p ** alpha ELSE 0 END AS raised,
             CASE WHEN p > 0 THEN (max(p) OVER () / p) ** (1 - alpha) ELSE 1 END AS passes FROM r, x),
w AS (SELECT s, raised / sum(raised) OVER () AS weight, tokens, CAST(round(tokens * passes) AS BIGINT) AS budget FROM e),
v AS (SELECT s, weight, CASE WHEN tokens = 0 THEN 1 ELSE budget // CAST(tokens AS BIGINT) END AS whole,
             CASE WHEN tokens = 0 THEN 0 ELSE budget % CAST(tokens AS BIGINT) END AS rest FROM w),
k AS (SELECT s, block, sum(n) AS bn FROM b GROUP BY s, block),
o AS (SELECT k.s, k.block, weight, whole, rest - (sum(bn) OVER (PARTITION BY k.s ORDER BY md5('mix|' || k.s || '|' || whole || '|' || k.block)) - bn) AS lft
      FROM k JOIN v ON k.s = v.s),
d AS (SELECT b.doc_id, b.source, b.n, o.weight, o.whole, o.lft,
             coalesce(sum(b.n) OVER (PARTITION BY b.s, b.block ORDER BY CAST('0x' || substr(md5('mix|' || coalesce(CAST(b.doc_id AS VARCHAR), '')), 1, 12) AS BIGINT)
                                     RANGE BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
      FROM b JOIN o ON b.s = o.s AND b.block = o.block)
SELECT doc_id, source, CAST(n AS BIGINT) AS n_tokens, round(weight, 6) AS weight,
       CAST(whole + CASE WHEN ahead < lft THEN 1 ELSE 0 END AS BIGINT) AS n_copies
FROM d
"""
