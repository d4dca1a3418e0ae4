"""Secret scans with a trigram inverted index, in DataFrame functions only.

From each rule's regular expression a Boolean trigram query is derived (on the driver, from
the parsed expression).  The index has a posting (trigram, text key) for every trigram that
some query uses and every text that contains it, lower-cased; equal texts share a key.
Postings are intersected per text into a bit set, queries are evaluated on it, and only the
candidates are verified with the expression itself.  A rule without mandatory trigrams is
verified on every text.  The index is a superset filter: it never changes a result.

Defined cases: null text is empty; an empty table gives no rows; every row is scanned on its
own, whatever its doc_id; spans count code points, end exclusive.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from re import _constants as _c
from re import _parser as _p

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, fresh_name, persisted


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    #: Least length of ``group`` for a match to stay.
    least: int = 1
    group: int = 0
    #: A quick necessary test for rules that no trigram can narrow.
    guard: str | None = None
    #: An expression with just those matches of ``pattern`` that are long enough.
    fast: str | None = None


def _either(word: str) -> str:
    return "".join(f"[{x.upper()}{x}]" if x.isalpha() else x for x in word)


# The base rules.
_KEYWORDS = "|".join([*map(_either, ("password", "passwd", "secret", "token")), "[Aa][Pp][Ii]_?[Kk][Ee][Yy]"])
BASE = (
    Rule("assign", rf"""({_KEYWORDS})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 12, 2),
    Rule("access", r"AKIA[A-Z0-9]+", 18, fast=r"AKIA[A-Z0-9]{14,}"),
    Rule("hex", r"[0-9a-f]+", 16, 0, r"[0-9a-f]{16}", r"(?<![0-9a-f])[0-9a-f]{16,}"),
)
#: Further rules, whose spans come on top of the base ones.
MORE = (
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("forge", r"gh[opsu]_[A-Za-z0-9]+", 24),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]+", 16),
    Rule("bearer", r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 24),
)
RULES = BASE + MORE

# ------------------------------------------------------------ trigram queries

#: A query: None (no constraint), or a set of alternatives, each a set of trigrams that all occur.
Query = frozenset[frozenset[str]] | None
_MOST = 96


def _either_of(a: Query, b: Query) -> Query:
    return None if a is None or b is None else _absorb(a | b)


def _both(a: Query, b: Query) -> Query:
    if a is None or b is None:
        return b if a is None else a
    return _absorb(frozenset(x | y for x in a for y in b)) if len(a) * len(b) <= _MOST else a


def _absorb(q: frozenset[frozenset[str]]) -> frozenset[frozenset[str]]:
    return frozenset(x for x in q if not any(y < x for y in q))


def _grams(strings: frozenset[str]) -> Query:
    if any(len(s) < 3 for s in strings):
        return None
    return _absorb(frozenset(frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in strings))


def _choices(items: list) -> frozenset[str] | None:
    """Lower-cased members of a small character set."""
    out: set[str] = set()
    for op, value in items:
        if op is _c.LITERAL:
            out.add(chr(value).lower())
        elif op is _c.RANGE and value[1] - value[0] < 8:
            out |= {chr(x).lower() for x in range(value[0], value[1] + 1)}
        else:
            return None
    return frozenset(out) if len(out) <= 6 else None


def _walk(parsed: object) -> tuple[frozenset[str] | None, Query]:
    """(the lower-cased strings it can match, if few; a query that every match satisfies)."""
    now: frozenset[str] = frozenset([""])
    query: Query = None
    exact = True

    def flush() -> None:
        nonlocal now, query, exact
        query, now, exact = _both(query, _grams(now)), frozenset([""]), False

    def add(strings: frozenset[str]) -> None:
        nonlocal now
        if len(now) * len(strings) > _MOST:
            flush()
        now = frozenset(a + b for a in now for b in strings)

    for op, value in parsed:
        strings, inner = None, None
        if op is _c.LITERAL:
            strings = frozenset([chr(value).lower()])
        elif op is _c.IN:
            strings = _choices(value)
        elif op is _c.SUBPATTERN:
            strings, inner = _walk(value[-1])
        elif op is _c.BRANCH:
            parts = [_walk(x) for x in value[1]]
            if all(s is not None for s, _ in parts) and sum(len(s) for s, _ in parts) <= _MOST:
                strings = frozenset().union(*(s for s, _ in parts))
            else:
                inner = reduce(_either_of, ((_both(q, _grams(s)) if s is not None else q) for s, q in parts))
        elif op in (_c.MAX_REPEAT, _c.MIN_REPEAT):
            low, high, body = value
            s, q = _walk(body)
            if s is not None and (low, high) in ((0, 1), (1, 1)):
                strings = s if low else s | {""}
            elif low >= 1:
                if s is not None:
                    add(s)
                flush()
                query = _both(query, q)
                continue
        if strings is not None:
            add(strings)
        else:
            flush()
            query = _both(query, inner)
    if exact:
        return now, query
    flush()
    return None, query


def trigram_query(pattern: str) -> Query:
    strings, query = _walk(_p.parse(pattern))
    return _both(query, _grams(strings)) if strings is not None else query


# ----------------------------------------------------------------------- index


def vocabulary(rules: tuple[Rule, ...]) -> list[str]:
    return sorted({t for r in rules for x in trigram_query(r.pattern) or () for t in x})


def text_key(text: Column) -> Column:
    return F.xxhash64(F.coalesce(text, F.lit("")))


def build_index(docs: DataFrame, trigrams: list[str]) -> DataFrame:
    """Postings (trigram number, key) of all texts."""
    low = docs.select(text_key(F.col("text")).alias("key"), F.lower("text").alias("low"))
    present = F.array_compact(F.array(*[F.when(F.contains(F.col("low"), F.lit(t)), F.lit(k)) for k, t in enumerate(trigrams)])) if trigrams else F.array().cast("array<int>")
    return low.select("key", F.explode(present).alias("trigram"))


def candidates(index: DataFrame, rules: tuple[Rule, ...], trigrams: list[str]) -> DataFrame:
    """(key, rules): keys whose postings satisfy some rule's query, with a bit per rule."""
    at = {t: k for k, t in enumerate(trigrams)}
    words = max(1, -(-len(trigrams) // 62))
    bit = lambda w: F.when(F.floor(F.col("trigram") / 62) == w, F.expr(f"shiftleft(1L, trigram - {62 * w})")).otherwise(F.lit(0).cast("long"))
    sets = index.groupBy("key").agg(*[F.bit_or(bit(w)).alias(f"has{w}") for w in range(words)])

    def holds(query: frozenset[frozenset[str]]) -> Column:
        def every(trigram_set: frozenset[str]) -> Column:
            masks = [0] * words
            for t in trigram_set:
                masks[at[t] // 62] |= 1 << (at[t] % 62)
            return reduce(lambda a, b: a & b, [F.col(f"has{w}").bitwiseAND(F.lit(m)) == m for w, m in enumerate(masks) if m])

        return reduce(lambda a, b: a | b, [every(x) for x in sorted(query, key=sorted)])

    hits = [F.when(holds(q), 1 << k).otherwise(0) for k, r in enumerate(rules) if (q := trigram_query(r.pattern)) is not None]
    return sets.select("key", reduce(lambda a, b: a + b, hits, F.lit(0)).cast("long").alias("rules")).where(F.col("rules") != 0)


# ---------------------------------------------------------------- verification


#: Matches whose positions are added up together.
_BLOCK = 64


def _spans(rule: Rule, rank: int, text: Column) -> Column:
    """Array of (start, stop, rank) of the matches that stay: lengths of the pieces between
    the matches and of the matches themselves add up to positions.  They are added up in blocks,
    as an array that grows with every match of a long text would be copied as often."""
    expression = rule.fast or rule.pattern
    every = F.regexp_extract_all(text, F.lit(expression), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(expression), F.lit(rule.group)) if rule.group else every
    lengths = lambda x: F.transform(x, lambda y: F.length(y))
    pieces = F.arrays_zip(lengths(F.slice(F.split(text, expression, -1), 1, F.size(every))).alias("gap"), lengths(every).alias("hit"), lengths(value).alias("size"))
    empty = "array<struct<start:int,stop:int,size:int>>"

    def walk(block: Column, at: Column) -> Column:
        one = lambda acc, x: F.struct((acc["at"] + x["gap"]).alias("start"), (acc["at"] + x["gap"] + x["hit"]).alias("stop"), x["size"].alias("size"))
        step = lambda acc, x: F.struct((acc["at"] + x["gap"] + x["hit"]).alias("at"), F.concat(acc["out"], F.array(one(acc, x))).alias("out"))
        return F.aggregate(block, F.struct(at.alias("at"), F.array().cast(empty).alias("out")), step, lambda acc: acc["out"])

    def far(p: Column) -> Column:
        cut = F.transform(F.sequence(F.lit(0), F.floor((F.size(p) - 1) / _BLOCK).cast("int")), lambda b: F.slice(p, b * _BLOCK + 1, F.lit(_BLOCK)))
        ahead = F.aggregate(
            cut,
            F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out")),
            lambda acc, x: F.struct(F.aggregate(x, acc["at"], lambda n, y: n + y["gap"] + y["hit"]).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")),
            lambda acc: acc["out"],
        )
        return F.flatten(F.transform(F.arrays_zip(cut.alias("block"), ahead.alias("at")), lambda x: walk(x["block"], x["at"])))

    # through an array of one, so that the pieces are found once
    walked = F.flatten(F.transform(F.array(pieces), lambda p: F.when(F.size(p) == 0, F.array().cast(empty)).when(F.size(p) <= _BLOCK, walk(p, F.lit(0))).otherwise(far(p))))
    return F.transform(F.filter(walked, lambda x: x["size"] >= rule.least), lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["stop"].alias("stop")))


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, column: str = "secrets") -> DataFrame:
    """Columns of ``docs`` as they are and ``column`` (with underscores after it where ``docs``
    has that name): array of (start, rank of the rule, stop), sorted; it comes last."""
    trigrams = vocabulary(rules)
    index = persisted(build_index(docs, trigrams).distinct(), "trigram-index")
    found = persisted(candidates(index, rules, trigrams), "secret-candidates")
    discard(index)
    key, which, column = fresh_name(docs, "secret_key"), fresh_name(docs, "secret_rules"), fresh_name(docs, column)
    narrowed = docs.withColumn(key, text_key(F.col("text"))).join(found.select(F.col("key").alias(key), F.col("rules").alias(which)), key, "left")
    none, text = F.array().cast("array<struct<start:int,rank:int,stop:int>>"), F.coalesce(F.col("text"), F.lit(""))
    columns = []
    for k, r in enumerate(rules):
        may = F.coalesce(F.col(which), F.lit(0)).bitwiseAND(F.lit(1 << k)) != 0 if trigram_query(r.pattern) is not None else text.rlike(r.guard) if r.guard else F.lit(True)
        columns.append(F.when(may, _spans(r, k, text)).otherwise(none))
    return narrowed.select(*[F.col(f"`{c}`") for c in docs.columns], F.array_sort(F.concat(*columns)).alias(column))


def _joined(spans: Column, rules: tuple[Rule, ...]) -> Column:
    kinds = F.array(*[F.lit(r.kind) for r in rules])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(kinds, x["rank"] + 1), x["start"].cast("string"), x["stop"].cast("string"))), ",")


def secret_digests(docs: DataFrame) -> DataFrame:
    got = scan(docs.select("doc_id", "text"))
    count = lambda k: F.size(F.filter("secrets", lambda x: x["rank"] == k)).cast("long")
    base = F.filter("secrets", lambda x: x["rank"] < len(BASE))
    return got.select("doc_id", *[count(k).alias(f"n_{r.kind}") for k, r in enumerate(BASE)], F.sha2(_joined(base, RULES).cast("binary"), 256).alias("base_sha256"), _joined(F.col("secrets"), RULES).alias("spans"))


def _sql() -> str:
    parts = []
    for k, r in enumerate(RULES):
        p = r.pattern.replace("'", "''")
        parts.append(f"""SELECT rid, {k} AS k, '{r.kind}' AS kind, unnest(range(1, len(m) + 1)) AS i, m, v, g, {r.least} AS least FROM (
            SELECT rid, regexp_extract_all(t, '{p}') AS m, regexp_extract_all(t, '{p}', {r.group}) AS v, string_split_regex(t, '{p}') AS g FROM d)""")
    return f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM documents),
x AS ({" UNION ALL ".join(parts)}),
y AS (SELECT rid, k, kind, length(m[i]) AS n, length(v[i]) >= least AS ok,
             list_sum([length(z) for z in g[1:i]]) + coalesce(list_sum([length(z) for z in m[1:i-1]]), 0) AS s FROM x),
z AS (SELECT rid, k, CAST(s AS BIGINT) AS s, kind || ':' || CAST(s AS BIGINT) || ':' || CAST(s + n AS BIGINT) AS span FROM y WHERE ok),
a AS (SELECT rid, count(*) FILTER (WHERE k = 0) AS n_assign, count(*) FILTER (WHERE k = 1) AS n_access, count(*) FILTER (WHERE k = 2) AS n_hex,
             string_agg(span, ',' ORDER BY s, k) FILTER (WHERE k < {len(BASE)}) AS base, string_agg(span, ',' ORDER BY s, k) AS spans FROM z GROUP BY rid)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM d LEFT JOIN a USING (rid)
"""


ORACLE_SQL = _sql()
