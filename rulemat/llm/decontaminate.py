"""Benchmark decontamination by winnowing.

From every text the minimum hash of each window of consecutive k-grams is kept.  With k-grams
of 5 words and windows of 6, every shared run of 10 words has a kept k-gram in common, so the
join of training and test fingerprints misses none.  Fingerprints carry the hashes of the
words around them; a hit is extended to both sides by comparing these, and counts where the
equal run is as long as a window of the benchmark.  Items shorter than a window are looked up
as whole runs of their own length.

Training fingerprints first pass a bitmap of the test fingerprints whose size is bounded
(``MAX_BITS``); it only lets more through when it is full.  The join itself is a shuffle join.

Defined cases: null or empty text has no words and no hits; an item without words matches
nothing; rows that repeat a doc_id are judged one by one; an item without item_id counts
for hits but is not listed; empty tables give no hits or no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ALNUM, exchange, groups, hash_bitmap, in_bitmap, int_column, mix, persisted, record, resting, runs, slices, word_hashes

U64 = np.uint64
WINDOW = 10
GRAM = 5
MAX_BITS = 1 << 27


def _minima(h: np.ndarray, doc: np.ndarray, gram: int, window: int) -> tuple[np.ndarray, np.ndarray]:
    """(position, k-gram hash) of the kept fingerprints of a slice."""
    g = runs(h, gram)
    span = window - gram + 1  # k-grams in a window
    m = len(g) - span + 1
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, U64)
    low = g[:m].copy()
    for k in range(1, span):
        np.minimum(low, g[k : k + m], out=low)
    whole = doc[:m] == doc[window - 1 : window - 1 + m]
    kept = np.zeros(len(g), bool)
    for k in range(span):
        kept[k : k + m] |= whole & (g[k : k + m] == low)
    at = np.flatnonzero(kept)
    return at, g[at]


def _around(h: np.ndarray, doc: np.ndarray, at: np.ndarray, left: int, width: int, outside: int) -> np.ndarray:
    """Hashes of ``width`` words from ``at - left`` on; ``outside`` beyond the document."""
    pos = at[:, None] - left + np.arange(width)
    safe = np.clip(pos, 0, max(0, len(h) - 1))
    ok = (pos >= 0) & (pos < len(h)) & (doc[safe] == doc[at][:, None])
    return np.where(ok, h[safe], U64(outside))


def _short_key(h: np.ndarray, n: int) -> np.ndarray:
    return mix(runs(h, n) ^ U64(n * 0x9E3779B9))


def _blobs(rows: np.ndarray) -> pa.Array:
    return pa.array([r.tobytes() for r in rows], pa.binary())


_TEST = "hash long, size int, item_id long, context binary"


def test_fingerprints(bench: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """Fingerprints of the benchmark; ``size`` is the window, or the length of a short item."""
    width, left = 2 * window - gram, window - gram

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0)
            for t in slices(batch.column(1)):
                h, doc = word_hashes(t, ALNUM)
                if not len(h):
                    continue
                at, g = _minima(h, doc, gram, window)
                ctx = _around(h, doc, at, left, width, 1)
                yield pa.RecordBatch.from_arrays([pa.array(g.view(np.int64)), pa.array(np.full(len(at), window, np.int32)), ids.take(pa.array(doc[at] + t.first)), _blobs(ctx)], names=["hash", "size", "item_id", "context"])
                n = np.bincount(doc, minlength=t.n)
                first = np.concatenate([[0], np.cumsum(n)])
                for d in np.flatnonzero((n > 0) & (n < window)):
                    own = h[first[d] : first[d + 1]]
                    yield pa.RecordBatch.from_arrays([pa.array(_short_key(own, len(own)).view(np.int64)), pa.array([len(own)], pa.int32()), ids.slice(t.first + int(d), 1), _blobs(own[None, :])], names=["hash", "size", "item_id", "context"])

    return bench.select(F.col("item_id").cast("long").alias("item_id"), "text").mapInArrow(resting(run), _TEST)


_FOUND = [("rid", "i8"), ("doc", "i8"), ("valid", "?"), ("words", "i8"), ("item", "i8"), ("item_valid", "?"), ("start", "i4"), ("end", "i4")]
_RESULT = "row_id long, doc_id long, n_words long, n_hit long, items array<long>"


def decontaminate(docs: DataFrame, bench: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(row_id, doc_id, n_words, n_hit, items) of every row of ``docs``: how many of its words
    lie in an occurrence of a benchmark window, and the items concerned."""
    spark = docs.sparkSession
    prints = persisted(test_fingerprints(bench, window, gram), "benchmark-prints")
    bitmap, bits = hash_bitmap(prints, "hash", MAX_BITS)
    shared = spark.sparkContext.broadcast(bitmap)
    short = sorted(r[0] for r in prints.where(F.col("size") < window).select("size").distinct().collect())  # below ``window`` values
    width, left = 2 * window - gram, window - gram
    schema = "row_id long, doc_id long, n_words long, hash long, size int, pos int, around binary"
    names = [x.split()[0] for x in schema.split(", ")]

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        may = shared.value

        def rows(rid: pa.Array, ids: pa.Array, n: pa.Array, g: pa.Array, size: int, pos: pa.Array, ctx: pa.Array) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([rid, ids, n, g, pa.array(np.full(len(rid), size, np.int32)), pos, ctx], names=names)

        for batch in batches:
            for t in slices(batch.column(2)):
                rid, ids = batch.column(0).slice(t.first, t.n), batch.column(1).slice(t.first, t.n)
                h, doc = word_hashes(t, ALNUM)
                n = np.bincount(doc, minlength=t.n)
                yield rows(rid, ids, pa.array(n, pa.int64()), pa.nulls(t.n, pa.int64()), 0, pa.nulls(t.n, pa.int32()), pa.nulls(t.n, pa.binary()))
                first = np.concatenate([[0], np.cumsum(n)])
                for size in (window, *short):
                    if size == window:
                        at, g = _minima(h, doc, gram, window)
                    elif len(h) >= size:
                        g = _short_key(h, size)
                        at = np.flatnonzero(doc[: len(g)] == doc[size - 1 :])
                        g = g[at]
                    else:
                        continue
                    hit = in_bitmap(g, may, bits)
                    at, g = at[hit], g[hit]
                    if len(at):
                        ctx = _around(h, doc, at, left, width, 0) if size == window else h[at[:, None] + np.arange(size)]
                        own = pa.array(doc[at])
                        yield rows(rid.take(own), ids.take(own), pa.nulls(len(at), pa.int64()), pa.array(g.view(np.int64)), size, pa.array((at - first[doc[at]]).astype(np.int32)), _blobs(ctx))

    # written once: row numbers stay, and rows that are in no join never share a key
    found = persisted(docs.select(F.monotonically_increasing_id().alias("row_id"), F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(resting(scan), schema), "found")
    columns = ["row_id", "doc_id", "n_words", "size", "pos", "around", "item_id", "context"]
    hits = found.where(F.col("hash").isNotNull()).join(prints.select("hash", "size", "item_id", "context"), ["hash", "size"]).select(*columns)
    rows = found.where(F.col("hash").isNull()).select(*columns[:-2], F.lit(None).cast("long").alias("item_id"), F.lit(None).cast("binary").alias("context"))
    joined = rows.unionByName(hits)

    def extend(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            rid, _ = int_column(batch.column(0))
            ids, valid = int_column(batch.column(1))
            n, base = int_column(batch.column(2))
            size, pos = int_column(batch.column(3))[0], int_column(batch.column(4))[0]
            item, item_valid = int_column(batch.column(6))
            start, end = np.full(len(rid), -1, np.int64), np.full(len(rid), -1, np.int64)
            for s in np.unique(size[~base]):
                k = np.flatnonzero(~base & (size == s))
                pick = pa.array(k)
                a, b = (np.frombuffer(b"".join(batch.column(c).take(pick).to_pylist()), U64).reshape(len(k), -1) for c in (5, 7))
                eq = a == b
                if s == window:
                    ok = eq[:, left : left + gram].all(axis=1)
                    back = np.minimum.accumulate(eq[:, :left][:, ::-1], axis=1).sum(axis=1)
                    on = np.minimum.accumulate(eq[:, left + gram :], axis=1).sum(axis=1)
                    ok &= back + on + gram >= window
                    start[k], end[k] = np.where(ok, pos[k] - back, -1), np.where(ok, pos[k] + gram + on, -1)
                else:
                    ok = eq.all(axis=1)
                    start[k], end[k] = np.where(ok, pos[k], -1), np.where(ok, pos[k] + s, -1)
            keep = base | (start >= 0)
            yield record(_FOUND, rid=rid[keep], doc=ids[keep], valid=valid[keep], words=np.where(base, n, -1)[keep], item=item[keep], item_valid=item_valid[keep], start=start[keep], end=end[keep])

    def settle(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        x = x[np.lexsort((x["start"], x["words"] < 0, x["rid"]))]
        a, b = groups(x["rid"])
        hit = np.zeros(len(a), np.int64)
        items: list[list[int]] = [[]] * len(a)
        for k in np.flatnonzero(b - a > 1):
            own = x[a[k] + 1 : b[k]]
            reach = np.concatenate([[0], np.maximum.accumulate(own["end"])[:-1]])
            hit[k] = np.maximum(0, own["end"].astype(np.int64) - np.maximum(own["start"], reach)).sum()
            items[k] = np.unique(own["item"][own["item_valid"]]).tolist()
        yield pa.RecordBatch.from_arrays([pa.array(x["rid"][a]), pa.array(x["doc"][a], mask=~x["valid"][a]), pa.array(x["words"][a]), pa.array(hit), pa.array(items, pa.list_(pa.int64()))], names=[c.split()[0] for c in _RESULT.split(", ")])

    return exchange(joined, extend, "rid", _FOUND, settle, _RESULT)


def contamination_digests(docs: DataFrame, bench: DataFrame) -> DataFrame:
    got = decontaminate(docs, bench)
    names = F.array_sort(F.transform("items", lambda i: i.cast("string")))
    return got.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join(names, ",").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


ORACLE_SQL = r"""
WITH dw AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                   '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
bw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                   '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
bm AS (SELECT item_id, ws, least(len(ws), 10) AS m FROM bw WHERE len(ws) > 0),
bk AS (SELECT DISTINCT item_id, m, array_to_string(ws[p : p + m - 1], ' ') AS key FROM (SELECT *, unnest(range(1, len(ws) - m + 2)) AS p FROM bm)),
dk AS (SELECT rid, p, m, array_to_string(ws[p : p + m - 1], ' ') AS key
       FROM (SELECT rid, ws, m, unnest(range(1, len(ws) - m + 2)) AS p FROM dw, (SELECT DISTINCT m FROM bk) WHERE len(ws) >= m)),
h AS (SELECT rid, p, dk.m, item_id FROM dk JOIN bk ON dk.m = bk.m AND dk.key = bk.key),
n AS (SELECT rid, count(DISTINCT w) AS n_hit FROM (SELECT rid, unnest(range(p, p + m)) AS w FROM h) GROUP BY rid),
i AS (SELECT rid, count(*) AS n_items, string_agg(id, ',' ORDER BY id) AS ids FROM (SELECT DISTINCT rid, CAST(item_id AS VARCHAR) AS id FROM h WHERE item_id IS NOT NULL) GROUP BY rid)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN n USING (rid) LEFT JOIN i USING (rid)
"""
