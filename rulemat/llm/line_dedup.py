"""Line deduplication across documents.

Lines are exploded, normalised (ASCII white space stripped at both ends, A-Z lower-cased)
and hashed to 128 bits; a map-side combined aggregation counts the documents of each hash
and keeps its largest doc_id; lines whose key has at least ``min_chars`` code points and
occurs in at least ``min_docs`` documents go from every document but that one; the others
are put together again by position.

Defined cases: null or empty text is one empty line; every row counts as a document of its
own, so rows that repeat a doc_id count each time and are treated alike; a row without
doc_id never holds the largest one; columns besides the two named ones are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, NOT_SPACE, Texts, pair_name, persisted, resting, slices, span_hashes


def split_lines(t: Texts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc, start, end) of every line of the slice; an empty document has one empty line."""
    newline = np.flatnonzero(t.data == 10)
    starts = np.concatenate([t.offs[:-1], newline + 1])
    doc = np.concatenate([np.arange(t.n), np.searchsorted(t.offs, newline, side="right") - 1])
    order = np.lexsort((starts, doc))
    starts, doc = starts[order], doc[order]
    ends = np.empty(len(starts), np.int64)
    ends[:-1] = starts[1:] - 1
    last = np.append(doc[1:] != doc[:-1], True) if len(doc) else np.zeros(0, bool)
    ends[last] = t.offs[1:][doc[last]]
    return doc, starts, ends


def line_keys(t: Texts, min_chars: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(doc, start, end, long enough, key hash, key hash) of every line."""
    doc, starts, ends = split_lines(t)
    solid = np.flatnonzero(NOT_SPACE[t.data])
    a, b = np.searchsorted(solid, starts), np.searchsorted(solid, ends)
    some = b > a
    ks, ke = np.zeros_like(starts), np.zeros_like(starts)
    ks[some], ke[some] = solid[a[some]], solid[b[some] - 1] + 1
    chars = np.concatenate([[0], np.cumsum((t.data & 0xC0) != 0x80)])
    long = chars[ke] - chars[ks] >= min_chars
    h1, h2 = np.zeros(len(ks), np.uint64), np.zeros(len(ks), np.uint64)
    values = LOWER[t.data]
    h1[long], h2[long] = (span_hashes(values, ks[long], ke[long], w) for w in (0, 1))
    return doc, starts, ends, long, h1, h2


def line_hashes(docs: DataFrame, min_chars: int) -> DataFrame:
    """One row per document and distinct key that is long enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0)
            for t in slices(batch.column(1)):
                doc, _, _, long, h1, h2 = line_keys(t, min_chars)
                doc, h1, h2 = doc[long], h1[long], h2[long]
                order = np.lexsort((h2, h1, doc))
                doc, h1, h2 = doc[order], h1[order], h2[order]
                new = np.ones(len(doc), bool)
                new[1:] = (doc[1:] != doc[:-1]) | (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(doc[new] + t.first)), pa.array(h1[new].view(np.int64)), pa.array(h2[new].view(np.int64))], names=["doc_id", "h1", "h2"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(resting(run), "doc_id long, h1 long, h2 long")


def dedup_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(doc_id, n_lines, n_dropped, text) of every document after line deduplication."""
    lines = persisted(line_hashes(docs, min_chars), "lines")
    common = lines.groupBy("h1", "h2").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper")).where(F.col("n") >= min_docs).select("h1", "h2", "keeper")
    common = persisted(common, "common-lines")  # so that the join may split the partition of a frequent line
    gone = lines.join(common, ["h1", "h2"]).where(F.col("keeper").isNotNull() & ~F.col("doc_id").eqNullSafe(F.col("keeper")))
    per_doc = gone.groupBy("doc_id").agg(F.collect_set(F.struct("h1", "h2")).alias("gone")).select(F.col("doc_id").alias("gone_id"), "gone")
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(per_doc, F.col("doc_id").eqNullSafe(F.col("gone_id")), "left").select("doc_id", "text", F.col("gone.h1").alias("h1"), F.col("gone.h2").alias("h2"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, h1s, h2s = batch.column(0), batch.column(2), batch.column(3)
            for t in slices(batch.column(1)):
                doc, starts, ends, long, h1, h2 = line_keys(t, min_chars)
                g1, g2 = h1s.slice(t.first, t.n), h2s.slice(t.first, t.n)
                own = np.repeat(np.arange(t.n), np.asarray(g1.value_lengths().fill_null(0)))
                drop = np.zeros(len(doc), bool)
                if len(own):
                    name = lambda a, b, d: pair_name(pair_name(a, b), d.astype(np.uint64))
                    goes = name(np.asarray(g1.flatten()).view(np.uint64), np.asarray(g2.flatten()).view(np.uint64), own)
                    drop = long & np.isin(name(h1, h2, doc), goes)
                n_lines, n_dropped = np.bincount(doc, minlength=t.n), np.bincount(doc[drop], minlength=t.n)
                first = np.concatenate([[0], np.cumsum(n_lines)])
                texts = []
                for d in range(t.n):
                    if n_dropped[d]:
                        raw, at = t.bytes_of(d), t.offs[d]
                        texts.append(b"\n".join(raw[starts[k] - at : ends[k] - at] for k in range(first[d], first[d + 1]) if not drop[k]))
                    else:
                        texts.append(t.bytes_of(d))
                yield pa.RecordBatch.from_arrays([ids.slice(t.first, t.n), pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(texts, pa.binary()).cast(pa.string())], names=["doc_id", "n_lines", "n_dropped", "text"])

    return joined.mapInArrow(resting(run), "doc_id long, n_lines long, n_dropped long, text string")


def line_digests(docs: DataFrame) -> DataFrame:
    return dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text"), 256).alias("kept_sha256"))


ORACLE_SQL = """
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
l AS (SELECT rid, doc_id, unnest(ls) AS line, unnest(range(len(ls))) AS pos FROM d),
k AS (SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
             'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
c AS (SELECT key, max(doc_id) AS keeper FROM (SELECT DISTINCT rid, doc_id, key FROM k WHERE length(key) >= 20)
      GROUP BY key HAVING count(*) >= 3),
m AS (SELECT k.*, coalesce(c.keeper IS NOT NULL AND k.doc_id IS DISTINCT FROM c.keeper, false) AS gone
      FROM k LEFT JOIN c ON k.key = c.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY rid, doc_id
"""
