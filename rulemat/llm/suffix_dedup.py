"""Removal of long repeated byte strings by distributed prefix doubling.

Every string of ``LENGTH`` bytes that also starts earlier is removed wherever it lies
(earlier: smaller doc_id, or the same document and an earlier start; judged on the input).

Ranks are names: the name of 2m bytes is the name of the pair (name of m bytes, name of the
m bytes at offset m), so ranks at growing offsets 1, 2, 4, ... come from array operations
where the text lies, and Spark sorts positions only at the lengths at which many drop out.

1. Names of ``GRAM`` bytes.  Of the grams in each window of LENGTH bytes the least name is the
   window's anchor; equal windows have equal anchors.  Only anchors travel: (name, name of the
   anchor's whole context, that is of all windows it stands for, position).  Spark deals and
   sorts them by rank: anchors whose name is unique leave; of those with one context all but
   the first are repeats, with all their windows; those with several contexts stay open.
2. The windows of open anchors are ranked at LENGTH bytes: Spark deals and sorts (rank, position)
   pairs, and all but the first of a rank are repeats.

A map task that holds the same context (or rank) several times sends its first one to be ranked
and the others as repeats, and one that holds more than ``HOT`` contexts of a name deals them by
context and leaves them open, so neither copies nor a passage that lies in very many documents
gather in one bucket.

Rows are ordered by (doc_id, text), nulls first, when doc_ids are missing or repeated; every
row is then a document of its own.  Null text is empty; a document of fewer than LENGTH
bytes loses nothing; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PACKED, Texts, bucket_count, dealt, exchange, groups, hash_bitmap, int_column, keyed_documents, maybe_in, mix, packed_batches, pair_name, persisted, record, resting, slices, span_hashes

U64 = np.uint64
LENGTH = 100
GRAM = 32
GRAMS = LENGTH - GRAM + 1
#: Bytes of text named at once: names take many times that.
NAMED_BYTES = 1 << 18
#: Contexts of one name that a task sends to the name's bucket at once.
HOT = 32

_ANCHOR = [("name", "u8"), ("context", "u8"), ("again", "u4"), ("key", "i8"), ("lo", "u4"), ("more", "u1"), ("state", "u1")]
_MARK = "key long, lo long, more int, repeat boolean"
_WINDOW = [("rank", "u8"), ("again", "u4"), ("key", "i8"), ("lo", "u4"), ("state", "u1")]
_CUT = [("key", "i8"), ("lo", "u4"), ("hi", "u4")]
_SPAN = "key long, lo long, hi long"
#: States: to be ranked; known to repeat one of its task; open whatever the others are; a note that a name is hot.
RANKED, REPEAT, OPEN, NOTE = range(4)


def names(values: np.ndarray, length: int) -> np.ndarray:
    """Names of all strings of ``length`` bytes (a power of two), by doubling; entry i starts at i."""
    h, m = mix(values.astype(U64) + U64(1)), 1
    while m < length:
        h, m = pair_name(h[:-m], h[m:]) if len(h) > m else h[:0], 2 * m
    return h


def window_ranks(values: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """96-bit names of the windows of LENGTH bytes that start at the given places: two steps
    further from names of GRAM bytes, once in pairs and once in a row."""
    g, last = names(values, GRAM), LENGTH - GRAM
    part = {k: g[at + k] for k in (0, GRAM, 2 * GRAM, last - GRAM, last)}
    rank = pair_name(pair_name(part[0], part[GRAM]), pair_name(part[last - GRAM], part[last]))
    again = part[0]
    for k in (GRAM, 2 * GRAM, last):
        again = pair_name(part[k] ^ U64(0xA0761D6478BD642F), again)
    return rank, (again >> U64(32)).astype(np.uint32)


def anchors(t: Texts) -> tuple[np.ndarray, ...]:
    """(doc, name, context's two names, first window, further windows) of every anchor."""
    none = tuple(np.zeros(0, d) for d in (np.int64, U64, U64, np.uint32, np.int64, np.int64))
    n = len(t.data)
    if n < LENGTH:
        return none
    g = names(t.data, GRAM)
    low = (g & U64(0xFFFFFFFF00000000)) | np.arange(len(g), dtype=U64)
    m = 1
    while 2 * m <= GRAMS:
        low, m = np.minimum(low[:-m], low[m:]), 2 * m
    if m < GRAMS:
        low = np.minimum(low[: m - GRAMS], low[GRAMS - m :])
    at = (low & U64(0xFFFFFFFF)).astype(np.int64)  # anchor of each window
    size = np.diff(t.offs)
    long = np.flatnonzero(size >= LENGTH)
    if not len(long):
        return none
    count = size[long] - LENGTH + 1
    stop = np.cumsum(count)
    s = np.repeat(t.offs[:-1][long] - (stop - count), count) + np.arange(int(stop[-1]))
    doc = np.repeat(long, count)
    a = at[s]
    new = np.ones(len(s), bool)
    new[1:] = (a[1:] != a[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(s)) - 1
    lo, hi, p, doc = s[first], s[last], a[first], doc[first]
    context = pair_name(span_hashes(t.data, lo, hi + LENGTH), (p - lo).astype(U64))
    again = (span_hashes(t.data, lo, hi + LENGTH, 1) >> U64(32)).astype(np.uint32)
    return doc, g[p], context, again, lo - t.offs[doc], hi - lo


def parts(t: Texts) -> Iterator[tuple[Texts, int]]:
    """The slice itself, or overlapping parts of a very long text that hold each of its windows
    once, with the place of a part's first byte."""
    if len(t.data) <= 4 * NAMED_BYTES:
        yield t, 0
        return
    for k in range(t.n):
        a, b = int(t.offs[k]), int(t.offs[k + 1])
        for at in range(a, max(a + 1, b - LENGTH + 1), NAMED_BYTES):
            end = min(b, at + NAMED_BYTES + LENGTH - 1)
            yield Texts(t.data[at:end], np.array([0, end - at]), t.first + k), at - a


def _first_of(x: np.ndarray, *by: str) -> tuple[np.ndarray, np.ndarray]:
    """Rows sorted by rank and position, and which of them are the first of their rank."""
    x = x[np.lexsort((x["lo"], x["key"], *(x[c] for c in reversed(by))))]
    first = np.ones(len(x), bool)
    first[1:] = np.logical_or.reduce([x[c][1:] != x[c][:-1] for c in by])
    return x, first


def _within_task(x: np.ndarray) -> np.ndarray:
    """What a task sends of its anchors."""
    x, first = _first_of(x, "name", "context", "again")
    x["state"][~first] = REPEAT
    a, b = groups(x["name"])
    many = np.add.reduceat(first, a) > HOT if len(a) else np.zeros(0, bool)
    hot = np.repeat(many, b - a)
    x["state"][hot & first] = OPEN
    note = x[a[many]].copy()
    note["state"] = NOTE
    return np.concatenate([x, note])


def _deal_anchors(x: np.ndarray) -> np.ndarray:
    at = pair_name(x["key"].astype(U64), x["lo"].astype(U64))
    return np.select([x["state"] == REPEAT, x["state"] == OPEN], [at, x["context"]], x["name"])


def _ranked_windows(x: np.ndarray) -> np.ndarray:
    x, first = _first_of(x, "rank", "again")
    x["state"][~first] = REPEAT
    return x


def _deal_windows(x: np.ndarray) -> np.ndarray:
    return np.where(x["state"] == REPEAT, pair_name(x["key"].astype(U64), x["lo"].astype(U64)), x["rank"])


def repeated_spans(keyed: DataFrame) -> DataFrame:
    """(key, lo, hi): byte ranges to remove; they may overlap."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            keys, _ = int_column(batch.column(0))
            for t in slices(batch.column(1), NAMED_BYTES):
                for p, ahead in parts(t):
                    doc, name, context, again, lo, more = anchors(p)
                    yield record(_ANCHOR, name=name, context=context, again=again, key=keys[doc + p.first], lo=lo + ahead, more=more, state=np.zeros(len(doc)))

    def rank(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        done, hot = x[x["state"] == REPEAT], np.unique(x["name"][x["state"] == NOTE])
        apart, first_apart = _first_of(x[x["state"] == OPEN], "name", "context", "again")
        x, first = _first_of(x[x["state"] == RANKED], "name", "context", "again")
        a, b = groups(x["name"])
        several = np.add.reduceat(first, a) > 1 if len(a) else np.zeros(0, bool)
        several |= np.isin(x["name"][a], hot)
        stays = first & np.repeat(several, b - a)
        for part, repeat in ((done, True), (x[~first], True), (apart[~first_apart], True), (x[stays], False), (apart[first_apart], False)):
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(part["key"])), pa.array(part["lo"].astype(np.int64)), pa.array(part["more"].astype(np.int32)), pa.array(np.full(len(part), repeat))], names=[c.split()[0] for c in _MARK.split(", ")])

    marks = persisted(exchange(keyed.select("key", "text"), find, _deal_anchors, _ANCHOR, rank, _MARK, combine=_within_task), "marks")
    open_ = marks.where(~F.col("repeat")).groupBy("key").agg(F.collect_list(F.struct("lo", "more")).alias("o"))
    needed = hash_bitmap(marks.where(~F.col("repeat")).select("key").distinct(), "key")
    fetched = maybe_in(keyed.select("key", "text"), "key", *needed).join(open_, "key").select("key", "text", F.col("o.lo").alias("lo"), F.col("o.more").alias("more"))
    buckets = bucket_count(keyed.sparkSession)

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
        for batch in batches:
            keys, _ = int_column(batch.column(0))
            for t in slices(batch.column(1)):
                los, mores = (batch.column(k).slice(t.first, t.n) for k in (2, 3))
                own = np.repeat(np.arange(t.n), np.asarray(los.value_lengths().fill_null(0)))
                lo, n = np.asarray(los.flatten()).astype(np.int64), np.asarray(mores.flatten()).astype(np.int64) + 1
                for k in range(0, len(own), 2048):  # names take many times the bytes they stand for
                    o, x, w = own[k : k + 2048], lo[k : k + 2048], n[k : k + 2048]
                    size = w + LENGTH - 1
                    first, count = np.cumsum(size) - size, np.cumsum(w) - w
                    raw = t.data[np.repeat(t.offs[o] + x - first, size) + np.arange(int(size.sum()))]
                    step = np.arange(int(w.sum())) - np.repeat(count, w)
                    rank, again = window_ranks(raw, np.repeat(first, w) + step)
                    yield record(_WINDOW, rank=rank, again=again, key=np.repeat(keys[o + t.first], w), lo=np.repeat(x, w) + step, state=np.zeros(len(step)))

    def settle(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        ranked, first = _first_of(x[x["state"] == RANKED], "rank", "again")
        for part in (x[x["state"] == REPEAT], ranked[~first]):
            yield from packed_batches(record(_CUT, key=part["key"], lo=part["lo"], hi=part["lo"] + np.uint32(LENGTH)), "key", buckets)

    def merge(x: np.ndarray) -> Iterator[pa.RecordBatch]:
        x = x[np.lexsort((x["lo"], x["key"]))]
        new = np.ones(len(x), bool)
        new[1:] = (x["key"][1:] != x["key"][:-1]) | (x["lo"][1:] > x["hi"][:-1])  # all are equally long
        i = np.flatnonzero(new)
        j = np.append(i[1:], len(x)) - 1
        yield pa.RecordBatch.from_arrays([pa.array(x["key"][i]), pa.array(x["lo"][i].astype(np.int64)), pa.array(x["hi"][j].astype(np.int64))], names=["key", "lo", "hi"])

    windows = exchange(fetched, fetch, _deal_windows, _WINDOW, settle, PACKED, combine=_ranked_windows)
    fully = marks.where("repeat").select("key", "lo", (F.col("lo") + F.col("more") + LENGTH).alias("hi"))
    return fully.unionByName(dealt(windows, _CUT, merge, _SPAN))


def dedup_strings(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, n_removed, spans, kept) of every document."""
    keyed = keyed_documents(docs)
    spans = persisted(repeated_spans(keyed).groupBy("key").agg(F.collect_list(F.struct("lo", "hi")).alias("s")), "spans")
    some = hash_bitmap(spans, "key")
    columns = ["doc_id", "text", F.col("s.lo").alias("lo"), F.col("s.hi").alias("hi")]
    joined = maybe_in(keyed.select("key", "doc_id", "text"), "key", *some).join(spans, "key", "left").select(*columns)
    nothing = F.lit(None).cast("array<bigint>")
    untouched = maybe_in(keyed.select("key", "doc_id", "text"), "key", *some, outside=True).select("doc_id", "text", nothing.alias("lo"), nothing.alias("hi"))
    schema = "doc_id long, n_bytes long, n_removed long, spans array<struct<start:long,stop:long>>, kept binary"
    pair = pa.struct([("start", pa.int64()), ("stop", pa.int64())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in slices(batch.column(1)):
                los, his = (batch.column(k).slice(t.first, t.n) for k in (2, 3))
                own = np.repeat(np.arange(t.n), np.asarray(los.value_lengths().fill_null(0)))
                lo, hi = np.asarray(los.flatten()).astype(np.int64), np.asarray(his.flatten()).astype(np.int64)
                order = np.lexsort((lo, own))
                own, lo, hi = own[order], lo[order] + t.offs[own[order]], hi[order] + t.offs[own[order]]
                reach = np.maximum.accumulate(hi) if len(hi) else hi
                fresh = np.ones(len(lo), bool)
                fresh[1:] = (lo[1:] > reach[:-1]) | (own[1:] != own[:-1])
                i = np.flatnonzero(fresh)
                j = np.append(i[1:], len(lo))[: len(i)] - 1
                own, lo, hi = own[i], lo[i], reach[j]
                removed = np.bincount(own, weights=hi - lo, minlength=t.n).astype(np.int64)
                size = np.diff(t.offs)
                # kept ranges: the gaps around the removed ones
                turn = np.empty(2 * len(lo) + 2, np.int64)
                turn[0], turn[1:-1:2], turn[2:-1:2], turn[-1] = 0, lo, hi, len(t.data)
                kept = t.data[np.repeat(np.arange(len(turn) - 1) % 2 == 0, np.diff(turn))].tobytes()
                stop = np.cumsum(size - removed)
                rest = [kept[a:b] for a, b in zip((stop - size + removed).tolist(), stop.tolist(), strict=True)]
                base = t.offs[own]
                count = np.bincount(own, minlength=t.n)
                flat = pa.StructArray.from_arrays([pa.array(lo - base), pa.array(hi - base)], fields=list(pair))
                spans = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count)]), pa.int32()), flat)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(t.first, t.n), pa.array(size), pa.array(removed), spans, pa.array(rest, pa.binary())], names=["doc_id", "n_bytes", "n_removed", "spans", "kept"])

    return joined.unionByName(untouched).mapInArrow(resting(cut), schema)


def span_digests(docs: DataFrame) -> DataFrame:
    return dedup_strings(docs).select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
